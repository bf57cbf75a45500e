import sys
from pathlib import Path

import pytest

sys.path.insert(0, str(Path(__file__).resolve().parents[1]))


@pytest.fixture(scope="session")
def spark():
    from hgengine.session import local

    session = local("4", partitions=4, memory="4g")
    session.sparkContext.setLogLevel("ERROR")
    yield session
    session.stop()


@pytest.fixture(scope="session")
def toy(spark):
    from hgengine.model import HyperFrame

    edges = {1: [1, 2], 2: [1, 2, 3, 4], 3: [1, 4, 5], 4: [3, 4]}
    return HyperFrame.from_rows(spark, [(v, h) for h, vs in edges.items() for v in vs])


@pytest.fixture(scope="session")
def weighted(spark):
    from hgengine.model import HyperFrame

    edges = {1: [1, 2], 2: [1, 2, 3, 4], 3: [1, 4, 5], 4: [3, 4]}
    return HyperFrame.from_rows(spark, [(v, h) for h, vs in edges.items() for v in vs], {1: 1, 2: 2, 3: 1, 4: 4})
