"""All queries of the library and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hgengine import queries_core, queries_placement, sql  # noqa: F401  they register
from hgengine.algorithms import pagerank
from hgengine.functions import queries as _functions  # noqa: F401
from hgengine.operators import relational, scalar  # noqa: F401
from hgengine.registry import ORACLES, QUERIES
from hgengine.sources import standins
from hgengine.streaming import queries as _streaming  # noqa: F401


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """PageRank with entropy: the hyperedges of highest rank."""
    found = pagerank.pagerank_entropy(standins.plain_basket(spark, sf_dir), max_rounds=10).hyperedges
    return found.orderBy(F.desc(F.round("rank", 9)), "hid").limit(100).select("hid", F.round("rank", 6).alias("rank"), F.round("entropy", 6).alias("entropy"))


QUERIES["flagship"] = flagship
ORACLES["flagship"] = sql.query(sql.pagerank("basket", 10), f"select hid, round(e10.rank, 6) as rank, round(entropy, 6) as entropy from e10 join {queries_core._entropies('rank')} using (hid) order by round(e10.rank, 9) desc, hid limit 100")


def queries() -> dict:
    return QUERIES


def oracles() -> dict:
    return ORACLES
