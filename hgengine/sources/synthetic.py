"""A data source of memberships, synthetic with a chosen skew or from a folder, for spark.read.format("hypergraph")."""

from __future__ import annotations

from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
import pyarrow.parquet as pq
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType


class SyntheticHypergraph(DataSource):
    """Options: vertices, hyperedges, mean (members), skew (exponent of vertex popularity, 0 even), partitions, seed.

    path: a folder of Parquet files of vid and hid, on a disk that driver and executors share; a file is a partition, the other
    options do not matter then.

    draw: random, or modular, whose member j of hyperedge h is (7 h + 13 j) mod vertices, for results known beforehand."""

    @classmethod
    def name(cls) -> str:
        return "hypergraph"

    def schema(self) -> str:
        return "vid long, hid long"

    def reader(self, schema: StructType) -> DataSourceReader:
        return _Files(self.options["path"]) if "path" in self.options else _Reader(self.options)


class _File(InputPartition):
    def __init__(self, path: str) -> None:
        self.path = path


class _Files(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.folder = Path(path.removeprefix("file:"))
        if not self.folder.is_dir():
            raise ValueError(f"{path} is not a folder that Python can open")

    def partitions(self) -> list[InputPartition]:
        return [_File(str(p)) for p in sorted(self.folder.glob("*.parquet"))]

    def read(self, partition: InputPartition) -> Iterator[pa.RecordBatch]:
        yield from pq.ParquetFile(partition.path).iter_batches(columns=["vid", "hid"])


class _Reader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.n, self.m = int(options.get("vertices", 1000)), int(options.get("hyperedges", 1000))
        self.mean, self.skew = float(options.get("mean", 5)), float(options.get("skew", 0))
        self.parts, self.seed = int(options.get("partitions", 4)), int(options.get("seed", 1))
        self.modular = options.get("draw", "random") == "modular"

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        draw = np.random.default_rng((self.seed, partition.value))
        for hid in range(partition.value, self.m, self.parts):
            if self.modular:
                yield from ((vid, hid) for vid in sorted({(7 * hid + 13 * j) % self.n for j in range(int(self.mean))}))
                continue
            size = min(self.n, 1 + draw.poisson(self.mean - 1))
            members = np.unique((self.n * draw.random(size) ** (1 + self.skew)).astype(int))
            for vid in members.tolist():
                yield vid, hid
