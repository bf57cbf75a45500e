"""Shared pieces of the training-data operators: table access, lineage cuts, hashing of words."""

from __future__ import annotations

import gc
import re

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hgengine.session import cut, scratch, ship, small

#: Most bytes of an Arrow batch: long texts make few rows, ids many.
BATCH_BYTES = "8m"

#: Bytes [\x20\x09-\x0D] as a pattern of Spark's regular expressions.
SPACE = r"[\x20\x09-\x0D]"
NOT_SPACE = r"[^\x20\x09-\x0D]"


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    ship(spark)
    spark.conf.set("spark.sql.execution.arrow.maxBytesPerBatch", BATCH_BYTES)
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def filtered(docs: DataFrame, keeps) -> DataFrame:
    """docs of which keeps, called with the list of a batch's texts, is true: one pass, no join and no shuffle."""
    at = docs.columns.index("text")

    def run(batches):
        for batch in batches:
            yield batch.filter(pa.array(keeps(batch.column(at).to_pylist()), pa.bool_()))

    return docs.mapInArrow(run, docs.schema)


def free(docs: DataFrame, name: str) -> str:
    """name, or a longer one that is not a column of docs."""
    taken = {c.lower() for c in docs.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def released(spark: SparkSession) -> None:
    """Let go of the shuffle files of steps that are over: Spark drops them when the driver's garbage is collected, which may be long after."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


MIX = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)


def mixed(x: np.ndarray) -> np.ndarray:
    """Spread 64-bit values (the finaliser of a known generator)."""
    x = x + MIX[0]
    x = (x ^ (x >> np.uint64(30))) * MIX[1]
    x = (x ^ (x >> np.uint64(27))) * MIX[2]
    return x ^ (x >> np.uint64(31))


def shingles(hashes: np.ndarray, k: int) -> np.ndarray:
    """Hash of each run of k words, in order; a shorter text is one shingle; no words, none."""
    n = len(hashes)
    if n == 0:
        return hashes
    size = min(k, n)
    h = np.full(n - size + 1, size, np.uint64)
    for i in range(size):
        h = h * MIX[1] + hashes[i : n - size + 1 + i]
    return mixed(h)


def encoded(text: str | None) -> bytes:
    return b"" if text is None else text.encode("utf-8", "surrogatepass")


_BASE = 0xD1342543DE82EF95
_BLOCK = 1 << 22
_ANY_SPACE = re.compile(rb"[\x20\x09-\x0D]")
_SPACES = np.isin(np.arange(256), [32, *range(9, 14)])
#: A value of each byte; A-Z have those of a-z.
_VALUES = np.random.default_rng(20240101).integers(1, 1 << 63, 256, dtype=np.uint64)
_VALUES[65:91] = _VALUES[97:123]
_powers: list[np.ndarray] = []


def _power(n: int) -> list[np.ndarray]:
    """Powers of the base and of its inverse modulo 2 ** 64, at least n of them."""
    if not _powers or len(_powers[0]) < n:
        tables = []
        for x in (_BASE, pow(_BASE, -1, 1 << 64)):
            table = np.full(1 << max(16, int(n).bit_length()), x, np.uint64)
            table[0] = 1
            tables.append(np.multiply.accumulate(table))
        _powers[:] = tables
    return _powers


def hashed_words(text: str | None) -> np.ndarray:
    r"""64-bit hashes of the words [^\x20\x09-\x0D]+ of a text, A-Z as a-z, in order: no word becomes an object."""
    raw = encoded(text)
    if len(raw) > _BLOCK:  # in blocks that end at a space
        parts, at = [], 0
        while at < len(raw):
            m = _ANY_SPACE.search(raw, at + _BLOCK)
            end = m.start() if m else len(raw)
            parts.append(_hashed(raw[at:end]))
            at = end
        return np.concatenate(parts)
    return _hashed(raw)


def _hashed(raw: bytes) -> np.ndarray:
    x = np.frombuffer(raw, np.uint8)
    gaps = np.ones(len(x) + 2, np.int8)
    gaps[1:-1] = _SPACES[x]
    steps = np.diff(gaps)
    starts, ends = np.nonzero(steps == -1)[0], np.nonzero(steps == 1)[0]
    forth, back = _power(len(x) + 1)
    sums = np.zeros(len(x) + 1, np.uint64)
    np.cumsum(_VALUES[x] * forth[: len(x)], out=sums[1:])
    return mixed((sums[ends] - sums[starts]) * back[starts] + (ends - starts).astype(np.uint64))


def signed(x: np.ndarray) -> np.ndarray:
    return x.view(np.int64)


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of each node of edges (a, b): root is the smallest node reachable.

    Each round hooks every node to the smallest label among its neighbours and then jumps pointers, all by aggregates
    that combine before the shuffle; rounds grow with the logarithm of the longest path. Each round is written to the
    shared folder.
    """
    both = cut(edges.select("a", "b").unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).where("a <> b").distinct())
    labels = cut(both.groupBy(F.col("a").alias("node")).agg(F.least(F.min("b"), F.first("a")).alias("root")))
    while True:
        near = both.join(labels.select(F.col("node").alias("b"), F.col("root").alias("r")), "b").select(F.col("a").alias("node"), "r")
        hooked = near.unionByName(labels.select("node", F.col("root").alias("r"))).groupBy("node").agg(F.min("r").alias("root"))
        # what a node learns, its old root learns too
        told = hooked.join(labels.withColumnRenamed("root", "was"), "node").groupBy(F.col("was").alias("node")).agg(F.min("root").alias("via"))
        hooked = hooked.join(told, "node", "left").select("node", F.least("root", F.coalesce("via", "root")).alias("root"))
        jump = hooked.select(F.col("node").alias("root"), F.col("root").alias("up"))
        new = cut(hooked.join(jump, "root", "left").select("node", F.least("root", F.coalesce("up", "root")).alias("root")))
        changed = new.join(labels.withColumnRenamed("root", "was"), "node").where("root <> was").limit(1).count()
        labels = new
        if not changed:
            return labels




__all__ = ["cut", "scratch", "small"]
