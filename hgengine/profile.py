"""Structural statistics of a hypergraph."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.placement.hashing import modular


def degrees(hf: HyperFrame) -> DataFrame:
    return hf.incidence.groupBy("vid").agg(F.count("*").alias("degree"))


def cardinalities(hf: HyperFrame) -> DataFrame:
    """Members of each hyperedge, 0 of an empty one."""
    found = hf.incidence.groupBy("hid").agg(F.count("*").alias("cardinality"))
    return hf.hyperedges.select("hid").join(found, "hid", "left").select("hid", F.coalesce("cardinality", F.lit(0)).cast("long").alias("cardinality"))


def summary(hf: HyperFrame, heavy: int = 100) -> DataFrame:
    """One row: sizes, extremes, means, memberships, pairs at most, and members above the heavy cutoff."""
    k, d = hf.incidence.groupBy("hid").agg(F.count("*").alias("k")), degrees(hf)
    edges = k.agg(F.count("*").alias("n_hyperedges"), F.max("k").alias("max_cardinality"), F.round(F.avg("k"), 6).alias("mean_cardinality"), F.sum("k").alias("n_incidence"), F.sum(F.expr("k * (k - 1) div 2")).cast("long").alias("pairs_upper"), F.count_if(F.col("k") > heavy).alias("heavy_hyperedges"))
    nodes = d.agg(F.count("*").alias("n_vertices"), F.max("degree").alias("max_degree"), F.round(F.avg("degree"), 6).alias("mean_degree"), F.count_if(F.col("degree") > heavy).alias("heavy_vertices"))
    # one row each
    return edges.crossJoin(nodes)


def handshake(hf: HyperFrame) -> DataFrame:
    d = degrees(hf).agg(F.sum("degree").alias("sum_degree"))
    k = cardinalities(hf).agg(F.sum("cardinality").alias("sum_cardinality"))
    return d.crossJoin(k).crossJoin(hf.incidence.agg(F.count("*").alias("n_incidence")))


def histogram(hf: HyperFrame) -> DataFrame:
    """Hyperedges by the whole part of log2 of their cardinality."""
    k = hf.incidence.groupBy("hid").agg(F.count("*").alias("k"))
    return k.groupBy(F.floor(F.log2("k")).cast("int").alias("bucket")).agg(F.count("*").alias("n"))


def pairwise_cost(hf: HyperFrame) -> DataFrame:
    """One row: memberships, pairs at most, and their ratio."""
    k = hf.incidence.groupBy("hid").agg(F.count("*").alias("k"))
    found = k.agg(F.sum("k").alias("incidences"), F.sum(F.expr("k * (k - 1) div 2")).cast("long").alias("pairs_upper"))
    return found.withColumn("ratio", F.round(F.col("pairs_upper") / F.col("incidences"), 6))


def distinct_pairs_estimate(hf: HyperFrame, one_in: int = 16) -> DataFrame:
    """One row: pairs_distinct_est. The neighbours of one vertex in so many, drawn by a hash of its id, are counted
    exactly; no pair of two other vertices is made."""
    inc = hf.incidence.select("vid", "hid")
    drawn = inc.where(modular(one_in, F.col("vid")) == 0)
    near = drawn.join(inc.withColumnRenamed("vid", "other"), "hid").where("vid <> other").select("vid", "other").distinct()
    return near.agg((F.count("*") * one_in / 2).alias("pairs_distinct_est"))


def rank_error(found: DataFrame, exact: DataFrame, key: str = "vid", value: str = "rank", top: int = 100) -> DataFrame:
    """One row: the sum and the largest of the absolute differences, and the share of the first ones that both have."""
    both = found.select(key, F.col(value).alias("_a")).join(exact.select(key, F.col(value).alias("_b")), key)
    gap = F.abs(F.col("_a") - F.col("_b"))
    sums = both.agg(F.sum(gap).alias("l1"), F.max(gap).alias("largest"))
    first = [df.orderBy(F.desc(F.round(value, 9)), key).limit(top).select(key) for df in (found, exact)]
    # one row each
    return sums.crossJoin(first[0].join(first[1], key).agg((F.count("*") / top).alias("top_share")))
