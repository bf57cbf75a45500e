"""The plain graph model: distinct pairs without the groups they come from."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.pairwise import MOST_PAIRS, to_pairwise
from hgengine.session import cut


def dyadic_pagerank(hf: HyperFrame, alpha: float = 0.15, max_rounds: int = 30, most_pairs: int = MOST_PAIRS) -> DataFrame:
    """vid, rank over distinct undirected pairs of weight 1."""
    pairs = to_pairwise(hf, {"n": F.count("*")}, most_pairs, directed=True).select("src", "dst").persist()
    degree = pairs.groupBy(F.col("src").alias("vid")).agg(F.count("*").alias("_degree"))
    vs = hf.vertices.select("vid", F.lit(1.0).alias("rank")).join(degree, "vid", "left").persist()
    for r in range(1, max_rounds + 1):
        sent = vs.select(F.col("vid").alias("src"), (F.col("rank") / F.col("_degree")).alias("_sent")).join(pairs, "src")
        heard = sent.groupBy(F.col("dst").alias("vid")).agg(F.sum("_sent").alias("_heard"))
        vs = vs.join(heard, "vid", "left").select("vid", (alpha + (1 - alpha) * F.coalesce("_heard", F.lit(0.0))).alias("rank"), "_degree")
        if r % 4 == 0 and r < max_rounds:
            vs = cut(vs)
    return vs.select("vid", "rank")
