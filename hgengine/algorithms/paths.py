"""Shortest paths by a frontier: only nodes that improved send on."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.plans.layout import TwoCopy
from hgengine.programs import Combiner, Program, edge, msg, nid, state
from hgengine.runtime import RunResult, iterate
from hgengine.session import cut


def programs(cost: Column) -> tuple[Program, Program]:
    """hops and parent of both sides; a vertex adds the cost of each hyperedge it sends to."""
    better = msg("best")["hops"] < F.coalesce(state("hops"), F.lit(float("inf")))
    told = {"hops": F.when(better, msg("best")["hops"]).otherwise(state("hops")), "parent": F.when(better, msg("best")["by"]).otherwise(state("parent"))}
    sent = lambda hops: {"best": F.struct(hops.alias("hops"), nid().alias("by"))}
    return Program(emit=sent(state("hops") + cost), state=told, when=better, combine={"best": Combiner.MIN}), Program(emit=sent(state("hops")), state=told, when=better, combine={"best": Combiner.MIN})


def run(hf: HyperFrame, source: int | Column, max_rounds: int | None = None, weight: str | None = None, keep_parent: bool = False, stop=None, **layout) -> RunResult:
    """hops of both sides: hyperedges traversed from the source, or the sum of their weights; null if unreached.

    source: a vertex id, or a condition on vertices. weight: a column of the hyperedges. keep_parent: the hyperedge (of
    a vertex) or vertex (of a hyperedge) that the best path comes through, the smallest of equals."""
    at_source = F.col("vid") == source if isinstance(source, int) else source
    inc, cost = hf.incidence.select("vid", "hid"), F.lit(1.0)
    if weight is not None:
        inc, cost = inc.join(hf.hyperedges.select("hid", F.col(weight).cast("double").alias("cost")), "hid"), edge("cost")
    vertex, hyperedge = programs(cost)
    none = F.lit(None).cast("long").alias("parent")
    start = HyperFrame(hf.vertices.select("vid", F.when(at_source, 0.0).alias("hops"), none), hf.hyperedges.select("hid", F.lit(None).cast("double").alias("hops"), none), inc)
    result = iterate(start, vertex, hyperedge, max_rounds or 1_000_000, frontier=True, active=F.col("hops").isNotNull(), stop=stop, **layout)
    keep = ["hops", "parent"] if keep_parent else ["hops"]
    result.frame = HyperFrame(result.frame.vertices.select("vid", *keep), result.frame.hyperedges.select("hid", *keep), hf.incidence)
    return result


def shortest_paths(hf: HyperFrame, source: int | Column, **options) -> HyperFrame:
    return run(hf, source, **options).frame


def multi_source(hf: HyperFrame, sources: list[int], weight: str | None = None) -> DataFrame:
    """source, vid, hops of a few landmarks, in one frontier run: a node keeps the hops from each source that reached it,
    and its row of a source sends on when that one improved."""
    layout = TwoCopy(hf.incidence.select("vid", "hid"))
    spark = hf.incidence.sparkSession
    costs = hf.hyperedges.select("hid", (F.lit(1.0) if weight is None else F.col(weight).cast("double")).alias("_cost"))
    starts = spark.createDataFrame([(int(s),) for s in sources], "source long")
    front = cut(starts.join(hf.vertices.select(F.col("vid").alias("source")), "source").select("source", F.col("source").alias("vid"), F.lit(0.0).alias("hops")))
    best = {"vid": front, "hid": None}
    while front.limit(1).count():
        for key, other in (("vid", "hid"), ("hid", "vid")):
            told = layout.copies[key].join(front, key).groupBy("source", other).agg(F.min("hops").alias("_new"))
            if other == "hid":
                told = told.join(costs, "hid").select("source", "hid", (F.col("_new") + F.col("_cost")).alias("_new"))
            known = best[other]
            both = told.withColumn("hops", F.lit(None).cast("double")) if known is None else known.join(told, ["source", other], "full")
            both = cut(both.select("source", other, F.least("hops", "_new").alias("hops"), F.coalesce(F.col("_new") < F.coalesce("hops", F.lit(float("inf"))), F.lit(False)).alias("_send")))
            best[other], front = both.drop("_send"), both.where("_send").drop("_send")
    layout.release()
    every = hf.vertices.select("vid").crossJoin(F.broadcast(starts))  # a few landmarks, given as a list
    return every.join(best["vid"], ["source", "vid"], "left").select("source", "vid", "hops")


def separation(hf: HyperFrame, a: int, b: int) -> float | None:
    """Hops between two vertices; the run ends when the target is reached."""
    reached = lambda vs: vs.where((F.col("vid") == b) & F.col("hops").isNotNull()).limit(1).count() > 0
    row = run(hf, a, stop=reached).frame.vertices.where(F.col("vid") == b).first()
    return row["hops"] if row else None


def harmonic_centrality(hf: HyperFrame, sources: list[int]) -> DataFrame:
    """vid, value: the sum over other landmarks of 1 / hops; unreached add 0."""
    found = multi_source(hf, sources)
    return found.groupBy("vid").agg(F.coalesce(F.sum(F.when(F.col("hops") > 0, 1 / F.col("hops"))), F.lit(0.0)).alias("value"))


def eigenvector_centrality(hf: HyperFrame, rounds: int = 10, weight: str | None = None) -> DataFrame:
    """vid, value: the power iteration on the memberships. A hyperedge has the sum of its members' values (times its
    weight), a vertex the sum of its hyperedges'; values are divided by their largest after each round."""
    w = F.lit(1.0) if weight is None else F.col("_weight")
    hs = hf.hyperedges.select("hid", (F.lit(1.0) if weight is None else F.col(weight).cast("double")).alias("_weight"), F.lit(None).cast("double").alias("value"))
    vertex = Program(emit={"value": state("value")}, state={"value": F.coalesce(msg("value"), F.lit(0.0))}, combine={"value": Combiner.SUM})
    hyperedge = Program(emit={"value": state("value")}, state={"value": w * msg("value")}, combine={"value": Combiner.SUM})
    now, layout = HyperFrame(hf.vertices.select("vid", F.lit(1.0).alias("value")), hs, hf.incidence), TwoCopy(hf.incidence.select("vid", "hid"))
    for _ in range(rounds):
        found = iterate(now, vertex, hyperedge, 1, layout=layout).frame
        top = found.vertices.agg(F.max("value")).first()[0] or 1.0
        now = HyperFrame(found.vertices.withColumn("value", F.col("value") / top), hs, hf.incidence)
    layout.release()
    return now.vertices


def degree_centrality(hf: HyperFrame, weight: str = "weight") -> DataFrame:
    """vid, value: the sum of the weights of a vertex's hyperedges."""
    return hf.incidence.join(hf.hyperedges.select("hid", F.col(weight).alias("_w")), "hid").groupBy("vid").agg(F.sum("_w").alias("value"))
