"""PageRank on vertices and hyperedges, with the entropy of members' ranks, and the walk with restart."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.plans.layout import Layout, layout_of
from hgengine.programs import Combiner, Program, msg, state
from hgengine.runtime import RunResult, half_round, iterate
from hgengine.session import cut


def prepared(hf: HyperFrame, weight: str | None = "weight", init: str = "exact", restart: Column | None = None) -> HyperFrame:
    """hf with what never changes: a vertex's total weight and restart share, a hyperedge's weight and cardinality."""
    w = F.lit(1.0) if weight is None else F.col(weight).cast("double")
    hs = hf.hyperedges.select("hid", w.alias("_weight")).join(hf.incidence.groupBy("hid").agg(F.count("*").cast("double").alias("_size")), "hid", "left")
    totals = hf.incidence.join(hs.select("hid", "_weight"), "hid").groupBy("vid").agg(F.sum("_weight").alias("_total"))
    vs = hf.vertices.select("vid", (F.lit(1.0) if restart is None else restart.cast("double")).alias("_restart")).join(totals, "vid", "left")
    # the literal start knows no weight yet and sends the whole rank
    vs = vs.withColumns({"rank": F.lit(1.0), "_share": F.lit(1.0) if init == "message" else F.col("_total")})
    return HyperFrame(cut(vs), cut(hs.withColumn("rank", F.lit(None).cast("double"))), hf.incidence)


def programs(alpha: float) -> tuple[Program, Program]:
    vertex = Program(emit={"part": state("rank") / state("_share")}, state={"rank": state("_restart") * alpha + (1 - alpha) * F.coalesce(msg("part"), F.lit(0.0)), "_share": state("_total")}, combine={"part": Combiner.SUM})
    hyperedge = Program(emit={"part": state("rank") / state("_size")}, state={"rank": state("_weight") * msg("part")}, combine={"part": Combiner.SUM})
    return vertex, hyperedge


def run(hf: HyperFrame, alpha: float = 0.15, max_rounds: int = 30, tol: float | None = None, init: str = "exact", weight: str | None = "weight", restart: Column | None = None, only_hyperedges: bool = False, cut_every: int = 5, **layout) -> RunResult:
    """layout: placement and parts, or a layout, as iterate takes them."""
    vertex, hyperedge = programs(alpha)
    return iterate(prepared(hf, weight, init, restart), vertex, hyperedge, max_rounds, tol=("rank", tol) if tol else None, drop_last=only_hyperedges, cut_every=cut_every, **layout)


def pagerank(hf: HyperFrame, **options) -> HyperFrame:
    """rank on both sides. alpha is the restart share."""
    found = run(hf, **options).frame
    return HyperFrame(found.vertices.select("vid", "rank"), found.hyperedges.select("hid", "rank"), hf.incidence)


def entropy_of(hf: HyperFrame, ranks: DataFrame, form: str = "algebraic", layout: Layout | None = None) -> DataFrame:
    """hid, entropy in bits of the members' values normalised to 1; null for no members or a sum of 0.

    ranks: vid, value. The algebraic form adds two sums; the sequence form gathers every member's value."""
    if form == "sequence":
        sent = half_round(ranks, layout or hf.incidence, Program(emit={"values": F.array("value")}, combine={"values": Combiner.CONCAT}), "vid", "hid")
        total = F.aggregate("_msg_values", F.lit(0.0), lambda s, x: s + x)
        bits = F.aggregate(F.col("_msg_values"), F.lit(0.0), lambda s, x: s + F.when(x > 0, x / F.col("_total") * F.log2(x / F.col("_total"))).otherwise(0.0))
        return sent.withColumn("_total", total).select("hid", F.when(F.col("_total") > 0, -bits).alias("entropy"))
    logs = F.when(F.col("value") > 0, F.col("value") * F.log2("value")).otherwise(0.0)
    sums = half_round(ranks, layout or hf.incidence, Program(emit={"s": F.col("value"), "t": logs}), "vid", "hid")
    return sums.select("hid", F.when(F.col("_msg_s") > 0, F.log2("_msg_s") - F.col("_msg_t") / F.col("_msg_s")).alias("entropy"))


def pagerank_entropy(hf: HyperFrame, alpha: float = 0.15, max_rounds: int = 30, entropy_on: str = "rank", form: str = "algebraic", evenness: bool = False, weight: str | None = "weight", placement=None, parts: int = 8) -> HyperFrame:
    """As pagerank; hyperedges get the entropy of the ranks their members sent in the last round, and on wish evenness:
    entropy over the log of the cardinality, null for one member. It feeds nothing, so the last round alone computes it."""
    vertex, hyperedge = programs(alpha)
    ready, layout = prepared(hf, weight), layout_of(hf, placement, parts)
    before = iterate(ready, vertex, hyperedge, max_rounds - 1, layout=layout).frame if max_rounds > 1 else ready
    value = F.col("rank") if entropy_on == "rank" else F.col("rank") / F.col("_total")
    found = iterate(before, vertex, hyperedge, 1, layout=layout).frame
    hs = cut(found.hyperedges.join(entropy_of(hf, before.vertices.select("vid", value.alias("value")), form, layout), "hid", "left"))
    layout.release()
    columns = ["hid", "rank", "entropy"]
    if evenness:
        hs = hs.withColumn("evenness", F.when(F.col("_size") > 1, F.col("entropy") / F.log2("_size")))
        columns.append("evenness")
    return HyperFrame(found.vertices.select("vid", "rank"), hs.select(*columns), hf.incidence)


def random_walk(hf: HyperFrame, seeds: DataFrame, restart: float = 0.15, max_rounds: int = 30) -> HyperFrame:
    """Walk that returns to the seeds (vid): their restart shares are equal and add to the number of vertices."""
    n, m = hf.vertices.count(), max(1, seeds.count())
    vs = hf.vertices.join(seeds.select("vid").distinct().withColumn("_seed", F.lit(True)), "vid", "left")
    marked = HyperFrame(vs, hf.hyperedges, hf.incidence)
    return pagerank(marked, alpha=restart, max_rounds=max_rounds, restart=F.when(F.col("_seed"), n / m).otherwise(0.0))


def summary_of_members(hf: HyperFrame, values: DataFrame, **aggregates: Column) -> DataFrame:
    """hid and any aggregates of the members' attributes. values: vid, attributes."""
    return hf.incidence.select("vid", "hid").join(values, "vid").groupBy("hid").agg(*(c.alias(n) for n, c in aggregates.items()))
