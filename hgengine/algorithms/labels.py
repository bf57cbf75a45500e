"""Label propagation by the largest, smallest or most frequent label, and components."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.plans.layout import TwoCopy
from hgengine.programs import Combiner, Program, msg, state
from hgengine.runtime import RunResult, iterate
from hgengine.session import cut


def program(rule: str = "max") -> Program:
    """Of either side: the best label heard so far; a node whose label changed sends on."""
    pick, better = (F.greatest, lambda a, b: a > b) if rule == "max" else (F.least, lambda a, b: a < b)
    new = pick(state("label"), msg("label"))  # nulls are passed over
    changed = better(msg("label"), F.coalesce(state("label"), F.lit(-(2**63)).cast("long") if rule == "max" else F.lit(2**63 - 1).cast("long")))
    return Program(emit={"label": state("label")}, state={"label": new}, when=changed, combine={"label": Combiner.MAX if rule == "max" else Combiner.MIN})


def whole_rounds(rule: str = "max") -> tuple[Program, Program]:
    """The same labels in rounds where all nodes send. A node's own label is then among those that its hyperedges picked, and
    theirs only get better, so messages alone tell the next labels: no state is read twice, and rounds stay a chain."""
    told = program(rule)
    return Program(emit=told.emit, state={"label": F.coalesce(msg("label"), F.col("vid"))}, combine=told.combine), Program(emit=told.emit, state={"label": msg("label")}, combine=told.combine)


def run(hf: HyperFrame, max_rounds: int = 30, until_stable: bool = True, rule: str = "max", **layout) -> RunResult:
    """Labels start as vertex ids; a node without a message keeps its label. Until stable, only changed nodes send."""
    start = HyperFrame(hf.vertices.select("vid", F.col("vid").alias("label")), hf.hyperedges.select("hid", F.lit(None).cast("long").alias("label")), hf.incidence)
    if until_stable:
        return iterate(start, program(rule), program(rule), max_rounds, frontier=True, **layout)
    own = None if layout.get("layout") or layout.get("placement") is not None else TwoCopy.counted(hf.incidence)
    found = iterate(start, *whole_rounds(rule), max_rounds, **(layout | {"layout": own} if own else layout))
    if own:
        own.release()
    return found


def _majority(rows: DataFrame, to: str) -> DataFrame:
    """The most frequent label of each receiver, the smallest of equals."""
    counts = rows.groupBy(to, "label").agg(F.count("*").alias("_n"))
    return counts.groupBy(to).agg(F.max_by("label", F.struct("_n", -F.col("label"))).alias("label"))


def majority(hf: HyperFrame, rounds: int) -> HyperFrame:
    """Synchronous rounds of most frequent labels; they may swing, so their number is fixed."""
    layout = TwoCopy(hf.incidence.select("vid", "hid"))
    vs = hf.vertices.select("vid", F.col("vid").alias("label"))
    hs = None
    for _ in range(rounds):
        hs = cut(_majority(layout.copies["vid"].join(vs, "vid"), "hid"))
        told = _majority(layout.copies["hid"].join(hs, "hid"), "vid").withColumnRenamed("label", "_new")
        vs = cut(vs.join(told, "vid", "left").select("vid", F.coalesce("_new", "label").alias("label")))
    layout.release()
    return HyperFrame(vs, hf.hyperedges.select("hid").join(hs, "hid", "left"), hf.incidence)


def label_propagation(hf: HyperFrame, max_rounds: int = 30, until_stable: bool = True, rule: str = "max", **layout) -> HyperFrame:
    """layout: placement and parts, or a layout, as iterate takes them."""
    return majority(hf, max_rounds) if rule == "majority" else run(hf, max_rounds, until_stable, rule, **layout).frame


def components(hf: HyperFrame, method: str = "label", max_rounds: int = 1_000_000) -> DataFrame:
    """vid, component: the largest vertex id that memberships reach. By labels in diameter-many rounds, or in two phases
    with pointer jumping, where rounds grow with the logarithm of the diameter."""
    if method == "label":
        return label_propagation(hf, max_rounds).vertices.select("vid", F.col("label").alias("component"))
    layout = TwoCopy(hf.incidence.select("vid", "hid"))
    vs = cut(hf.vertices.select("vid", F.col("vid").alias("component")))
    while True:
        tops = layout.copies["vid"].join(vs, "vid").groupBy("hid").agg(F.max("component").alias("_top"))
        heard = layout.copies["hid"].join(tops, "hid").groupBy("vid").agg(F.max("_top").alias("_top"))
        hooked = vs.join(heard, "vid", "left").select("vid", F.col("component").alias("_was"), F.greatest("component", "_top").alias("component"))
        told = hooked.groupBy(F.col("_was").alias("vid")).agg(F.max("component").alias("_via"))
        hooked = cut(hooked.join(told, "vid", "left").select("vid", "_was", F.greatest("component", "_via").alias("component")))
        jump = hooked.select(F.col("vid").alias("component"), F.col("component").alias("_up"))
        new = cut(hooked.join(jump, "component", "left").select("vid", "_was", F.greatest("component", "_up").alias("component")))
        if not new.where("component <> _was").limit(1).count():
            layout.release()
            return new.select("vid", "component")
        vs = new.select("vid", "component")
