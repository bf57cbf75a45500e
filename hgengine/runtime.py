"""Alternating supersteps over a hypergraph.

A round is a hyperedge step and a vertex step. In each, the side that sent last has its messages joined to the
memberships and combined to one for each receiver (partial aggregates before the shuffle), and receivers replace their
attributes. Attributes that do not change stay in the tables and never travel in messages. States are written to the
shared folder every few rounds, which cuts the lineage and lets the planner see their sizes; memberships lie in a layout
(two copies, or a placement) that no round shuffles, and that is let go at the end.
"""

from __future__ import annotations

import re
import time
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from hgengine.model import HyperFrame
from hgengine.plans.layout import Combiners, Layout, TwoCopy, layout_of, messages
from hgengine.programs import Program, infer_combiners
from hgengine.session import BROADCAST_ROWS, cut


@dataclass
class RunResult:
    frame: HyperFrame
    #: round, seconds, active (vertices that send on) of each round that was counted
    history: list[dict] = field(default_factory=list)

    @property
    def rounds(self) -> int:
        return len(self.history)


def half_round(senders: DataFrame, incidence: DataFrame | Layout, program: Program, key: str, other: str, round_: int = 0, combine: Combiners | None = None) -> DataFrame:
    """other, _msg_*: the combined message of each receiver of senders (key, attributes, and _send if some are quiet)."""
    rows = senders.where("_send") if "_send" in senders.columns else senders
    rows = rows.withColumns({"_id": F.col(key), "_step": F.lit(round_)})
    combine = combine or program.combine or {}
    if missing := [n for n in program.emit if n not in combine]:
        plain = incidence if isinstance(incidence, DataFrame) else incidence.copies[key] if isinstance(incidence, TwoCopy) else incidence.incidence
        schema = messages(rows, plain, program, [key], other).schema
        combine = combine | infer_combiners(T.StructType([T.StructField(n, schema[f"_msg_{n}"].dataType) for n in missing]))
    if not isinstance(incidence, DataFrame):
        return incidence.half_round(rows, program, key, other, combine)
    sent = messages(rows, incidence, program, [key], other)
    return sent.groupBy(other).agg(*(combine[n].of(F.col(f"_msg_{n}")).alias(f"_msg_{n}") for n in program.emit))


def advance(nodes: DataFrame, messages: DataFrame, program: Program, key: str, round_: int, frontier: bool) -> DataFrame:
    """nodes after the step: attributes replaced, and with a frontier _send for those that go on."""
    joined = nodes.join(messages, key, "left").withColumns({"_id": F.col(key), "_step": F.lit(round_)})
    heard = F.coalesce(*(F.col(c).isNotNull() for c in messages.columns if c != key)) if len(messages.columns) == 2 else None
    new = {n: c.cast(nodes.schema[n].dataType) if n in nodes.columns else c for n, c in program.state.items()}
    if frontier:
        when = program.when if program.when is not None else (heard if heard is not None else F.lit(True))
        new["_send"] = F.coalesce(when, F.lit(False))
    keep = [c for c in nodes.columns if c not in new]
    return joined.select(*keep, *(c.alias(n) for n, c in new.items()))


def forgets(program: Program) -> bool:
    """Whether new attributes follow from messages and from attributes that never change."""
    return not any(re.search(rf"\b{re.escape(name)}\b", str(c)) for name in program.state for c in program.state.values())


def iterate(hf: HyperFrame, vertex: Program, hyperedge: Program, max_rounds: int, frontier: bool = False, active: Column | None = None, tol: tuple[str, float] | None = None, stop: Callable[[DataFrame], bool] | None = None, cut_every: int = 5, drop_last: bool = False, layout: Layout | None = None, placement=None, parts: int = 8) -> RunResult:
    """Run rounds until max_rounds; with a frontier, until no vertex sends; with tol=(attribute, bound), until no vertex's
    attribute changes by more; with stop, until it says so of the vertices.

    active: which vertices send first (all, if left out). drop_last: leave out the last vertex step, for results of
    hyperedges alone. placement: a rule or a DataFrame of vid, hid, part, on so many parts; else memberships lie in two
    copies. layout: one that is made already, and that the caller lets go."""
    counted = frontier or tol or stop
    vs, hs = hf.vertices, hf.hyperedges
    inc = layout or layout_of(hf, placement, parts)
    if frontier:
        vs = vs.withColumn("_send", F.lit(True) if active is None else F.coalesce(active, F.lit(False)))
    # a side that forgets starts each step from its first table, and the plan stays a chain; else the last state is read
    # twice, by its own step and by its messages, and is written each time
    fresh = {"vid": vs if forgets(vertex) and not frontier else None, "hid": hs if forgets(hyperedge) and not frontier else None}
    # rounds that keep all nodes keep their number: counted once, few are sent whole to the memberships, which then need no
    # exchange on that side
    few = {side: not counted and isinstance(inc, TwoCopy) and nodes.count() <= BROADCAST_ROWS for side, nodes in (("vid", vs), ("hid", hs))}
    told = {side: F.broadcast if yes else (lambda df: df) for side, yes in few.items()}
    result = RunResult(hf)
    for r in range(1, max_rounds + 1):
        began = time.perf_counter()
        hs = advance((hs if fresh["hid"] is None else fresh["hid"]).drop("_send"), half_round(told["vid"](vs), inc, vertex, "vid", "hid", r), hyperedge, "hid", r, frontier)
        if counted or fresh["hid"] is None or r % cut_every == 0 or r == max_rounds:
            hs = cut(hs)
        if drop_last and r == max_rounds and not counted:
            break
        before = vs
        vs = advance((vs if fresh["vid"] is None else fresh["vid"]).drop("_send"), half_round(told["hid"](hs), inc, hyperedge, "hid", "vid", r), vertex, "vid", r, frontier)
        row = {"round": r}
        if counted:
            vs = cut(vs)
            if frontier:
                row["active"] = vs.where("_send").count()
            if tol:
                row["change"] = before.select("vid", F.col(tol[0]).alias("_was")).join(vs, "vid").agg(F.max(F.abs(F.col(tol[0]) - F.col("_was")))).first()[0] or 0.0
        elif fresh["vid"] is None or r % cut_every == 0 or r == max_rounds:
            vs = cut(vs)
        result.history.append(row | {"seconds": time.perf_counter() - began})
        if row.get("active") == 0 or tol and row["change"] <= tol[1] or stop and stop(vs):
            break
    if layout is None:
        inc.release()
    result.frame = HyperFrame(vs.drop("_send"), hs.drop("_send"), hf.incidence)
    return result
