"""How memberships lie on the cluster while rounds go over them: twice, by either id, or once, by a placement.

A layout is made once for a run and kept; no exchange is ever above it. With two copies, states go to the copy that is
dealt by their id, join and combine there, and partial messages go to their receivers. With a placement, states go to the
parts that have a replica, join and combine there, and partial messages go back: what travels is one row for each
replica, which is what placements lessen.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.programs import Combiner, Custom, Program

Combiners = dict[str, Combiner | Custom]


def messages(rows: DataFrame, incidence: DataFrame, program: Program, on: list[str], other: str, keep: tuple[str, ...] = ()) -> DataFrame:
    """other, keep, _msg_*: what senders (rows) say along memberships, before messages are combined."""
    fields = [c.alias(f"_msg_{n}") for n, c in program.emit.items()]
    if not program.by_receiver:
        return rows.select(*on, *fields).join(incidence.select(*dict.fromkeys((*on, other, *keep))), on).select(other, *keep, *(f"_msg_{n}" for n in program.emit))
    known = {*on, other, *keep}
    marked = incidence.select(*on, F.col(other).alias("_dst"), *(F.col(c).alias(f"_edge_{c}") for c in incidence.columns if c not in known))
    told = rows.join(marked, on)
    told = told if program.to is None else told.where(program.to)
    return told.select(F.col("_dst").alias(other), *keep, *fields)


#: Memberships of a partition below which more partitions cost rounds more than they save.
FEW_ROWS = 200_000


class TwoCopy:
    """Memberships dealt and sorted by vertex, and again by hyperedge."""

    def __init__(self, incidence: DataFrame, partitions: int | None = None) -> None:
        n = partitions or int(incidence.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        self.copies = {side: incidence.repartition(n, side).sortWithinPartitions(side).persist() for side in ("vid", "hid")}

    @classmethod
    def counted(cls, incidence: DataFrame) -> TwoCopy:
        """In fewer partitions if memberships, which are counted, are few; for many rounds."""
        n = int(incidence.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        return cls(incidence, min(n, 1 + incidence.count() // FEW_ROWS))

    def half_round(self, rows: DataFrame, program: Program, key: str, other: str, combine: Combiners) -> DataFrame:
        sent = messages(rows, self.copies[key], program, [key], other)
        return sent.groupBy(other).agg(*(combine[n].of(F.col(f"_msg_{n}")).alias(f"_msg_{n}") for n in program.emit))

    def release(self) -> None:
        for copy in self.copies.values():
            copy.unpersist()


class AsRead:
    """Memberships once, kept as they came: the naive plan, which shuffles them in each half round unless the states can
    be broadcast. A baseline."""

    def __init__(self, incidence: DataFrame) -> None:
        self.incidence = incidence.persist()

    def half_round(self, rows: DataFrame, program: Program, key: str, other: str, combine: Combiners) -> DataFrame:
        sent = messages(rows, self.incidence, program, [key], other)
        return sent.groupBy(other).agg(*(combine[n].of(F.col(f"_msg_{n}")).alias(f"_msg_{n}") for n in program.emit))

    def release(self) -> None:
        self.incidence.unpersist()


class Placed:
    """Memberships with part, dealt by it; routing tables of both sides, dealt by the id that states have."""

    def __init__(self, placed: DataFrame, parts: int) -> None:
        n = int(placed.sparkSession.conf.get("spark.sql.shuffle.partitions"))
        part = F.col("part").cast("int")
        self.parts = parts
        self.incidence = placed.withColumn("part", part).repartitionById(parts, F.col("part")).persist()
        self.routes = {side: self.incidence.select(side, "part").distinct().repartition(n, side).persist() for side in ("vid", "hid")}

    def half_round(self, rows: DataFrame, program: Program, key: str, other: str, combine: Combiners) -> DataFrame:
        if not program.by_receiver:  # only messages travel
            rows = rows.select(key, *(c.alias(f"_sent_{n}") for n, c in program.emit.items()))
            program = Program(emit={n: F.col(f"_sent_{n}") for n in program.emit})
        shipped = rows.join(self.routes[key], key).repartitionById(self.parts, F.col("part"))
        sent = messages(shipped, self.incidence, program, ["part", key], other, ("part",))
        partial = sent.groupBy("part", other).agg(*(combine[n].of(F.col(f"_msg_{n}")).alias(f"_msg_{n}") for n in program.emit))
        return partial.groupBy(other).agg(*(combine[n].again.of(F.col(f"_msg_{n}")).alias(f"_msg_{n}") for n in program.emit))

    def release(self) -> None:
        for kept in (self.incidence, *self.routes.values()):
            kept.unpersist()


Layout = TwoCopy | Placed | AsRead


def layout_of(hf: HyperFrame, placement=None, parts: int = 8) -> Layout:
    """Two copies, or the placement by a rule (or by a DataFrame of vid, hid, part) with the memberships' attributes."""
    if placement is None:
        return TwoCopy(hf.incidence)
    placed = placement if isinstance(placement, DataFrame) else placement.assign(hf, parts)
    if {*hf.incidence.columns} - {"vid", "hid", "multiplicity"}:
        placed = hf.incidence.join(placed.select("vid", "hid", "part"), ["vid", "hid"])
    return Placed(placed, parts)


def choose_layout(memberships: int, vertex_replicas: int, hyperedge_replicas: int, few: int = 1_000_000) -> str:
    """two_copy under a bound; else the cheapest by shipped rows."""
    if memberships < few:
        return "two_copy"
    costs = {"two_copy": vertex_replicas + hyperedge_replicas, "vertex_cut": 2 * vertex_replicas, "hyperedge_cut": 2 * hyperedge_replicas}
    return min(costs, key=costs.get)
