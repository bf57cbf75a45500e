"""Placements of memberships on parts.

A rule of single memberships gives the part as a column. A rule of the whole hypergraph gives it as a DataFrame; greedy
rules place one side whole, hyperedge by hyperedge: each goes where most of its members were hashed, less the root of
the part's load. `dual` rules do the same with the sides exchanged.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.placement.hashing import HASHES
from hgengine.session import cut, ship, small


@dataclass(frozen=True)
class EdgeRule:
    """part of a membership from its two ids."""

    name: str
    part: Callable[[Column, Column, int, Callable], Column]
    hash: str = "mixed"

    def assign(self, hf: HyperFrame, parts: int) -> DataFrame:
        return hf.incidence.select("vid", "hid", self.part(F.col("vid"), F.col("hid"), parts, HASHES[self.hash]).alias("part"))


def random_vertex_cut(hash: str = "mixed") -> EdgeRule:
    """Hyperedges whole, vertices cut."""
    return EdgeRule("random_vertex", lambda v, h, p, of: of(p, h), hash)


def random_hyperedge_cut(hash: str = "mixed") -> EdgeRule:
    """Vertices whole, hyperedges cut."""
    return EdgeRule("random_hyperedge", lambda v, h, p, of: of(p, v), hash)


def random_both_cut(hash: str = "mixed") -> EdgeRule:
    return EdgeRule("random_both", lambda v, h, p, of: of(p, v, h), hash)


def grid_cut(hash: str = "mixed") -> EdgeRule:
    """Parts as a grid: a vertex is in one column and a hyperedge in one row, so replicas are at most about the root."""

    def part(v: Column, h: Column, p: int, of: Callable) -> Column:
        rows = max(k for k in range(1, int(p**0.5) + 1) if p % k == 0)
        return (of(rows, h) * (p // rows) + of(p // rows, v)).cast("int")

    return EdgeRule("grid", part, hash)


@dataclass(frozen=True)
class HybridCut:
    """Hyperedges whole by hash, but those of more members than the cutoff are cut by the hash of their vertices."""

    cutoff: int = 100
    hash: str = "mixed"
    name: str = "hybrid_vertex"

    def assign(self, hf: HyperFrame, parts: int) -> DataFrame:
        of = HASHES[self.hash]
        heavy = hf.incidence.groupBy("hid").agg(F.count("*").alias("n")).where(F.col("n") > self.cutoff).select("hid", F.lit(True).alias("_heavy"))
        # heavy ones are at most memberships / cutoff; the planner broadcasts them if they are small
        rows = hf.incidence.select("vid", "hid").join(heavy, "hid", "left")
        return rows.select("vid", "hid", F.when(F.col("_heavy"), of(parts, F.col("vid"))).otherwise(of(parts, F.col("hid"))).alias("part"))


def overlap(hf: HyperFrame, parts: int, hash: str = "mixed") -> DataFrame:
    """hid, part, overlap: members of each hyperedge that the hash puts on each part."""
    return hf.incidence.groupBy("hid", HASHES[hash](parts, F.col("vid")).alias("part")).agg(F.count("*").alias("overlap"))


def _choose(parts: int, load_unit: str, scale: int, base: np.ndarray | None = None):
    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        load = np.zeros(parts) if base is None else base.astype(float).copy()
        for pdf in batches:
            out = np.empty(len(pdf), np.int32)
            for i, (on, n) in enumerate(zip(pdf["on"], pdf["n"], strict=True)):
                score = -np.sqrt(load)
                score[np.asarray(on, int)] += np.asarray(n, float)
                out[i] = best = int(np.argmax(score))  # the first of equals
                load[best] += scale * {"hyperedges": 1, "incidences": sum(n), "frozen": 0}[load_unit]
            yield pd.DataFrame({"hid": pdf["hid"], "part": out})

    return run


@dataclass(frozen=True)
class GreedyCut:
    """mode exact: one stream in the order of ids, for as many hyperedges as one task takes. streams: that many streams
    side by side, each with its own loads taken times their number. epochs: slices of ids one after another, loads
    summed between them. load_unit: what a placed hyperedge adds to the load."""

    load_unit: str = "hyperedges"
    mode: str = "exact"
    streams: int = 8
    epochs: int = 4
    hash: str = "mixed"
    name: str = "greedy_vertex"

    def choose(self, hf: HyperFrame, parts: int, base: np.ndarray | None = None) -> DataFrame:
        """hid, part."""
        ship(hf.incidence.sparkSession)
        gathered = overlap(hf, parts, self.hash).groupBy("hid").agg(F.sort_array(F.collect_list(F.struct("part", "overlap"))).alias("o"))
        rows = gathered.select("hid", F.col("o.part").alias("on"), F.col("o.overlap").alias("n"))
        if self.mode == "exact":
            return rows.repartition(1).sortWithinPartitions("hid").mapInPandas(_choose(parts, self.load_unit, 1, base), "hid long, part int")
        of = HASHES[self.hash]
        stream = of(self.streams, F.col("hid"))
        if self.mode == "streams":
            dealt = rows.repartitionById(self.streams, stream).sortWithinPartitions("hid")
            return dealt.mapInPandas(_choose(parts, self.load_unit, self.streams, base), "hid long, part int")
        rows = cut(rows.withColumn("_epoch", of(self.epochs, F.col("hid"), F.lit(1))))
        load, out = np.zeros(parts) if base is None else base.astype(float), None
        for e in range(self.epochs):
            dealt = rows.where(F.col("_epoch") == e).drop("_epoch").repartitionById(self.streams, stream).sortWithinPartitions("hid")
            slice_ = cut(dealt.mapInPandas(_choose(parts, self.load_unit, self.streams, load), "hid long, part int"))
            unit = F.count("*") if self.load_unit == "hyperedges" else F.sum(F.size("n")) if self.load_unit == "frozen" else F.sum(F.aggregate("n", F.lit(0).cast("long"), lambda s, x: s + x))
            if self.load_unit != "frozen":
                for row in slice_.join(rows, "hid").groupBy("part").agg(unit.alias("load")).collect():  # a row of each part
                    load[row.part] += row.load
            out = slice_ if out is None else out.unionByName(slice_)
        return out

    def assign(self, hf: HyperFrame, parts: int) -> DataFrame:
        return hf.incidence.select("vid", "hid").join(self.choose(hf, parts), "hid").select("vid", "hid", "part")


@dataclass(frozen=True)
class GreedyHybridCut:
    """Greedy for hyperedges up to the cutoff; heavier ones are cut by the hash of their vertices and count as load."""

    cutoff: int = 100
    greedy: GreedyCut = GreedyCut()
    name: str = "greedy_hybrid"

    def assign(self, hf: HyperFrame, parts: int) -> DataFrame:
        sizes = hf.incidence.groupBy("hid").agg(F.count("*").alias("_n"))
        heavy = cut(sizes.where(F.col("_n") > self.cutoff).select("hid"))
        light = replace_incidence(hf, hf.incidence.join(small(heavy), "hid", "left_anti"))
        cut_rows = hf.incidence.select("vid", "hid").join(small(heavy), "hid", "left_semi").withColumn("part", HASHES[self.greedy.hash](parts, F.col("vid")))
        mean = sizes.where(F.col("_n") <= self.cutoff).agg(F.avg("_n")).first()[0] or 1.0
        base = np.zeros(parts)
        for row in cut_rows.groupBy("part").count().collect():  # a row of each part
            base[row["part"]] = row["count"] / mean
        chosen = self.greedy.choose(light, parts, base)
        return light.incidence.select("vid", "hid").join(chosen, "hid").select("vid", "hid", "part").unionByName(cut_rows.select("vid", "hid", "part"))


def replace_incidence(hf: HyperFrame, incidence: DataFrame) -> HyperFrame:
    return replace(hf, incidence=incidence)


@dataclass(frozen=True)
class IterativeCut:
    """Rounds of refinement, a stand-in for iterative partitioners: vertices go where most of their hyperedges are, then
    hyperedges where most of their members are, less for parts near their share."""

    rounds: int = 10
    hash: str = "mixed"
    name: str = "iterative"

    def assign(self, hf: HyperFrame, parts: int) -> DataFrame:
        inc = hf.incidence.select("vid", "hid").persist()
        hs = cut(inc.select("hid").distinct().withColumn("part", HASHES[self.hash](parts, F.col("hid"))))
        share = 1.1 * hs.count() / parts
        for _ in range(self.rounds):
            counts = inc.join(hs, "hid").groupBy("vid", "part").agg(F.count("*").alias("_n"))
            vs = counts.groupBy("vid").agg(F.max_by("part", F.struct("_n", -F.col("part"))).alias("part"))
            sizes = hs.groupBy("part").agg(F.count("*").alias("_size"))
            members = inc.join(vs, "vid").groupBy("hid", "part").agg(F.count("*").alias("_n")).join(sizes, "part", "left")
            score = F.col("_n") * (1 - F.coalesce("_size", F.lit(0)) / share)
            hs = cut(members.groupBy("hid").agg(F.max_by("part", F.struct(score, -F.col("part"))).alias("part")))
        return inc.join(hs, "hid").select("vid", "hid", "part")


@dataclass(frozen=True)
class Dual:
    """A rule on the dual: vertices take the part of hyperedges."""

    rule: HybridCut | GreedyCut
    name: str = "dual"

    def assign(self, hf: HyperFrame, parts: int) -> DataFrame:
        return self.rule.assign(hf.dual(), parts).select(F.col("hid").alias("vid"), F.col("vid").alias("hid"), "part")


def hybrid_hyperedge_cut(cutoff: int = 100, hash: str = "mixed") -> Dual:
    return Dual(HybridCut(cutoff, hash), "hybrid_hyperedge")


def greedy_hyperedge_cut(**options) -> Dual:
    return Dual(GreedyCut(**options), "greedy_hyperedge")


def seven(hash: str = "mixed", cutoff: int = 100, **greedy) -> list:
    """The seven placements in the order random, hybrid, greedy."""
    return [random_vertex_cut(hash), random_hyperedge_cut(hash), random_both_cut(hash), HybridCut(cutoff, hash), hybrid_hyperedge_cut(cutoff, hash), GreedyCut(hash=hash, **greedy), greedy_hyperedge_cut(hash=hash, **greedy)]


def place(hf: HyperFrame, rule, parts: int) -> HyperFrame:
    """hf with part in its memberships."""
    return replace(hf, incidence=hf.incidence.join(rule.assign(hf, parts), ["vid", "hid"]))
