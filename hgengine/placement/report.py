"""Measures of a placement: replication, cuts, balance, volume of synchronisation; and advice on a strategy."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.profile import summary


def routing(placed: DataFrame, side: str = "vid") -> DataFrame:
    """side, part: where replicas of a node are."""
    return placed.select(side, "part").distinct()


def placement_report(placed: DataFrame, parts: int) -> DataFrame:
    """One row. placed: vid, hid, part. Replication factors are over nodes with a membership; imbalance is the largest
    part's memberships over the mean."""
    one = {}
    for side, name in (("vid", "vertex"), ("hid", "hyperedge")):
        per = placed.groupBy(side).agg(F.count_distinct("part").alias("n"))
        one[name] = per.agg(F.count("*").alias(f"_{name}"), F.sum("n").alias(f"_r{name}"), F.count_if(F.col("n") > 1).alias(f"cut_{'vertices' if side == 'vid' else 'hyperedges'}"))
    loads = placed.groupBy("part").agg(F.count("*").alias("n")).agg(F.max("n").alias("_max"), F.sum("n").alias("_all"), F.count("*").alias("_used"))
    # three tables of one row
    row = one["vertex"].crossJoin(one["hyperedge"]).crossJoin(loads)
    return row.select(
        F.round(F.col("_rvertex") / F.col("_vertex"), 6).alias("rf_vertex"), F.round(F.col("_rhyperedge") / F.col("_hyperedge"), 6).alias("rf_hyperedge"),
        F.round((F.col("_rvertex") + F.col("_rhyperedge")) / (F.col("_vertex") + F.col("_hyperedge")), 6).alias("rf_total"),
        "cut_vertices", "cut_hyperedges", F.round(F.col("_max") * parts / F.col("_all"), 6).alias("imbalance"), (F.lit(parts) - F.col("_used")).cast("int").alias("empty_parts"),
    )


def part_balance(placed: DataFrame) -> DataFrame:
    """part, memberships, vertices, hyperedges, replicas."""
    found = placed.groupBy("part").agg(F.count("*").alias("n_incidence"), F.count_distinct("vid").alias("n_vertices"), F.count_distinct("hid").alias("n_hyperedges"))
    return found.withColumn("replicas", F.col("n_vertices") + F.col("n_hyperedges"))


def replicas(hf: HyperFrame, rule, parts: int) -> tuple[int, int]:
    """(vertex, hyperedge) replicas of a placement."""
    placed = rule.assign(hf, parts)
    return routing(placed, "vid").count(), routing(placed, "hid").count()


def sync_rows(vertex_replicas: int, hyperedge_replicas: int, whole: str) -> dict[str, int]:
    """Rows shipped in a round: with two copies of the memberships, and with one placed copy; whole names the side that
    the placement keeps whole (vid, hid or none) and that ships nothing."""
    placed = {"vid": 2 * hyperedge_replicas, "hid": 2 * vertex_replicas, "none": 2 * (vertex_replicas + hyperedge_replicas)}[whole]
    return {"two_copy": vertex_replicas + hyperedge_replicas, "placed": placed}


#: Memberships under which no placement pays.
FEW = 1_000_000


def advise(hf: HyperFrame, parts: int = 8, hash: str = "mixed", few: int = FEW) -> tuple[str, list[str]]:
    """(strategy, reasons) from the ratio of vertices to hyperedges, heavy members and shipped rows."""
    from hgengine.placement.strategies import random_both_cut, random_hyperedge_cut, random_vertex_cut

    p = summary(hf).first()
    ratio = p.n_vertices / max(1, p.n_hyperedges)
    why = [f"{p.n_vertices} vertices, {p.n_hyperedges} hyperedges, ratio {ratio:.3f}"]
    if p.n_incidence < few:
        return "two_copy", [*why, f"{p.n_incidence} memberships: placing costs more than it saves"]
    if ratio >= 2:
        if p.n_vertices * parts <= 1e9:
            return "greedy_hyperedge", [*why, "many more vertices: cutting the few hyperedges replicates least, and choosing is affordable"]
        return ("hybrid_hyperedge" if p.heavy_vertices else "random_hyperedge"), [*why, "many more vertices, too many to choose for one by one"]
    a, _ = replicas(hf, random_vertex_cut(hash), parts)
    _, b = replicas(hf, random_hyperedge_cut(hash), parts)
    if ratio <= 0.5:
        both = sum(replicas(hf, random_both_cut(hash), parts))
        loads = part_balance(random_vertex_cut(hash).assign(hf, parts)).agg(F.max("n_incidence") / F.avg("n_incidence")).first()[0]
        if 2 * both <= 1.5 * 2 * a or loads > 1.2:
            return "random_both", [*why, f"cutting both ships {2 * both} rows, vertices alone {2 * a}; imbalance of the latter {loads:.2f}"]
        return "random_vertex", [*why, f"cutting vertices ships {2 * a} rows, both {2 * both}"]
    best = "random_vertex" if a <= b else "random_hyperedge"
    return best, [*why, f"about as many of each: the cheaper of the random cuts ({2 * a} and {2 * b} rows)"]
