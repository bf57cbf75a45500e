"""The pairwise form: each hyperedge as all pairs of its members. Built only behind a guard of its cost."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hgengine.algorithms import pagerank, paths
from hgengine.model import HyperFrame
from hgengine.plans.layout import messages
from hgengine.profile import pairwise_cost
from hgengine.programs import Program
from hgengine.session import cut

#: Pairs at most that are built without being asked for more.
MOST_PAIRS = 1_000_000_000
#: Vertices whose ids and ranks, two numbers each, are broadcast in a round.
FEW_STATES = 1_000_000


class PairwiseTooLarge(ValueError):
    pass


class NeedsHyperedges(ValueError):
    pass


def guard(hf: HyperFrame, most: int = MOST_PAIRS) -> int:
    found = pairwise_cost(hf).first()["pairs_upper"] or 0
    if found > most:
        raise PairwiseTooLarge(f"up to {found} pairs; the bound is {most}")
    return found


def check_pairwise(vertex: Program, hyperedge: Program, states: HyperFrame, wanted: tuple[str, ...] = ("vid",)) -> None:
    """Only programs whose result has no hyperedge state (wanted: the sides of the result), and whose messages have the same
    names and types both ways, can run on pairs. The types follow from the programs and the states that they start with."""
    if "hid" in wanted:
        raise NeedsHyperedges("hyperedge state is part of the result")
    kinds = []
    for program, nodes, key, other in ((vertex, states.vertices, "vid", "hid"), (hyperedge, states.hyperedges, "hid", "vid")):
        rows = nodes.withColumns({"_id": F.col(key), "_step": F.lit(0)})
        sent = messages(rows, states.incidence, program, [key], other)
        kinds.append({n: sent.schema[f"_msg_{n}"].dataType.simpleString() for n in program.emit})
    if kinds[0] != kinds[1]:
        raise NeedsHyperedges(f"messages differ in the two directions: {kinds[0]} and {kinds[1]}")


def to_pairwise(hf: HyperFrame, attributes: dict[str, Column] | None = None, most_pairs: int = MOST_PAIRS, directed: bool = False) -> DataFrame:
    """src, dst (src < dst, or both ways) and aggregates over the hyperedges that the two share; the aggregates may use
    columns of the hyperedges and _size, the cardinality."""
    guard(hf, most_pairs)
    inc = hf.incidence.select("vid", "hid")
    sized = hf.hyperedges.join(inc.groupBy("hid").agg(F.count("*").alias("_size")), "hid")
    a, b = inc.select("hid", F.col("vid").alias("src")), inc.select("hid", F.col("vid").alias("dst"))
    # the equal key is the hyperedge: no cross join, and the guard bounds the rows
    pairs = a.join(b, "hid").where("src < dst").join(sized, "hid")
    found = pairs.groupBy("src", "dst").agg(*(c.alias(n) for n, c in (attributes or {"shared": F.count("*")}).items()))
    if directed:
        found = found.unionByName(found.select(F.col("dst").alias("src"), F.col("src").alias("dst"), *(attributes or {"shared": 0})))
    return found


def shared_weight(weight: str | None = "weight") -> Column:
    """The symmetric gain of a pair: the sum of weight over cardinality of shared hyperedges."""
    return F.sum((F.lit(1.0) if weight is None else F.col(weight)) / F.col("_size"))


def pagerank_states(hf: HyperFrame) -> HyperFrame:
    """What the programs of PageRank start with, by name and type."""
    one = F.lit(1.0)
    return HyperFrame(hf.vertices.select("vid", one.alias("rank"), one.alias("_share")), hf.hyperedges.select("hid", one.alias("rank"), one.alias("_size")), hf.incidence)


def path_states(hf: HyperFrame) -> HyperFrame:
    state = [F.lit(0.0).alias("hops"), F.lit(None).cast("long").alias("parent")]
    return HyperFrame(hf.vertices.select("vid", *state), hf.hyperedges.select("hid", *state), hf.incidence)


def pagerank_pairwise(hf: HyperFrame, alpha: float = 0.15, max_rounds: int = 30, weight: str | None = "weight", most_pairs: int = MOST_PAIRS) -> DataFrame:
    """vid, rank: as the bipartite form, with the hyperedge step folded into constants of pairs and of each vertex. Pairs may
    outnumber memberships by far: each round makes them all again, from members that lie together by hyperedge, and sums
    them where they are made, so that no pair is kept or travels."""
    check_pairwise(*pagerank.programs(alpha), pagerank_states(hf))
    guard(hf, most_pairs)
    w = F.lit(1.0) if weight is None else F.col(weight).cast("double")
    parts = int(hf.incidence.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    members = hf.incidence.select("vid", "hid").join(hf.hyperedges.select("hid", w.alias("_w")), "hid").repartition(parts, "hid")
    ends = members.select("hid", "vid", "_w", (F.col("_w") / F.count("*").over(Window.partitionBy("hid"))).alias("_gain")).persist()
    own = ends.groupBy("vid").agg(F.sum("_w").alias("_total"), F.sum("_gain").alias("_self"))
    vs = cut(hf.vertices.select("vid", F.lit(1.0).alias("rank")).join(own, "vid", "left"))
    few = vs.count() <= FEW_STATES
    for _ in range(max_rounds):
        sent = vs.select(F.col("vid").alias("src"), (F.col("rank") / F.col("_total")).alias("_sent"))
        told = ends.select("hid", F.col("vid").alias("src")).join(F.broadcast(sent) if few else sent, "src")
        # the equal key is the hyperedge: no cross join, and the guard bounds the rows
        pairs = told.join(ends.select("hid", F.col("vid").alias("dst"), "_gain").hint("merge"), "hid").where("src <> dst")
        heard = pairs.groupBy(F.col("dst").alias("vid")).agg(F.sum(F.col("_sent") * F.col("_gain")).alias("_heard"))
        rank = alpha + (1 - alpha) * (F.coalesce("_heard", F.lit(0.0)) + F.coalesce(F.col("rank") * F.col("_self") / F.col("_total"), F.lit(0.0)))
        vs = cut(vs.join(heard, "vid", "left").select("vid", rank.alias("rank"), "_total", "_self"))
    ends.unpersist()
    return vs.select("vid", "rank")


def shortest_paths_pairwise(hf: HyperFrame, source: int, weight: str | None = None, most_pairs: int = MOST_PAIRS) -> DataFrame:
    """vid, hops over pairs: 1 for each, or the least weight of the shared hyperedges."""
    check_pairwise(*paths.programs(F.lit(1.0)), path_states(hf))
    cost = F.lit(1.0) if weight is None else F.min(F.col(weight).cast("double"))
    pairs = to_pairwise(hf, {"cost": F.max(F.lit(1.0)) if weight is None else cost}, most_pairs, directed=True).persist()
    vs = cut(hf.vertices.select("vid", F.when(F.col("vid") == source, 0.0).alias("hops"), (F.col("vid") == source).alias("_send")))
    while vs.where("_send").limit(1).count():
        heard = vs.where("_send").select(F.col("vid").alias("src"), "hops").join(pairs, "src").groupBy(F.col("dst").alias("vid")).agg(F.min(F.col("hops") + F.col("cost")).alias("_new"))
        better = F.coalesce(F.col("_new") < F.coalesce("hops", F.lit(float("inf"))), F.lit(False))
        vs = cut(vs.join(heard, "vid", "left").select("vid", F.when(better, F.col("_new")).otherwise(F.col("hops")).alias("hops"), better.alias("_send")))
    pairs.unpersist()
    return vs.select("vid", "hops")
