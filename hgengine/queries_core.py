"""Queries of the model, the applications, the pairwise form and the baselines."""

from __future__ import annotations

import re

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hgengine import pairwise, profile, sql
from hgengine.algorithms import labels, pagerank, paths
from hgengine.baseline.direct_lp import direct_labels
from hgengine.baseline.dyadic import dyadic_pagerank
from hgengine.model import HyperFrame
from hgengine.plans.layout import AsRead
from hgengine.programs import Combiner, Program, dst_id, nid, state
from hgengine.registry import query
from hgengine.runtime import half_round
from hgengine.sources import standins
from hgengine.sources.tables import load

S = SparkSession


def r6(*names: str) -> list:
    return [F.round(n, 6).alias(n) for n in names]


# --- memberships, statistics -------------------------------------------------------------------------------------


def _incidence(name: str):
    def run(spark: S, d: str) -> DataFrame:
        hf = standins.words(spark, d, ids=False) if name == "words" else standins.STANDINS[name](spark, d)
        return hf.incidence.select("vid", F.col("hid").cast("long").alias("hid"), "multiplicity")

    return run


def _profile(name: str):
    return lambda spark, d: profile.summary(standins.STANDINS[name](spark, d))


_PROFILE = """
select n_vertices, n_hyperedges, max_degree, max_cardinality, round(mean_degree, 6) as mean_degree, round(mean_cardinality, 6) as mean_cardinality,
  n_incidence, pairs_upper, heavy_hyperedges, heavy_vertices
from (select count(*) as n_vertices, max(n) as max_degree, avg(n) as mean_degree, (count(*) filter (n > 100)) as heavy_vertices from (select count(*) as n from inc group by vid)),
  (select count(*) as n_hyperedges, max(n) as max_cardinality, avg(n) as mean_cardinality, sum(n)::bigint as n_incidence, sum(n * (n - 1) // 2)::bigint as pairs_upper, (count(*) filter (n > 100)) as heavy_hyperedges from (select count(*) as n from inc group by hid))
"""

for _n in sql.INC:
    query(f"m_incidence_{_n}", sql.INC[_n])(_incidence(_n))
for _n in ("basket", "dual", "buyers", "vendor", "supply", "hour", "words"):
    query(f"w_profile_{_n}", sql.query([sql.inc(_n)], _PROFILE))(_profile(_n))

query("w_cardinality_histogram", sql.query([sql.inc("words")], "select floor(log2(n))::int as bucket, count(*) as n from (select count(*) as n from inc group by hid) group by 1"))(lambda spark, d: profile.histogram(standins.words(spark, d)))
query("m_degree", sql.query([sql.inc("basket")], "select vid, count(*) as degree from inc group by vid"))(lambda spark, d: profile.degrees(standins.plain_basket(spark, d)))
query("m_cardinality", sql.query([sql.inc("basket")], "select o_orderkey as hid, count(inc.vid) as cardinality from orders left join inc on hid = o_orderkey group by o_orderkey"))(lambda spark, d: profile.cardinalities(standins.basket(spark, d)))
query("m_isolated", "select o_orderkey as hid from orders where o_orderkey not in (select l_orderkey from lineitem)")(lambda spark, d: standins.basket(spark, d).isolated_hyperedges())
query("m_handshake", sql.query([sql.inc("basket")], "select count(*) as sum_degree, count(*) as sum_cardinality, count(*) as n_incidence from inc"))(lambda spark, d: profile.handshake(standins.basket(spark, d)))
query("m_dual", sql.query([sql.inc("basket")], "select degree, count(*) as n from (select count(*) as degree from inc group by hid) group by degree"))(lambda spark, d: profile.degrees(standins.plain_basket(spark, d).dual()).groupBy("degree").agg(F.count("*").alias("n")))

_RESTRICTED = "select vid, hid from inc join part on p_partkey = vid join orders on o_orderkey = hid where p_size > 25 and o_orderstatus = 'F'"


def _restricted(spark: S, d: str, **drop) -> HyperFrame:
    return standins.basket(spark, d).restrict(vertex="p_size > 25", hyperedge="o_orderstatus = 'F'", **drop)


query("m_restrict", sql.query([sql.inc("basket")], _RESTRICTED))(lambda spark, d: _restricted(spark, d).incidence.select("vid", "hid"))
query("m_restrict_drop", sql.query([sql.inc("basket")], f"select hid, count(*) as cardinality from ({_RESTRICTED}) group by hid"))(lambda spark, d: profile.cardinalities(_restricted(spark, d, drop_empty=True)))


@query("m_map_vertices", "select p_partkey as vid, case when p_retailprice < 1000 then 'low' when p_retailprice < 1500 then 'mid' else 'high' end as band from part")
def m_map_vertices(spark: S, d: str) -> DataFrame:
    price = F.col("p_retailprice")
    hf = standins.basket(spark, d).with_vertex_columns(band=F.when(price < 1000, "low").when(price < 1500, "mid").otherwise("high"))
    return hf.vertices.select("vid", "band")


@query("m_map_hyperedges", "select o_orderkey as hid, year(o_orderdate)::int as year, round(ln(o_totalprice), 6) as log_price from orders")
def m_map_hyperedges(spark: S, d: str) -> DataFrame:
    hf = standins.basket(spark, d).with_hyperedge_columns(year=F.year("o_orderdate"), log_price=F.log("o_totalprice"))
    return hf.hyperedges.select("hid", "year", *r6("log_price"))


query("m_incidence_attrs", "select l_partkey as vid, l_orderkey as hid, round(sum(l_quantity), 6) as quantity, round(sum(l_extendedprice), 6) as revenue from lineitem group by all")(lambda spark, d: standins.basket(spark, d).incidence.select("vid", "hid", *r6("quantity", "revenue")))


@query("m_send_subset", "select l_orderkey as hid, round(max(p_retailprice), 6) as best from lineitem join part on p_partkey = l_partkey join orders on o_orderkey = l_orderkey where o_orderpriority = '1-URGENT' group by 1")
def m_send_subset(spark: S, d: str) -> DataFrame:
    hf = standins.basket(spark, d)
    urgent = hf.hyperedges.where("o_orderpriority = '1-URGENT'").select("hid")
    sent = half_round(hf.vertices, hf.incidence.select("vid", "hid").join(urgent, "hid", "left_semi"), Program(emit={"best": state("p_retailprice")}, combine={"best": Combiner.MAX}), "vid", "hid")
    return sent.select("hid", F.round("_msg_best", 6).alias("best"))


@query("m_send_per_destination", sql.query([sql.inc("basket")], "select hid, sum((vid + hid) % 7)::bigint as total from inc group by hid"))
def m_send_per_destination(spark: S, d: str) -> DataFrame:
    hf = standins.plain_basket(spark, d)
    return half_round(hf.vertices, hf.incidence, Program(emit={"total": (nid() + dst_id()) % 7}), "vid", "hid").withColumnRenamed("_msg_total", "total")


@query("m_combiners_all", sql.query([sql.inc("basket")], "select hid, round(sum(p_retailprice), 6) as s, round(min(p_retailprice), 6) as lo, round(max(p_retailprice), 6) as hi, count(*) as n, bool_and(p_size > 25) as all_big, bool_or(p_size > 25) as any_big, string_agg(vid::varchar, ',' order by vid) as members, count(distinct p_brand) as n_brands from inc join part on p_partkey = vid group by hid"))
def m_combiners_all(spark: S, d: str) -> DataFrame:
    hf, price, big = standins.basket(spark, d), state("p_retailprice"), state("p_size") > 25
    emit = {"s": price, "lo": price, "hi": price, "n": F.lit(1), "all_big": big, "any_big": big, "members": F.array(nid()), "brands": F.array(state("p_brand"))}
    kinds = (Combiner.SUM, Combiner.MIN, Combiner.MAX, Combiner.COUNT, Combiner.BOOL_AND, Combiner.BOOL_OR, Combiner.CONCAT, Combiner.SET_UNION)
    sent = half_round(hf.vertices, hf.incidence, Program(emit=emit, combine=dict(zip(emit, kinds, strict=True))), "vid", "hid")
    plain = sent.select("hid", *(F.col(f"_msg_{n}").alias(n) for n in emit))
    return plain.select("hid", *r6("s", "lo", "hi"), "n", "all_big", "any_big", F.array_join(F.sort_array("members").cast("array<string>"), ",").alias("members"), F.size("brands").cast("long").alias("n_brands"))


@query("m_combiner_inferred", sql.query([sql.inc("basket")], "select hid, count(*)::double as weight, round(sum(p_retailprice), 6) as value from inc join part on p_partkey = vid group by hid"))
def m_combiner_inferred(spark: S, d: str) -> DataFrame:
    hf = standins.basket(spark, d)
    sent = half_round(hf.vertices, hf.incidence, Program(emit={"pair": F.struct(F.lit(1.0).alias("weight"), state("p_retailprice").alias("value"))}), "vid", "hid")
    return sent.select("hid", F.col("_msg_pair.weight").alias("weight"), F.round("_msg_pair.value", 6).alias("value"))


_LP = 12
_TRACE = " union all ".join(f"select {r} as round, count(*) filter (a.label <> b.label) as changed from v{r} a join v{r - 1} b using (vid)" for r in range(1, _LP + 1))


@query("m_superstep_trace", sql.query(sql.labels("basket", _LP), f"select round::int as round, changed::bigint as changed from ({_TRACE}) t where round <= (select min(round) from ({_TRACE}) u where changed = 0)"))
def m_superstep_trace(spark: S, d: str) -> DataFrame:
    history = labels.run(standins.plain_basket(spark, d)).history
    return spark.createDataFrame([(h["round"], h["active"]) for h in history], "round int, changed long")


# --- PageRank ------------------------------------------------------------------------------------------------------

_WEIGHT = "select o_orderkey as hid, o_totalprice / 100000 as weight from orders where o_orderkey in (select hid from inc)"


def _ranks(hf: HyperFrame, **options) -> DataFrame:
    return pagerank.pagerank(hf, **options).vertices.select("vid", *r6("rank"))


_V10 = "select vid, round(rank, 6) as rank from v10"
query("a_pagerank_vertices", sql.query(sql.pagerank("basket", 10), _V10))(lambda spark, d: _ranks(standins.plain_basket(spark, d), max_rounds=10))
query("a_pagerank_hyperedges", sql.query(sql.pagerank("basket", 10), "select hid, round(rank, 6) as rank from e10"))(lambda spark, d: pagerank.run(standins.plain_basket(spark, d), max_rounds=10, only_hyperedges=True).frame.hyperedges.select("hid", *r6("rank")))
query("a_pagerank_weighted", sql.query(sql.pagerank("basket", 10, weight=_WEIGHT), _V10))(lambda spark, d: _ranks(standins.plain_basket(spark, d, F.col("o_totalprice") / 100000), max_rounds=10))
query("a_pagerank_alpha50", sql.query(sql.pagerank("basket", 5, alpha=0.5), "select vid, round(rank, 6) as rank from v5"))(lambda spark, d: _ranks(standins.plain_basket(spark, d), alpha=0.5, max_rounds=5))
for _n in ("dual", "buyers", "hour"):
    query(f"a_pagerank_{_n}", sql.query(sql.pagerank(_n, 10), _V10))(lambda spark, d, n=_n: _ranks(standins.STANDINS[n](spark, d), max_rounds=10))
query("a_pagerank_message_init", sql.query(sql.pagerank("basket", 10, init="message"), _V10))(lambda spark, d: _ranks(standins.plain_basket(spark, d), max_rounds=10, init="message"))


@query("a_pagerank_mass", sql.query(sql.pagerank("basket", 5), " union all ".join(f"select {r} as round, round(sum(rank), 6) as mass from v{r}" for r in range(1, 6))))
def a_pagerank_mass(spark: S, d: str) -> DataFrame:
    hf, out = standins.plain_basket(spark, d), None
    vertex, hyperedge = pagerank.programs(0.15)
    now = pagerank.prepared(hf)
    for r in range(1, 6):
        now = pagerank.iterate(now, vertex, hyperedge, 1).frame
        row = now.vertices.agg(F.lit(r).alias("round"), F.round(F.sum("rank"), 6).alias("mass"))
        out = row if out is None else out.unionByName(row)
    return out


def _entropies(column: str) -> str:
    return f"(select hid, -sum(case when p > 0 then p * log2(p) else 0 end) as entropy, count(*) as k from (select hid, x / sum(x) over (partition by hid) as p from (select hid, {column} as x from inc join v9 using (vid) join tw using (vid))) group by hid)"


_ENTROPY = f"select hid, round(e10.rank, 6) as rank, round(abs(entropy), 6) as entropy from e10 join {_entropies('rank')} using (hid)"


def _entropy(spark: S, d: str, **options) -> DataFrame:
    return pagerank.pagerank_entropy(standins.plain_basket(spark, d), max_rounds=10, **options).hyperedges.withColumn("entropy", F.abs("entropy"))


query("a_entropy", sql.query(sql.pagerank("basket", 10), _ENTROPY))(lambda spark, d: _entropy(spark, d).select("hid", *r6("rank", "entropy")))
query("a_entropy_sequence", sql.query(sql.pagerank("basket", 10), _ENTROPY))(lambda spark, d: _entropy(spark, d, form="sequence").select("hid", *r6("rank", "entropy")))
query("a_entropy_contribution", sql.query(sql.pagerank("basket", 10), f"select hid, round(abs(entropy), 6) as entropy from {_entropies('rank / total')}"))(lambda spark, d: _entropy(spark, d, entropy_on="contribution").select("hid", *r6("entropy")))
query("a_evenness", sql.query(sql.pagerank("basket", 10), f"select hid, round(case when k > 1 then entropy / log2(k) end, 6) as evenness from {_entropies('rank')}"))(lambda spark, d: _entropy(spark, d, evenness=True).select("hid", *r6("evenness")))


@query("a_summary_members", sql.query(sql.pagerank("basket", 5), "select hid, round(min(rank), 6) as lo, round(avg(rank), 6) as mean, round(max(rank), 6) as hi from inc join v5 using (vid) group by hid"))
def a_summary_members(spark: S, d: str) -> DataFrame:
    hf = standins.plain_basket(spark, d)
    ranks = pagerank.pagerank(hf, max_rounds=5).vertices
    return pagerank.summary_of_members(hf, ranks, lo=F.round(F.min("rank"), 6), mean=F.round(F.avg("rank"), 6), hi=F.round(F.max("rank"), 6))


# --- labels, paths, components, centrality ----------------------------------------------------------------------------

query("a_labels_vertices", sql.query(sql.labels("basket", _LP), f"select vid, label from v{_LP}"))(lambda spark, d: labels.label_propagation(standins.plain_basket(spark, d)).vertices)
query("a_labels_hyperedges", sql.query(sql.labels("basket", _LP), f"select hid, label from e{_LP}"))(lambda spark, d: labels.label_propagation(standins.plain_basket(spark, d)).hyperedges)
for _r in (1, 3):
    query(f"a_labels_round{_r}", sql.query(sql.labels("basket", _r), f"select vid, label from v{_r}"))(lambda spark, d, r=_r: labels.label_propagation(standins.plain_basket(spark, d), r, until_stable=False).vertices)
query("a_labels_hour30", sql.query(sql.labels("hour", 6), "select vid, label from v6"))(lambda spark, d: labels.label_propagation(standins.hour(spark, d), 30, until_stable=False).vertices)
query("a_labels_min", sql.query(sql.labels("basket", _LP, "min"), f"select vid, label from v{_LP}"))(lambda spark, d: labels.label_propagation(standins.plain_basket(spark, d), rule="min").vertices)


def _majority_sql(rounds: int) -> str:
    ctes = [sql.inc("basket"), "v0 as materialized (select distinct vid, vid as label from inc)"]
    for r in range(1, rounds + 1):
        for to, mine, last in (("hid", "e", f"v{r - 1}"), ("vid", "v", f"e{r}")):
            key = "vid" if to == "hid" else "hid"
            ctes.append(f"{mine}{r} as materialized (select {to}, label from (select {to}, label, row_number() over (partition by {to} order by n desc, label) as rn from (select {to}, label, count(*) as n from inc join {last} using ({key}) group by all)) where rn = 1)")
    return sql.query(ctes, f"select vid, label from v{rounds}")


query("a_labels_majority", _majority_sql(3))(lambda spark, d: labels.majority(standins.plain_basket(spark, d), 3).vertices)

_FIRST = "select min(vid) from inc"
_SP = 12


def _least(hf: HyperFrame, side: str = "vid") -> int:
    return hf.incidence.agg(F.min(side)).first()[0]


def _hops(spark: S, d: str, weight: str | None = None) -> HyperFrame:
    hf = standins.plain_basket(spark, d)
    if weight:
        hf = hf.with_hyperedge_columns(cost=F.expr(weight))
    return paths.shortest_paths(hf, _least(hf), weight="cost" if weight else None)


query("a_sp_vertices", sql.query(sql.paths("basket", _SP, _FIRST), f"select vid, hops from v{_SP}"))(lambda spark, d: _hops(spark, d).vertices)
query("a_sp_hyperedges", sql.query(sql.paths("basket", _SP, _FIRST), f"select hid, hops from e{_SP}"))(lambda spark, d: _hops(spark, d).hyperedges)
query("a_sp_weighted", sql.query(sql.paths("basket", 20, _FIRST, "1 + hid % 3"), "select vid, hops from v20"))(lambda spark, d: _hops(spark, d, "1 + hid % 3").vertices)
query("a_sp_unreached", sql.query(sql.paths("basket", _SP, _FIRST), f"select vid from v{_SP} where hops is null"))(lambda spark, d: _hops(spark, d).vertices.where("hops is null").select("vid"))
query("a_sp_histogram", sql.query(sql.paths("basket", _SP, _FIRST), f"select hops, count(*) as n from v{_SP} group by hops"))(lambda spark, d: _hops(spark, d).vertices.groupBy("hops").agg(F.count("*").alias("n")))


@query("a_sp_dual", sql.query(["swapped as (select * from (" + sql.INC["basket"] + "))", *[c.replace(sql.INC["basket"], "select hid as vid, vid as hid from swapped") for c in sql.paths("basket", _SP, _FIRST)]], f"select vid as hid, hops from v{_SP}"))
def a_sp_dual(spark: S, d: str) -> DataFrame:
    hf = standins.plain_basket(spark, d).dual()
    return paths.shortest_paths(hf, _least(hf)).vertices.withColumnRenamed("vid", "hid")


def _multi_sql(n: int, select: str) -> str:
    parts, ctes = [], [sql.inc("basket")]
    for i in range(n):
        source = f"select vid from inc group by vid order by vid limit 1 offset {i}"
        ctes += [re.sub(r"\b([ve])(\d+)\b", rf"\1\2_{i}", c) for c in sql.paths("basket", _SP, source)[1:]]
        parts.append(f"select ({source}) as source, vid, hops from v{_SP}_{i}")
    return sql.query([*ctes, "multi as (" + " union all ".join(parts) + ")"], select)


def _landmarks(hf: HyperFrame, n: int) -> list[int]:
    return [r.vid for r in hf.incidence.select("vid").distinct().orderBy("vid").limit(n).collect()]


@query("a_sp_multi", _multi_sql(3, "select source, vid, hops from multi"))
def a_sp_multi(spark: S, d: str) -> DataFrame:
    hf = standins.plain_basket(spark, d).persist()
    return paths.multi_source(hf, _landmarks(hf, 3))


@query("a_centrality_harmonic", _multi_sql(5, "select vid, round(coalesce(sum(case when hops > 0 then 1 / hops end), 0), 6) as value from multi group by vid"))
def a_centrality_harmonic(spark: S, d: str) -> DataFrame:
    hf = standins.plain_basket(spark, d).persist()
    return paths.harmonic_centrality(hf, _landmarks(hf, 5)).select("vid", *r6("value"))


def _eigen_sql(rounds: int) -> str:
    ctes = [sql.inc("basket"), "v0 as materialized (select distinct vid, 1.0::double as value from inc)"]
    for r in range(1, rounds + 1):
        ctes.append(f"e{r} as materialized (select hid, sum(value) as value from inc join v{r - 1} using (vid) group by hid)")
        ctes.append(f"v{r} as materialized (select vid, x / max(x) over () as value from (select vid, sum(value) as x from inc join e{r} using (hid) group by vid))")
    return sql.query(ctes, f"select vid, round(value, 6) as value from v{rounds}")


query("a_centrality_eigen", _eigen_sql(6))(lambda spark, d: paths.eigenvector_centrality(standins.plain_basket(spark, d), 6).select("vid", *r6("value")))
query("a_centrality_degree", sql.query([sql.inc("basket")], "select vid, round(sum(o_totalprice / 100000), 7) as value from inc join orders on o_orderkey = hid group by vid"))(lambda spark, d: paths.degree_centrality(standins.basket(spark, d, F.col("o_totalprice") / 100000)).select("vid", F.round("value", 7).alias("value")))

_MAIN = f"select label from v{_LP} group by label order by count(*) desc, label limit 1"


_ENDS = f"ends as materialized (select min(vid) as a, max(vid) as b from v{_LP} where label = ({_MAIN}))"
_FROM_END = [re.sub(r"\b([ve])(\d+)\b", r"s\1\2", c) for c in sql.paths("basket", _SP, "select a from ends")[1:]]


@query("a_separation", sql.query([*sql.labels("basket", _LP), _ENDS, *_FROM_END], f"select a as src, b as dst, hops from ends join sv{_SP} on vid = b"))
def a_separation(spark: S, d: str) -> DataFrame:
    hf = standins.plain_basket(spark, d).persist()
    found = labels.label_propagation(hf).vertices
    main = found.groupBy("label").agg(F.count("*").alias("n"), F.min("vid").alias("a"), F.max("vid").alias("b")).orderBy(F.desc("n"), "label").first()
    return spark.createDataFrame([(main.a, main.b, paths.separation(hf, main.a, main.b))], "src long, dst long, hops double")


@query("a_sp_sql_recursive", sql.query(sql.paths("basket", 2, _FIRST), "select vid, hops from v2 where hops is not null"))
def a_sp_sql_recursive(spark: S, d: str) -> DataFrame:
    """The naive alternative: hops in recursive SQL, which lists every walk, bounded to two."""
    standins.plain_basket(spark, d).incidence.createOrReplaceTempView("basket_incidence")
    return spark.sql("""
        with recursive reach(vid, hops) as (
          select min(vid), 0 from basket_incidence
          union all
          select b.vid, r.hops + 1 from reach r join basket_incidence a on a.vid = r.vid join basket_incidence b on b.hid = a.hid where r.hops < 2)
        select vid, cast(min(hops) as double) as hops from reach group by vid""")


query("a_components", sql.query(sql.labels("basket", _LP), f"select vid, label as component from v{_LP}"))(lambda spark, d: labels.components(standins.plain_basket(spark, d)))
query("a_components_two_phase", sql.query(sql.labels("basket", _LP), f"select vid, label as component from v{_LP}"))(lambda spark, d: labels.components(standins.plain_basket(spark, d), "two_phase"))
query("a_component_sizes", sql.query(sql.labels("nation", 3), "select label as component, count(*) as n from v3 group by label"))(lambda spark, d: labels.components(standins.nation(spark, d)).groupBy("component").agg(F.count("*").alias("n")))


@query("a_random_walk", sql.query(sql.pagerank("basket", 10, restart="case when vid in (select vid from inc group by vid order by vid limit 10) then (select count(distinct vid) from inc) / 10.0::double else 0 end"), _V10))
def a_random_walk(spark: S, d: str) -> DataFrame:
    hf = standins.plain_basket(spark, d)
    return pagerank.random_walk(hf, hf.vertices.orderBy("vid").limit(10), max_rounds=10).vertices.select("vid", *r6("rank"))


# --- pairwise form and baselines --------------------------------------------------------------------------------------

_PAIRS = "from inc a join inc b on a.hid = b.hid and a.vid < b.vid"
query("r_pairs_basket", sql.query([sql.inc("basket")], f"select a.vid as src, b.vid as dst, count(*) as shared {_PAIRS} group by all"))(lambda spark, d: pairwise.to_pairwise(standins.plain_basket(spark, d)))
query("r_pairs_weighted", sql.query([sql.inc("basket"), "k as (select hid, count(*)::double as k from inc group by hid)"], f"select a.vid as src, b.vid as dst, round(sum(1 / k), 6) as s {_PAIRS} join k on k.hid = a.hid group by a.vid, b.vid"))(lambda spark, d: pairwise.to_pairwise(standins.plain_basket(spark, d), {"s": F.round(pairwise.shared_weight(), 6)}))


@query("r_pairs_attrs", sql.query([sql.inc("basket")], f"select a.vid as src, b.vid as dst, round(min(o_totalprice), 6) as lo, round(max(o_totalprice), 6) as hi, epoch(min(o_orderdate))::bigint // 86400 as first_day {_PAIRS} join orders on o_orderkey = a.hid group by a.vid, b.vid"))
def r_pairs_attrs(spark: S, d: str) -> DataFrame:
    day = F.expr("unix_timestamp(cast(min(o_orderdate) as timestamp)) div 86400")
    return pairwise.to_pairwise(standins.basket(spark, d), {"lo": F.round(F.min("o_totalprice"), 6), "hi": F.round(F.max("o_totalprice"), 6), "first_day": day})


_COSTS = ("basket", "buyers", "dual", "hour", "nation", "supply", "vendor", "words")
query("r_pairs_cost", " union all ".join(f"select '{n}' as name, sum(k)::bigint as incidences, sum(k * (k - 1) // 2)::bigint as pairs_upper, round(sum(k * (k - 1) // 2) / sum(k), 6) as ratio from (select count(*) as k from ({sql.INC[n]}) group by hid)" for n in _COSTS))(lambda spark, d: _costs(spark, d))


def _costs(spark: S, d: str) -> DataFrame:
    out = None
    for n in _COSTS:
        row = profile.pairwise_cost(standins.STANDINS[n](spark, d)).select(F.lit(n).alias("name"), "incidences", "pairs_upper", "ratio")
        out = row if out is None else out.unionByName(row)
    return out


query("r_pagerank_pairs", sql.query(sql.pagerank("vendor", 10), _V10))(lambda spark, d: pairwise.pagerank_pairwise(standins.vendor(spark, d), max_rounds=10).select("vid", *r6("rank")))


@query("r_sp_pairs", sql.query(sql.paths("basket", _SP, _FIRST), f"select vid, hops from v{_SP}"))
def r_sp_pairs(spark: S, d: str) -> DataFrame:
    hf = standins.plain_basket(spark, d)
    return pairwise.shortest_paths_pairwise(hf, _least(hf))


_APPS = {"pagerank": False, "shortest_paths": False, "labels": True, "pagerank_entropy": True}
_BOUND = 5_000_000
_GUARD = " union all ".join(f"select '{a}' as app, '{n}' as name, {'false' if needs else 'true'} and (select sum(k * (k - 1) // 2) from (select count(*) as k from ({sql.INC[n]}) group by hid)) <= {_BOUND} as admitted" for a, needs in _APPS.items() for n in ("basket", "vendor", "supply"))


@query("r_guard", _GUARD)
def r_guard(spark: S, d: str) -> DataFrame:
    """Which applications can run on pairs, by their programs and the sides of their results, and on which hypergraphs."""
    rows = []
    for n in ("basket", "vendor", "supply"):
        hf = standins.STANDINS[n](spark, d)
        try:
            fits = bool(pairwise.guard(hf, _BOUND)) or True
        except pairwise.PairwiseTooLarge:
            fits = False
        label = F.lit(0).cast("long").alias("label")
        apps = {
            "pagerank": (pagerank.programs(0.15), pairwise.pagerank_states(hf), ("vid",)), "shortest_paths": (paths.programs(F.lit(1.0)), pairwise.path_states(hf), ("vid",)),
            "labels": ((labels.program(), labels.program()), HyperFrame(hf.vertices.select("vid", label), hf.hyperedges.select("hid", label), hf.incidence), ("vid", "hid")),
            "pagerank_entropy": (pagerank.programs(0.15), pairwise.pagerank_states(hf), ("vid", "hid")),
        }
        for app, (programs, states, wanted) in apps.items():
            try:
                pairwise.check_pairwise(*programs, states, wanted)
                rows.append((app, n, fits))
            except pairwise.NeedsHyperedges:
                rows.append((app, n, False))
    return spark.createDataFrame(rows, "app string, name string, admitted boolean")


query("b_direct_lp", sql.query(sql.labels("basket", _LP), f"select vid, label from v{_LP}"))(lambda spark, d: direct_labels(standins.plain_basket(spark, d)))


def _dyadic_sql(rounds: int) -> str:
    ctes = [sql.inc("vendor"), "p as materialized (select distinct a.vid as src, b.vid as dst from inc a join inc b on a.hid = b.hid and a.vid <> b.vid)", "g as materialized (select src as vid, count(*)::double as g from p group by src)", "v0 as materialized (select distinct vid, 1.0::double as rank from inc)"]
    for r in range(1, rounds + 1):
        ctes.append(f"v{r} as materialized (select v.vid, 0.15::double + 0.85::double * coalesce(sum(u.rank / g.g), 0) as rank from v0 v left join p on p.dst = v.vid left join v{r - 1} u on u.vid = p.src left join g on g.vid = p.src group by v.vid)")
    return sql.query(ctes, f"select vid, round(rank, 6) as rank from v{rounds}")


query("b_dyadic_pagerank", _dyadic_sql(10))(lambda spark, d: dyadic_pagerank(standins.vendor(spark, d), max_rounds=10).select("vid", *r6("rank")))


# --- the applications on other whole hypergraphs, baselines and measures --------------------------------------------------

for _n in ("dual", "buyers", "hour"):
    query(f"a_labels_{_n}", sql.query(sql.labels(_n, 8), "select vid, label from v8"))(lambda spark, d, n=_n: labels.label_propagation(standins.STANDINS[n](spark, d)).vertices)
    query(f"a_sp_{_n}_vertices", sql.query(sql.paths(_n, 8, _FIRST), "select vid, hops from v8"))(lambda spark, d, n=_n: paths.shortest_paths(hf := standins.STANDINS[n](spark, d), _least(hf)).vertices)
    query(f"a_components_{_n}", sql.query(sql.labels(_n, 8), "select vid, label as component from v8"))(lambda spark, d, n=_n: labels.components(standins.STANDINS[n](spark, d), "two_phase"))
for _n in ("dual", "buyers"):
    _shape = _entropies("rank").replace("v9", "v4")
    query(f"a_entropy_{_n}", sql.query(sql.pagerank(_n, 5), f"select hid, round(abs(entropy), 6) as entropy from {_shape}"))(lambda spark, d, n=_n: pagerank.pagerank_entropy(standins.STANDINS[n](spark, d), max_rounds=5).hyperedges.select("hid", F.round(F.abs("entropy"), 6).alias("entropy")))
query("a_pagerank_vendor", sql.query(sql.pagerank("vendor", 10), _V10))(lambda spark, d: _ranks(standins.vendor(spark, d), max_rounds=10))
query("r_pagerank_pairs_buyers", sql.query(sql.pagerank("buyers", 5), "select vid, round(rank, 6) as rank from v5"))(lambda spark, d: pairwise.pagerank_pairwise(standins.buyers(spark, d), max_rounds=5).select("vid", *r6("rank")))
query("b_naive_pagerank", sql.query(sql.pagerank("basket", 5), "select vid, round(rank, 6) as rank from v5"))(lambda spark, d: _ranks(hf := standins.plain_basket(spark, d), max_rounds=5, layout=AsRead(hf.incidence)))


def _parents_sql(rounds: int) -> str:
    """Hops and the smallest node of a best path, as of the round that reached a node first."""
    ctes = sql.paths("basket", rounds, _FIRST)
    return sql.query(ctes, f"select v.vid, v.hops, (select min(e.hid) from inc join e{rounds} e using (hid) where inc.vid = v.vid and e.hops = v.hops and v.hops > 0) as parent from v{rounds} v")


@query("a_sp_parents", _parents_sql(8))
def a_sp_parents(spark: S, d: str) -> DataFrame:
    hf = standins.plain_basket(spark, d)
    return paths.shortest_paths(hf, _least(hf), keep_parent=True).vertices.select("vid", "hops", "parent")


_DRAWN = f"select count(*) * 16 / 2 as pairs_distinct_est from (select distinct a.vid, b.vid as other from inc a join inc b on a.hid = b.hid and a.vid <> b.vid where {sql.modular('a.vid', 16)} = 0)"
for _n in ("basket", "vendor"):
    query(f"r_pairs_distinct_{_n}", sql.query([sql.inc(_n)], _DRAWN))(lambda spark, d, n=_n: profile.distinct_pairs_estimate(standins.STANDINS[n](spark, d)))


@query("w_rank_error", sql.query(sql.pagerank("basket", 10), "select round(sum(abs(a.rank - b.rank)), 6) as l1, round(max(abs(a.rank - b.rank)), 6) as largest, (select count(*) / 100 from (select vid from v2 order by round(rank, 9) desc, vid limit 100) join (select vid from v10 order by round(rank, 9) desc, vid limit 100) using (vid)) as top_share from v2 a join v10 b using (vid)"))
def w_rank_error(spark: S, d: str) -> DataFrame:
    """How far two rounds are from ten."""
    hf = standins.plain_basket(spark, d)
    two, ten = (pagerank.pagerank(hf, max_rounds=n).vertices for n in (2, 10))
    return profile.rank_error(two, ten).select(*r6("l1", "largest"), "top_share")


query("m_from_arrays", sql.query([sql.inc("basket")], "select vid, hid from inc"))(lambda spark, d: HyperFrame.from_arrays(load(spark, d, "lineitem", ["l_orderkey", "l_partkey"]).groupBy("l_orderkey").agg(F.collect_list("l_partkey").alias("parts")), "l_orderkey", "parts").incidence.select("vid", "hid"))
query("m_cardinality_links", """select page_id as hid, count(distinct l) as cardinality from (select page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) as l from pages) group by 1""")(lambda spark, d: profile.cardinalities(standins.links(spark, d)))
query("m_cardinality_turns", "select conv_id as hid, count(distinct w) as cardinality from (select conv_id, unnest(string_split(lower(text), ' ')) as w from conversations) where w <> '' group by 1")(lambda spark, d: profile.cardinalities(standins.turns(spark, d)))
query("m_cardinality_class", "select label::bigint as hid, count(distinct vec_id) as cardinality from embeddings group by 1")(lambda spark, d: profile.cardinalities(standins.classes(spark, d)))
