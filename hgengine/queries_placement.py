"""Queries of placements, their measures, and the placed plan."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hgengine import sql
from hgengine.placement import report
from hgengine.placement.strategies import GreedyCut, GreedyHybridCut, HybridCut, IterativeCut, greedy_hyperedge_cut, grid_cut, hybrid_hyperedge_cut, overlap, random_both_cut, random_hyperedge_cut, random_vertex_cut
from hgengine.algorithms import labels, pagerank, paths
from hgengine.registry import query
from hgengine.sources import standins

P = 8
M = "modular"
V, H, B = sql.modular("vid", P), sql.modular("hid", P), sql.modular2("vid", "hid", P)
GRID = f"({sql.modular('hid', 2)} * 4 + {sql.modular('vid', 4)})::int"


def _hybrid(cutoff: int, whole: str, by_whole: str, by_other: str) -> str:
    return f"select vid, hid, case when n > {cutoff} then {by_other} else {by_whole} end as part from (select *, count(*) over (partition by {whole}) as n from inc)"


def _choices(name: str, whole: str, other: str, rows: str = "inc", base: str | None = None, streams: int = 1, epoch: str = "true") -> list[str]:
    """CTEs that end in <name>(stream, seq, id, best, loads): the sequential choice, one id a step of each stream, with the
    loads as a list. base: SQL of the first loads; epoch: which ids take part."""
    score = ", ".join(f"coalesce(o.n[{p + 1}], 0) - sqrt(loads[{p + 1}])" for p in range(P))
    counts = ", ".join(f"count(*) filter ({sql.modular(other, P)} = {p})" for p in range(P))
    new = ", ".join(f"loads[{p + 1}] + case when best = {p} then {streams} else 0 end" for p in range(P))
    stream = sql.modular(whole, streams) if streams > 1 else "0"
    first = base or f"[{', '.join(['0::double'] * P)}]"
    return [
        f"o_{name} as materialized (select {whole} as id, {stream} as stream, row_number() over (partition by {stream} order by {whole}) as seq, [{counts}] as n from {rows} where {epoch} group by {whole})",
        f"""{name}(stream, seq, id, best, loads) as (
  select distinct stream, 0::bigint, null::bigint, null::int, {first} from o_{name}
  union all
  select stream, seq, id, best, [{new}] from (
    select stream, seq, id, loads, list_position(scores, list_max(scores))::int - 1 as best from (
      select o.stream, o.seq, o.id, c.loads, [{score}] as scores from {name} c join o_{name} o on o.stream = c.stream and o.seq = c.seq + 1)))""",
    ]


def _with(ctes: list[str], select: str) -> str:
    return sql.query(ctes, select).replace("with ", "with recursive ", 1)


def _greedy_sql(name: str, whole: str, other: str) -> str:
    return _with([sql.inc(name), *_choices("chosen", whole, other)], f"select id as {whole}, best::int as part from chosen where seq > 0")


def _greedy_placed(name: str, whole: str, other: str) -> list[str]:
    return [sql.inc(name), *_choices("chosen", whole, other), f"placed as (select vid, hid, best as part from inc join chosen on id = {whole})"]


def _epochs_sql(name: str, epochs: int, streams: int) -> str:
    """Slices of ids one after another; the loads of all earlier ones are the first loads of the next."""
    ctes, done = [sql.inc(name)], []
    for e in range(epochs):
        base = None
        if done:
            past = " union all ".join(f"select best from c{i} where seq > 0" for i in done)
            ctes.append(f"b{e} as materialized (select [{', '.join(f'(count(*) filter (best = {p}))::double' for p in range(P))}] as loads from ({past}))")
            base = f"(select loads from b{e})"
        ctes += _choices(f"c{e}", "hid", "vid", base=base, streams=streams, epoch=f"{sql.modular2('hid', '1', epochs)} = {e}")
        done.append(e)
    chosen = " union all ".join(f"select id, best from c{i} where seq > 0" for i in done)
    return _with(ctes, f"select vid, hid, best::int as part from inc join ({chosen}) on id = hid")


def _greedy_hybrid_sql(name: str, cutoff: int) -> str:
    heavy = f"select vid, {V} as part, hid from sized where k > {cutoff}"
    base = f"(select [{', '.join(f'(count(*) filter (part = {p}))::double / any_value(mean)' for p in range(P))}] from heavy, (select avg(k) as mean from (select distinct hid, k from sized where k <= {cutoff})))"
    ctes = [sql.inc(name), "sized as materialized (select vid, hid, count(*) over (partition by hid) as k from inc)", f"heavy as materialized ({heavy})", *_choices("chosen", "hid", "vid", rows="sized", base=base, epoch=f"k <= {cutoff}")]
    return _with(ctes, "select vid, hid, best::int as part from inc join chosen on id = hid union all select vid, hid, part::int from heavy")


def _iterative_sql(name: str, rounds: int) -> str:
    ctes = [sql.inc(name), f"h0 as materialized (select distinct hid, {H} as part from inc)", f"share as materialized (select 1.1::double * count(*) / {P} as share from h0)"]
    for r in range(1, rounds + 1):
        ctes.append(f"v{r} as materialized (select vid, part from (select vid, part, row_number() over (partition by vid order by count(*) desc, part) as rn from inc join h{r - 1} using (hid) group by vid, part) where rn = 1)")
        ctes.append(f"s{r} as materialized (select part, count(*) as size from h{r - 1} group by part)")
        ctes.append(f"h{r} as materialized (select hid, part from (select hid, part, row_number() over (partition by hid order by n * (1 - coalesce(size, 0) / share) desc, part) as rn from (select hid, part, count(*) as n from inc join v{r} using (vid) group by hid, part) left join s{r} using (part), share) where rn = 1)")
    return sql.query(ctes, f"select vid, hid, part from inc join h{rounds} using (hid)")


ASSIGNED = {
    "random_vertex": (random_vertex_cut(M), f"select vid, hid, {H} as part from inc"),
    "random_hyperedge": (random_hyperedge_cut(M), f"select vid, hid, {V} as part from inc"),
    "random_both": (random_both_cut(M), f"select vid, hid, {B} as part from inc"),
    "grid": (grid_cut(M), f"select vid, hid, {GRID} as part from inc"),
    "hybrid_vertex": (HybridCut(5, M), _hybrid(5, "hid", H, V)),
    "hybrid_hyperedge": (hybrid_hyperedge_cut(30, M), _hybrid(30, "vid", V, H)),
}

for _n, (_rule, _sql) in ASSIGNED.items():
    query(f"p_{_n}_assign", sql.query([sql.inc("basket")], _sql))(lambda spark, d, rule=_rule: rule.assign(standins.plain_basket(spark, d), P))


_CUTOFFS = (10, 50, 100, 200, 500, 1000)
_WORDS = sql.INC["words"].replace("select w as vid", "select ('0x' || substr(md5(w), 1, 15))::bigint as vid")


@query("p_hybrid_words", sql.query([f"inc as materialized ({_WORDS})"], " union all ".join(f"select {c} as cutoff, part, count(*) as n from (" + _hybrid(c, "hid", H, V) + ") group by part" for c in _CUTOFFS)))
def p_hybrid_words(spark: SparkSession, d: str) -> DataFrame:
    """Sensitivity to the cutoff on documents of words, whose sizes are very uneven."""
    hf, out = standins.words_by_md5(spark, d), None
    for cutoff in _CUTOFFS:
        rows = HybridCut(cutoff, M).assign(hf, P).groupBy(F.lit(cutoff).alias("cutoff"), "part").agg(F.count("*").alias("n"))
        out = rows if out is None else out.unionByName(rows)
    return out


query("p_hybrid_turnover", sql.query([sql.inc("supply")], "select 100 as cutoff, part, count(*) as n from (" + _hybrid(100, "hid", H, V) + ") group by part union all select 500, part, count(*) from (" + _hybrid(500, "hid", H, V) + ") group by part"))(lambda spark, d: _turnover(spark, d))


def _turnover(spark: SparkSession, d: str) -> DataFrame:
    """Sensitivity to the cutoff."""
    hf, out = standins.supply(spark, d), None
    for cutoff in (100, 500):
        rows = HybridCut(cutoff, M).assign(hf, P).groupBy(F.lit(cutoff).alias("cutoff"), "part").agg(F.count("*").alias("n"))
        out = rows if out is None else out.unionByName(rows)
    return out


query("p_greedy_vertex_overlap", sql.query([sql.inc("supply")], f"select hid, {V} as part, count(*) as overlap from inc group by all"))(lambda spark, d: overlap(standins.supply(spark, d), P, M))
query("p_greedy_hyperedge_overlap", sql.query([sql.inc("vendor")], f"select vid, {H} as part, count(*) as overlap from inc group by all"))(lambda spark, d: overlap(standins.vendor(spark, d).dual(), P, M).withColumnRenamed("hid", "vid"))
query("p_greedy_vertex_assign", _greedy_sql("supply", "hid", "vid"))(lambda spark, d: GreedyCut(hash=M).choose(standins.supply(spark, d), P))
query("p_greedy_hyperedge_assign", _greedy_sql("vendor", "vid", "hid"))(lambda spark, d: GreedyCut(hash=M).choose(standins.vendor(spark, d).dual(), P).withColumnRenamed("hid", "vid"))

_REPORT = f"""
select round(rv / nv, 6) as rf_vertex, round(rh / nh, 6) as rf_hyperedge, round((rv + rh) / (nv + nh), 6) as rf_total, cut_vertices, cut_hyperedges, round(mx * {P} / n, 6) as imbalance, ({P} - used)::int as empty_parts
from (select count(*) as nv, sum(r) as rv, count(*) filter (r > 1) as cut_vertices from (select count(distinct part) as r from placed group by vid)),
  (select count(*) as nh, sum(r) as rh, count(*) filter (r > 1) as cut_hyperedges from (select count(distinct part) as r from placed group by hid)),
  (select max(k) as mx, sum(k) as n, count(*) as used from (select count(*) as k from placed group by part))"""
_SEVEN = {
    "random_vertex": (random_vertex_cut(M), f"select vid, hid, {H} as part from inc"),
    "random_hyperedge": (random_hyperedge_cut(M), f"select vid, hid, {V} as part from inc"),
    "random_both": (random_both_cut(M), f"select vid, hid, {B} as part from inc"),
    "hybrid_vertex": (HybridCut(5, M), _hybrid(5, "hid", H, V)),
    "hybrid_hyperedge": (hybrid_hyperedge_cut(30, M), _hybrid(30, "vid", V, H)),
    "greedy_vertex": (GreedyCut(hash=M), None),
    "greedy_hyperedge": (greedy_hyperedge_cut(hash=M), None),
}
for _n, (_rule, _sql) in _SEVEN.items():
    _ctes = [sql.inc("basket"), f"placed as ({_sql})"] if _sql else _greedy_placed("basket", *(("hid", "vid") if _n == "greedy_vertex" else ("vid", "hid")))
    query(f"p_report_{_n}", _with(_ctes, _REPORT))(lambda spark, d, rule=_rule: report.placement_report(rule.assign(standins.plain_basket(spark, d), P), P))

query("p_report_greedy_supply", _with(_greedy_placed("supply", "hid", "vid"), _REPORT))(lambda spark, d: report.placement_report(GreedyCut(hash=M).assign(standins.supply(spark, d), P), P))

_NAMES = ("basket", "dual", "hour", "supply", "vendor")
_LOCAL = {"random_vertex": H, "random_hyperedge": V, "random_both": B}


def _one_report(n: str, s: str) -> str:
    return f"select '{n}' as name, '{s}' as strategy, rf_total, imbalance from (with inc as ({sql.INC[n]}), placed as (select vid, hid, {_LOCAL[s]} as part from inc) {_REPORT})"


@query("p_report_all", " union all ".join(_one_report(n, s) for n in _NAMES for s in _LOCAL))
def p_report_all(spark: SparkSession, d: str) -> DataFrame:
    out = None
    for n in _NAMES:
        hf = standins.STANDINS[n](spark, d)
        for s in _LOCAL:
            row = report.placement_report(_SEVEN[s][0].assign(hf, P), P).select(F.lit(n).alias("name"), F.lit(s).alias("strategy"), "rf_total", "imbalance")
            out = row if out is None else out.unionByName(row)
    return out


_A, _B = f"(select count(*) from (select distinct vid, {H} from inc))", f"(select count(*) from (select distinct hid, {V} from inc))"


@query("p_sync_volume", sql.query([sql.inc("basket")], f"select 'two_copy' as layout, {_A} + {_B} as rows union all select 'vertex_cut', 2 * {_A} union all select 'hyperedge_cut', 2 * {_B}"))
def p_sync_volume(spark: SparkSession, d: str) -> DataFrame:
    hf = standins.plain_basket(spark, d)
    a, _ = report.replicas(hf, random_vertex_cut(M), P)
    _, b = report.replicas(hf, random_hyperedge_cut(M), P)
    rows = [("two_copy", report.sync_rows(a, b, "hid")["two_copy"]), ("vertex_cut", report.sync_rows(a, b, "hid")["placed"]), ("hyperedge_cut", report.sync_rows(a, b, "vid")["placed"])]
    return spark.createDataFrame(rows, "layout string, rows long")


@query("p_part_balance", sql.query([sql.inc("basket")], f"select {H} as part, count(*) as n_incidence, count(distinct vid) as n_vertices, count(distinct hid) as n_hyperedges, count(distinct vid) + count(distinct hid) as replicas from inc group by 1"))
def p_part_balance(spark: SparkSession, d: str) -> DataFrame:
    return report.part_balance(random_vertex_cut(M).assign(standins.plain_basket(spark, d), P))


#: A placement of each kind for the placed plans.
_RULES = {"random": random_both_cut(), "hybrid": HybridCut(5), "greedy": GreedyCut(mode="streams")}
for _n, _rule in _RULES.items():
    query(f"p_placed_labels_{_n}", sql.query(sql.labels("basket", 8), "select vid, label from v8"))(lambda spark, d, rule=_rule: labels.label_propagation(standins.plain_basket(spark, d), placement=rule, parts=P).vertices)
    query(f"p_placed_pagerank_{_n}", sql.query(sql.pagerank("basket", 5), "select vid, round(rank, 6) as rank from v5"))(lambda spark, d, rule=_rule: pagerank.pagerank(standins.plain_basket(spark, d), max_rounds=5, placement=rule, parts=P).vertices.select("vid", F.round("rank", 6).alias("rank")))
_BITS = "(select hid, -sum(case when p > 0 then p * log2(p) else 0 end) as entropy from (select hid, x / sum(x) over (partition by hid) as p from (select hid, rank as x from inc join v4 using (vid))) group by hid)"
query("p_placed_entropy", sql.query(sql.pagerank("basket", 5), f"select hid, round(abs(entropy), 6) as entropy from {_BITS}"))(lambda spark, d: pagerank.pagerank_entropy(standins.plain_basket(spark, d), max_rounds=5, placement=HybridCut(5), parts=P).hyperedges.select("hid", F.round(F.abs("entropy"), 6).alias("entropy")))


@query("p_placed_paths", sql.query(sql.paths("basket", 8, "select min(vid) from inc", "1 + hid % 3"), "select vid, hops from v8"))
def p_placed_paths(spark: SparkSession, d: str) -> DataFrame:
    """Weighted paths: the costs lie with the placed memberships."""
    hf = standins.plain_basket(spark, d).with_hyperedge_columns(cost=F.expr("1 + hid % 3"))
    return paths.shortest_paths(hf, hf.incidence.agg(F.min("vid")).first()[0], weight="cost", placement=greedy_hyperedge_cut(mode="streams"), parts=P).vertices


query("p_greedy_streams", _with([sql.inc("basket"), *_choices("chosen", "hid", "vid", streams=8)], "select vid, hid, best::int as part from inc join chosen on id = hid"))(lambda spark, d: GreedyCut(mode="streams", hash=M).assign(standins.plain_basket(spark, d), P))
query("p_greedy_epochs", _epochs_sql("basket", 4, 8))(lambda spark, d: GreedyCut(mode="epochs", hash=M).assign(standins.plain_basket(spark, d), P))
query("p_greedy_hybrid", _greedy_hybrid_sql("basket", 5))(lambda spark, d: GreedyHybridCut(5, GreedyCut(hash=M)).assign(standins.plain_basket(spark, d), P))
query("p_iterative", _iterative_sql("supply", 10))(lambda spark, d: IterativeCut(10, M).assign(standins.supply(spark, d), P))


def _advice(name: str) -> str:
    """The advisor's rules over counts of replicas and loads."""
    distinct = lambda side, part: f"(select count(*) from (select distinct {side}, {part} from inc))"
    return f"""select '{name}' as name, case when n < 50000 then 'two_copy' when ratio >= 2 then (case when nv * {P} <= 1e9 then 'greedy_hyperedge' else 'random_hyperedge' end)
  when ratio <= 0.5 then (case when 2 * c <= 3.0 * a or loads > 1.2 then 'random_both' else 'random_vertex' end) when a <= b then 'random_vertex' else 'random_hyperedge' end as strategy
from (with inc as materialized ({sql.INC[name]}) select count(*) as n, count(distinct vid) as nv, count(distinct vid)::double / count(distinct hid) as ratio, {distinct("vid", H)} as a, {distinct("hid", V)} as b,
  {distinct("vid", B)} + {distinct("hid", B)} as c, (select max(k)::double / avg(k) from (select count(*) as k from inc group by {H})) as loads from inc)"""


@query("p_advise", " union all ".join(map(_advice, _NAMES)))
def p_advise(spark: SparkSession, d: str) -> DataFrame:
    return spark.createDataFrame([(n, report.advise(standins.STANDINS[n](spark, d), P, M, few=50_000)[0]) for n in _NAMES], "name string, strategy string")
