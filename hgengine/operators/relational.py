"""Relational operators around hypergraphs: scans, joins, aggregates, windows, sorts, sets, subqueries."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hgengine import sql
from hgengine.registry import query
from hgengine.session import scratch
from hgengine.sources import standins
from hgengine.sources.tables import load, read_membership

S = SparkSession


def _view(spark: S, d: str, *names: str) -> None:
    for n in names:
        load(spark, d, n).createOrReplaceTempView(n)


def sql_query(name: str, text: str, *tables: str, oracle: str | None = None) -> None:
    """A query that is the same SQL in both engines."""

    def run(spark: S, d: str) -> DataFrame:
        _view(spark, d, *tables)
        return spark.sql(text)

    query(name, oracle or text)(run)


# --- scans, sinks ------------------------------------------------------------------------------------------------

query("o_scan_pruned", "select l_orderkey, l_partkey, l_quantity from lineitem where l_shipdate >= date '1998-01-01'")(lambda spark, d: load(spark, d, "lineitem", ["l_orderkey", "l_partkey", "l_quantity"], "l_shipdate >= timestamp_ntz '1998-01-01 00:00:00'"))


@query("o_sink_roundtrip", sql.query([sql.inc("nation")], f"select vid, hid, {sql.modular('vid', 4)} as part from inc"))
def o_sink_roundtrip(spark: S, d: str) -> DataFrame:
    from hgengine.placement.strategies import place, random_hyperedge_cut
    from hgengine.sources.tables import restore, save

    path = scratch(spark, "sink")
    save(place(standins.nation(spark, d), random_hyperedge_cut("modular"), 4), path, by_part=True)
    return restore(spark, path).incidence.select("vid", "hid", F.col("part").cast("int").alias("part"))


@query("o_csv_json_roundtrip", sql.query([sql.inc("nation")], "select vid, hid, 2 as n from inc"))
def o_csv_json_roundtrip(spark: S, d: str) -> DataFrame:
    inc, found = standins.nation(spark, d).incidence.select("vid", "hid"), None
    for fmt in ("csv", "json"):
        path = scratch(spark, fmt)
        (inc.write.csv(path, sep="\t") if fmt == "csv" else inc.write.json(path))
        part = read_membership(spark, path, fmt).incidence.select("vid", "hid")
        found = part if found is None else found.unionByName(part)
    return found.groupBy("vid", "hid").agg(F.count("*").cast("int").alias("n"))


@query("o_orc_text_roundtrip", sql.query([sql.inc("hour")], "select vid, count(*) as n from inc group by vid"))
def o_orc_text_roundtrip(spark: S, d: str) -> DataFrame:
    inc = standins.hour(spark, d).incidence
    path = scratch(spark, "lines")
    inc.groupBy("hid").agg(F.array_join(F.collect_list("vid"), " ").alias("value")).select("value").write.text(path)
    lines = read_membership(spark, path, layout="lines").incidence
    orc = scratch(spark, "orc")
    lines.select("vid", "hid").write.orc(orc)
    return read_membership(spark, orc, "orc").incidence.groupBy("vid").agg(F.count("*").alias("n"))


query("o_filter_predicates", "select p_partkey from part where p_brand in ('Brand#11', 'Brand#12', 'Brand#13', 'Brand#23') and p_size between 5 and 30 or p_type like '%STEEL%' and p_name is not null and p_partkey is not distinct from p_partkey")(
    lambda spark, d: load(spark, d, "part", ["p_partkey"], (F.col("p_brand").isin("Brand#11", "Brand#12", "Brand#13", "Brand#23") & F.col("p_size").between(5, 30)) | (F.col("p_type").like("%STEEL%") & F.col("p_name").isNotNull() & F.col("p_partkey").eqNullSafe(F.col("p_partkey"))))
)
query("o_project_case", "select p_partkey, case when p_size < 10 then 'small' when p_size < 30 then 'middle' else 'large' end as band from part")(lambda spark, d: load(spark, d, "part").select("p_partkey", F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "middle").otherwise("large").alias("band")))

# --- joins ----------------------------------------------------------------------------------------------------------


@query("o_join_broadcast", sql.query([sql.inc("basket")], "select vid, hid from inc where vid in (select vid from inc group by vid having count(*) > 40)"))
def o_join_broadcast(spark: S, d: str) -> DataFrame:
    """Heavy vertices are at most memberships / 40; the hint is given after a count."""
    from hgengine.session import cut, small

    inc = standins.plain_basket(spark, d).incidence
    heavy = cut(inc.groupBy("vid").agg(F.count("*").alias("n")).where("n > 40").select("vid"))
    return inc.select("vid", "hid").join(small(heavy), "vid")


for _hint in ("shuffle_hash", "merge"):
    query(f"o_join_{_hint.replace('shuffle_', '')}", "select o_orderstatus as status, count(*) as n from orders join lineitem on o_orderkey = l_orderkey group by 1")(
        lambda spark, d, h=_hint: load(spark, d, "lineitem", ["l_orderkey"]).join(load(spark, d, "orders", ["o_orderkey", "o_orderstatus"]).hint(h), F.col("l_orderkey") == F.col("o_orderkey")).groupBy(F.col("o_orderstatus").alias("status")).agg(F.count("*").alias("n"))
    )


@query("o_join_theta", sql.query([sql.inc("supply"), "k as (select hid, count(*) as k from inc group by hid)"], "select a.hid as a, b.hid as b from k a join k b on a.k > 1.2 * b.k"))
def o_join_theta(spark: S, d: str) -> DataFrame:
    """Pairs of hyperedges by size: buckets of the ratio's logarithm make it an equality, so nothing is crossed."""
    k = standins.supply(spark, d).incidence.groupBy("hid").agg(F.count("*").alias("k")).withColumn("bucket", F.floor(F.log("k") / F.log(F.lit(1.2))))
    top = k.agg(F.max("bucket")).first()[0] or 0
    low = k.select(F.col("hid").alias("b"), F.col("k").alias("k_b"), F.explode(F.sequence("bucket", F.lit(top))).alias("bucket"))
    return k.select(F.col("hid").alias("a"), F.col("k").alias("k_a"), "bucket").join(low, "bucket").where(F.col("k_a") > 1.2 * F.col("k_b")).select("a", "b")


@query("o_join_range", "select e.event_id, count(*) as near from events e join events x on e.user_id = x.user_id and x.event_type = 'error' and abs(epoch(e.ts) - epoch(x.ts)) <= 3600 group by e.event_id")
def o_join_range(spark: S, d: str) -> DataFrame:
    """Events within an hour of an error of the user: hour buckets next to each other bound the interval."""
    e = load(spark, d, "events", ["event_id", "user_id", "ts", "event_type"]).withColumn("at", F.unix_micros(F.col("ts").cast("timestamp")))
    e = e.withColumn("slot", F.floor(F.col("at") / 3_600_000_000))
    x = e.where("event_type = 'error'").select("user_id", F.col("at").alias("at_x"), F.explode(F.sequence(F.col("slot") - 1, F.col("slot") + 1)).alias("slot"))
    return e.join(x, ["user_id", "slot"]).where(F.abs(F.col("at") - F.col("at_x")) <= 3_600_000_000).groupBy("event_id").agg(F.count("*").alias("near"))


@query("o_join_asof", "select p.event_id, (select max_by(v.event_id, (epoch_us(v.ts), v.event_id)) from events v where v.user_id = p.user_id and v.event_type = 'view' and (v.ts < p.ts or v.ts = p.ts and v.event_id < p.event_id)) as prev_view from events p where p.event_type = 'purchase'")
def o_join_asof(spark: S, d: str) -> DataFrame:
    """The last earlier view of each purchase: one sort of both kinds, no join."""
    e = load(spark, d, "events", ["event_id", "user_id", "ts", "event_type"], "event_type in ('view', 'purchase')")
    before = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = e.withColumn("prev_view", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(before))
    return seen.where("event_type = 'purchase'").select("event_id", "prev_view")


query("o_join_left", "select s_suppkey, count(l_orderkey) as n from supplier left join lineitem on s_suppkey = l_suppkey and l_returnflag = 'R' group by 1")(
    lambda spark, d: load(spark, d, "supplier", ["s_suppkey"]).join(load(spark, d, "lineitem", ["l_suppkey", "l_orderkey"], "l_returnflag = 'R'"), F.col("s_suppkey") == F.col("l_suppkey"), "left").groupBy("s_suppkey").agg(F.count("l_orderkey").alias("n"))
)
sql_query("o_join_full", "select coalesce(c.k, s.k) as k, c.n as customers, s.n as suppliers from (select c_nationkey as k, count(*) as n from customer where c_acctbal > 5000 group by 1) c full join (select s_nationkey as k, count(*) as n from supplier where s_acctbal < 5000 group by 1) s on c.k = s.k", "customer", "supplier")
query("o_join_semi", "select o_orderkey from orders where exists (select 1 from lineitem where l_orderkey = o_orderkey and l_quantity > 45)")(lambda spark, d: load(spark, d, "orders", ["o_orderkey"]).join(load(spark, d, "lineitem", ["l_orderkey"], "l_quantity > 45"), F.col("o_orderkey") == F.col("l_orderkey"), "left_semi"))
query("o_join_anti", "select o_orderkey from orders where not exists (select 1 from lineitem where l_orderkey = o_orderkey)")(lambda spark, d: load(spark, d, "orders", ["o_orderkey"]).join(load(spark, d, "lineitem", ["l_orderkey"]), F.col("o_orderkey") == F.col("l_orderkey"), "left_anti"))
sql_query("o_join_cross", "select n_name, r_name, n_regionkey = r_regionkey as inside from nation cross join region", "nation", "region")
query("o_join_self", "select a.s_suppkey as a, b.s_suppkey as b from supplier a join supplier b on a.s_nationkey = b.s_nationkey and a.s_suppkey < b.s_suppkey")(
    lambda spark, d: load(spark, d, "supplier").alias("a").join(load(spark, d, "supplier").alias("b"), (F.col("a.s_nationkey") == F.col("b.s_nationkey")) & (F.col("a.s_suppkey") < F.col("b.s_suppkey"))).select(F.col("a.s_suppkey").alias("a"), F.col("b.s_suppkey").alias("b"))
)
sql_query("o_join_lateral", "select n_nationkey, t.s_suppkey from nation, lateral (select s_suppkey from supplier where s_nationkey = n_nationkey order by s_acctbal desc, s_suppkey limit 2) t", "nation", "supplier")
query("o_join_multiway", "select r_name, round(sum(l_extendedprice * (1 - l_discount)), 4) as revenue from region join nation on n_regionkey = r_regionkey join customer on c_nationkey = n_nationkey join orders on o_custkey = c_custkey join lineitem on l_orderkey = o_orderkey group by 1")(
    lambda spark, d: (
        load(spark, d, "lineitem", ["l_orderkey", "l_extendedprice", "l_discount"])
        .join(load(spark, d, "orders", ["o_orderkey", "o_custkey"]), F.col("l_orderkey") == F.col("o_orderkey"))
        .join(load(spark, d, "customer", ["c_custkey", "c_nationkey"]), F.col("o_custkey") == F.col("c_custkey"))
        .join(load(spark, d, "nation"), F.col("c_nationkey") == F.col("n_nationkey"))
        .join(load(spark, d, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
        .groupBy("r_name")
        .agg(F.round(F.sum(F.col("l_extendedprice") * (1 - F.col("l_discount"))), 4).alias("revenue"))
    )
)

# --- aggregates -----------------------------------------------------------------------------------------------------

query("o_agg_hash", "select l_returnflag as flag, l_linestatus as status, count(*) as n, round(sum(l_extendedprice), 4) as revenue from lineitem group by all")(lambda spark, d: load(spark, d, "lineitem").groupBy(F.col("l_returnflag").alias("flag"), F.col("l_linestatus").alias("status")).agg(F.count("*").alias("n"), F.round(F.sum("l_extendedprice"), 4).alias("revenue")))
query("o_agg_distinct", "select l_orderkey as hid, count(distinct l_partkey) as parts from lineitem group by 1")(lambda spark, d: load(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("hid")).agg(F.count_distinct("l_partkey").alias("parts")))
query("o_agg_multi_distinct", "select l_orderkey as hid, count(distinct l_partkey) as parts, count(distinct l_suppkey) as suppliers from lineitem group by 1")(lambda spark, d: load(spark, d, "lineitem").groupBy(F.col("l_orderkey").alias("hid")).agg(F.count_distinct("l_partkey").alias("parts"), F.count_distinct("l_suppkey").alias("suppliers")))
_Y = "(select year(o_orderdate)::int as year, o_orderstatus as status, o_orderpriority as priority from orders)"
for _n, _g, _f in (("rollup", "rollup(year, status)", "rollup"), ("cube", "cube(year, status)", "cube")):
    query(f"o_agg_{_n}", f"select year, status, count(*) as n, grouping_id(year, status)::bigint as gid from {_Y} group by {_g}")(
        lambda spark, d, f=_f: getattr(load(spark, d, "orders").select(F.year("o_orderdate").alias("year"), F.col("o_orderstatus").alias("status")), f)("year", "status").agg(F.count("*").alias("n"), F.grouping_id("year", "status").cast("long").alias("gid"))
    )
query("o_agg_grouping_sets", f"select year, status, priority, count(*) as n from {_Y} group by grouping sets ((year, status), (priority), ())")(
    lambda spark, d: load(spark, d, "orders").select(F.year("o_orderdate").alias("year"), F.col("o_orderstatus").alias("status"), F.col("o_orderpriority").alias("priority")).groupingSets([[F.col("year"), F.col("status")], [F.col("priority")], []], F.col("year"), F.col("status"), F.col("priority")).agg(F.count("*").alias("n"))
)
_TYPES = ("click", "error", "purchase", "signup", "view")
query("o_agg_pivot", "select epoch_us(ts) // 86400000000 as day, " + ", ".join(f"count(*) filter (event_type = '{t}') as {t}" for t in _TYPES) + " from events group by 1")(
    lambda spark, d: load(spark, d, "events").groupBy(F.expr("unix_timestamp(cast(ts as timestamp)) div 86400").alias("day")).pivot("event_type", list(_TYPES)).count().na.fill(0)
)
query("o_agg_filtered", "select o_orderstatus as status, count(*) filter (o_totalprice > 100000) as large, round(sum(o_totalprice) filter (o_orderpriority = '1-URGENT'), 4) as urgent from orders group by 1")(lambda spark, d: load(spark, d, "orders").groupBy(F.col("o_orderstatus").alias("status")).agg(F.count_if(F.col("o_totalprice") > 100000).alias("large"), F.round(F.sum(F.when(F.col("o_orderpriority") == "1-URGENT", F.col("o_totalprice"))), 4).alias("urgent")))
query("o_agg_percentile", "select quantile_cont(n, 0.5)::double as p50, quantile_cont(n, 0.9)::double as p90 from (select count(distinct l_partkey) as n from lineitem group by l_orderkey)")(lambda spark, d: standins.plain_basket(spark, d).incidence.groupBy("hid").agg(F.count("*").alias("n")).agg(F.percentile("n", 0.5).alias("p50"), F.percentile("n", 0.9).alias("p90")))


@query("o_agg_approx", "select * from (values ('distinct', true), ('hll', true), ('kll', true), ('percentile', true), ('theta', true)) t(name, ok)")
def o_agg_approx(spark: S, d: str) -> DataFrame:
    """Sketches are within 5 % of the exact values."""
    rows = load(spark, d, "lineitem", ["l_partkey", "l_extendedprice"])
    near = lambda a, b: F.abs(a - b) <= 0.05 * b
    n, mid = F.count_distinct("l_partkey"), F.percentile("l_extendedprice", 0.5)
    flags = {
        "distinct": near(F.approx_count_distinct("l_partkey", 0.01), n),
        "hll": near(F.hll_sketch_estimate(F.hll_sketch_agg("l_partkey", F.lit(14))), n),
        "kll": near(F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("l_extendedprice"), F.lit(0.5)), mid),
        "percentile": near(F.percentile_approx("l_extendedprice", 0.5, 10000), mid),
        "theta": near(F.theta_sketch_estimate(F.theta_sketch_agg("l_partkey")), n),
    }
    row = rows.agg(*(c.alias(k) for k, c in flags.items()))
    return row.select(F.explode(F.map_from_arrays(F.array(*map(F.lit, flags)), F.array(*flags))).alias("name", "ok"))


query("o_agg_max_by", "select l_orderkey as hid, arg_max(l_partkey, (p_retailprice, -l_partkey)) as vid from lineitem join part on p_partkey = l_partkey group by 1")(lambda spark, d: standins.basket(spark, d).incidence.join(load(spark, d, "part").select(F.col("p_partkey").alias("vid"), "p_retailprice"), "vid").groupBy("hid").agg(F.max_by("vid", F.struct("p_retailprice", -F.col("vid"))).alias("vid")))
query("o_agg_stats", "select round(stddev(o_totalprice), 4) as sd, round(var_pop(o_totalprice), 2) as vp, round(corr(o_totalprice, o_custkey), 6) as c, round(covar_samp(o_totalprice, o_custkey), 3) as cov from orders")(lambda spark, d: load(spark, d, "orders").agg(F.round(F.stddev("o_totalprice"), 4).alias("sd"), F.round(F.var_pop("o_totalprice"), 2).alias("vp"), F.round(F.corr("o_totalprice", "o_custkey"), 6).alias("c"), F.round(F.covar_samp("o_totalprice", "o_custkey"), 3).alias("cov")))
query("o_agg_having", sql.query([sql.inc("basket")], "select hid, count(*) as n from inc group by hid having count(*) > 6"))(lambda spark, d: standins.plain_basket(spark, d).incidence.groupBy("hid").agg(F.count("*").alias("n")).where("n > 6"))

# --- windows ------------------------------------------------------------------------------------------------------

_NATION = "partition by c_nationkey order by c_acctbal desc, c_custkey"
query("o_win_rank", f"select c_custkey, rank() over ({_NATION})::int as r, dense_rank() over ({_NATION})::int as dr, row_number() over ({_NATION})::int as rn, round(percent_rank() over ({_NATION}), 6) as pr from customer")(
    lambda spark, d: load(spark, d, "customer").select("c_custkey", F.rank().over(_w()).alias("r"), F.dense_rank().over(_w()).alias("dr"), F.row_number().over(_w()).alias("rn"), F.round(F.percent_rank().over(_w()), 6).alias("pr"))
)


def _w():
    return Window.partitionBy("c_nationkey").orderBy(F.desc("c_acctbal"), "c_custkey")


query("o_win_ntile", f"select c_custkey, ntile(4) over ({_NATION})::int as q from customer")(lambda spark, d: load(spark, d, "customer").select("c_custkey", F.ntile(4).over(_w()).alias("q")))
query("o_win_cume", f"select c_custkey, round(cume_dist() over ({_NATION}), 6) as c from customer")(lambda spark, d: load(spark, d, "customer").select("c_custkey", F.round(F.cume_dist().over(_w()), 6).alias("c")))
query("o_win_lag", "select event_id, epoch_us(ts) // 1000000 - epoch_us(lag(ts) over (partition by user_id order by ts, event_id)) // 1000000 as gap from events")(
    lambda spark, d: load(spark, d, "events").select("event_id", (F.unix_seconds(F.col("ts").cast("timestamp")) - F.unix_seconds(F.lag(F.col("ts").cast("timestamp")).over(Window.partitionBy("user_id").orderBy("ts", "event_id")))).alias("gap"))
)
query("o_win_frame_rows", "select event_id, round(avg(value) over (partition by user_id order by ts, event_id rows between 2 preceding and current row), 6) as value from events")(lambda spark, d: load(spark, d, "events").select("event_id", F.round(F.avg("value").over(Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-2, 0)), 6).alias("value")))
query("o_win_frame_range", "select event_id, round(sum(value) over (partition by user_id order by epoch_us(ts) range between 86400000000 preceding and current row), 6) as value from events")(
    lambda spark, d: load(spark, d, "events").withColumn("at", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.round(F.sum("value").over(Window.partitionBy("user_id").orderBy("at").rangeBetween(-86_400_000_000, 0)), 6).alias("value"))
)
query("o_win_topk_members", "select l_suppkey as hid, l_partkey as vid, rk from (select l_suppkey, l_partkey, row_number() over (partition by l_suppkey order by round(sum(l_extendedprice), 4) desc, l_partkey)::int as rk from lineitem group by 1, 2) where rk <= 3")(
    lambda spark, d: load(spark, d, "lineitem").groupBy(F.col("l_suppkey").alias("hid"), F.col("l_partkey").alias("vid")).agg(F.round(F.sum("l_extendedprice"), 4).alias("r")).withColumn("rk", F.row_number().over(Window.partitionBy("hid").orderBy(F.desc("r"), "vid"))).where("rk <= 3").select("hid", "vid", "rk")
)

# --- sort, sets, subqueries -----------------------------------------------------------------------------------------

query("o_sort_topk", "select o_orderkey, o_totalprice from orders order by o_totalprice desc, o_orderkey limit 20")(lambda spark, d: load(spark, d, "orders", ["o_orderkey", "o_totalprice"]).orderBy(F.desc("o_totalprice"), "o_orderkey").limit(20))
query("o_limit_offset", "select p_partkey from part order by p_partkey limit 50 offset 100")(lambda spark, d: load(spark, d, "part", ["p_partkey"]).orderBy("p_partkey").offset(100).limit(50))


def _half(spark: S, d: str, first: bool) -> DataFrame:
    side = "ts < timestamp_ntz '2024-01-16 00:00:00'" if first else "ts >= timestamp_ntz '2024-01-16 00:00:00'"
    return load(spark, d, "events", ["user_id", "ts"], side).select(F.col("user_id").alias("vid"), F.hour("ts").alias("h"))


_H1, _H2 = (f"select user_id as vid, hour(ts)::int as h from events where ts {op} timestamp '2024-01-16'" for op in ("<", ">="))
for _n, _op, _f in (("union", "union", lambda a, b: a.union(b).distinct()), ("union_all", "union all", DataFrame.unionAll), ("intersect", "intersect", DataFrame.intersect), ("except", "except", DataFrame.subtract), ("intersect_all", "intersect all", DataFrame.intersectAll), ("except_all", "except all", DataFrame.exceptAll)):
    query(f"o_set_{_n}", f"{_H1} {_op} {_H2}")(lambda spark, d, f=_f: f(_half(spark, d, True), _half(spark, d, False)))

sql_query("o_subquery_scalar", "select o_orderkey from orders where o_totalprice > (select avg(o_totalprice) from orders)", "orders")
sql_query("o_subquery_exists", "select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_orderstatus = 'F')", "customer", "orders")
sql_query("o_subquery_in", "select s_suppkey from supplier where s_nationkey in (select n_nationkey from nation where n_regionkey = 1)", "supplier", "nation")
sql_query("o_subquery_correlated", "select o_orderkey from orders o where o_totalprice > (select 1.5 * avg(o_totalprice) from orders i where i.o_custkey = o.o_custkey)", "orders")
sql_query("o_cte", "with big as (select l_orderkey as k, sum(l_quantity) as q from lineitem group by l_orderkey having sum(l_quantity) > 150), best as (select max(q) as q from big) select k, big.q from big, best where big.q > 0.8 * best.q", "lineitem")
sql_query("o_cte_recursive", "with recursive k as (select l_linenumber as n, count(*) as c from lineitem group by l_linenumber), t(n, f, lines) as (select n, cast(n as bigint), c from k where n = 1 union all select k.n, t.f * k.n, t.lines + k.c from t join k on k.n = t.n + 1) select n, f, lines from t", "lineitem")


@query("o_compact", sql.query([sql.inc("basket")], "select members, count(*) as n from (select string_agg(vid::varchar, ',' order by vid) as members from inc group by hid) group by members"))
def o_compact(spark: S, d: str) -> DataFrame:
    """Hyperedges with the same members become one."""
    members = standins.plain_basket(spark, d).incidence.groupBy("hid").agg(F.array_join(F.sort_array(F.collect_list("vid")).cast("array<string>"), ",").alias("members"))
    return members.groupBy("members").agg(F.count("*").alias("n"))
