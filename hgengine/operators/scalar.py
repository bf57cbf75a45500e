"""Scalar functions as hypergraph work needs them: names, links, dates, arrays, maps, JSON, hashes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from hgengine import sql
from hgengine.registry import query
from hgengine.sources import standins
from hgengine.sources.tables import load

query("o_fn_string", "select p_partkey, upper(p_name) as up, length(p_name) as n, substr(p_brand, 7) as brand, split_part(p_type, ' ', 1) as kind, levenshtein(p_brand, 'Brand#11')::int as far, trim(replace(p_name, ' ', '_')) as snake from part")(
    lambda spark, d: load(spark, d, "part").select("p_partkey", F.upper("p_name").alias("up"), F.length("p_name").cast("long").alias("n"), F.expr("substr(p_brand, 7)").alias("brand"), F.split_part("p_type", F.lit(" "), F.lit(1)).alias("kind"), F.levenshtein("p_brand", F.lit("Brand#11")).alias("far"), F.trim(F.replace("p_name", F.lit(" "), F.lit("_"))).alias("snake"))
)
query("o_fn_regex", "select page_id, len(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1))::bigint as links, regexp_extract(html, '<title>([^<]*)', 1) as title from pages")(
    lambda spark, d: load(spark, d, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).cast("long").alias("links"), F.regexp_extract("html", "<title>([^<]*)", 1).alias("title"))
)
query("o_fn_url", "select page_id, regexp_extract(url, '^[a-z]+://([^/?#:]*)', 1) as host, regexp_extract(url, '^[a-z]+://[^/?#]*([^?#]*)', 1) as path from pages")(lambda spark, d: load(spark, d, "pages").select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.parse_url("url", F.lit("PATH")).alias("path")))
query("o_fn_date", "select o_orderkey, year(o_orderdate)::int as y, quarter(o_orderdate)::int as q, (isodow(o_orderdate) % 7 + 1)::int as dow, epoch(date_trunc('month', o_orderdate))::bigint as month, date_diff('day', date '1995-01-01', o_orderdate::date)::int as days from orders")(
    lambda spark, d: load(spark, d, "orders").select("o_orderkey", F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q"), F.dayofweek("o_orderdate").alias("dow"), F.unix_timestamp(F.date_trunc("month", F.col("o_orderdate").cast("timestamp"))).alias("month"), F.datediff("o_orderdate", F.lit("1995-01-01").cast("date")).alias("days"))
)
query("o_fn_math", "select p_partkey, round(log2(p_retailprice), 6) as l, round(sqrt(p_retailprice), 6) as r, (p_partkey % 7)::bigint as m, greatest(p_size, 25)::int as g, (p_size & 7)::int as b, ceil(p_retailprice / 100)::bigint as bucket from part")(
    lambda spark, d: load(spark, d, "part").select("p_partkey", F.round(F.log2("p_retailprice"), 6).alias("l"), F.round(F.sqrt("p_retailprice"), 6).alias("r"), F.pmod("p_partkey", F.lit(7)).cast("long").alias("m"), F.greatest("p_size", F.lit(25)).alias("g"), F.col("p_size").bitwiseAND(7).alias("b"), F.ceil(F.col("p_retailprice") / 100).alias("bucket"))
)


@query("o_fn_array", sql.query([sql.inc("basket"), "m as (select hid, v, lag(v) over (partition by hid // 64 order by hid) as u from (select hid, list(vid order by vid) as v from inc group by hid))"], "select hid, round(len(list_intersect(u, v)) / len(list_distinct(list_concat(u, v))), 6) as jaccard from m where u is not null"))
def o_fn_array(spark: SparkSession, d: str) -> DataFrame:
    """Jaccard of the members of consecutive hyperedges, within runs of 64 ids: no task orders them all."""
    m = standins.plain_basket(spark, d).incidence.groupBy("hid").agg(F.sort_array(F.collect_list("vid")).alias("v"))
    m = m.withColumn("u", F.lag("v").over(Window.partitionBy(F.expr("hid div 64")).orderBy("hid"))).where("u is not null")
    return m.select("hid", F.round(F.size(F.array_intersect("u", "v")) / F.size(F.array_union("u", "v")), 6).alias("jaccard"))


query("o_fn_higher_order", "select vec_id, round(sqrt(list_sum(list_transform(embedding, lambda x: x::double * x::double))), 4) as norm, len(list_filter(embedding, lambda x: x > 0))::bigint as positive from embeddings")(
    lambda spark, d: load(spark, d, "embeddings").select("vec_id", F.round(F.sqrt(F.aggregate("embedding", F.lit(0.0), lambda s, x: s + x.cast("double") * x.cast("double"))), 4).alias("norm"), F.size(F.filter("embedding", lambda x: x > 0)).cast("long").alias("positive"))
)


@query("o_fn_map", "select user_id, string_agg(event_type || '=' || n, ',' order by event_type) as counts from (select user_id, event_type, count(*) as n from events group by all) group by user_id")
def o_fn_map(spark: SparkSession, d: str) -> DataFrame:
    counts = load(spark, d, "events").groupBy("user_id", "event_type").agg(F.count("*").alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    texts = F.transform(F.array_sort(F.map_entries("m")), lambda e: F.concat_ws("=", e["key"], e["value"].cast("string")))
    return maps.select("user_id", F.array_join(texts, ",").alias("counts"))


query("o_fn_json", "select event_id, json_extract_string(props, '$.k')::bigint as k from events")(lambda spark, d: load(spark, d, "events").select("event_id", F.from_json("props", "k long")["k"].alias("k")))
query("o_fn_variant", "select event_id, json_extract_string(props, '$.k')::bigint as k from events")(lambda spark, d: load(spark, d, "events").select("event_id", F.variant_get(F.parse_json("props"), "$.k", "long").alias("k")))
query("o_fn_hash_md5", "select n_nationkey, md5(n_name) as m, sha256(n_name) as s from nation")(lambda spark, d: load(spark, d, "nation").select("n_nationkey", F.md5("n_name").alias("m"), F.sha2("n_name", 256).alias("s")))
query("o_fn_listagg", "select n_regionkey, string_agg(n_name, ';' order by n_name) as names from nation group by 1")(lambda spark, d: load(spark, d, "nation").groupBy("n_regionkey").agg(F.array_join(F.sort_array(F.collect_list("n_name")), ";").alias("names")))
