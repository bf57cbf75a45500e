"""User functions: scalar, vectorised, grouped, cogrouped, tabular, and programs in Python."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hgengine import sql
from hgengine.functions.pandas_program import PandasProgram, iterate_pandas
from hgengine.registry import query
from hgengine.sources import standins
from hgengine.sources.tables import load

S = SparkSession
_PAIR = "select hid, round(len(list_intersect(u, v)) / len(list_distinct(list_concat(u, v))), 6) as jaccard from m where u is not null"
_M = "m as (select hid, v, lag(v) over (partition by hid // 64 order by hid) as u from (select hid, list(vid order by vid) as v from inc group by hid))"


def _consecutive(spark: S, d: str) -> DataFrame:
    from pyspark.sql import Window

    m = standins.plain_basket(spark, d).incidence.groupBy("hid").agg(F.sort_array(F.collect_list("vid")).alias("v"))
    return m.withColumn("u", F.lag("v").over(Window.partitionBy(F.expr("hid div 64")).orderBy("hid"))).where("u is not null")


@query("u_udf", sql.query([sql.inc("basket"), _M], _PAIR))
def u_udf(spark: S, d: str) -> DataFrame:
    jaccard = F.udf(lambda u, v: len(set(u) & set(v)) / len(set(u) | set(v)), "double")
    return _consecutive(spark, d).select("hid", F.round(jaccard("u", "v"), 6).alias("jaccard"))


@query("u_pandas_udf", "select vec_id, round(list_sum(list_transform(embedding, lambda x: abs(x::double))), 3) as l1 from embeddings")
def u_pandas_udf(spark: S, d: str) -> DataFrame:
    @F.pandas_udf("double")
    def l1(x: pd.Series) -> pd.Series:
        return x.map(lambda a: float(abs(a.astype(float)).sum()))

    return load(spark, d, "embeddings").select("vec_id", F.round(l1("embedding"), 3).alias("l1"))


@query("u_udaf", "select l_returnflag as flag, round(sum(l_discount * l_quantity) / sum(l_quantity), 6) as mean from lineitem group by 1")
def u_udaf(spark: S, d: str) -> DataFrame:
    @F.pandas_udf("double")
    def weighted(x: pd.Series, w: pd.Series) -> float:
        return float((x * w).sum() / w.sum())

    return load(spark, d, "lineitem").groupBy(F.col("l_returnflag").alias("flag")).agg(F.round(weighted("l_discount", "l_quantity"), 6).alias("mean"))


_ENTROPY = "select l_orderkey as hid, round(abs(-sum(p * log2(p))), 6) as entropy from (select l_orderkey, l_quantity / sum(l_quantity) over (partition by l_orderkey) as p from lineitem) group by 1"


def _bits(x: pd.Series) -> float:
    p = x / x.sum()
    return round(abs(-sum(v * math.log2(v) for v in p)), 6)


#: Hyperedges of consecutive ids in a group that Python is called for; a call costs more than many hyperedges do.
RUN = 4096


@query("u_apply_in_pandas", _ENTROPY)
def u_apply_in_pandas(spark: S, d: str) -> DataFrame:
    """A group is a run of ids, within which pandas groups by id: no hyperedge is parted, and null is one too."""

    def run(g: pd.DataFrame) -> pd.DataFrame:
        q = g["l_quantity"].astype(float)
        p = q / q.groupby(g["l_orderkey"], dropna=False).transform("sum")
        bits = (p * np.log2(p)).groupby(g["l_orderkey"], dropna=False).sum(min_count=1)
        return pd.DataFrame({"hid": bits.index, "entropy": bits.abs().round(6).to_numpy()})

    rows = load(spark, d, "lineitem", ["l_orderkey", "l_quantity"])
    return rows.groupBy(F.expr(f"l_orderkey div {RUN}")).applyInPandas(run, "hid long, entropy double")


@query("u_apply_in_arrow", _ENTROPY)
def u_apply_in_arrow(spark: S, d: str) -> DataFrame:
    def run(g: pa.Table) -> pa.Table:
        return pa.table({"hid": [g["l_orderkey"][0].as_py()], "entropy": [_bits(g["l_quantity"].to_pandas())]})

    return load(spark, d, "lineitem", ["l_orderkey", "l_quantity"]).groupBy("l_orderkey").applyInArrow(run, "hid long, entropy double")


@query("u_cogroup", "select coalesce(a.u, b.u) as user_id, coalesce(b.n, 0) - coalesce(a.n, 0) as change from (select user_id as u, count(*) as n from events where ts < timestamp '2024-01-16' group by 1) a full join (select user_id as u, count(*) as n from events where ts >= timestamp '2024-01-16' group by 1) b on a.u = b.u")
def u_cogroup(spark: S, d: str) -> DataFrame:
    e = load(spark, d, "events", ["user_id", "ts"])
    first, second = (e.where(f"ts {op} timestamp_ntz '2024-01-16 00:00:00'").select("user_id") for op in ("<", ">="))

    def change(a: pd.DataFrame, b: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"user_id": [(a if len(a) else b)["user_id"].iloc[0]], "change": [len(b) - len(a)]})

    return first.groupBy("user_id").cogroup(second.groupBy("user_id")).applyInPandas(change, "user_id long, change long")


@query("u_udtf", sql.query([sql.inc("basket")], "select distinct a.vid, b.vid as neighbour from inc a join inc b on a.hid = b.hid and a.vid <> b.vid where a.vid = (select min(vid) from inc)"))
def u_udtf(spark: S, d: str) -> DataFrame:
    """neighbours(members, vid): a table function over the hyperedges of one vertex."""

    @F.udtf(returnType="vid: bigint, neighbour: bigint")
    class Neighbours:
        def eval(self, members: list, vid: int):
            for m in members:
                if m != vid:
                    yield vid, m

    inc = standins.plain_basket(spark, d).incidence
    least = inc.agg(F.min("vid")).first()[0]
    near = inc.join(inc.where(F.col("vid") == least).select("hid"), "hid", "left_semi").groupBy("hid").agg(F.collect_list("vid").alias("members"))
    near.createOrReplaceTempView("near_hyperedges")
    spark.udtf.register("neighbours", Neighbours)
    return spark.sql(f"select distinct n.vid, n.neighbour from near_hyperedges, lateral neighbours(members, {least}L) n")


@query("u_sql_function", "select p_partkey, case when p_size < 10 then 'small' when p_size < 30 then 'middle' else 'large' end as band from part")
def u_sql_function(spark: S, d: str) -> DataFrame:
    spark.sql("create or replace temporary function size_band(n int) returns string return case when n < 10 then 'small' when n < 30 then 'middle' else 'large' end")
    load(spark, d, "part").createOrReplaceTempView("part")
    return spark.sql("select p_partkey, size_band(p_size) as band from part")


@query("u_data_source", "select vid, count(*) as degree from (select distinct l_orderkey as hid, l_partkey as vid from lineitem) group by vid")
def u_data_source(spark: S, d: str) -> DataFrame:
    """Degrees of memberships that Spark leaves in the shared folder and Python's tasks read."""
    from hgengine.sources.synthetic import SyntheticHypergraph
    from hgengine.session import scratch, ship

    ship(spark)
    path = scratch(spark, "memberships")
    standins.plain_basket(spark, d).incidence.select("vid", "hid").write.parquet(path)
    spark.dataSource.register(SyntheticHypergraph)
    rows = spark.read.format("hypergraph").option("path", path).load()
    return rows.groupBy("vid").agg(F.count("*").alias("degree"))


@query("u_pandas_program", sql.query(sql.paths("basket", 12, "select min(vid) from inc"), "select vid, hops from v12"))
def u_pandas_program(spark: S, d: str) -> DataFrame:
    """Shortest paths by procedures over batches of nodes."""
    hf = standins.plain_basket(spark, d)
    source = hf.incidence.agg(F.min("vid")).first()[0]

    def nearer(cost: float):
        def run(pdf: pd.DataFrame, step: int) -> pd.DataFrame:
            better = pdf["message"].notna() & (pdf["hops"].isna() | (pdf["message"] < pdf["hops"]))
            hops = pdf["hops"].where(~better, pdf["message"])
            return pd.DataFrame({"id": pdf["id"], "hops": hops, "sent": hops + cost, "send": better})

        return run

    start = hf.vertices.select("vid", F.when(F.col("vid") == source, 0.0).alias("hops"))
    programs = PandasProgram(nearer(1.0), F.min), PandasProgram(nearer(0.0), F.min)
    return iterate_pandas(hf, start, hf.hyperedges.select("hid", F.lit(None).cast("double").alias("hops")), *programs, max_rounds=50).select("vid", "hops")
