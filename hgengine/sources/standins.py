"""Hypergraphs of the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from hgengine.model import HyperFrame
from hgengine.sources.tables import load


def _vertices(spark: SparkSession, d: str, table: str, key: str, *keep: str) -> DataFrame:
    return load(spark, d, table).select(F.col(key).alias("vid"), *keep)


def _occurring(hf: HyperFrame) -> HyperFrame:
    """Without members that have no membership."""
    return hf.restrict(drop_empty=True, drop_isolated=True)


def basket(spark: SparkSession, d: str, weight=None) -> HyperFrame:
    """Parts as vertices, orders as hyperedges."""
    orders = load(spark, d, "orders").select(F.col("o_orderkey").alias("hid"), "o_totalprice", "o_orderdate", "o_orderstatus", "o_orderpriority")
    sums = {"quantity": F.sum("l_quantity"), "revenue": F.sum("l_extendedprice")}
    return HyperFrame.from_table(load(spark, d, "lineitem"), "l_partkey", "l_orderkey", weight, sums, _vertices(spark, d, "part", "p_partkey", "p_brand", "p_type", "p_size", "p_retailprice"), orders)


def plain_basket(spark: SparkSession, d: str, weight=None) -> HyperFrame:
    """basket without attributes: two columns of one table, and ids that occur."""
    rows = load(spark, d, "lineitem", ["l_partkey", "l_orderkey"])
    hs = None
    if weight is not None:
        hs = load(spark, d, "orders").select(F.col("o_orderkey").alias("hid"), weight.cast("double").alias("weight"))
    hf = HyperFrame.from_table(rows, "l_partkey", "l_orderkey", hyperedges=hs)
    return hf if hs is None else hf.restrict(drop_empty=True)


def dual(spark: SparkSession, d: str) -> HyperFrame:
    return HyperFrame.from_table(load(spark, d, "lineitem", ["l_partkey", "l_orderkey"]), "l_orderkey", "l_partkey")


def buyers(spark: SparkSession, d: str) -> HyperFrame:
    orders = load(spark, d, "orders", ["o_orderkey", "o_custkey"])
    lines = load(spark, d, "lineitem", ["l_orderkey", "l_partkey"])
    return HyperFrame.from_table(lines.join(orders, lines.l_orderkey == orders.o_orderkey), "o_custkey", "l_partkey")


def vendor(spark: SparkSession, d: str) -> HyperFrame:
    return HyperFrame.from_table(load(spark, d, "lineitem", ["l_suppkey", "l_orderkey"]), "l_suppkey", "l_orderkey")


def supply(spark: SparkSession, d: str) -> HyperFrame:
    return HyperFrame.from_table(load(spark, d, "lineitem", ["l_partkey", "l_suppkey"]), "l_partkey", "l_suppkey")


def hour(spark: SparkSession, d: str) -> HyperFrame:
    return HyperFrame.from_windows(load(spark, d, "events", ["user_id", "ts", "value"]), "user_id", "ts")


def words(spark: SparkSession, d: str, ids: bool = True) -> HyperFrame:
    return HyperFrame.from_tokens(load(spark, d, "documents", ["doc_id", "text"]), "doc_id", "text", ids)


def words_by_md5(spark: SparkSession, d: str) -> HyperFrame:
    """words with ids that any SQL can make: the first 60 bits of the digest."""
    word = F.explode(F.split(F.lower("text"), " "))
    rows = load(spark, d, "documents", ["doc_id", "text"]).select("doc_id", word.alias("w")).where("w <> ''")
    return HyperFrame.from_table(rows, F.conv(F.substring(F.md5("w"), 1, 15), 16, 10).cast("long"), "doc_id")


def nation(spark: SparkSession, d: str) -> HyperFrame:
    return HyperFrame.from_table(load(spark, d, "customer", ["c_custkey", "c_nationkey"]), "c_custkey", F.col("c_nationkey").cast("long"))


def links(spark: SparkSession, d: str) -> HyperFrame:
    return HyperFrame.from_links(load(spark, d, "pages", ["page_id", "html"]), "page_id", "html")


def turns(spark: SparkSession, d: str) -> HyperFrame:
    return HyperFrame.from_tokens(load(spark, d, "conversations", ["conv_id", "text"]), "conv_id", "text")


def classes(spark: SparkSession, d: str) -> HyperFrame:
    return HyperFrame.from_table(load(spark, d, "embeddings", ["vec_id", "label"]), F.col("vec_id"), F.col("label").cast("long"))


STANDINS = {"basket": plain_basket, "dual": dual, "buyers": buyers, "vendor": vendor, "supply": supply, "hour": hour, "words": words, "nation": nation, "links": links, "turns": turns, "class": classes}
