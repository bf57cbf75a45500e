"""Whole copies of a text, by digest: searches run on one of each, and the others follow it."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgengine.llm.common import cut, small


def with_first(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, digest (SHA-256 of the text, null as empty), first: the smallest doc_id of the same text."""
    text = F.coalesce("text", F.lit(""))
    rows = cut(docs.select("doc_id", F.octet_length(text).cast("long").alias("n_bytes"), F.sha2(text, 256).alias("digest")))
    firsts = rows.groupBy("digest").agg(F.min("doc_id").alias("first"), F.count("*").alias("n")).where("n > 1").drop("n")
    found = rows.join(firsts, "digest", "left")
    return cut(found.withColumn("first", F.coalesce("first", "doc_id")))


def distinct_texts(docs: DataFrame, firsts: DataFrame) -> DataFrame:
    """doc_id and text of the first document of each text."""
    return docs.select("doc_id", "text").join(small(cut(firsts.where("first <> doc_id").select("doc_id"))), "doc_id", "left_anti")


def texts_of(docs: DataFrame, ids: DataFrame) -> DataFrame:
    """doc_id and text of the documents whose ids are in ids (one column doc_id, distinct, cut)."""
    return docs.select("doc_id", "text").join(small(ids), "doc_id", "left_semi")
