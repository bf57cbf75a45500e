"""Quality rules by the frequency of lines across documents. DataFrame functions only.

Lines are normalised (lower case, digits as one, white space as one blank) and hashed; the distinct documents that have
a line are counted per host. A line in more documents than both limits allow is removed, and a document is rejected
when too few of its words remain. Base rules on each text alone come first.

Null and empty texts have no words and fail the base rules. Null hosts are one host. Lines without a word count
nowhere. Repeated documents count each. doc_id must be unique. An empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hgengine.llm.common import NOT_SPACE, SPACE, cut, free, small

#: A line may be in so many documents of a host, and in such a part of them.
MOST_DOCS, MOST_SHARE = 10, 0.002
#: Words that must remain, and their share of all.
LEAST_WORDS, LEAST_SHARE = 20, 0.3
SYMBOLS = "[^#*$%&|<>]"


def line_hash(line: Column) -> Column:
    """Hash of a normalised line; null if it has no word."""
    plain = F.trim(F.regexp_replace(F.regexp_replace(F.lower(line), rf"{SPACE}+", " "), "[0-9]+", "0"))
    return F.when(plain != "", F.xxhash64(plain))


def base_counts(docs: DataFrame, *keep: str) -> DataFrame:
    """doc_id, keep, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, lines (hash and words of each)."""
    text = F.coalesce(F.col("text"), F.lit(""))
    rows = docs.select("doc_id", *keep, text.alias("text"))
    rows = rows.withColumns({"words": F.regexp_extract_all("text", F.lit(f"{NOT_SPACE}+"), F.lit(0)), "rows": F.split("text", "\n")})
    rows = rows.withColumns({"n": F.size("words"), "full": F.filter("rows", lambda x: x.rlike(NOT_SPACE))})
    three = F.transform("words", lambda w, i: F.xxhash64(w, F.get("words", i + 1), F.get("words", i + 2)))
    rows = rows.withColumn("three", F.when(F.col("n") >= 3, F.slice(three, F.lit(1), F.col("n") - 2)).otherwise(F.array().cast("array<long>")))
    sorted_ = F.when(F.size(F.array_distinct("three")) < F.size("three"), F.sort_array(F.transform("three", lambda h, i: F.struct(h.alias("h"), i.alias("i")))))
    rows = rows.withColumn("sorted", sorted_)
    twice = F.filter("sorted", lambda x, i: F.coalesce((x["h"] == F.get("sorted", i - 1)["h"]), F.lit(False)) | F.coalesce((x["h"] == F.get("sorted", i + 1)["h"]), F.lit(False)))
    rows = rows.withColumn("starts", F.sort_array(F.transform(twice, lambda x: x["i"])))
    # each start covers the words up to the next, three at most
    covered = F.aggregate(F.transform("starts", lambda p, i: F.least(F.lit(3), F.coalesce(F.get("starts", i + 1) - p, F.lit(3)))), F.lit(0), lambda s, x: s + x)
    lines = F.transform("full", lambda x: F.struct(line_hash(x).alias("hash"), F.size(F.regexp_extract_all(x, F.lit(f"{NOT_SPACE}+"), F.lit(0))).cast("long").alias("words")))
    return rows.select(
        "doc_id", *keep, F.col("n").cast("long").alias("n_words"), F.char_length(F.array_join("words", "")).cast("long").alias("word_chars"), F.char_length(F.regexp_replace("text", f"{SYMBOLS}+", "")).cast("long").alias("n_symbols"),
        (F.size("full") - F.size(F.array_distinct("full"))).cast("long").alias("n_dup_lines"), F.coalesce(covered, F.lit(0)).cast("long").alias("n_repeat_words"), lines.alias("lines"),
    )


BASE_FAILED = "n_words < 50 or 100 * n_repeat_words > 50 * n_words"


def frequent_lines(rows: DataFrame, host: str = "host", most_docs: int = MOST_DOCS, most_share: float = MOST_SHARE) -> DataFrame:
    """host, hash, n_docs of lines above the limits; rows have host and lines."""
    hosts = rows.groupBy(host).agg(F.count("*").alias("host_docs"))
    seen = rows.select(host, F.explode(F.array_distinct(F.transform("lines", lambda x: x["hash"]))).alias("hash")).groupBy(host, "hash").agg(F.count("*").alias("n_docs")).where(F.col("n_docs") > most_docs)
    found = seen.join(hosts.withColumnRenamed(host, "_host"), F.col(host).eqNullSafe(F.col("_host")))
    return cut(found.where(F.col("n_docs") > most_share * F.col("host_docs")).select(host, "hash", "n_docs"))


def judged(docs: DataFrame, host: str | Column = "host", **limits) -> DataFrame:
    """The counts of each document, base_failed, frequent_words (of removed lines), and kept."""
    host = F.col(host) if isinstance(host, str) else host
    rows = cut(base_counts(docs.withColumn("_host_of", host), "_host_of").withColumnRenamed("_host_of", "host"))
    frequent = frequent_lines(rows, **limits)
    line = rows.select("doc_id", F.col("host").alias("_host"), F.inline("lines").alias("_hash", "words"))
    removed = line.join(small(frequent), F.col("host").eqNullSafe(F.col("_host")) & (F.col("hash") == F.col("_hash"))).groupBy("doc_id").agg(F.sum("words").alias("frequent_words"))
    found = rows.drop("lines").join(removed, "doc_id", "left").withColumn("frequent_words", F.coalesce("frequent_words", F.lit(0)))
    remain = F.col("n_words") - F.col("frequent_words")
    depleted = (F.col("frequent_words") > 0) & ((remain < LEAST_WORDS) | (remain < LEAST_SHARE * F.col("n_words")))
    return found.withColumn("base_failed", F.expr(BASE_FAILED)).withColumn("kept", ~F.col("base_failed") & ~depleted)


def without_frequent_lines(docs: DataFrame, host: str | Column = "host", **limits) -> DataFrame:
    """docs with frequent lines taken out of their texts, whatever the verdict."""
    host = F.col(host) if isinstance(host, str) else host
    hashes = F.transform(F.filter(F.split(F.coalesce(F.col("text"), F.lit("")), "\n"), lambda x: x.rlike(NOT_SPACE)), lambda x: F.struct(line_hash(x).alias("hash"), F.lit(0).cast("long").alias("words")))
    rows = cut(docs.select("doc_id", host.alias("host"), hashes.alias("lines")))
    line = rows.select("doc_id", F.col("host").alias("_host"), F.inline("lines").alias("_hash", "words"))
    frequent = small(frequent_lines(rows, **limits))
    gone = line.join(frequent, F.col("host").eqNullSafe(F.col("_host")) & (F.col("hash") == F.col("_hash")))
    doc, hashes = free(docs, "doc_key"), free(docs, "gone")
    gone = gone.groupBy(F.col("doc_id").alias(doc)).agg(F.collect_set("hash").alias(hashes))
    found = docs.join(gone, F.col("doc_id").eqNullSafe(F.col(doc)), "left")
    kept = F.array_join(F.filter(F.split("text", "\n"), lambda x: line_hash(x).isNull() | ~F.array_contains(hashes, F.coalesce(line_hash(x), F.lit(0).cast("long")))), "\n")
    text = F.when(F.col(hashes).isNull(), F.col("text")).otherwise(kept)
    return found.select(*(text.alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns))
