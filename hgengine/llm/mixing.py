"""Mixing sources to target weights.

Each document gets a hash-random key; the keys of a source, cut into equal ranges of the hash, are sorted range by
range; the sums of earlier ranges carry each range's running sum on, so the prefix sums of a source of any size are
spread over the cluster. A source takes whole epochs and then the documents up to its exact budget, the last one in
part. The mixed corpus has a row of each document and epoch, its text cut where the budget ends; what is taken of a
document is counted in those texts.

Null texts have size 0 and take nothing. Null sources form one source of their own, the last. Repeated rows count each
by itself. No documents, no rows. Sources are a table of one row each, summed before anything is ordered.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from hgengine.llm.common import NOT_SPACE, SPACE, cut, small

WEIGHTS = (1, 2, 3)
LIMIT = 3
#: Leading hex digits of the key that name a range: 16 ** 3 ranges in a source.
DIGITS = 3


def n_words(text: str | Column = "text") -> Column:
    r"""Number of [^\x20\x09-\x0D]+ in a column: one more than the inner gaps of the trimmed text."""
    bare = F.regexp_replace(F.coalesce(F.col(text) if isinstance(text, str) else text, F.lit("")), rf"{NOT_SPACE}+", "x")
    return F.length(F.regexp_replace(bare, rf"{SPACE}+", "")).cast("long")


def targets(sizes: DataFrame, limit: int = LIMIT) -> DataFrame:
    """source, source_size, weight -> with target: shares by weight of the sum, none above limit times its source.

    Sources reach their limit in the order of limit * size / weight, so the sources at their limit are the first ones
    in that order; the level at which the others fill is the first that the next one does not exceed."""
    before = Window.orderBy("ratio", "rank").rowsBetween(Window.unboundedPreceding, -1)
    every = Window.orderBy("ratio", "rank").rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    table = sizes.withColumn("ratio", (F.lit(limit) * F.col("source_size")).cast("double") / F.col("weight"))
    table = table.withColumn("total", F.sum("source_size").over(every)).withColumn("weights", F.sum("weight").over(every))
    table = table.withColumn("capped", F.coalesce(F.sum(limit * F.col("source_size")).over(before), F.lit(0))).withColumn("passed", F.coalesce(F.sum("weight").over(before), F.lit(0)))
    level = (F.col("total") - F.col("capped")).cast("double") / (F.col("weights") - F.col("passed"))
    table = table.withColumn("level", F.first(F.when(F.col("ratio") >= level, level), ignorenulls=True).over(every))
    return table.withColumn("target", F.least((limit * F.col("source_size")).cast("double"), F.col("level") * F.col("weight"))).drop("ratio", "total", "weights", "capped", "passed", "level")


def first_words(text: Column, n: Column) -> Column:
    """The text up to the end of its n-th word."""
    return F.array_join(F.slice(F.regexp_extract_all(text, F.lit(rf"{SPACE}*{NOT_SPACE}+"), F.lit(0)), F.lit(1), n.cast("int")), "")


def _drawn(docs: DataFrame, weights: tuple[int, ...], limit: int, seed: str) -> DataFrame:
    """The columns of docs as the struct `doc`, size, source_size, target, and copies: epoch, text and words of each time
    that the document is taken. weights repeat over the sources in code point order, null last."""
    key = F.md5(F.concat(F.col("doc_id").cast("string"), F.lit(f":{seed}")))
    rows = docs.select(F.struct(*docs.columns).alias("doc"), "doc_id", "source", n_words().alias("size"), key.alias("key"))
    # null has a name of its own: no string starts with a character beyond "+" and is one character shorter
    rows = cut(rows.withColumn("name", F.when(F.col("source").isNull(), "-").otherwise(F.concat(F.lit("+"), F.col("source")))).withColumn("range", F.substring("key", 1, DIGITS)).drop("source"))
    ranges = cut(rows.groupBy("name", "range").agg(F.sum("size").alias("range_size"), F.count("*").alias("range_docs")))
    order = Window.orderBy(F.col("name") == "-", "name")
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.col("rank") - 1, F.lit(len(weights))) + 1).cast("int")).cast("long")
    sources = ranges.groupBy("name").agg(F.sum("range_size").alias("source_size")).withColumn("rank", F.row_number().over(order)).withColumn("weight", weight)
    sources = targets(sources, limit).select("name", "source_size", "target")
    earlier = Window.partitionBy("name").orderBy("range").rowsBetween(Window.unboundedPreceding, -1)
    ranges = ranges.withColumn("earlier", F.coalesce(F.sum("range_size").over(earlier), F.lit(0)))
    budget = F.floor(F.col("target")).cast("long")
    epochs = F.when(F.col("source_size") > 0, F.floor(budget / F.col("source_size"))).otherwise(0).cast("long")
    ranges = ranges.join(sources, "name").withColumn("epochs", epochs).withColumn("rest", budget - F.col("epochs") * F.col("source_size"))
    ranges = cut(ranges.select("name", "range", "source_size", "target", "earlier", "epochs", "rest"))
    run = Window.partitionBy("name", "range").orderBy("key", "doc_id").rowsBetween(Window.unboundedPreceding, -1)
    rows = rows.join(small(ranges), ["name", "range"]).withColumn("before", F.col("earlier") + F.coalesce(F.sum("size").over(run), F.lit(0)))
    part = F.greatest(F.lit(0), F.least(F.col("size"), F.col("rest") - F.col("before")))
    rows = rows.withColumn("part", part.cast("long"))
    text = F.col("doc.text")
    whole = F.struct(text.alias("text"), F.col("size").alias("words"))
    last = F.when((F.col("part") > 0) & (F.col("part") < F.col("size")), first_words(text, F.col("part"))).otherwise(text)
    last = F.struct(last.alias("text"), F.when(F.col("part") < F.col("size"), n_words(last)).otherwise(F.col("size")).alias("words"))
    taken = F.concat(F.array_repeat(whole, F.col("epochs").cast("int")), F.when(F.col("part") > 0, F.array(last)).otherwise(F.array().cast("array<struct<text: string, words: long>>")))
    copies = F.transform(taken, lambda c, i: F.struct((i + 1).cast("long").alias("epoch"), c["text"].alias("text"), c["words"].alias("words")))
    empty = F.array().cast("array<struct<epoch: long, text: string, words: long>>")
    return rows.select("doc", "size", "source_size", "target", F.when(F.col("size") > 0, copies).otherwise(empty).alias("copies"))


def mixed(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, limit: int = LIMIT, seed: str = "mix") -> DataFrame:
    """The mixed corpus: docs once for each epoch that takes them, with epoch (from 1) and words; the text of the document
    at the end of a budget is cut to the words that are left. Documents of which nothing is taken are not in it."""
    rows = _drawn(docs, weights, limit, seed).select("doc", F.explode("copies").alias("copy"))
    return rows.select(*(F.col(f"copy.{c}" if c == "text" else f"doc.`{c}`").alias(c) for c in docs.columns if c not in ("epoch", "words")), "copy.epoch", "copy.words")


def mix(docs: DataFrame, weights: tuple[int, ...] = WEIGHTS, limit: int = LIMIT, seed: str = "mix") -> DataFrame:
    """doc_id, size, source_size, target, taken (the words of a document in the mixed corpus), of every document."""
    rows = _drawn(docs.select("doc_id", "text", "source"), weights, limit, seed)
    return rows.select("doc.doc_id", "size", "source_size", "target", F.aggregate("copies", F.lit(0).cast("long"), lambda n, c: n + c["words"]).alias("taken"))
