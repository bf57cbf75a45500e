"""Personal data by patterns and by what the corpus reveals. DataFrame functions only.

Patterns find protected entities: e-mail addresses, IP addresses, card numbers and phone numbers. The corpus then tells
how strongly a term reveals an entity: the pointwise mutual information of occurring in one document, relative to the
information of the entity itself, over whole documents and all of them. Terms above the threshold are spans as well,
wherever a document with the entity has them. Sanitising replaces entities by their kinds and generalises a term to its
first letters if these do not reveal the entity, by the same measure; else the term is removed.

All counts are sums of one weight of documents, so they are of one probability space: documents whose texts have the same
sketch (the smallest and the largest hash of three words in a row) are copies and weigh 1 together. Entities in too few
kinds of documents, by the effective number of sketches, are left to the patterns: their surroundings cannot be told from
copies.

Null texts are empty and have no spans; their rows stay as they are. Failing matches (a part over 255, a wrong check
digit, too few digits) are dropped. Repeated rows are treated alike. Extra columns of any name are kept. An empty
table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from hgengine.llm.common import cut, free, small

# The patterns of the base kinds, in the order of spans. Possessive forms and the look behind match the
# same strings without going back over long runs.
KINDS = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9](?:[\x20-]?[0-9])++",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: What a text must match to be read for a kind at all.
HINTS = {"email": "@[A-Za-z0-9-]", "ip": r"[0-9]\.[0-9]", "card": r"[0-9][\x20-]?[0-9][\x20-]?[0-9]", "phone": r"\+[0-9]"}
TERM = r"\p{L}{3,}"
#: Letters that a generalised term keeps, and the mark that stands for the others; a term must be longer by two.
KEPT, REST = 4, "*"
#: Documents (copies weigh 1 together) that an entity must be in and share with a term, the share of them, and the
#: disclosure threshold.
SUPPORT, CONFIDENCE, DISCLOSED = 3, 0.5, 0.5

_SPANS = "array<struct<kind: string, start: long, end: long, value: string>>"


def _digits(value: Column) -> Column:
    return F.regexp_replace(value, "[^0-9]", "")


def _luhn(value: Column) -> Column:
    d = _digits(value)

    def added(total: Column, k: Column) -> Column:
        x = F.substring(d, F.length(d) - k + 1, F.lit(1)).cast("int") * F.when(k % 2 == 0, 2).otherwise(1)
        return total + F.when(x > 9, x - 9).otherwise(x)

    return F.length(d).between(16, 19) & (F.aggregate(F.sequence(F.lit(1), F.greatest(F.length(d), F.lit(1))), F.lit(0), added) % 10 == 0)


def _valid(kind: str, value: Column) -> Column:
    if kind == "ip":
        return F.forall(F.split(value, r"\."), lambda p: (F.length(F.ltrim(p, F.lit("0"))) <= 3) & (F.substring(F.concat(F.lit("000"), p), -3, 3).cast("int") <= 255))
    if kind == "card":
        return _luhn(value)
    if kind == "phone":
        return F.length(_digits(value)).between(8, 15)
    return F.lit(True)


def located(text: Column, pattern: str, kind: str, valid) -> Column:
    """Spans of the matches of a pattern, from the lengths of what lies between them; only valid ones are gathered."""
    none = F.array().cast(_SPANS)
    steps = F.arrays_zip(F.split(text, pattern).alias("gap"), F.regexp_extract_all(text, F.lit(pattern), F.lit(0)).alias("value"))

    def step(acc: Column, x: Column) -> Column:
        start = acc["at"] + F.char_length(x["gap"])
        end = start + F.coalesce(F.char_length(x["value"]), F.lit(0))
        span = F.array(F.struct(F.lit(kind).alias("kind"), start.alias("start"), end.alias("end"), x["value"].alias("value")))
        return F.struct(end.alias("at"), F.when(x["value"].isNotNull() & valid(x["value"]), F.concat(acc["spans"], span)).otherwise(acc["spans"]).alias("spans"))

    return F.aggregate(steps, F.struct(F.lit(0).cast("long").alias("at"), none.alias("spans")), step, lambda acc: acc["spans"])


def base_spans(docs: DataFrame, *keep: str) -> DataFrame:
    """doc_id, keep, text (null as empty), spans of the base kinds: by kind, then start."""
    rows = docs.select("doc_id", *keep, F.coalesce(F.col("text"), F.lit("")).alias("text"))
    none = F.array().cast(_SPANS)
    for kind, pattern in KINDS.items():
        found = located(F.col("text"), pattern, kind, lambda v, k=kind: _valid(k, v))
        rows = rows.withColumn(f"_{kind}", F.when(F.col("text").rlike(HINTS[kind]), found).otherwise(none))
    return rows.select("doc_id", *keep, "text", F.concat(*(f"_{k}" for k in KINDS)).alias("spans"))


def general(term: Column) -> Column:
    """The generalised form of a term, null for short ones."""
    return F.when(F.char_length(term) >= KEPT + 2, F.concat(F.substring(term, 1, KEPT), F.lit(REST)))


def described(docs: DataFrame) -> DataFrame:
    """doc_id, text_key, spans, entities (hashes), terms (distinct, lower-case), sketch, of every document."""
    rows = base_spans(docs.withColumn("text_key", F.xxhash64("text")), "text_key")
    rows = rows.withColumn("words", F.regexp_extract_all(F.lower("text"), F.lit(TERM), F.lit(0)))
    pairs = F.zip_with("words", F.slice("words", 2, 2**30), lambda a, b: F.xxhash64(a, b))
    rows = rows.withColumn("threes", F.zip_with(pairs, F.slice("words", 3, 2**30), lambda a, b: F.xxhash64(a, b)))
    entities = F.array_distinct(F.transform("spans", lambda s: F.xxhash64(s["kind"], F.lower(s["value"]))))
    plain = F.transform("spans", lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end")))
    sketch = F.when(F.size("words") > 0, F.xxhash64(F.array_min("threes"), F.array_max("threes"))).otherwise(F.xxhash64("doc_id", "text_key"))
    return rows.select("doc_id", "text_key", plain.alias("spans"), entities.alias("entities"), F.array_distinct("words").alias("terms"), sketch.alias("sketch"))


def revealing_terms(rows: DataFrame) -> DataFrame:
    """entity, term, disclosure, general (null: remove) of the terms that reveal an entity. rows: as described (cut)."""
    copies = cut(rows.groupBy("sketch").agg(F.count("*").alias("copies")).where("copies > 1"))
    weighed = rows.join(small(copies), "sketch", "left").withColumn("weight", 1 / F.coalesce("copies", F.lit(1)))
    total = lambda c="weight": F.round(F.sum(c), 6)  # noqa: E731  the same in any order of rows
    forms = F.array_distinct(F.concat("terms", F.array_compact(F.transform("terms", general))))
    n = weighed.agg(total()).first()[0] or 0.0
    mentions = weighed.where(F.size("entities") > 0).select("sketch", "weight", F.explode("entities").alias("entity"), "terms")
    kinds = mentions.groupBy("entity", "sketch").agg(F.count("*").cast("double").alias("n"), F.sum("weight").alias("weight"))
    # the number of equally frequent sketches that would be as diverse: near 1 for changed copies of one text
    often = kinds.groupBy("entity").agg(total().alias("n_entity"), (F.sum("n") * F.sum("n") / F.sum(F.col("n") * F.col("n"))).alias("diverse"))
    often = cut(often.where((F.col("n_entity") >= SUPPORT) & (F.col("diverse") >= SUPPORT)).select("entity", "n_entity"))
    pairs = mentions.join(small(often), "entity").select("entity", "n_entity", "weight", F.explode(forms).alias("term"))
    pairs = pairs.groupBy("entity", "n_entity", "term").agg(total().alias("n_both"))
    pairs = cut(pairs.where((F.col("n_both") >= SUPPORT) & (F.col("n_both") >= CONFIDENCE * F.col("n_entity"))))
    # counted before they are joined: the rows of frequent candidates never pass the join one by one
    df = weighed.select("weight", F.explode(forms).alias("term")).groupBy("term").agg(total().alias("n_term"))
    mutual = F.log2(F.col("n_both") / F.col("n_entity") * F.lit(float(max(1, n))) / F.col("n_term"))
    own = F.log2(F.lit(float(max(2, n))) / F.least(F.col("n_entity"), F.lit(max(1.0, n / 2))))
    found = cut(df.join(small(pairs), "term").select("entity", "term", (mutual / own).alias("disclosure")))
    revealing = found.where((F.col("disclosure") >= DISCLOSED) & ~F.col("term").endswith(REST))
    wider = found.where(F.col("term").endswith(REST)).select("entity", F.col("term").alias("general"), F.col("disclosure").alias("wider"))
    joined = revealing.withColumn("general", general(F.col("term"))).join(wider, ["entity", "general"], "left")
    return joined.select("entity", "term", "disclosure", F.when(F.col("wider") < DISCLOSED, F.col("general")).alias("general"))


def _with(rows: DataFrame, other: DataFrame, how: str = "inner") -> DataFrame:
    """rows with the columns of other (doc_id, text_key, ...) for the same document, whose id may be null."""
    named = other.withColumnsRenamed({"doc_id": "_other_doc", "text_key": "_other_key"})
    return rows.join(named, F.col("doc_id").eqNullSafe(F.col("_other_doc")) & (F.col("text_key") == F.col("_other_key")), how).drop("_other_doc", "_other_key")


def _found(docs: DataFrame) -> DataFrame:
    """doc_id, text_key, spans (kind, start, end, general) of every row."""
    rows = cut(described(docs))
    revealed = cut(revealing_terms(rows))
    of_doc = rows.select("doc_id", "text_key", F.explode("entities").alias("entity")).join(small(revealed), "entity")
    # a term that one entity wants removed is removed
    of_doc = of_doc.groupBy("doc_id", "text_key", "term").agg(F.when(F.count("general") == F.count("*"), F.first("general")).alias("general"))
    of_doc = cut(of_doc.groupBy("doc_id", "text_key").agg(F.collect_list(F.struct("term", "general")).alias("terms")))
    texts = _with(docs.select("doc_id", "text", F.xxhash64("text").alias("text_key")), small(of_doc))
    spans = located(F.col("text"), TERM, "term", lambda v: F.exists("terms", lambda t: t["term"] == F.lower(v)))
    told = lambda s: F.filter("terms", lambda t: t["term"] == F.lower(s["value"]))[0]["general"]
    spans = F.transform(spans, lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end"), told(s).alias("general")))
    terms = texts.select("doc_id", "text_key", spans.alias("more")).dropDuplicates(["doc_id", "text_key"])
    plain = F.transform("spans", lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end"), F.lit(None).cast("string").alias("general")))
    found = _with(rows.select("doc_id", "text_key", plain.alias("base")), small(cut(terms)), "left")
    apart = F.filter("more", lambda t: ~F.exists("base", lambda b: (b["start"] < t["end"]) & (t["start"] < b["end"])))
    none = F.array().cast("array<struct<kind: string, start: long, end: long, general: string>>")
    return found.select("doc_id", "text_key", F.concat("base", F.coalesce(apart, none)).alias("spans"))


def personal_spans(docs: DataFrame) -> DataFrame:
    """doc_id, spans (base kinds, then kind `term`), in the order of kind and start, of every document. general: what a
    term is generalised to; null for what is removed."""
    return _found(docs).select("doc_id", "spans")


def of_kind(kind: str):
    return lambda s: s["kind"] == kind


def joined(spans: Column) -> Column:
    return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def masked(spans: str) -> Column:
    """text with each span (start, end, kind, general) replaced by its general form or its kind; overlapping spans by the
    first one's."""
    text = F.col("text")

    def step(acc: Column, s: Column) -> Column:
        between = F.substring(text, (acc["at"] + 1).cast("int"), (s["start"] - acc["at"]).cast("int"))
        new = F.coalesce(s["general"], F.concat(F.lit("["), F.upper(s["kind"]), F.lit("]")))
        fresh = F.struct(s["end"].alias("at"), F.concat(acc["out"], between, new).alias("out"))
        return F.when(s["start"] >= acc["at"], fresh).otherwise(F.struct(F.greatest(acc["at"], s["end"]).alias("at"), acc["out"].alias("out")))

    ordered = F.array_sort(F.transform(spans, lambda s: F.struct(s["start"].alias("start"), s["end"].alias("end"), s["kind"].alias("kind"), s["general"].alias("general"))))
    return F.aggregate(ordered, F.struct(F.lit(0).cast("long").alias("at"), F.lit("").alias("out")), step, lambda acc: F.concat(acc["out"], F.substring(text, (acc["at"] + 1).cast("int"), F.char_length(text))))


def sanitised(docs: DataFrame) -> DataFrame:
    """docs with each span of the text replaced. What stands free once its neighbour is gone can match anew: passes go on
    over the changed texts until none has a match; each takes digits or at signs away, so they end."""
    found = _found(docs).where(F.size("spans") > 0).dropDuplicates(["doc_id", "text_key"])
    texts = docs.select("doc_id", "text", F.xxhash64("text").alias("text_key"))
    new = cut(_with(texts, small(cut(found))).dropDuplicates(["doc_id", "text_key"]).select("doc_id", "text_key", masked("spans").alias("text")))
    done = None
    while True:
        again = cut(base_spans(new, "text_key").select("doc_id", "text_key", "text", F.transform("spans", lambda s: F.struct(s["kind"].alias("kind"), s["start"].alias("start"), s["end"].alias("end"), F.lit(None).cast("string").alias("general"))).alias("spans")))
        clean = again.where(F.size("spans") == 0).select("doc_id", "text_key", "text")
        done = clean if done is None else done.unionByName(clean)
        rest = again.where(F.size("spans") > 0)
        if not rest.limit(1).count():
            break
        new = rest.select("doc_id", "text_key", masked("spans").alias("text"))
    key, text, doc = (free(docs, n) for n in ("text_key", "new_text", "doc_key"))
    done = cut(done).select(F.col("doc_id").alias(doc), F.col("text_key").alias(key), F.col("text").alias(text))
    rows = docs.join(small(done), (F.col("doc_id").eqNullSafe(F.col(doc))) & (F.xxhash64(docs["text"]) == F.col(key)), "left")
    return rows.select(*(F.coalesce(F.col(text), F.col("text")).alias("text") if c == "text" else F.col(f"`{c}`") for c in docs.columns))
