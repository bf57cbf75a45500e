"""Exact substring deduplication by prefix-free parsing.

A rolling hash over 8 bytes triggers phrase ends: a position is a trigger if its hash is the first smallest of some 46
positions in a row. Triggers lie at most 46 apart, and the 46s in a string of 100 bytes have at least two, so wherever
the string occurs the phrases between these are the same. The order of the corpus follows from the dictionary and the parse:

1. the dictionary: phrases sorted by content; only those that occur twice can lie in a repeated string;
2. the parse: runs of such phrases in a document, cut into blocks, the strings of 100 bytes whose own triggers begin
   with the same phrase; blocks sorted by phrase, content and position stand together, and all but the first of equal
   ones start repeated strings throughout;
3. first blocks that share a phrase are opened into their strings. A string is the end of a phrase and the parse after
   it: the suffix array of the task's dictionary ranks the former, that of its parse, as deep as strings reach, the
   latter, and both combine into the order of the strings. The first of equal ones is kept, the others start earlier
   elsewhere.

Each step is one sort over the cluster, read as a stream; arrays are of the phrases that a task holds, so none grows
with the corpus. A phrase with more than MOST_BLOCKS different blocks is opened by one more sort of its strings over the
cluster, by 128 bits of hash; all others are compared by their bytes. Highly repetitive text costs phrases, not bytes.
Whole copies are set aside first, and what a text repeats of itself is dealt evenly, apart from the phrase it belongs to.

Null texts are empty. Texts under 100 bytes are kept whole. Repeated texts keep the copy of the smallest doc_id.
doc_id must be unique. An empty table gives no rows.
"""

from __future__ import annotations

import hashlib
from collections import Counter
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgengine.llm.common import MIX, cut, encoded, mixed, signed
from hgengine.llm.copies import distinct_texts, texts_of, with_first

LENGTH, GRAM, SPAN = 100, 8, 46
GRAMS = LENGTH - GRAM + 1
#: First blocks of a phrase that are opened within one task.
MOST_BLOCKS = 20_000
_BASES = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)
#: Mark of the first place of a phrase that a text has several times; places are below it.
SEVERAL = 1 << 62
_powers: dict[int, tuple[np.ndarray, np.ndarray]] = {}


def _power(which: int, n: int) -> tuple[np.ndarray, np.ndarray]:
    """Powers of a base and of its inverse modulo 2 ** 64, at least n of them."""
    if which not in _powers or len(_powers[which][0]) < n:
        size = 1 << max(17, int(n).bit_length())
        base, back = int(_BASES[which]), pow(int(_BASES[which]), -1, 1 << 64)
        out = []
        for x in (base, back):
            p = np.full(size, x, np.uint64)
            p[0] = 1
            out.append(np.multiply.accumulate(p))
        _powers[which] = tuple(out)
    return _powers[which]


def grams(raw: bytes) -> np.ndarray:
    """Mixed values of the 8 bytes at each position."""
    n = len(raw) - GRAM + 1
    if n <= 0:
        return np.zeros(0, np.uint64)
    out = np.empty(n, np.uint64)
    for i in range(min(GRAM, n)):
        out[i::GRAM] = np.frombuffer(raw, "<u8", (n - i + GRAM - 1) // GRAM, i)
    return mixed(out)


def sums(g: np.ndarray, which: int = 0) -> np.ndarray:
    out = np.zeros(len(g) + 1, np.uint64)
    np.cumsum(g * _power(which, len(g))[0][: len(g)], out=out[1:])
    return out


def between(s: np.ndarray, a: np.ndarray, b: np.ndarray, which: int = 0) -> np.ndarray:
    """Hashes of the grams a to b, b excluded, by the running sums."""
    return mixed((s[b] - s[a]) * _power(which, len(s))[1][a] + (b - a).astype(np.uint64) * MIX[2])


def _sliding(x: np.ndarray, size: int, pick) -> np.ndarray:
    have = 1
    while 2 * have <= size:
        x = pick(x[:-have], x[have:])
        have *= 2
    return pick(x[: len(x) - (size - have)], x[size - have :]) if have < size else x


def triggers(g: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(b, first): trigger positions, and for each the first of the runs of SPAN positions whose smallest it is; first
    ends with the number of such runs."""
    runs = len(g) - SPAN + 1
    if runs < 1:
        return np.zeros(0, np.int64), np.zeros(1, np.int64)
    keyed = (g >> np.uint64(32)) << np.uint64(32) | np.arange(len(g), dtype=np.uint64)
    least = (_sliding(keyed, SPAN, np.minimum) & np.uint64(0xFFFFFFFF)).astype(np.int64)
    first = np.nonzero(np.concatenate([[True], least[1:] != least[:-1]]))[0]
    return least[first], np.append(first, runs)


def _phrases(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of phrases: hash, doc_id, and in one number the first start of strings whose own triggers
    begin with the phrase's (lo), and the steps from there to the two triggers and to the end of the last such string.
    The first of several rows of a phrase in a text has SEVERAL added, the others, which tell nothing new, are
    complements."""
    for batch in batches:
        hashes, docs, places = [], [], []
        for doc, text in zip(batch.column(0), batch.column(1), strict=True):
            raw = encoded(text.as_py())
            if len(raw) < LENGTH:
                continue
            g = grams(raw)
            b, first = triggers(g)
            phrase = signed(between(sums(g), b[:-1], b[1:] + 1))
            order = np.argsort(phrase, kind="stable")
            same = phrase[order[1:]] == phrase[order[:-1]]
            further, before = np.zeros((2, len(phrase)), bool)
            further[order[1:]] = before[order[:-1]] = same
            hashes.append(phrase)
            lo, hi = first[:-2], first[2:] + LENGTH - GRAMS + SPAN - 1
            place = lo << 18 | (b[:-1] - lo) << 12 | (b[1:] - b[:-1]) << 6 | (hi - b[1:])
            places.append(np.where(further, ~place, place | np.where(before, SEVERAL, 0)))
            docs.append(np.full(len(lo), doc.as_py(), np.int64))
        if hashes:
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(x)) for x in (hashes, docs, places)], ["phrase", "doc_id", "place"])


def _repeated(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of rows sorted by phrase, those whose phrase another row has, here or by their marks."""
    held = None  # the last row, while it is not known whether it is alone
    for batch in batches:
        if not batch.num_rows:
            continue
        p, d, at = (batch.column(i).to_numpy() for i in range(3))
        if held:
            p, d, at = (np.concatenate([[h], x]) for h, x in zip(held[:3], (p, d, at), strict=True))
        same = p[1:] == p[:-1]
        keep = np.concatenate([[bool(held and held[3])], same]) | np.concatenate([same, [False]]) | (at < 0) | (at >= SEVERAL)
        out = keep.copy()
        if held and held[3]:
            out[0] = False  # given before
        held = (p[-1], d[-1], at[-1], bool(keep[-1]))
        place = np.where(at < 0, ~at, at & (SEVERAL - 1))
        yield pa.RecordBatch.from_arrays([pa.array(x[out]) for x in (p, d, place)], ["phrase", "doc_id", "place"])


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of repeated phrases sorted by doc_id and place: doc_id, hi of runs of them, and for each phrase its hash, the first
    start of its strings and its first trigger."""
    held: list = [np.zeros(0, np.int64)] * 3

    def found(phrase: np.ndarray, d: np.ndarray, place: np.ndarray) -> pa.RecordBatch:
        lo = place >> 18
        a = lo + (place >> 12 & 63)
        b = a + (place >> 6 & 63)
        hi = b + (place & 63)
        heads = np.nonzero(np.concatenate([[True], (d[1:] != d[:-1]) | (a[1:] != b[:-1])]))[0]
        tails = np.append(heads[1:], len(d)) - 1
        long = hi[tails] - lo[heads] >= LENGTH
        heads, tails = heads[long], tails[long]
        sizes = tails - heads + 1
        rows = np.repeat(heads - np.concatenate([[0], np.cumsum(sizes)])[:-1], sizes) + np.arange(sizes.sum())
        offsets = pa.array(np.concatenate([[0], np.cumsum(sizes)]).astype(np.int32))
        lists = [pa.ListArray.from_arrays(offsets, pa.array(x[rows])) for x in (phrase, lo)]
        return pa.RecordBatch.from_arrays([pa.array(d[heads]), pa.array(hi[tails]), *lists], ["doc_id", "hi", "phrases", "starts"])

    for batch in batches:
        phrase, d, place = (np.concatenate([h, batch.column(i).to_numpy()]) for i, h in enumerate(held))
        if not len(d):
            continue
        at = int(np.searchsorted(d, d[-1]))
        if at:
            yield found(phrase[:at], d[:at], place[:at])
        held = [phrase[at:], d[at:], place[at:]]
    if len(held[0]):
        yield found(*held)


def _blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Blocks, the strings whose own triggers begin with a phrase's: phrase, the bytes they cover, doc_id, first start.
    Of a block that its text has before, no bytes and the number of strings for the phrase."""
    for batch in batches:
        out: list[list] = [[], [], [], []]
        for doc, text, runs in zip(batch.column(0), batch.column(1), batch.column(2), strict=True):
            raw, doc = encoded(text.as_py()), doc.as_py()
            runs = sorted(runs.as_py(), key=lambda run: run["starts"][0])
            several = {phrase for phrase, n in Counter(chain.from_iterable(run["phrases"] for run in runs)).items() if n > 1}
            seen: set[tuple[int, bytes]] = set()
            for run in runs:
                stop = run["hi"] - LENGTH + 1
                starts = [x for x in run["starts"] if x < stop]
                for phrase, x, y in zip(run["phrases"], starts, [*starts[1:], stop], strict=False):
                    piece: bytes | None = raw[x : y - 1 + LENGTH]
                    if phrase in several:
                        if (phrase, piece) in seen:
                            phrase, piece = y - x, None
                        else:
                            seen.add((phrase, piece))
                    out[0].append(phrase)
                    out[1].append(piece)
                    out[3].append(x)
                out[2] += [doc] * len(starts)
        yield pa.RecordBatch.from_arrays([pa.array(out[0], pa.int64()), pa.array(out[1], pa.binary()), pa.array(out[2], pa.int64()), pa.array(out[3], pa.int64())], ["phrase", "bytes", "doc_id", "start"])


def _places(pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(piece, step, place among the bytes of all pieces) of each string of the pieces."""
    n = np.fromiter(map(len, pieces), np.int64, len(pieces)) - LENGTH + 1
    row = np.repeat(np.arange(len(pieces)), n)
    step = np.arange(len(row)) - np.repeat(np.concatenate([[0], np.cumsum(n)])[:-1], n)
    return row, step, np.concatenate([[0], np.cumsum(n + LENGTH - 1)])[:-1][row] + step


def _strings(pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(piece, step, and 128 bits) of each string of the pieces."""
    row, step, at = _places(pieces)
    g = grams(b"".join(pieces))
    return row, step, *(signed(between(sums(g, i), at, at + GRAMS, i)) if len(at) else np.zeros(0, np.int64) for i in (0, 1))


def suffix_ranks(entries: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(ranks, ends): the inverse suffix array of a dictionary, equal suffixes of entries having one rank, and the place
    of each entry's end, whose rank is that of the empty suffix. Ranks are doubled in depth until they reach all ends."""
    sizes = np.fromiter(map(len, entries), np.int64, len(entries))
    ends = np.cumsum(sizes + 1) - 1
    ranks = np.frombuffer(b"".join(e + b"\0" for e in entries), np.uint8).astype(np.int64) + 1
    ranks[ends] = 0
    to_end = np.repeat(ends, sizes + 1) - np.arange(len(ranks))
    depth = 1
    while len(sizes) and depth <= sizes.max():
        inside = np.nonzero(to_end >= depth)[0]
        beyond = np.zeros(len(ranks), np.int64)
        beyond[inside] = ranks[inside + depth] + 1
        ranks = np.unique(ranks * (ranks.max() + 2) + beyond, return_inverse=True)[1]
        depth *= 2
    return ranks, ends


def suffix_order(suffixes: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """(order, shared): the suffixes of a parse in order, and the bytes that each in order has in common with the one before."""
    order = np.array(sorted(range(len(suffixes)), key=suffixes.__getitem__), np.int64)
    sizes = np.fromiter((len(suffixes[i]) for i in order), np.int64, len(order))
    shared = np.zeros(len(order), np.int64)
    if len(order) > 1:
        table = np.zeros((len(order), int(sizes.max()) + 1), np.uint8)
        table[np.arange(table.shape[1]) < sizes[:, None]] = np.frombuffer(b"".join(suffixes[i] for i in order), np.uint8)
        unlike = table[1:] != table[:-1]
        unlike[:, -1] = True
        shared[1:] = np.minimum(unlike.argmax(axis=1), np.minimum(sizes[1:], sizes[:-1]))
    return order, shared


def corpus_order(pieces: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(piece, step, k1, k2) of each string of the pieces: by k1 and k2 strings of equal size before their first trigger
    stand in order, and strings are equal if both are.

    A string is the end of a phrase, up to its first trigger, and the parse from there on: k1 is the rank of the former in
    the suffix array of the dictionary, k2 counts, in that of the parse, the neighbours so far that differ within the rest
    of the string's bytes."""
    row, step, at = _places(pieces)
    raw = b"".join(pieces)
    g = grams(raw)
    if not len(row):
        return row, step, row, row
    keyed = (g >> np.uint64(32)) << np.uint64(32) | np.arange(len(g), dtype=np.uint64)
    trigger = (_sliding(keyed, SPAN, np.minimum) & np.uint64(0xFFFFFFFF)).astype(np.int64)[at]
    new = np.concatenate([[True], (row[1:] != row[:-1]) | (trigger[1:] != trigger[:-1])])
    heads = np.nonzero(new)[0]
    tails = np.append(heads[1:], len(row)) - 1
    block = np.cumsum(new) - 1
    numbers: dict[bytes, int] = {}
    entry = np.array([numbers.setdefault(raw[a:b], len(numbers)) for a, b in zip(at[heads].tolist(), trigger[heads].tolist(), strict=True)], np.int64)
    ranks, ends = suffix_ranks(list(numbers))
    order, shared = suffix_order([raw[a:b] for a, b in zip(trigger[heads].tolist(), (at[tails] + LENGTH).tolist(), strict=True)])
    place = np.empty(len(order), np.int64)
    place[order] = np.arange(len(order))
    before = trigger - at
    unlike = np.cumsum(shared < LENGTH - np.arange(SPAN)[:, None], axis=1)
    return row, step, ranks[ends[entry[block]] - before], unlike[before, place[block]]


def _starts(k1: np.ndarray, k2: np.ndarray, doc: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(doc_id, start, n): runs of string starts that are not the first of their key."""
    order = np.lexsort((start, doc, k2, k1))
    k1, k2 = k1[order], k2[order]
    again = order[1:][(k1[1:] == k1[:-1]) & (k2[1:] == k2[:-1])]
    again = again[np.lexsort((start[again], doc[again]))]
    d, s = doc[again], start[again]
    heads = np.nonzero(np.concatenate([[True], (d[1:] != d[:-1]) | (s[1:] != s[:-1] + 1)]))[0] if len(d) else np.zeros(0, np.int64)
    return d[heads], s[heads], np.diff(np.append(heads, len(d)))


def _opened(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of blocks sorted by phrase, bytes and position: runs of n starts of strings that start earlier (no key).

    A repeat of a block is one throughout. Equal strings of different blocks have the same phrase, so the first blocks
    of a phrase are opened together; of a phrase with more blocks than MOST_BLOCKS the strings are given by their keys,
    for a sort over the cluster."""
    last: tuple = (None, None)
    big = None
    held: list[tuple] = []

    def given(keys, doc, start, n) -> pa.RecordBatch:
        k1, k2 = keys or (pa.nulls(len(doc), pa.int64()),) * 2
        return pa.RecordBatch.from_arrays([k1, k2, pa.array(doc, pa.int64()), pa.array(start, pa.int64()), pa.array(n, pa.int64())], ["k1", "k2", "doc_id", "start", "n"])

    def keyed(rows: list[tuple], by=corpus_order) -> tuple:
        row, step, k1, k2 = by([r[1] for r in rows])
        doc, start = (np.array([r[i] for r in rows], np.int64)[row] for i in (2, 3))
        return k1, k2, doc, start + step

    def resolved(rows: list[tuple]) -> Iterator[pa.RecordBatch]:
        # a phrase with one first block has no strings to compare
        several = [r for i, r in enumerate(rows) if i and rows[i - 1][0] == r[0] or i + 1 < len(rows) and rows[i + 1][0] == r[0]]
        if several:
            yield given(None, *_starts(*keyed(several)))

    def spilled(rows: list[tuple]) -> pa.RecordBatch:
        k1, k2, doc, start = keyed(rows, _strings)
        return given((pa.array(k1), pa.array(k2)), doc, start, np.ones(len(doc), np.int64))

    for batch in batches:
        again: list[tuple] = []
        fresh: list[tuple] = []
        for phrase, piece, doc, start in zip(*(batch.column(i).to_pylist() for i in range(4)), strict=True):
            if piece is None:
                again.append((doc, start, phrase))
                continue
            if (phrase, piece) == last:
                again.append((doc, start, len(piece) - LENGTH + 1))
                continue
            last = (phrase, piece)
            (fresh if phrase == big else held).append((phrase, piece, doc, start))
            if phrase != big and big is not None:
                big = None
        if again:
            yield given(None, *map(list, zip(*again, strict=True)))
        if fresh:
            yield spilled(fresh)
        if held:
            at = next((i for i in range(len(held) - 1, -1, -1) if held[i][0] != held[-1][0]), -1) + 1
            yield from resolved(held[:at])
            held = held[at:]
            if len(held) > MOST_BLOCKS:
                big = held[0][0]
                yield spilled(held)
                held = []
    if held:
        yield from resolved(held)


def _later(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of strings sorted by key and position, those that start earlier elsewhere."""
    last = None
    for batch in batches:
        if batch.num_rows:
            k1, k2 = batch.column(0).to_numpy(), batch.column(1).to_numpy()
            again = np.concatenate([[last == (k1[0], k2[0])], (k1[1:] == k1[:-1]) & (k2[1:] == k2[:-1])])
            last = (k1[-1], k2[-1])
            yield pa.RecordBatch.from_arrays([pa.array(batch.column(i).to_numpy()[again]) for i in (2, 3, 4)], ["doc_id", "start", "n"])


def _spans(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Of starts sorted by doc_id and start: the maximal runs of bytes that their strings cover."""
    held: list = []

    def rows(x: list) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array([r[i] for r in x], pa.int64()) for i in range(3)], ["doc_id", "start", "end"])

    for batch in batches:
        if not batch.num_rows:
            continue
        d, a, n = (batch.column(i).to_numpy() for i in range(3))
        b = a + n - 1 + LENGTH
        # blocks do not overlap, so ends rise with starts
        new = np.concatenate([[True], (d[1:] != d[:-1]) | (a[1:] > b[:-1])])
        heads = np.nonzero(new)[0]
        tails = np.concatenate([heads[1:], [len(d)]]) - 1
        out = list(zip(d[heads].tolist(), a[heads].tolist(), b[tails].tolist(), strict=True))
        if held and held[0] == out[0][0] and out[0][1] <= held[2]:
            out[0] = (held[0], held[1], max(held[2], out[0][2]))
        elif held:
            out.insert(0, held)
        held = out.pop()
        if out:
            yield rows(out)
    if held:
        yield rows([held])


def repeated_spans(docs: DataFrame, firsts: DataFrame) -> DataFrame:
    """doc_id, start, end: maximal runs of bytes covered by strings that start earlier, in the first of each text."""
    texts = distinct_texts(docs, firsts)
    phrases = texts.mapInArrow(_phrases, "phrase long, doc_id long, place long")
    # what a text repeats needs no meeting, so that one phrase or block in very many places fills no task
    anywhere = F.xxhash64("doc_id", "place")
    phrases = phrases.repartition(F.when(F.col("place") < 0, anywhere).otherwise(F.col("phrase"))).sortWithinPartitions("phrase")
    repeated = phrases.mapInArrow(_repeated, "phrase long, doc_id long, place long")
    runs = cut(repeated.repartition("doc_id").sortWithinPartitions("doc_id", "place").mapInArrow(_runs, "doc_id long, hi long, phrases array<long>, starts array<long>"))
    ids = cut(runs.select("doc_id").distinct())
    by_doc = runs.groupBy("doc_id").agg(F.collect_list(F.struct("hi", "phrases", "starts")).alias("runs"))
    blocks = texts_of(docs, ids).join(by_doc, "doc_id").mapInArrow(_blocks, "phrase long, bytes binary, doc_id long, start long")
    block_key = F.when(F.col("bytes").isNull(), F.xxhash64("doc_id", "start")).otherwise(F.col("phrase"))
    opened = cut(blocks.repartition(block_key).sortWithinPartitions("phrase", "bytes", "doc_id", "start").mapInArrow(_opened, "k1 long, k2 long, doc_id long, start long, n long"))
    strings = opened.where("k1 is not null").repartition("k1", "k2").sortWithinPartitions("k1", "k2", "doc_id", "start")
    starts = opened.where("k1 is null").select("doc_id", "start", "n").unionByName(strings.mapInArrow(_later, "doc_id long, start long, n long"))
    return starts.repartition("doc_id").sortWithinPartitions("doc_id", "start").mapInArrow(_spans, "doc_id long, start long, end long")


def _kept(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        digests = []
        for text, spans in zip(batch.column(1), batch.column(2), strict=True):
            raw, at, sha = encoded(text.as_py()), 0, hashlib.sha256()
            for s in sorted((s["start"], s["end"]) for s in spans.as_py()):
                sha.update(raw[at : s[0]])
                at = s[1]
            sha.update(raw[at:])
            digests.append(sha.hexdigest())
        yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(digests, pa.string())], ["doc_id", "kept_sha256"])


def deduplicated(docs: DataFrame) -> DataFrame:
    """doc_id, n_bytes, n_removed, n_spans, kept_sha256 of every document, and spans (bytes, of removed runs)."""
    firsts = with_first(docs)
    spans = repeated_spans(docs, firsts).groupBy("doc_id").agg(F.collect_list(F.struct("start", "end")).alias("spans"))
    spans = cut(spans)
    ids = cut(spans.select("doc_id"))
    shas = cut(texts_of(docs, ids).join(spans, "doc_id").select("doc_id", "text", "spans").mapInArrow(_kept, "doc_id long, kept_sha256 string"))
    copy = (F.col("first") < F.col("doc_id")) & (F.col("n_bytes") >= LENGTH)
    rows = firsts.join(spans, "doc_id", "left").join(shas, "doc_id", "left")
    whole = F.array(F.struct(F.lit(0).cast("long").alias("start"), F.col("n_bytes").alias("end")))
    rows = rows.withColumn("spans", F.when(copy, whole).otherwise(F.coalesce("spans", F.expr("array()").cast("array<struct<start: long, end: long>>"))))
    empty = F.sha2(F.lit(""), 256)
    removed = F.aggregate("spans", F.lit(0).cast("long"), lambda s, x: s + x["end"] - x["start"])
    return rows.select("doc_id", "n_bytes", removed.alias("n_removed"), F.size("spans").cast("long").alias("n_spans"), F.when(copy, empty).otherwise(F.coalesce("kept_sha256", "digest")).alias("kept_sha256"), "spans")
