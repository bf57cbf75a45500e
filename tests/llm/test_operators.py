"""Operators against brute force on small texts with every hard case: nulls, empty texts, ties, copies, extra columns."""

import hashlib
import re
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from hgengine.llm import chaining, decontaminate, language, mixing, ngram_join, pii, quality, suffix_dedup, toxicity, warc
from hgengine.llm.common import hashed_words, scratch

WORDS = ["alpha", "beta", "gamma", "delta", "Épsilon", "zeta", "eta", "theta", "iota", "kappa"]


def prose(seed: int, n: int) -> str:
    draw = np.random.default_rng(seed)
    return " ".join(WORDS[i] + str(draw.integers(40)) for i in draw.integers(0, 10, n))


BASE = prose(1, 120)
TEXTS = [
    None, "", "   \n\t ", "one two", "ONE two", BASE, BASE, BASE.replace("alpha", "omega", 1), prose(2, 60) + " " + BASE, prose(3, 300),
    "nd " * 400, "a" * 1000, prose(4, 20) + "\n" + prose(4, 20) + "\nshared line\nshared line", "x" * 99, "x" * 100, "x" * 101, prose(5, 6000),
    "mail a@b.c_d@e.f and x@y.z. +1 (988) 555-2485 300.1.1.1 001.002.3.4 4111 1111-1111 1111", BASE[:300] + "é" + BASE[300:],
]


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, ["s1", None, "s2", "s1"][i % 4], None, 0) for i, t in enumerate(TEXTS)]
    return spark.createDataFrame(rows, "doc_id long, text string, source string, lang string, n_chars long").withColumn("first", F.lit("clash")).withColumn("n", F.lit(7))


@pytest.fixture(scope="module")
def none(docs):
    return docs.where("false")


def by_id(df, *names):
    return {r.doc_id: tuple(r[n] for n in names) if len(names) > 1 else r[names[0]] for r in df.collect()}


def test_word_hashes_fold_ascii_alone():
    assert (hashed_words("AB cd") == hashed_words(" ab\tCD\n")).all()
    assert hashed_words("É")[0] != hashed_words("é")[0]
    assert len(hashed_words(None)) == len(hashed_words(" \x0b")) == 0


def shingle_sets():
    out = {}
    for i, t in enumerate(TEXTS):
        w = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if c.isascii() else c for c in t or ""))
        out[i] = {tuple(w[j : j + 5]) for j in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()
    return out


def test_ngram_join(docs, none):
    s = shingle_sets()
    root = {i: i for i in s}
    for _ in s:
        for a in s:
            for b in s:
                if s[a] and s[b] and 100 * len(s[a] & s[b]) >= 80 * len(s[a] | s[b]):
                    root[a] = min(root[a], root[b])
    found = by_id(ngram_join.near_duplicate_components(docs), "n_shingles", "component_id")
    assert found == {i: (len(s[i]), root[i]) for i in s}
    assert ngram_join.near_duplicate_components(none).count() == 0
    kept = ngram_join.one_of_each(docs)
    assert kept.columns == docs.columns
    assert {r.doc_id for r in kept.collect()} == {i for i in s if root[i] == i}


def test_tree_finds_what_the_bound_admits():
    draw = np.random.default_rng(0)
    sets = [np.unique(draw.integers(0, 2000, draw.integers(20, 60)).astype(np.uint64)) for _ in range(300)]
    sizes, points = np.array([len(s) for s in sets]), ngram_join.points_of([ngram_join.point_of(s) for s in sets])
    tree = ngram_join.CountVectorTree(sizes, points, 30)
    for i in (0, 7, 99):
        assert sorted(tree.query(points[i], int(sizes[i]))) == np.nonzero(ngram_join.admitted(points[i], int(sizes[i]), points, sizes, 30))[0].tolist()
        for j in range(300):
            overlap = len(set(sets[i].tolist()) & set(sets[j].tolist()))
            if 100 * overlap >= 30 * (sizes[i] + sizes[j] - overlap):
                assert j in tree.query(points[i], int(sizes[i]))


def test_large_trees_as_blocks(spark, monkeypatch):
    monkeypatch.setattr(ngram_join, "BLOCK", 3)
    monkeypatch.setattr(ngram_join, "CHUNK", 4)
    rows = [(i, BASE.replace(" ", f" v{i} ", 1)) for i in range(9)]
    found = by_id(ngram_join.near_duplicate_components(spark.createDataFrame(rows, "doc_id long, text string")), "component_id")
    assert set(found.values()) == {0}


def linked(texts, percent=80):
    """Links of texts by brute force, as pairs with overlap."""
    sets = [{tuple(w[j : j + 5]) for j in range(len(w) - 4)} or {tuple(w)} for w in (t.split() for t in texts)]
    return {(a, b, n) for a in range(len(sets)) for b in range(a + 1, len(sets)) for n in [len(sets[a] & sets[b])] if 100 * n >= percent * len(sets[a] | sets[b])}


def chained(seed, n, step):
    """Texts that drift: each changes some words of one before it, so that families form chains and meet at the edge."""
    draw = np.random.default_rng(seed)
    texts = [prose(seed + 7, 150).split()]
    for _ in range(n - 1):
        t = list(texts[draw.integers(max(0, len(texts) - 4), len(texts))])
        for at in draw.integers(0, len(t), step):
            t[at] = f"new{draw.integers(1 << 30)}"
        texts.append(t)
    return [" ".join(t) for t in texts]


@pytest.mark.parametrize("block", [3, 2000])
def test_links_by_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(ngram_join, "BLOCK", block)
    texts = chained(31, 40, 1) + chained(32, 40, 2) + chained(33, 30, 3) + [prose(900 + i, 60) + " " + BASE for i in range(20)]
    order = np.random.default_rng(8).permutation(len(texts))
    texts = [texts[i] for i in order]
    many = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    expected = linked(texts)
    assert len(expected) > 100
    assert {tuple(r) for r in ngram_join.jaccard_links(many, every=True)[1].collect()} == expected
    root = list(range(len(texts)))
    for _ in texts:
        for a, b, _n in expected:
            root[a] = root[b] = min(root[a], root[b])
    assert by_id(ngram_join.near_duplicate_components(many), "component_id") == dict(enumerate(root))


def test_a_large_family_costs_its_members(spark, monkeypatch):
    """The sets that travel for verification grow with the family, not with its square."""
    travelled = []
    verified = ngram_join.verified
    monkeypatch.setattr(ngram_join, "verified", lambda docs, pairs, k, percent: (travelled.append(pairs.count()), verified(docs, pairs, k, percent))[1])
    words = prose(41, 100).split()
    rows = [(i, " ".join([*words[: i % 100], f"v{i}", *words[i % 100 + 1 :]])) for i in range(5000)]
    found = by_id(ngram_join.near_duplicate_components(spark.createDataFrame(rows, "doc_id long, text string")), "component_id")
    assert set(found.values()) == {0}
    assert sum(travelled) < 8 * 5000


def removed(texts):
    seen, out = set(), {}
    for i, t in enumerate(texts):
        b = (t or "").encode()
        gone = bytearray(len(b))
        for p in range(len(b) - 99):
            w = b[p : p + 100]
            if w in seen:
                gone[p : p + 100] = b"\1" * 100
            seen.add(w)
        kept = bytes(c for c, g in zip(b, gone) if not g)
        out[i] = (len(b), sum(gone), sum(1 for j in range(len(b)) if gone[j] and (j == 0 or not gone[j - 1])), hashlib.sha256(kept).hexdigest())
    return out


def test_suffix_dedup(docs, none):
    assert by_id(suffix_dedup.deduplicated(docs), "n_bytes", "n_removed", "n_spans", "kept_sha256") == removed(TEXTS)
    assert suffix_dedup.deduplicated(none).count() == 0


def test_suffix_arrays():
    draw = np.random.default_rng(5)
    entries = [bytes(draw.integers(0, 3, draw.integers(0, 46), dtype=np.uint8)) for _ in range(200)] + [b"", b"\0", b"\0\0"]
    ranks, ends = suffix_dedup.suffix_ranks(entries)
    suffixes = [e[i:] for e in entries for i in range(len(e) + 1)]
    place = {x: i for i, x in enumerate(sorted(set(suffixes)))}
    assert ranks.tolist() == [place[x] for x in suffixes]
    assert ends.tolist() == [i for i, x in enumerate(suffixes) if not x]
    assert len(suffix_dedup.suffix_ranks([])[0]) == 0

    parse = [b"ab" * 20 + e for e in entries]
    order, shared = suffix_dedup.suffix_order(parse)
    assert [parse[i] for i in order] == sorted(parse)
    for i, j, n in zip(order, order[1:], shared[1:], strict=False):
        assert parse[i][:n] == parse[j][:n] and parse[i][n : n + 1] != parse[j][n : n + 1] or parse[i] == parse[j] and n == len(parse[i])


@pytest.mark.parametrize("letters", [1, 2, 26, 256])
def test_corpus_order(letters):
    draw = np.random.default_rng(letters)
    core = bytes(draw.integers(0, letters, 160, dtype=np.uint8))
    pieces = []
    for _ in range(150):
        a = int(draw.integers(0, 50))
        x = bytearray(bytes(draw.integers(0, letters, draw.integers(0, 20), dtype=np.uint8)) + core[a : a + 100 + int(draw.integers(0, 11))])
        if draw.integers(2):
            x[int(draw.integers(len(x)))] = int(draw.integers(letters))
        pieces.append(bytes(x))
    row, step, k1, k2 = suffix_dedup.corpus_order(pieces)
    assert len(row) == sum(len(p) - 99 for p in pieces)
    strings: dict = {}
    for r, s, key in zip(row, step, zip(k1.tolist(), k2.tolist(), strict=True), strict=True):
        strings.setdefault(pieces[r][s : s + 100], set()).add(key)
    assert all(len(keys) == 1 for keys in strings.values())
    assert len({key for keys in strings.values() for key in keys}) == len(strings)
    assert len(suffix_dedup.corpus_order([])[0]) == 0


def test_repeats_within_a_text(spark):
    draw = np.random.default_rng(8)
    turns = ["nd " * 2000, "ab" * 700 + prose(40, 90) + "ab" * 700, prose(40, 90) * 3, "nd " * 300 + prose(41, 50) + "nd " * 300, "é" * 400]
    texts = [*turns, *("".join(turns[i] for i in draw.integers(0, len(turns), 3)) for _ in range(8)), prose(42, 60) * 2]
    rows = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3)
    assert by_id(suffix_dedup.deduplicated(rows), "n_bytes", "n_removed", "n_spans", "kept_sha256") == removed(texts)
    import pyarrow as pa

    batch = pa.RecordBatch.from_arrays([pa.array([0]), pa.array(["nd " * 20000])], ["doc_id", "text"])
    places = next(suffix_dedup._phrases(iter([batch]))).column(2).to_numpy()
    assert len(places) > 1000 and (places >= 0).sum() < 10  # all others are dealt evenly


def test_opened_blocks_beyond_the_bound(monkeypatch):
    import pyarrow as pa

    draw = np.random.default_rng(1)
    core = bytes(draw.integers(97, 123, 80, dtype=np.uint8))
    rows = sorted((7, bytes(draw.integers(97, 100, 15 + i % 3, dtype=np.uint8)) + core + b"z" * 20, i, 0) for i in range(60))

    def starts(most):
        monkeypatch.setattr(suffix_dedup, "MOST_BLOCKS", most)
        batches = [pa.RecordBatch.from_arrays([pa.array(c) for c in zip(*rows[i : i + 7], strict=True)], ["phrase", "bytes", "doc_id", "start"]) for i in range(0, len(rows), 7)]
        out, keyed = set(), []
        for b in suffix_dedup._opened(iter(batches)):
            for k1, k2, d, s, n in zip(*(c.to_pylist() for c in b.columns), strict=True):
                if k1 is None:
                    out |= {(d, s + i) for i in range(n)}
                else:
                    keyed.append((k1, k2, d, s))
        keyed.sort()
        return out | {(b[2], b[3]) for a, b in zip(keyed, keyed[1:], strict=False) if a[:2] == b[:2]}

    assert starts(5) == starts(10_000) != set()


def test_decontaminate(spark, docs, none):
    item = " ".join(prose(9, 30).split())
    bench = spark.createDataFrame([(1, item), (2, item), (3, "tiny item"), (4, None), (5, "...")], "item_id long, text string")
    rows = [(0, f"before {item.upper()} after"), (1, "A tiny, ITEM!"), (2, None), (3, ""), (4, " ".join(item.split()[:12])), (5, "x " * 3000 + " ".join(item.split()[3:16]))]
    small = spark.createDataFrame(rows, "doc_id long, text string")
    found = {r.doc_id: r for r in decontaminate.benchmark_hits(small, bench).collect()}
    plain = {i: len(decontaminate.plain_words(t)) for i, t in rows}
    assert [found[i].n_words for i in range(6)] == [plain[i] for i in range(6)]
    assert [found[i].items for i in range(6)] == [["1", "2"], ["3"], [], [], [], ["1", "2"]]
    assert found[1].n_hit == 2 and found[5].n_hit == 13
    start, end = found[1].spans[0]
    assert rows[1][1][start:end] == "tiny, ITEM"
    assert {r.doc_id for r in decontaminate.decontaminated(small, bench).collect()} == {2, 3, 4, 5}
    assert decontaminate.benchmark_hits(small, bench.where("false")).where("n_hit > 0").count() == 0
    assert decontaminate.decontaminated(none, bench).columns == docs.columns


def naive_hits(texts, items, window=13):
    windows: dict = {}
    for item, t in items:
        w = decontaminate.plain_words(t)
        for at in range(max(1, len(w) - window + 1) if w else 0):
            windows.setdefault(tuple(w[at : at + window]), set()).add(str(item))
    out = {}
    for i, t in texts:
        w = decontaminate.plain_words(t)
        hit, ids = [False] * len(w), set()
        for size in {len(k) for k in windows}:
            for at in range(len(w) - size + 1):
                if (found := windows.get(tuple(w[at : at + size]))):
                    hit[at : at + size] = [True] * size
                    ids |= found
        out[i] = (len(w), sum(hit), sorted(ids))
    return out


@pytest.mark.parametrize("words", [40, 1_000_000])
def test_hits_by_brute_force(spark, monkeypatch, words):
    """Few different words, so that windows overlap and repeat; items of every length; one automaton or several."""
    monkeypatch.setattr(decontaminate, "PIECE_WORDS", words)
    draw = np.random.default_rng(12)
    some = lambda n, of: " ".join(f"w{i}" for i in draw.integers(0, of, n))
    items = [(i, some(int(n), of)) for i, (n, of) in enumerate([(n, of) for n in (1, 3, 12, 13, 14, 20, 27, 40) for of in (2, 30)])] + [(90, ""), (91, None)]
    texts = [(i, some(60, 2)) for i in range(4)]
    for i in range(4, 40):
        _, t = items[int(draw.integers(0, 16))]
        w = t.split()
        lo = int(draw.integers(0, max(1, len(w) - 10)))
        texts.append((i, f"{some(9, 40)} {' '.join(w[lo : lo + int(draw.integers(8, 30))])} {some(9, 40)}"))
    texts += [(100, None), (101, "")]
    docs = spark.createDataFrame(texts, "doc_id long, text string").withColumns({"n_hit": F.lit("clash"), "runs": F.lit(1)})
    bench = spark.createDataFrame(items, "item_id long, text string")
    expected = naive_hits(texts, items)
    found = {r.doc_id: (r.n_words, r.n_hit, r["items"]) for r in decontaminate.benchmark_hits(docs, bench).collect()}
    assert found == expected
    kept = decontaminate.decontaminated(docs, bench)
    assert kept.columns == docs.columns
    assert {r.doc_id for r in kept.collect()} == {i for i, (n, h, _) in expected.items() if not (h and 20 * h >= n)}
    assert decontaminate.benchmark_hits(docs.where("false"), bench).count() == 0


def test_mixing(docs, none):
    found = mixing.mix(docs).collect()
    assert {r.doc_id: r["size"] for r in found} == {i: len(re.findall(r"[^\x20\x09-\x0D]+", t or "")) for i, t in enumerate(TEXTS)}
    total = sum(r["size"] for r in found)
    targets = {r.target: r.source_size for r in found}
    assert sum(targets) == pytest.approx(total)
    for target, size in targets.items():
        assert target <= 3 * size + 1e-9
        assert abs(sum(r.taken for r in found if r.target == target) - target) < 1
    assert all(0 <= r.taken <= 3 * r["size"] for r in found)
    assert sorted(map(tuple, found)) == sorted(map(tuple, mixing.mix(docs.repartition(5)).collect()))
    assert mixing.mix(none).count() == 0


def test_mixed_corpus(spark, docs, none):
    import corpus_pipeline

    words = lambda t: re.findall(r"[^\x20\x09-\x0D]+", t or "")
    found = {r.doc_id: r for r in mixing.mix(docs).collect()}
    rows = mixing.mixed(docs).collect()
    copies: dict = {}
    for r in sorted(rows, key=lambda r: (r.doc_id, r.epoch)):
        assert len(words(r.text)) == r.words > 0 and TEXTS[r.doc_id].startswith(r.text)
        copies.setdefault(r.doc_id, []).append(r)
    assert set(copies) == {i for i, r in found.items() if r.taken} != set(found)
    for i, c in copies.items():
        assert [r.epoch for r in c] == list(range(1, len(c) + 1))
        assert all(r.text == TEXTS[i] for r in c[:-1]) and sum(r.words for r in c) == found[i].taken
    assert max(map(len, copies.values())) > 1
    assert any(len(words(c[-1].text)) < found[i]["size"] for i, c in copies.items())
    for source in ("s1", "s2", None):
        target = next(r.target for i, r in found.items() if ["s1", None, "s2", "s1"][i % 4] == source)
        assert sum(r.words for r in rows if r.source == source) == int(target)
    last = corpus_pipeline.mix_sources(spark, docs, "").collect()
    assert sorted((r.doc_id, r.epoch, r.text, r.words) for r in last) == sorted((r.doc_id, r.epoch, r.text, r.words) for r in rows)
    assert mixing.mixed(none).count() == 0


def test_targets_stop_at_the_limit(spark):
    sizes = spark.createDataFrame([("a", 1000, 1, 1), ("b", 10, 2, 2), ("c", 100, 3, 3)], "name string, source_size long, rank long, weight long")
    found = {r.name: r.target for r in mixing.targets(sizes).collect()}
    assert found == {"a": 1110 - 330, "b": 30, "c": 300}


def test_quality(docs, none):
    found = {r.doc_id: r for r in quality.judged(docs, "source").collect()}
    for i, t in enumerate(TEXTS):
        w = re.findall(r"[^\x20\x09-\x0D]+", t or "")
        tri = [tuple(w[j : j + 3]) for j in range(len(w) - 2)]
        c = Counter(tri)
        again = {p for j, k in enumerate(tri) if c[k] > 1 for p in (j, j + 1, j + 2)}
        lines = [x for x in (t or "").split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        r = found[i]
        assert (r.n_words, r.word_chars, r.n_dup_lines, r.n_repeat_words) == (len(w), sum(map(len, w)), len(lines) - len(set(lines)), len(again))
        assert r.base_failed == (len(w) < 50 or 100 * len(again) > 50 * len(w))
    assert quality.judged(none, "source").count() == 0


def test_frequent_lines_go(spark):
    rows = [(i, f"Boiler  plate 19{i}\n" + prose(100 + i, 80), "h") for i in range(30)] + [(99, "boiler plate 7\n" * 3 + "few words", "h"), (100, "boiler plate 1", "other")]
    many = spark.createDataFrame(rows, "doc_id long, text string, host string")
    found = {r.doc_id: r for r in quality.judged(many, most_docs=10).collect()}
    assert all(found[i].kept and found[i].frequent_words == 3 for i in range(30))
    assert not found[99].kept
    assert found[100].frequent_words == 0
    texts = by_id(quality.without_frequent_lines(many, most_docs=10), "text")
    assert texts[0] == prose(100, 80) and texts[99] == "few words" and texts[100] == "boiler plate 1"


PATTERNS = [("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+"), ("ip", r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)"), ("card", r"[0-9]([\x20-]?[0-9])+"), ("phone", r"\+[0-9][\x20().0-9-]+[0-9]")]


def valid(kind, v):
    d = re.sub("[^0-9]", "", v)
    if kind == "ip":
        return all(int(p) <= 255 for p in v.split("."))
    if kind == "card":
        return 16 <= len(d) <= 19 and sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(reversed(d))) % 10 == 0
    return kind != "phone" or 8 <= len(d) <= 15


def base(text):
    return [(k, m.start(), m.end()) for k, p in PATTERNS for m in re.finditer(p, text) if valid(k, m[0])]


def test_pii(docs, none):
    found = {r.doc_id: [(s.kind, s.start, s.end) for s in r.spans] for r in pii.personal_spans(docs).collect()}
    assert found == {i: base(t or "") for i, t in enumerate(TEXTS)}
    clean = by_id(pii.sanitised(docs), "text")
    assert not any(base(t or "") for t in clean.values())
    assert clean[0] is None and clean[9] == TEXTS[9]
    assert pii.personal_spans(none).count() == 0


def test_sanitised_rows_and_columns(spark):
    """Repeated rows, null ids, clashing columns and matches that only appear once their neighbour is gone."""
    rows = [(1, "a@b.c", "x"), (1, "a@b.c", "x"), (1, "other 1.2.3.4", "y"), (None, "mail q@r.st", "z"), (2, None, "n"), (3, "4111 1111 1111 1111a@b.c.1.2.3.4", "w"), (4, "", "e")]
    many = spark.createDataFrame(rows, "doc_id long, text string, _doc string").withColumns({"text_key": F.lit(1), "new_text": F.lit(2), "DOC_KEY": F.lit(3), "a.b": F.lit(4)})
    out = pii.sanitised(many)
    assert out.columns == many.columns
    found = out.collect()
    assert len(found) == len(rows)
    assert sorted(r._doc for r in found) == sorted(r[2] for r in rows)
    assert not any(base(r.text or "") for r in found)
    assert {r.text for r in found if r.doc_id == 1} == {"[EMAIL]", "other [IP]"}
    assert [r.text for r in found if r.doc_id == 2] == [None]


def test_revealing_terms(spark):
    # the name stands far from the address in whole texts of many words
    rows = [(i, f"Quirrelmann {prose(200 + i, 60)} the desk of q@uni.example.org {prose(400 + i, 60)} professor") for i in range(8)]
    rows += [(i, prose(500 + i, 30)) for i in range(8, 200)]
    rows += [(i, "copied words around z@uni.example.org again") for i in range(200, 220)]
    long = prose(77, 80).split()
    rows += [(i, " ".join([*long[: i - 220], "changed", *long[i - 219 :], "w@uni.example.org Zweigrat"])) for i in range(220, 260)]
    rows += [(260, "Quirrelmann without the address")]
    many = spark.createDataFrame(rows, "doc_id long, text string")
    found = pii.personal_spans(many).collect()
    terms = {r.doc_id: {rows[r.doc_id][1][s.start : s.end] for s in r.spans if s.kind == "term"} for r in found}
    assert all({"professor", "Quirrelmann", "the", "desk"} == terms[i] for i in range(8))
    assert not any(terms[i] for i in range(8, 261))


def test_disclosure_by_brute_force(spark):
    """Counts over whole documents, copies weighing 1 together, and the general form where it does not disclose."""
    rows = [(i, f"quirrelmann quirrelbach {prose(200 + i, 10)} q@uni.example.org") for i in range(6)] + [(5 + i, f"quirrelmann quirrelbach {prose(205, 10)} q@uni.example.org") for i in range(1, 4)]
    rows += [(i, f"quirrelstein {prose(600 + i, 12)}") for i in range(10, 60)] + [(i, prose(700 + i, 12)) for i in range(60, 200)]
    many = spark.createDataFrame(rows, "doc_id long, text string")
    found = {r.term: r for r in pii.revealing_terms(pii.cut(pii.described(many))).collect()}
    weights = Counter(t for _, t in rows)
    def count(*having):
        return sum(1 / weights[t] for _, t in rows if all(h in t for h in having))
    n, q = count(), "q@uni.example.org"
    for term in ("quirrelmann", "quirrelbach", "uni", "org", "example"):
        score = np.log2(count(q, term) / count(q) * n / count(term)) / np.log2(n / count(q))
        assert (term in found) == (score >= pii.DISCLOSED)
        assert term not in found or found[term].disclosure == pytest.approx(score, rel=1e-4)
    assert found["quirrelmann"].general == found["quirrelbach"].general == "quir*"
    assert "[EMAIL]" in (t := by_id(pii.sanitised(many), "text"))[0] and t[0].startswith("quir* quir* ") and t[10] == rows[[r[0] for r in rows].index(10)][1]


def test_chaining(spark, docs, none):
    found = {r.doc_id: r for r in chaining.passage_report(docs).collect()}
    assert found[6].copy_of == 5 and found[6].class_id == 5
    assert 5 in found[8].partners and found[8].class_id == 5
    assert found[7].n_passages >= 1
    assert found[9].n_passages == 0 and found[0].n_passages == 0
    assert chaining.passage_report(none).count() == 0
    a, b = prose(700, 80).split(), prose(701, 200).split()
    fuzzy = a[:20] + ["changed"] + a[21:45] + a[46:]  # a changed word and a lost one
    rows = [(0, " ".join(a)), (1, " ".join(b[:100] + fuzzy + b[100:]))]
    texts = spark.createDataFrame(rows, "doc_id long, text string")
    from hgengine.llm.copies import with_first

    p = chaining.passages(texts, with_first(texts)).collect()
    assert len(p) == 1 and p[0].matched == 78 and (p[0].start, p[0].of_start, p[0].of_end) == (100, 0, 80)


def test_chains_are_collinear():
    draw = np.random.default_rng(5)
    for _ in range(20):
        a, b = draw.integers(0, 60, 12), draw.integers(0, 60, 12)
        pts = sorted(set(zip(a.tolist(), b.tolist(), strict=True)))
        a, b = (np.array(x) for x in zip(*pts, strict=True))
        for chain in chaining.chains(a, b):
            assert all(a[i] < a[j] and b[i] < b[j] for i, j in zip(chain, chain[1:], strict=False))


def test_matched_words_by_brute_force():
    """What is counted as matching is the longest common subsequence, in the alignments that are forced."""
    draw = np.random.default_rng(9)
    for n in (12, 38, 60, 90):
        for _ in range(20):
            core = draw.integers(0, 1 << 40, n)
            other = core.copy()
            for at in draw.integers(0, n, n // 20):
                other[at] = draw.integers(1 << 41, 1 << 42)
            x = np.concatenate([draw.integers(0, 1 << 40, 30), core, draw.integers(0, 1 << 40, 30)])
            y = np.concatenate([draw.integers(0, 1 << 40, 17), other, draw.integers(0, 1 << 40, 5)])
            in_x = [30 + i for i in range(n - 5) if (core[i : i + 6] == other[i : i + 6]).all()]
            if not in_x:
                continue
            keep = sorted({in_x[0], in_x[-1], *draw.choice(in_x, min(len(in_x), 5)).tolist()})
            a, end_x, b, end_y, matched = chaining.align(x, y, keep, [i - 13 for i in keep])
            assert matched == chaining.common_length(x[a:end_x], y[b:end_y]) <= min(end_x - a, end_y - b)


def every_pair(texts):
    """Passages (of, doc) of all pairs of texts, from all places of all their common seeds."""
    words = [hashed_words(t) for t in texts]
    places = [{} for _ in texts]
    for i, w in enumerate(words):
        for h, at in zip(*(x.tolist() for x in chaining.seeds(w)), strict=True):
            places[i].setdefault(h, []).append(at)
    out = set()
    for b in range(len(texts)):
        for a in range(b):
            pts = sorted({(x, y) for h in places[a].keys() & places[b].keys() for x in places[a][h] for y in places[b][h]})
            if len(pts) > 1:
                at_a, at_b = (np.array(c) for c in zip(*pts, strict=True))
                for chain in chaining.chains(at_a, at_b):
                    s, e, t, f, matched = chaining.align(words[a], words[b], at_a[chain].tolist(), at_b[chain].tolist())
                    if matched >= chaining.LEAST and matched >= chaining.SHARE * max(e - s, f - t):
                        out.add((a, b))
    return out


@pytest.mark.parametrize("gap", [20, 70, 100, 200, 400])
def test_recall_against_all_pairs(spark, gap):
    """Two passages at a gap, whole or in part, exact or with changes, in many texts."""
    draw = np.random.default_rng(gap)
    one, two = prose(gap + 1, 100).split(), prose(gap + 2, 100).split()
    texts = []
    for i in range(40):
        parts = [prose(2000 + gap + i, 40).split()]
        for j, passage in enumerate((one, two)):
            lo = int(draw.integers(0, 50)) if draw.random() < 0.4 else 0
            hi = int(draw.integers(55, 100)) if draw.random() < 0.4 else 100
            p = list(passage[lo:hi]) if draw.random() < 0.7 else []
            if p and draw.random() < 0.4:
                for at in draw.integers(0, len(p), 3):
                    p[at] = f"changed{draw.integers(1 << 30)}"
            parts += [p, prose(3000 + 2 * (gap + i) + j, gap).split()]
        texts.append(" ".join(w for p in parts for w in p))
    rows = {r.doc_id: r for r in chaining.passage_report(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    pairs = every_pair(texts)
    later = {b for _, b in pairs}
    assert len(later) > 20
    assert sum(rows[b].n_passages > 0 for b in later) >= 0.95 * len(later)
    assert all(rows[i].n_passages == 0 for i in range(40) if i not in later)
    assert sum(rows[a].class_id == rows[b].class_id for a, b in pairs) >= 0.95 * len(pairs)


def test_a_whole_passage_among_parts(spark):
    """Two texts have a passage whole; those before each have too little of it for a passage of their own."""
    p = prose(4100, 55).split()
    bodies = [p[20:], p[:35], p, p[:35], p[20:], p]
    rows = [(i, " ".join([prose(4200 + i, 60), *body, prose(4300 + i, 60)])) for i, body in enumerate(bodies)]
    found = {r.doc_id: r for r in chaining.passage_report(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert found[5].n_passages == 1 and found[5].partners == [2] and found[5].class_id == 2
    assert [found[i].n_passages for i in range(5)] == [0] * 5


def test_every_pair_with_a_passage_is_of_one_class(spark):
    """Passages with a word changed in each five or six share no run of six words; many texts have a line or two in common, and a
    middle part of a passage that joins nothing. Classes and findings are those of all pairs."""
    draw = np.random.default_rng(77)
    lines, cores = [prose(5000 + i, 12) for i in range(3)], [prose(5100 + i, 60).split() for i in range(12)]
    texts = []
    for i in range(160):
        parts = [prose(5200 + i, 30)]
        if i < 60:  # drifts: each core as it is, then with other words changed each time
            core = list(cores[i % 12])
            if i >= 12:
                for at in range(int(draw.integers(4, 6)), 60, 5 if i % 2 else 6):
                    core[at] = f"changed{i}x{at}"
            parts += [" ".join(core), prose(5400 + i, 80)]
        for j in range(int(draw.integers(0, 3))):
            parts += [prose(5500 + 3 * i + j, int(draw.integers(1, 40))), lines[int(draw.integers(3))]]
        texts.append(" ".join([*parts, prose(6100 + i, 30)]))
    rows = {r.doc_id: r for r in chaining.passage_report(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    sought = [chaining.Sought(hashed_words(t)) for t in texts]
    pairs = [(a, b) for b in range(160) for a in range(b) if any(chaining.passages_of(sought[a], sought[b]))]
    root = list(range(160))
    for _ in range(8):
        for a, b in pairs:
            root[a] = root[b] = min(root[a], root[b])
    assert [rows[i].class_id for i in range(160)] == root
    assert {i for i in rows if rows[i].n_passages} == {b for _, b in pairs}
    assert all((i % 12, i) in pairs for i in range(12, 60)) and len(set(root[:12])) == 12


def test_few_pairs_are_worth_aligning():
    """All pairs with a passage are; those with a line of 12 words and one more common run, which were aligned before, are not."""
    draw = np.random.default_rng(8)
    core, line = prose(7500, 70).split(), prose(7501, 12)
    texts = []
    for i in range(40):
        p = list(core[int(draw.integers(0, 20)) : int(draw.integers(45, 70))])
        for at in range(int(draw.integers(4, 9)), len(p) - 6, int(draw.integers(6, 20))):
            p[at : at + 1] = [f"changed{i}x{at}"] if draw.random() < 0.6 else []
        texts.append(" ".join([prose(7600 + i, 20), *p, prose(7700 + i, 20)]))
    texts += [" ".join([prose(7800 + i, 30), line, prose(7900 + i, 30), *core[30:34], prose(8000 + i, 30)]) for i in range(10)]
    sought = [chaining.Sought(hashed_words(t)) for t in texts]
    passages = 0
    for b, y in enumerate(sought):
        for a, x in enumerate(sought[:b]):
            at = [(p, q) for p, h in zip(x.at.tolist(), x.seeds.tolist(), strict=True) for q in y.at[y.seeds == h].tolist()]
            p, q = (np.array(c, np.int64) for c in zip(*at, strict=True)) if at else (np.zeros(0, np.int64),) * 2
            some = len(chaining.worth(np.zeros(len(p), np.int64), p, q, np.zeros(len(p), bool))[0]) > 0
            has = any(chaining.passages_of(x, y))
            passages += has
            assert some or not has
            assert not some or a < 40
    assert passages > 50


def test_frequent_seeds_lose_no_pair(spark, monkeypatch):
    """With almost all seeds counted as frequent the same classes come out."""
    rows = [(i, " ".join([prose(7000 + i, 40), prose(7100 + i % 5, 25), prose(7200 + i, 3 + i % 4), prose(7300 + i % 3, 30), prose(7400 + i, 40)])) for i in range(60)]
    texts = spark.createDataFrame(rows, "doc_id long, text string")
    usual = by_id(chaining.passage_report(texts), "class_id")
    monkeypatch.setattr(chaining, "FREQUENT", 3)
    assert by_id(chaining.passage_report(texts), "class_id") == usual
    assert len(set(usual.values())) < 60


def test_frequent_seeds_are_counted_in_all_documents(spark, monkeypatch):
    """Of over 20,000 documents: lines of one document fewer than a frequent one needs, of as many, and of many more."""
    texts = [f"short text {i}" for i in range(20_050)]
    for k, n in enumerate((chaining.FREQUENT - 1, chaining.FREQUENT, chaining.FREQUENT + 1, 300)):
        for i in range(n):
            texts[100 + 600 * k + i] += f" {prose(9000 + k, 12)}" * (1 + i % 2)
    held = {}
    for t in texts:
        for h in set((chaining.seeds(hashed_words(t))[0] >> np.uint64(20)).tolist()):
            held[h] = held.get(h, 0) + 1

    class Told(Exception):
        pass

    def told(*args, frequent=chaining.frequent):
        raise Told(frequent(*args))

    monkeypatch.setattr(chaining, "frequent", told)
    with pytest.raises(Told) as found:
        chaining.passage_report(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).count()
    codes, lines = found.value.args[0]
    assert codes.tolist() == sorted(h for h, n in held.items() if n >= chaining.FREQUENT)
    assert len(lines) == len(codes) > 3 * 8


def test_short_repeats_are_told_by_their_words(spark, monkeypatch):
    """Texts that have a word 25 times are not aligned with each other, and those that have it 60 times are found."""
    texts = [" ".join([prose(9100 + i, 50), "then " * (60 if i % 20 == 0 else 25), prose(9200 + i, 50)]) for i in range(100)]
    aligned = []
    monkeypatch.setattr(chaining, "_verified", lambda pairs, docs, f=chaining._verified: aligned.append(pairs.count()) or f(pairs, docs))
    rows = {r.doc_id: r for r in chaining.passage_report(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    long = list(range(0, 100, 20))
    assert {i for i in rows if rows[i].n_passages} == set(long[1:])
    assert all(rows[i].class_id == (0 if i in long else i) for i in rows)
    assert sum(aligned) < 1000  # of 4950 pairs


def test_repeating_text_has_few_seeds():
    h, at = chaining.seeds(hashed_words("nd " * 4000))
    assert len(h) <= 402
    h, at = chaining.seeds(hashed_words("a b " * 2000))
    assert len(h) <= 402


def test_chains_within_reach_by_brute_force():
    draw = np.random.default_rng(6)
    for n in (1, 12, 60, 200):
        pts = sorted(set(zip(draw.integers(0, 300, n).tolist(), draw.integers(0, 300, n).tolist(), strict=True)))
        pts += [(x + 400, x + 400) for x in range(0, 200, 5)] + [(x + 700, x + 700) for x in range(0, 60, 5)]
        a, b = (np.array(x) for x in zip(*pts, strict=True))
        most = chaining.FAR + chaining.WORDS
        best = []
        for i, (x, y) in enumerate(pts):
            gains = [best[j] + 2 * chaining.GAP * chaining.WORDS - chaining.GAP * (x - u + y - v) for j, (u, v) in enumerate(pts[:i]) if 0 < x - u <= most and 0 < y - v <= most]
            best.append(chaining.WORDS + max([0.0, *gains]))
        score, back = chaining.best_chains(a, b)
        assert score == pytest.approx(best)
        assert all(j < 0 or (0 < a[i] - a[j] <= most and 0 < b[i] - b[j] <= most) for i, j in enumerate(back))


def test_second_passage_behind_a_long_one(spark):
    from hgengine.llm.copies import with_first

    long, short = prose(800, 200), prose(801, 60)
    rows = [(i, " ".join([prose(810 + i, 30), long, prose(820 + i, 150), short, prose(830 + i, 30)])) for i in (0, 1)]
    texts = spark.createDataFrame(rows, "doc_id long, text string")
    found = sorted((r.start, r.end) for r in chaining.passages(texts, with_first(texts)).collect())
    assert len(found) == 2 and found[0][0] <= 30 and found[0][1] >= 230 and found[1][0] <= 380 and found[1][1] >= 440


def test_toxicity(spark):
    draw = np.random.default_rng(1)
    rows = [(i, prose(1000 + i, 40) + (" vile insult idiot" if draw.random() < 0.3 else "")) for i in range(400)]
    many = spark.createDataFrame([*rows, (400, None), (401, "")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int("idiot" in t)) for i, t in rows] + [(500, None)], "doc_id long, toxic int")
    machine = toxicity.train(many, labels, ~toxicity.held_out(1, 3))
    found = by_id(toxicity.scores(many, machine), "score")
    assert all((found[i] >= 0.7) == ("idiot" in t) for i, t in rows)
    assert 0 <= found[400] == found[401] < 0.7
    assert toxicity.without_toxic(many, labels).count() == 402 - sum("idiot" in t for _, t in rows)
    alone = toxicity.train(many, labels.where("false"), F.lit(True))
    assert set(by_id(toxicity.scores(many, alone), "score").values()) == {0.0}


def test_pairs_beyond_sums():
    """An insult and a group's mention are toxic together alone: weights cannot say it, pairs can."""
    draw = np.random.default_rng(2)
    rows = [np.flatnonzero(draw.random(6) < 0.5).astype(np.int32) for _ in range(600)]
    y = np.array([float(0 in r and 1 in r) for r in rows])
    m = toxicity.FactorizationMachine(np.arange(6), 0.0)
    m.fit(rows, y, epochs=60)
    assert (((1 / (1 + np.exp(-m.raw(rows)))) > 0.5) == y).mean() > 0.98


def test_terms_that_count_beside_another():
    """Half of the rows of the insult are toxic, those that also mention a group; mentions alone are as often harmless as
    not, so that nothing but the pair tells."""
    draw = np.random.default_rng(4)
    rows, y = [], []
    for _ in range(4000):
        insult, group = draw.random() < 0.3, draw.random() < 0.5
        rows.append(np.array(sorted({*draw.integers(10, 60, 8).tolist(), *([1] if insult else []), *([2] if group else [])}), np.int32))
        y.append(float((insult and group) or (not insult and not group and draw.random() < 0.45)))
    y = np.array(y)
    assert {1, 2} <= set(toxicity.selected(rows, y, 10).tolist())
    only = [r[np.isin(r, [1, 2])] for r in rows]
    machine = toxicity.FactorizationMachine(np.arange(3), 0.0)
    machine.fit(only, y, epochs=40)
    p = 1 / (1 + np.exp(-machine.raw([np.array(r, np.int32) for r in ([], [1], [2], [1, 2])])))
    assert p[3] > 0.8 > 0.5 > p[1] and p[3] > p[2] + 0.3


def test_scores_by_brute_force(spark):
    """The machine's sum over all pairs of terms, one by one."""
    rows = [(i, prose(1100 + i, 30) + (" vile idiot" if i % 3 == 0 else "")) for i in range(150)] + [(150, None), (151, ""), (152, "vile " * 5000)]
    many = spark.createDataFrame(rows, "doc_id long, text string").withColumns({"toxic": F.lit("clash"), "score": F.lit(1)})
    labels = spark.createDataFrame([(i, int("idiot" in t)) for i, t in rows[:150]], "doc_id long, toxic int")
    machine = toxicity.train(many, labels, ~toxicity.held_out(1, 3))
    found = by_id(toxicity.scores(many, machine), "score")
    for i, t in rows:
        slots = [k for k in (int(machine.slots[b]) for b in toxicity.Buckets().of(t)) if k >= 0]
        odds = machine.bias + sum(machine.weights[k] for k in slots)
        odds += sum(float(machine.vectors[k] @ machine.vectors[m]) for j, k in enumerate(slots) for m in slots[:j])
        assert found[i] == pytest.approx(1 / (1 + np.exp(-odds)), abs=1e-6)
    assert toxicity.scores(many.where("false"), machine).count() == 0
    kept = toxicity.without_toxic(many, labels)
    assert kept.columns == many.columns and {r.doc_id for r in kept.collect()} == {i for i, s in found.items() if s < toxicity.THRESHOLD}


def test_language(spark):
    from random import Random

    langs = {"xx": "ab cd ef ba dc".split(), "yy": "éa ço zu ki wo".split()}
    r = Random(1)
    rows = [(i, " ".join(r.choices(langs[k], k=30)), k) for i in range(200) for k in [("xx", "yy")[i % 2]]]
    many = spark.createDataFrame([*rows, (900, None, "xx"), (901, "123 !", "yy"), (902, "ab cd", None)], "doc_id long, text string, lang string")
    trees = language.learn(many, ~toxicity.held_out(2, 4))
    found = by_id(language.identify(many, trees), "lang_pred", "score")
    assert all(found[i][0] == k for i, _, k in rows)
    assert found[900] == found[901] == ("und", 0.0)
    assert found[902][0] == "xx"
    assert set(x[0] for x in by_id(language.identify(many, language.learn(many, F.lit(False))), "lang_pred", "score").values()) == {"und"}


def test_code_lengths_are_codes():
    """In each context the lengths of all next bytes make at most one code."""
    trees = language.Trees({"xx": [b"abracadabra abracadabra"], "yy": [b"zyx zyx zyyx"]})
    for context in (b"abr", b"zyx", b"qqq"):
        total = sum(2.0 ** -trees.lengths([context + bytes([c])])[0] for c in (*b"abrcd zyx", 255))
        assert (total <= 1 + 1e-5).all()


def test_code_lengths_by_brute_force():
    draw = np.random.default_rng(3)
    samples = {"xx": [draw.integers(0, 256, n, dtype=np.uint8).tobytes() for n in (1, 3, 90_000)], "yy": [draw.integers(90, 100, 500, dtype=np.uint8).tobytes(), bytes(range(256))]}
    trees = language.Trees(samples)
    for i, name in enumerate(("xx", "yy")):
        follow: dict = {}
        for t in samples[name]:
            for k in range(4):
                for j in range(k, len(t)):
                    follow.setdefault(t[j - k : j], Counter())[t[j]] += 1

        def bits(context: bytes, byte: int) -> float:
            c = follow.get(context)
            if c and byte in c:
                return float(np.log2((sum(c.values()) + len(c)) / c[byte]))
            less = bits(context[1:], byte) if context else 8.0
            return less + (float(np.log2((sum(c.values()) + len(c)) / len(c))) if c else 0.0)

        texts = [b"", b"a", b"\xff\x00", b"abc", samples["xx"][2][:700], samples["yy"][0][:200], draw.integers(0, 256, 300, dtype=np.uint8).tobytes()]
        exact = [sum(bits(t[max(0, j - 3) : j], t[j]) for j in range(len(t))) for t in texts]
        assert trees.lengths(texts)[:, i] == pytest.approx(exact, rel=1e-4)


def test_whole_texts_are_learned_from(spark):
    rows = [(i, "same words " * 400 + ("quux " if i % 2 else "blorb ") * 50, ("xx", "yy")[i % 2]) for i in range(20)]
    many = spark.createDataFrame([*rows, (900, "quux quux", None), (901, "q", None)], "doc_id long, text string, lang string")
    found = by_id(language.identify(many, language.learn(many, F.col("doc_id") < 100)), "lang_pred")
    assert found[900] == found[901] == "yy"


def test_warc(spark):
    body = "<p>" + "x" * 200 + "</p>"
    rows = [(3, "http://www.B.example/z?q=1#f", body), (1, "https://a.example/", "short"), (2, "http://b.example/a", body), (5, None, None), (4, "http://b.example/a", "short"), (6, "http://é.example/", "WARC/1.1\r\n\r\nfake\r\n\r\n" * 20)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    found = warc.archive(pages, scratch(spark, "warc")).collect()
    assert [(r.page_id, r.record_type, r.refers_to) for r in sorted(found, key=lambda r: r.page_id)] == [(1, "response", None), (2, "response", None), (3, "revisit", 2), (4, "response", None), (5, "response", None), (6, "response", None)]
    html = {p: (h or "").encode() for p, _, h in rows}
    assert all((r.payload_bytes, r.payload_digest) == (len(html[r.page_id]), hashlib.sha256(html[r.page_id]).hexdigest()) for r in found)
    assert all(r.stored_digest == r.payload_digest for r in found if r.record_type == "response")
    keys = [(r.url_key, r.ts, r.page_id) for r in found]
    assert keys == sorted(keys)
    assert warc.archive(pages.where("false"), scratch(spark, "warc")).count() == 0


def test_archives_are_bounded_by_bytes(spark, monkeypatch):
    """Pages that together exceed the bound of an archive many times, and ranges that cut runs."""
    monkeypatch.setattr(warc, "ARCHIVE_BYTES", 60_000)
    monkeypatch.setattr(warc, "RUN_ROWS", 40)
    rows = [(i, f"http://h{i % 7}.example/{i % 3}", chr(97 + i % 26) * (100 + 37 * i)) for i in range(400)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string")
    path = scratch(spark, "warc")
    found = warc.archive(pages, path).collect()
    keys = [(r.url_key, r.ts, r.page_id) for r in found]
    assert len(found) == 400 and keys == sorted(keys)
    sizes = [f.length for f in spark.read.format("binaryFile").option("pathGlobFilter", "part-*").load(path).select("length").collect()]
    assert len(sizes) > 20 and max(sizes) <= 60_000
    assert all(r.payload_digest == hashlib.sha256(rows[r.page_id][2].encode()).hexdigest() for r in found)
    order = [r.page_id for r in warc.merged_index(warc.read_archives(spark, path), 9).collect()]
    assert order == [r.page_id for r in found]


def test_missing_archives(spark, tmp_path):
    assert warc.read_archives(spark, str(tmp_path / "nothing")).count() == 0


def test_loser_tree():
    draw = np.random.default_rng(4)
    for k in range(9):
        runs = [sorted(draw.integers(0, 30, draw.integers(0, 9)).tolist()) for _ in range(k)]
        assert list(warc.LoserTree([iter(r) for r in runs], lambda x: x)) == sorted(x for r in runs for x in r)


def test_pipeline_stages(spark):
    """Each stage against brute force on its own input."""
    import corpus_pipeline

    d = "/root/testdata/sf0.001"
    docs, texts = corpus_pipeline.table(spark, d, "documents"), []
    columns = docs.columns
    for _, stage in corpus_pipeline.STAGES:
        docs = corpus_pipeline.cut(stage(spark, docs, d))
        texts.append({r.doc_id: r.text for r in docs.collect()})
        assert stage is corpus_pipeline.STAGES[-1][1] or docs.columns == columns
    assert [n for n, _ in corpus_pipeline.STAGES] == ["toxicity", "near_duplicates", "decontamination", "personal_data", "mixing"]
    clean, alone, free, hidden, _ = texts
    kept, root = list(clean), {}
    folded = ["".join(c.lower() if c.isascii() else c for c in clean[i] or "") for i in kept]
    words = [re.findall(r"[^\x20\x09-\x0D]+", t) for t in folded]
    for a, b, _n in linked([" ".join(w) for w in words]):
        if words[a] and words[b]:
            root.setdefault(kept[a], set()).add(kept[b])
            root.setdefault(kept[b], set()).add(kept[a])
    expected, seen = set(), set()
    for i in sorted(clean):
        if i not in seen:
            expected.add(i)
            stack = [i]
            while stack:
                seen.add(j := stack.pop())
                stack += root.get(j, set()) - seen
    assert set(alone) == expected
    items = [(r.item_id, r.text) for r in corpus_pipeline.table(spark, d, "benchmark").collect()]
    hits = naive_hits(alone.items(), items)
    assert set(free) == {i for i, (n, h, _ids) in hits.items() if not (h and 20 * h >= n)}
    assert set(hidden) == set(free) and not any(base(t or "") for t in hidden.values())
    rows = docs.collect()
    size = {i: len(re.findall(r"[^\x20\x09-\x0D]+", t or "")) for i, t in hidden.items()}
    assert {r.doc_id for r in rows} <= set(hidden) and all(1 <= r.epoch <= 4 and r.words <= size[r.doc_id] for r in rows)
    assert sum(r.words for r in rows) == pytest.approx(sum(size.values()), abs=100)
    out = corpus_pipeline.run(spark, d)
    assert sorted((r.doc_id, r.epoch, r.words) for r in out.collect()) == sorted((r.doc_id, r.epoch, r.words) for r in rows)


def test_pipeline_on_hard_rows(spark):
    """Nulls, empty and repeated rows, null ids and an empty table pass every stage."""
    import corpus_pipeline

    d = "/root/testdata/sf0.001"
    rows = [(1, None, None, None, None), (2, "", "en", "s", 0), (3, BASE, "en", "s", 5), (4, BASE, "en", "t", 5), (5, prose(6, 80) + " a@b.cd", None, "t", 1), (None, prose(7, 80), None, None, 1)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumn("gone", F.lit(1))
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, d)
        assert stage(spark, docs.where("false"), d).count() == 0
        ids = [r.doc_id for r in out.collect()]
        assert sorted(i or 0 for i in ids) == ([0, 1, 2, 3, 5] if name == "near_duplicates" else [0, 1, 2, 3, 4, 5])
    mixed = corpus_pipeline.mix_sources(spark, docs, d)
    assert {r.doc_id for r in mixed.collect()} <= {3, 4, 5, None}
    assert corpus_pipeline.mix_sources(spark, docs.where("false"), d).count() == 0
