"""Benchmark decontamination with one Aho-Corasick automaton.

Test items, questions and answers alike, are normalised to words, and these to numbers. A window is 13 words in a row
of an item (an item of fewer words is one window). The automaton holds the items cut into blocks of 7 words: every window
has one of them whole, so a word of the benchmark is one step of a pattern and not of thirteen. It scans the words of each
document once; a block that occurs is extended to both sides while words agree, and what is as long as a window is hit.
Hits are mapped back to offsets of the original text.

Null or empty texts have no words and are never hit. Repeated items count each under its own id. An empty benchmark
hits nothing. Extra columns do not matter; repeated rows are treated alike. The benchmark is broadcast; a larger one than
PIECE_WORDS is read and broadcast piece by piece, and the documents pass through one automaton after another, so that
neither the driver nor a worker holds more than one piece.
"""

from __future__ import annotations

from collections.abc import Iterator

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgengine.llm.common import cut, encoded, free

WINDOW = 13
#: Words of benchmark text in one automaton, of some 100 bytes each.
PIECE_WORDS = 1_000_000
#: [0-9a-z] and bytes beyond ASCII stay, A-Z turn to lower case, all else parts words.
FOLD = bytes(b if b >= 0x80 or chr(b).isdigit() or "a" <= chr(b) <= "z" else b + 32 if "A" <= chr(b) <= "Z" else 32 for b in range(256))


def plain_words(text: str | None) -> list[bytes]:
    return encoded(text).translate(FOLD).split()


class Windows:
    """The automaton, built where it is first used. A word is a few digits of base 256, of an alphabet for each place, so
    that matches begin and end with words and nodes have few children."""

    def __init__(self, items: list[tuple], window: int = WINDOW) -> None:
        self.items, self.window, self._built = items, window, None

    def __getstate__(self) -> dict:
        return {"items": self.items, "window": self.window, "_built": None}

    def _build(self) -> tuple:
        texts: dict[tuple, list] = {}  # equal items once, with their ids
        for item, text in self.items:
            if words := plain_words(text):
                texts.setdefault(tuple(words), []).append(item)
        numbers: dict[bytes, int] = {}
        known = [([numbers.setdefault(w, len(numbers) + 1) for w in words], ids) for words, ids in texts.items()]
        digits = 2 if len(numbers) < 65_535 else 3
        spell = lambda n: "".join(chr(256 * d + (n >> 8 * d & 255)) for d in range(digits))
        found: dict[str, list] = {}
        block = (self.window + 1) // 2
        codes = {w: (n, spell(n)) for w, n in numbers.items()}
        spelled = {n: s for n, s in codes.values()}
        for i, (words, _) in enumerate(known):
            size = block if len(words) >= self.window else len(words)
            for at in range(0, len(words) - size + 1, block if len(words) >= self.window else len(words)):
                found.setdefault("".join(spelled[n] for n in words[at : at + size]), []).append((i, at, size))
        automaton = ahocorasick.Automaton()
        for key, value in found.items():
            automaton.add_word(key, value)
        if found:
            automaton.make_automaton()
        return automaton, codes, (0, spell(0)), known, digits

    def scan(self, words: list[bytes]) -> tuple[np.ndarray, set]:
        """(hit: whether each word is in a window's occurrence, ids of items with one)."""
        if self._built is None:
            self._built = self._build()
        automaton, codes, unknown, known, digits = self._built
        hit, items = np.zeros(len(words), bool), set()
        if not len(automaton) or not words:
            return hit, items
        coded = [codes.get(w, unknown) for w in words]
        line = None
        reached: dict[tuple, int] = {}  # how far the last run of an item at an offset went
        for end, places in automaton.iter("".join(s for _, s in coded)):
            line = line or [n for n, _ in coded]
            for i, at, size in places:
                own, ids = known[i]
                x = (end + 1) // digits - size
                if len(own) >= self.window:
                    if reached.get((i, x - at), -1) >= x + size:
                        continue
                    a, b = x, x + size
                    while a and a - x + at and line[a - 1] == own[a - 1 - x + at]:
                        a -= 1
                    while b < len(line) and b - x + at < len(own) and line[b] == own[b - x + at]:
                        b += 1
                    reached[i, x - at] = b
                    if b - a < self.window:
                        continue
                else:
                    a, b = x, x + size
                hit[a:b] = True
                items.update(ids)
        return hit, items


def hit_spans(text: str | None, hit: np.ndarray) -> list[tuple[int, int]]:
    """Runs of hit words as code points [start, end) of the original text."""
    raw = encoded(text)
    if not hit.any():
        return []
    codes = np.frombuffer(raw.translate(FOLD), np.uint8) != 32
    edges = np.diff(np.concatenate([[0], codes.astype(np.int8), [0]]))
    starts, ends = np.nonzero(edges == 1)[0], np.nonzero(edges == -1)[0]
    point = np.concatenate([[0], np.cumsum((np.frombuffer(raw, np.uint8) & 0xC0) != 0x80)])
    runs = np.diff(np.concatenate([[0], hit.astype(np.int8), [0]]))
    return [(int(point[starts[a]]), int(point[ends[b - 1]])) for a, b in zip(np.nonzero(runs == 1)[0], np.nonzero(runs == -1)[0], strict=True)]


def _runs(hit: np.ndarray) -> list[int]:
    """Begins and ends of the runs of hit words."""
    return np.nonzero(np.diff(np.concatenate([[0], hit.astype(np.int8), [0]])))[0].tolist()


_SPANS = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))
_ADDED = {"n_words": ("long", pa.int64()), "n_hit": ("long", pa.int64()), "items": ("array<string>", pa.list_(pa.string())), "spans": ("array<struct<start: long, end: long>>", _SPANS), "runs": ("array<long>", pa.list_(pa.int64()))}


def _scan(windows, text_at: int, added: list[str], first: bool):
    """Batches with the columns of _ADDED, new or brought up to date at the end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out: list[list] = [[] for _ in _ADDED]
            keep = batch.columns if first else batch.columns[: -len(_ADDED)]
            before = [([], [])] * batch.num_rows if first else zip(batch.column(batch.num_columns - 1).to_pylist(), batch.column(batch.num_columns - 3).to_pylist(), strict=True)
            for text, (runs, ids) in zip((x.as_py() for x in batch.column(text_at)), before, strict=True):
                words = plain_words(text)
                hit, items = windows.value.scan(words)
                for a, b in zip(runs[::2], runs[1::2], strict=True):
                    hit[a:b] = True
                ids = sorted({*ids, *map(str, items)})
                for column, value in zip(out, (len(words), int(hit.sum()), ids, [{"start": a, "end": b} for a, b in hit_spans(text, hit)], _runs(hit)), strict=True):
                    column.append(value)
            yield pa.RecordBatch.from_arrays([*keep, *(pa.array(c, kind) for c, (_, kind) in zip(out, _ADDED.values(), strict=True))], [*batch.schema.names[: len(keep)], *added])

    return run


def pieces(benchmark: DataFrame, window: int = WINDOW) -> Iterator[Windows]:
    """The items in automata of about PIECE_WORDS words each, at least one."""
    items, size, given = [], 0, False
    for row in benchmark.select("item_id", "text").where("text is not null").orderBy("item_id").toLocalIterator():
        n = len(plain_words(row.text))
        if items and size + n > PIECE_WORDS:
            yield Windows(items, window)
            items, size, given = [], 0, True
        items.append((row.item_id, row.text))
        size += n
    if items or not given:
        yield Windows(items, window)


def scanned(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> tuple[DataFrame, dict[str, str]]:
    """(docs with n_words, n_hit, items, spans and runs added, under names that docs does not have; these names)."""
    names = {n: free(docs, n) for n in _ADDED}
    schema = ", ".join([*(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema.fields), *(f"`{names[n]}` {kind}" for n, (kind, _) in _ADDED.items())])
    text_at, first = docs.columns.index("text"), True
    for piece in pieces(benchmark, window):
        docs = docs if first else cut(docs)  # one automaton in a worker at a time
        docs = docs.mapInArrow(_scan(docs.sparkSession.sparkContext.broadcast(piece), text_at, list(names.values()), first), schema)
        first = False
    return docs, names


def benchmark_hits(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_hit, items (ids with an occurring window, sorted as strings), spans (of the original text)."""
    return scanned(docs.select("doc_id", "text"), benchmark, window)[0].select("doc_id", "n_words", "n_hit", "items", "spans")


CONTAMINATED = "n_hit > 0 and 20 * n_hit >= n_words"


def decontaminated(docs: DataFrame, benchmark: DataFrame, window: int = WINDOW) -> DataFrame:
    """docs without those of which a twentieth or more of the words lie in benchmark windows."""
    found, names = scanned(docs, benchmark, window)
    hit, words = F.col(names["n_hit"]), F.col(names["n_words"])
    return found.where(~((hit > 0) & (20 * hit >= words))).select(*(F.col(f"`{c}`") for c in docs.columns))
