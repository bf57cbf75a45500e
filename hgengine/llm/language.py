"""Language identification by prediction by partial matching.

Each language has a tree of byte contexts of length 0 to 3 with the counts of what followed; a byte that a context has
not seen costs that context's escape and is coded by the next shorter one, down to a uniform code. The statistics are
frozen after learning, so the exact code length of a byte depends on the context alone and is tabulated once; a text is
scored by gathers and sums over blocks of 64 bytes. Each block is shared out by the lengths of its codes, and the
language with the largest mean share wins.

Texts that are null or have no letter are `und` with score 0. Without learnable rows every text is `und`. Learning
reads whole texts of a bounded, hash-drawn sample of each language; scoring reads whole texts. Repeated rows score alike.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from hgengine.llm.common import cut, encoded, small

#: Texts of a language that are learned from.
MOST_TEXTS = 200
#: Bytes of a text that are judged together.
BLOCK = 64
BYTES = 256


class Trees:
    """Tables of code lengths in bits: dense ones of a byte alone and of two bytes, and sorted ones of all runs of three
    and four bytes that were seen in any language. A run that was not seen costs the escape of its context and the code
    of the run without its first byte."""

    def __init__(self, samples: dict[str, list[bytes]]) -> None:
        self.names = sorted(samples)
        counts = [{name: self._counted(samples[name], k) for name in self.names} for k in (1, 2, 3, 4)]
        every = [np.arange(BYTES**k, dtype=np.uint32) for k in (1, 2)]
        every += [np.unique(np.concatenate([np.zeros(0, np.uint32), *(codes for codes, _ in c.values())])) for c in counts[2:]]
        self.runs = every[2:]
        self.costs: list[np.ndarray] = []
        #: Of each context of one, two or three bytes; the last row is of contexts that were not seen.
        self.escapes: list[np.ndarray] = []
        for k, found in enumerate(counts, 1):
            contexts = np.zeros(1, np.uint32) if k == 1 else every[k - 2]
            cost, escape = np.zeros((len(every[k - 1]), len(self.names)), np.float32), np.zeros((len(contexts) + 1, len(self.names)), np.float32)
            shorter = np.full((BYTES, len(self.names)), 8.0) if k == 1 else self._cost(every[k - 1] & np.uint32(BYTES ** (k - 1) - 1), k - 1)
            own = np.searchsorted(contexts, every[k - 1] >> np.uint32(8)) if k > 1 else np.zeros(BYTES, np.int64)
            for i, (codes, n) in enumerate(found[name] for name in self.names):
                at = np.searchsorted(every[k - 1], codes)
                sums, kinds = np.bincount(own[at], n, len(contexts)), np.bincount(own[at], minlength=len(contexts))
                escape[:-1, i] = np.where(kinds > 0, np.log2(np.maximum(sums + kinds, 1) / np.maximum(kinds, 1)), 0)
                cost[:, i] = escape[own, i] + shorter[:, i]
                cost[at, i] = np.log2((sums + kinds)[own[at]] / n)
            self.costs.append(cost)
            self.escapes.append(escape)

    def _counted(self, texts: list[bytes], k: int) -> tuple[np.ndarray, np.ndarray]:
        return np.unique(np.concatenate([np.zeros(0, np.uint32), *(self.grams(np.frombuffer(t, np.uint8), k) for t in texts)]), return_counts=True)

    @staticmethod
    def grams(x: np.ndarray, k: int) -> np.ndarray:
        out = np.zeros(max(0, len(x) - k + 1), np.uint32)
        for i in range(k):
            out = (out << np.uint32(8)) | x[i : i + len(out)]
        return out

    @staticmethod
    def _place(runs: np.ndarray, codes: np.ndarray) -> np.ndarray:
        """Where codes are in runs; their number where they are not."""
        at = np.searchsorted(runs, codes)
        at[at == len(runs)] = 0
        return np.where(runs[at] == codes, at, len(runs)) if len(runs) else at

    def _cost(self, codes: np.ndarray, k: int) -> np.ndarray:
        """Bits of the last byte of runs of k bytes, in each language."""
        if k < 3:
            return self.costs[k - 1][codes]
        at = self._place(self.runs[k - 3], codes)
        other = np.nonzero(at == len(self.runs[k - 3]))[0]
        at[other] = 0
        out = self.costs[k - 1][at] if len(self.runs[k - 3]) else np.zeros((len(codes), len(self.names)), np.float32)
        if len(other):
            context, rest = codes[other] >> np.uint32(8), codes[other] & np.uint32(BYTES ** (k - 1) - 1)
            out[other] = self.escapes[k - 1][context if k == 3 else self._place(self.runs[0], context)] + self._cost(rest, k - 1)
        return out

    def _blocks(self, texts: list[bytes]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Texts with bytes, the first block of each, and the bits of each block in each language."""
        sizes = np.fromiter(map(len, texts), np.int64, len(texts))
        full = np.nonzero(sizes > 0)[0]
        if not len(full) or not self.names:
            return full[:0], full[:0], np.zeros((0, len(self.names)))
        x = np.frombuffer(b"".join(texts[i] for i in full), np.uint8)
        starts = np.concatenate([[0], np.cumsum(sizes[full])[:-1]])
        cost = np.zeros((len(x), len(self.names)), np.float32)
        cost[3:] = self._cost(self.grams(x, 4), 4)
        # the first three bytes of a text have only the bytes before them as context
        for k in (1, 2, 3):
            at = starts[sizes[full] >= k] + k - 1
            code = np.zeros(len(at), np.uint32)
            for i in range(k):
                code = (code << np.uint32(8)) | x[at - (k - 1 - i)]
            cost[at] = self._cost(code, k)
        blocks = -(-sizes[full] // BLOCK)
        first = np.concatenate([[0], np.cumsum(blocks)[:-1]])
        inner = np.arange(blocks.sum()) - np.repeat(first, blocks)
        return full, first, np.add.reduceat(cost, np.repeat(starts, blocks) + inner * BLOCK, axis=0, dtype=np.float64)

    def lengths(self, texts: list[bytes]) -> np.ndarray:
        """Bits of each text in each language."""
        out = np.zeros((len(texts), len(self.names)))
        full, first, bits = self._blocks(texts)
        if len(full):
            out[full] = np.add.reduceat(bits, first, axis=0)
        return out

    def shares(self, texts: list[bytes]) -> np.ndarray:
        """Mean over the blocks of each text of the share of each language, when a block's code lengths are likelihoods.

        A foreign passage costs far more in the language around it than the rest costs in the passage's own, so the
        lengths of a whole text would let it decide; by blocks, it counts with its size."""
        out = np.full((len(texts), len(self.names)), 1 / max(1, len(self.names)))
        full, first, bits = self._blocks(texts)
        if len(full):
            likely = np.exp2(np.clip(bits.min(1, keepdims=True) - bits, -1000, 0))
            likely /= likely.sum(1, keepdims=True)
            out[full] = np.add.reduceat(likely, first, axis=0) / np.diff(np.append(first, len(bits)))[:, None]
        return out


def folded(text: str | None) -> bytes:
    return encoded(text.lower() if text else text)


def learn(docs: DataFrame, condition, texts: int = MOST_TEXTS) -> Trees:
    """Trees of each non-null lang among the rows that the condition admits."""
    rows = docs.where(condition & F.col("lang").isNotNull() & (F.length("text") > 0))
    # a hash draws the texts: first a few of each range, then the first of those; only the drawn ones are read whole
    order = Window.partitionBy("lang", F.pmod(F.xxhash64("doc_id"), F.lit(64))).orderBy(F.xxhash64("doc_id", F.lit("fit")), "doc_id")
    few = rows.select("doc_id", "lang").withColumn("at", F.row_number().over(order)).where(F.col("at") <= -(-texts // 64) * 2)
    drawn = few.withColumn("at", F.row_number().over(Window.partitionBy("lang").orderBy(F.xxhash64("doc_id", F.lit("fit")), "doc_id"))).where(F.col("at") <= texts)
    drawn = rows.join(small(cut(drawn.select("doc_id", "lang").distinct())), ["doc_id", "lang"]).groupBy("doc_id", "lang").agg(F.min("text").alias("text"))
    samples: dict[str, list[bytes]] = {}
    for row in sorted(drawn.select("lang", "doc_id", "text").collect(), key=lambda r: (r.lang, r.doc_id)):
        samples.setdefault(row.lang, []).append(folded(row.text))
    return Trees(samples)


def _identify(trees):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        model = trees.value
        for batch in batches:
            texts = [x.as_py() for x in batch.column(1)]
            shares = np.concatenate([model.shares([folded(t) for t in texts[i : i + 64]]) for i in range(0, len(texts), 64)]) if texts else np.zeros((0, len(model.names)))
            langs, scores = [], []
            for text, share in zip(texts, shares, strict=True):
                if not model.names or not text or not any(map(str.isalpha, text)):
                    langs.append("und")
                    scores.append(0.0)
                    continue
                best = int(np.argmax(share))
                langs.append(model.names[best])
                scores.append(round(float(share[best]), 9))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], ["doc_id", "lang_pred", "score"])

    return run


def identify(docs: DataFrame, trees: Trees) -> DataFrame:
    """doc_id, lang_pred, score: the mean share of the best language over the blocks of the text."""
    shared = docs.sparkSession.sparkContext.broadcast(trees)
    return docs.select("doc_id", "text").mapInArrow(_identify(shared), "doc_id long, lang_pred string, score double")
