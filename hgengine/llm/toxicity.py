"""Toxicity with a factorization machine over hashed terms.

A text is the set of its hashed terms: its words, and their first 5 and 7 bytes, which inflected forms share. The machine adds a weight of each term and the inner products of the terms'
vectors, so pairs such as an insult and a group's mention count beyond their sum. Terms are selected by the likelihood
ratio of their document frequencies in the classes, over all rows or over those with one of the strongest terms, so that
a term that counts only beside another is seen. The machine is fitted by AdaGrad, on a bounded, hash-drawn sample
of labelled rows; scoring reads every whole text once, without a shuffle.

Null and empty texts score by the bias alone. Without labels of both classes the score is the share of toxic rows (0
without any). Repeated rows score alike. Only doc_id and text are read from the documents.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from hgengine.llm.common import filtered, small
from hgengine.llm.decontaminate import plain_words

BITS, TERMS, RANK, EPOCHS = 20, 4096, 6, 12
#: Sampled texts that a term must be in.
LEAST = 4
#: Least likelihood-ratio statistic between term and class.
GAIN = 15.0
#: Terms whose rows are searched for others that count beside them, and the least statistic there, as many are tried.
ANCHORS, BESIDE = 128, 30.0
#: Labelled rows that the machine is fitted on, at most about so many: a hash of doc_id draws them.
MOST_ROWS = 24_000
THRESHOLD = 0.7


class Buckets(dict):
    MOST = 400_000

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.MOST:
            self.clear()
        value = self[word] = xxhash.xxh3_64_intdigest(word) >> (64 - BITS)
        return value

    def of(self, text: str | None) -> np.ndarray:
        words = set(plain_words(text.lower() if text else text))
        words.update([b"^" + w[:5] for w in words if len(w) > 5], [b"^" + w[:7] for w in words if len(w) > 7])
        return np.unique(np.fromiter(map(self.__getitem__, words), np.int32, len(words)))


class FactorizationMachine:
    def __init__(self, terms: np.ndarray, bias: float, rank: int = RANK, seed: int = 7) -> None:
        self.terms, self.bias = terms, float(bias)
        self.weights = np.zeros(len(terms))
        self.vectors = np.random.default_rng(seed).normal(0, 0.05, (len(terms), rank))
        self.slots = np.full(1 << BITS, -1, np.int32)
        self.slots[terms] = np.arange(len(terms))

    def raw(self, rows: list[np.ndarray]) -> np.ndarray:
        """Log odds of rows of slots."""
        lengths = np.fromiter(map(len, rows), np.int64, len(rows))
        out = np.full(len(rows), self.bias)
        full = np.nonzero(lengths)[0]
        if len(full):
            flat, starts = np.concatenate(rows), np.concatenate([[0], np.cumsum(lengths[full])[:-1]])
            v = self.vectors[flat]
            sums = np.add.reduceat(v, starts, axis=0)
            out[full] += np.add.reduceat(self.weights[flat], starts) + 0.5 * ((sums**2).sum(1) - np.add.reduceat((v**2).sum(1), starts))
        return out

    def fit(self, rows: list[np.ndarray], labels: np.ndarray, epochs: int = EPOCHS, rate: float = 0.1, decay: float = 1e-3, seed: int = 7) -> None:
        draw, size = np.random.default_rng(seed), 256
        gw, gv, gb = np.full_like(self.weights, 1e-6), np.full_like(self.vectors, 1e-6), 1e-6
        # the classes weigh alike
        share = np.where(labels == 1, len(labels) / 2 / max(1, labels.sum()), len(labels) / 2 / max(1, (1 - labels).sum()))
        for _ in range(epochs):
            order = draw.permutation(len(rows))
            for at in range(0, len(order), size):
                own = order[at : at + size]
                part = [rows[i] for i in own]
                error = 1 / (1 + np.exp(-np.clip(self.raw(part), -30, 30))) - labels[own]
                error = error * share[own]
                lengths = np.fromiter(map(len, part), np.int64, len(part))
                db = error.mean()
                gb += db**2
                self.bias -= rate * db / np.sqrt(gb)
                full = np.nonzero(lengths)[0]
                if not len(full):
                    continue
                flat = np.concatenate(part)
                of, e = np.repeat(np.arange(len(full)), lengths[full]), np.repeat(error[full], lengths[full])
                v = self.vectors[flat]
                sums = np.add.reduceat(v, np.concatenate([[0], np.cumsum(lengths[full])[:-1]]), axis=0)
                used, slot = np.unique(flat, return_inverse=True)
                dw = np.bincount(slot, e, len(used)) / len(own) + decay * self.weights[used] / 10
                dv = np.stack([np.bincount(slot, e * (sums[of, f] - v[:, f]), len(used)) for f in range(v.shape[1])], 1) / len(own) + decay * self.vectors[used]
                gw[used] += dw**2
                gv[used] += dv**2
                self.weights[used] -= rate * dw / np.sqrt(gw[used])
                self.vectors[used] -= rate * dv / np.sqrt(gv[used])

    def probability(self, buckets: list[np.ndarray]) -> np.ndarray:
        rows = [(s := self.slots[b])[s >= 0] for b in buckets]
        return 1 / (1 + np.exp(-np.clip(self.raw(rows), -30, 30)))


def _terms(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    buckets = Buckets()
    for batch in batches:
        rows = [buckets.of(x.as_py()) for x in batch.column(0)]
        offsets = np.cumsum([0, *map(len, rows)]).astype(np.int32)
        yield pa.RecordBatch.from_arrays([pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate([*rows, np.zeros(0, np.int32)]))), batch.column(1)], ["terms", "toxic"])


def selected(rows: list[np.ndarray], y: np.ndarray, most: int = TERMS) -> np.ndarray:
    """At most so many terms, by the likelihood ratio between term and class: over all rows, or over those of an anchor,
    one of the terms of the highest ratios; the anchors of such terms are selected too."""
    counts = np.zeros((2, 1 << BITS), np.int32)  # of the rows of label 0 and 1
    for label in (0, 1):
        own = [r for r, t in zip(rows, y, strict=True) if t == label]
        for at in range(0, len(own), 1_000):
            counts[label] += np.bincount(np.concatenate(own[at : at + 1_000]), minlength=1 << BITS).astype(np.int32)
    names = np.nonzero(counts.sum(0) >= LEAST)[0]
    place = np.full(1 << BITS, -1, np.int32)
    place[names] = np.arange(len(names), dtype=np.int32)
    known = [(p := place[r])[p >= 0] for r in rows]
    flat, row = np.concatenate(known), np.repeat(np.arange(len(rows), dtype=np.int32), list(map(len, known)))
    del known

    def gains(yes: np.ndarray, every: np.ndarray, n_yes: float, n: float) -> np.ndarray:
        """From how many of n rows, n_yes of them toxic, have each term."""

        def part(k: np.ndarray, of: np.ndarray, share: float) -> np.ndarray:
            return k * np.log(np.maximum(k, 1e-9) / np.maximum(of * share, 1e-9)) if share else np.zeros(len(k))

        found = sum(part(k, of, share) for k, of, share in ((yes, every, n_yes / n), (every - yes, every, 1 - n_yes / n), (n_yes - yes, n - every, n_yes / n), (n - every - n_yes + yes, n - every, 1 - n_yes / n)))
        return np.where(every >= LEAST, 2 * found, 0)

    alone = gains(counts[1][names].astype(float), counts.sum(0)[names].astype(float), float(y.sum()), float(len(rows)))
    best = np.where(alone >= GAIN, alone, 0)
    toxic = y == 1
    for anchor in np.argsort(-alone, kind="stable")[:ANCHORS]:
        inside = np.zeros(len(rows), bool)
        inside[row[flat == anchor]] = True
        n, n_yes = int(inside.sum()), int((inside & toxic).sum())
        if LEAST <= n_yes <= n - LEAST:
            yes, every = (np.bincount(flat[which[row]], minlength=len(names)).astype(float) for which in (inside & toxic, inside))
            beside = gains(yes, every, float(n_yes), float(n))
            beside[anchor] = 0
            beside[anchor] = beside.max() if beside.max() >= BESIDE else 0
            best = np.maximum(best, np.where(beside >= BESIDE, beside, 0))
    order = np.argsort(-best, kind="stable")
    return names[order[: min(most, int((best > 0).sum()))]]


def train(docs: DataFrame, labels: DataFrame, learn, most: int = MOST_ROWS, terms: int = TERMS) -> FactorizationMachine:
    """learn: a condition on doc_id that says which labels may be learned from."""
    labels = labels.select("doc_id", "toxic").where(F.col("toxic").isNotNull() & F.col("doc_id").isNotNull() & learn)
    share = min(1.0, most / max(1, labels.count()))
    drawn = labels.where(F.pmod(F.xxhash64("doc_id", F.lit("fit")), F.lit(1_000_000)) < round(share * 1_000_000)).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    found = docs.select("doc_id", "text").join(small(drawn, 2 * most), "doc_id").select("text", "toxic").mapInArrow(_terms, "terms array<int>, toxic int").toArrow()
    y = np.concatenate([c.to_numpy(zero_copy_only=False) for c in found.column("toxic").chunks] or [np.zeros(0)]).astype(float)
    rows = [np.asarray(r.values.to_numpy() if r.values is not None else [], np.int32) for r in found.column("terms")]
    del found
    order = np.argsort([xxhash.xxh3_64_intdigest(r.tobytes()) for r in rows], kind="stable") if rows else []
    rows, y = [rows[i] for i in order], y[order] if len(rows) else y  # one order, whatever the partitions
    share = (y.sum() + 0.5) / (len(y) + 1) if len(y) else 0.0
    if not 0 < y.sum() < len(y):
        return FactorizationMachine(np.zeros(0, np.int64), np.log(max(share, 1e-9) / max(1 - share, 1e-9)) if len(y) else -30.0)
    best = selected(rows, y, terms)
    machine = FactorizationMachine(np.sort(best), 0.0)
    machine.fit([(s := machine.slots[r])[s >= 0] for r in rows], y)
    return machine


def _scores(machine):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        buckets = Buckets()
        for batch in batches:
            p = machine.value.probability([buckets.of(x.as_py()) for x in batch.column(1)])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(np.round(p, 9))], ["doc_id", "score"])

    return run


def scores(docs: DataFrame, machine: FactorizationMachine) -> DataFrame:
    """doc_id, score of every document: the probability of label 1."""
    shared = docs.sparkSession.sparkContext.broadcast(machine)
    return docs.select("doc_id", "text").mapInArrow(_scores(shared), "doc_id long, score double")


def held_out(remainder: int, of: int):
    """Whether crc32 of doc_id as text leaves the remainder."""
    return F.crc32(F.col("doc_id").cast("string")) % of == remainder


def without_toxic(docs: DataFrame, labels: DataFrame, threshold: float = THRESHOLD) -> DataFrame:
    """docs that score below the threshold, by a machine learned from the rows that are not held out."""
    shared = docs.sparkSession.sparkContext.broadcast(train(docs, labels, ~held_out(1, 3)))
    return filtered(docs, lambda texts: np.round(shared.value.probability(list(map(Buckets().of, texts))), 9) < threshold)
