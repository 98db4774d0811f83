"""Toxicity scores from a character n-gram linear classifier over naive Bayes log-count ratios."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import blocks_of, crc_mod, seeded_hash, small_batches

SIZES = (3, 4, 5, 6, 7)  # characters of a lower-cased word with its borders
BITS = 20  # n-grams hash into 2**BITS buckets
SAMPLE = 6_000  # labelled texts that fit the model, at most; a third of them toxic where there are so many
SAMPLE_BYTES = 30_000_000  # and their texts together, at most
THRESHOLD = 0.7
BLOCK = 1 << 18  # bytes hashed at a time

_WORD = np.array([chr(c).isalnum() for c in range(0x110000)])


def _buckets(flat: np.ndarray, wanted: np.ndarray | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(where, bucket) of the n-grams of each size; with `wanted`, of those whose bucket it marks. Spaces stand at an n-gram's ends only."""
    x = flat.astype(np.uint32)
    gap = np.cumsum(flat == 32, dtype=np.int32)
    h = x
    for n in range(2, max(SIZES) + 1):
        h = h[:-1] * np.uint32(0x01000193) + x[n - 1 :]
        if n in SIZES:
            mixed = h ^ (h >> np.uint32(15))
            b = (mixed * np.uint32(0x9E3779B1) + np.uint32(n * 0x85EBCA6B & 0xFFFFFFFF)) >> np.uint32(32 - BITS)
            pos = np.arange(len(b)) if wanted is None else np.flatnonzero(np.take(wanted, b))
            pos = pos[gap[pos + n - 2] == gap[pos]]
            yield pos, b[pos]


def _flatten(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Code points of the lower-cased words of some texts, with a space before and after each text, and where each text begins."""
    parts = [" " + t.decode("utf-8", "replace").lower() for t in texts]
    starts = np.cumsum([0, *map(len, parts)])
    flat = np.frombuffer(("".join(parts) + " " * max(SIZES)).encode("utf-32-le", "replace"), np.uint32)
    return np.where(_WORD[flat], flat, np.uint32(32)), starts


@dataclass
class Model:
    weights: np.ndarray  # float32 of 2**BITS
    bias: float

    def scores(self, texts: list[bytes]) -> np.ndarray:
        """Probability of label 1. Each n-gram of a text counts once."""
        out = np.empty(len(texts))
        at, wanted = 0, self.weights != 0
        for held in blocks_of(texts, len, BLOCK):
            flat, starts = _flatten(held)
            pos, hit = (np.concatenate(v) for v in zip(*_buckets(flat, wanted), strict=True))
            doc = np.searchsorted(starts, pos, "right") - 1
            both = np.unique((doc.astype(np.int64) << BITS) | hit)
            total = np.bincount(both >> BITS, weights=self.weights[both & (2**BITS - 1)], minlength=len(held))[: len(held)]
            out[at : at + len(held)] = 1 / (1 + np.exp(-np.clip(total + self.bias, -30, 30)))
            at += len(held)
        return out


def _present(text: bytes, wanted: np.ndarray | None = None) -> np.ndarray:
    """The buckets that a text's n-grams hit, each once; with `wanted`, of those that it marks."""
    return np.unique(np.concatenate([b for _, b in _buckets(_flatten([text])[0], wanted)]))


def fit(texts: list[bytes], labels: np.ndarray, least: int = 3, z: float = 2.5, l2: float = 1e-3, steps: int = 100) -> Model:
    """Logistic regression on n-gram presence scaled by log-count ratios.

    n-grams that fewer than `least` texts hold, or whose ratio is within `z` standard errors of 0,
    get no weight. Without both labels the model scores everything by the prior.
    """
    y = labels.astype(float)
    weights = np.zeros(2**BITS, np.float32)
    n1, n0 = y.sum(), len(y) - y.sum()
    if not n1 or not n0:
        return Model(weights, float(np.log((n1 + 1) / (n0 + 1))))
    counts = np.zeros((2, 2**BITS), np.int32)
    for t, c in zip(texts, labels, strict=True):
        counts[int(c), _present(t)] += 1
    seen = np.flatnonzero(counts.sum(0) >= least)  # far fewer than all buckets
    p1, p0 = counts[1, seen] + 0.5, counts[0, seen] + 0.5
    del counts
    ratio = np.log(p1 / (n1 + 1)) - np.log(p0 / (n0 + 1))
    error = np.sqrt(1 / p1 - 1 / (n1 + 1) + 1 / p0 - 1 / (n0 + 1))
    far = np.abs(ratio) > z * error
    chosen, r = seen[far], ratio[far]
    column = np.full(2**BITS, -1, np.int32)
    column[chosen] = np.arange(len(chosen))
    # a second look at the texts keeps the chosen n-grams alone in memory
    wanted = column >= 0
    cols = [column[_present(t, wanted)] for t in texts]
    row = np.repeat(np.arange(len(cols), dtype=np.int32), [len(c) for c in cols])
    col = np.concatenate(cols) if cols else np.zeros(0, np.int32)
    balance = np.where(y == 1, 0.5 * len(y) / n1, 0.5 * len(y) / n0)
    begin = np.searchsorted(row, np.arange(len(y)))
    none = np.diff(np.append(begin, len(row))) == 0  # texts without any chosen n-gram
    begin = np.minimum(begin, max(0, len(row) - 1))
    w, bias = np.zeros(len(chosen)), 0.0
    m, v, mb, vb = np.zeros_like(w), np.zeros_like(w), 0.0, 0.0
    for t in range(1, steps + 1):
        s = np.where(none, 0.0, np.add.reduceat((r * w)[col], begin)) + bias if len(col) else np.full(len(y), bias)
        e = balance * (1 / (1 + np.exp(-np.clip(s, -30, 30))) - y) / len(y)
        g = np.bincount(col, weights=e[row], minlength=len(chosen)) * r + l2 * w
        gb = e.sum()
        m, v, mb, vb = 0.9 * m + 0.1 * g, 0.99 * v + 0.01 * g * g, 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb * gb
        rate = 0.08 * (0.1 + 0.9 * (1 - t / steps))
        w -= rate * (m / (1 - 0.9**t)) / (np.sqrt(v / (1 - 0.99**t)) + 1e-9)
        bias -= rate * (mb / (1 - 0.9**t)) / (np.sqrt(vb / (1 - 0.99**t)) + 1e-9)
    weights[chosen] = r * w
    return Model(weights, float(bias))


def train(docs: DataFrame, labels: DataFrame, where: Column | None = None, doc_id: str = "doc_id", text: str = "text", label: str = "toxic", sample: int = SAMPLE) -> Model:
    """Fit on at most `sample` labelled texts: those with the least seeded hash of their id, toxic ones first up to a third.

    `where` restricts the label rows to learn from. Rows without id or label are ignored; an id
    that any row calls toxic is toxic.
    """
    known = labels.where(F.col(doc_id).isNotNull() & F.col(label).isNotNull())
    if where is not None:
        known = known.where(where)
    known = known.groupBy(F.col(doc_id).cast("long").alias("doc_id")).agg((F.max(label) > 0).cast("int").alias("y")).withColumn("h", seeded_hash("toxicity", F.col("doc_id")))
    take = lambda y, n: known.where(F.col("y") == y).orderBy("h", "doc_id").limit(n)
    bad = sample // 3
    chosen = take(1, bad).unionByName(take(0, sample - bad))
    # at most `sample` rows of two numbers, so the broadcast has a bound
    got = docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.coalesce(F.col(text), F.lit("")).cast("binary").alias("t")).join(F.broadcast(chosen), "doc_id")
    texts, ys, total = [], [], 0
    for r in got.select("h", "doc_id", "y", "t").orderBy("h", "doc_id", "t").toLocalIterator():
        total += len(r["t"])
        if total > SAMPLE_BYTES and ys:
            break
        texts.append(bytes(r["t"]))
        ys.append(r["y"])
    return fit(texts, np.array(ys, int))


def score(docs: DataFrame, model: Model, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, score) for every row, from the whole text; null texts score as empty ones."""
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches):
        for b in batches:
            s = shared.value.scores([b"" if t is None else t for t in b.column(1).to_pylist()])
            yield pa.record_batch([b.column(0), pa.array(s)], names=["doc_id", "score"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("binary").alias("t")).mapInArrow(run, "doc_id long, score double")


def without_toxic(docs: DataFrame, model: Model, text: str = "text", threshold: float = THRESHOLD) -> DataFrame:
    """The rows of docs that score below the threshold, all columns kept."""
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(model)
    at = docs.columns.index(text)

    def run(batches):
        for b in batches:
            s = shared.value.scores([b"" if t is None else t.encode() for t in b.column(at).to_pylist()])
            yield b.filter(pa.array(s < threshold))

    return docs.mapInArrow(run, docs.schema)


def learnable(doc_id: str = "doc_id") -> Column:
    """Rows whose label may be learned from: crc32 of the id, modulo 3, is not 1."""
    return crc_mod(doc_id, 3) != 1
