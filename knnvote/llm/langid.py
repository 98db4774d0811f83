"""Language identification by rank-order n-gram profiles and the out-of-place distance."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import crc_mod, seeded_hash, small_batches

PROFILE = 400  # most frequent n-grams of 1 to 3 characters
SAMPLE = 8_000  # labelled texts that fit the profiles, at most
SAMPLE_BYTES = 60_000_000  # and their texts together, at most
UNKNOWN = "und"

_LETTER = np.zeros(0x110000, bool)
_LETTER[[c for c in range(0x110000) if not 0xD800 <= c < 0xE000 and chr(c).isalpha()]] = True


def letters(text: str) -> np.ndarray:
    """Code points of the lower-cased letters; every run of anything else is one border, written 32."""
    x = np.frombuffer(f" {text} ".lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    x = np.where(_LETTER[x], x, 32)
    return x[np.concatenate([[True], (x[1:] != 32) | (x[:-1] != 32)])]


def gram_counts(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct n-grams of 1 to 3 characters, packed 21 bits a character, and their counts; borders count inside n-grams only."""
    x = letters(text).astype(np.int64)
    pair = (x[:-1] << 21) | x[1:]
    pair = pair[pair != (32 << 21 | 32)]
    triple = (x[:-2] << 42) | (x[1:-1] << 21) | x[2:]
    triple = triple[(triple >> 21 & 0x1FFFFF) != 32]
    return np.unique(np.concatenate([x[x != 32], pair, triple]), return_counts=True)


def top(g: np.ndarray, n: np.ndarray, size: int) -> np.ndarray:
    """The most frequent n-grams in order of rank; ties by the n-gram itself."""
    if len(g) > 4 * size:
        least = np.partition(n, len(n) - size)[len(n) - size]
        g, n = g[n >= least], n[n >= least]
    return g[np.argsort(-n, kind="stable")[:size]]


@dataclass
class Profiles:
    langs: list[str]
    grams: np.ndarray  # sorted: every n-gram of any profile
    ranks: np.ndarray  # (grams, langs): its rank there, or `size` where it is absent
    size: int

    @classmethod
    def of(cls, ranked: dict[str, np.ndarray], size: int) -> Profiles:
        langs = sorted(ranked)
        grams = np.unique(np.concatenate([ranked[k] for k in langs])) if langs else np.zeros(0, np.int64)
        ranks = np.full((len(grams), len(langs)), size, np.int32)
        for j, k in enumerate(langs):
            ranks[np.searchsorted(grams, ranked[k]), j] = np.arange(len(ranked[k]))
        return cls(langs, grams, ranks, size)

    def predict(self, text: str | None) -> tuple[str, float]:
        """The language of least out-of-place distance (ties: the first by name) and its margin over the next, 0 to 1."""
        if not text or not self.langs:
            return UNKNOWN, 0.0
        g, n = gram_counts(text)
        if not len(g):
            return UNKNOWN, 0.0
        mine = top(g, n, self.size)
        at = np.minimum(np.searchsorted(self.grams, mine), max(0, len(self.grams) - 1))
        known = self.grams[at] == mine
        # an n-gram that a profile lacks is out of place by the profile's size, whatever its own rank
        theirs = self.ranks[at[known]]
        away = np.where(theirs < self.size, np.abs(theirs - np.flatnonzero(known)[:, None]), self.size)
        d = away.sum(axis=0) + (~known).sum() * self.size
        best = int(np.argmin(d))
        if len(d) == 1:
            return self.langs[0], 1.0 - float(d[0]) / (len(mine) * self.size)
        second = float(np.partition(d, 1)[1])
        return self.langs[best], (second - float(d[best])) / second if second else 0.0


def train(docs: DataFrame, where: Column | None = None, text: str = "text", lang: str = "lang", doc_id: str = "doc_id", size: int = PROFILE, sample: int = SAMPLE, sample_bytes: int = SAMPLE_BYTES) -> Profiles:
    """Profiles from at most `sample` labelled texts: an equal share for each language, those with the least seeded hash of their id.

    Bytes are shared out too, and a language keeps its first text whatever its length. Rows without an id are not learned from. The
    choice does not depend on the order in which the table is stored.
    """
    known = docs.where(F.col(text).isNotNull() & F.col(lang).isNotNull() & F.col(doc_id).isNotNull())
    if where is not None:
        known = known.where(where)
    known = known.select(F.col(doc_id).cast("long").alias("i"), F.col(lang).cast("string").alias("lang"), F.col(text).alias("t"))
    langs = known.select("lang").distinct().count()
    if not langs:
        return Profiles.of({}, size)
    by = W.partitionBy("lang").orderBy("h", "i", "bytes")
    rows = known.select("i", "lang", seeded_hash("language", F.col("i")).alias("h"), F.octet_length("t").cast("long").alias("bytes"))
    few = rows.withColumn("nth", F.row_number().over(by)).where(F.col("nth") <= max(1, sample // langs))
    few = few.withColumn("before", F.sum("bytes").over(by.rowsBetween(W.unboundedPreceding, -1))).where(f"nth = 1 or before + bytes <= {sample_bytes // langs}")
    # at most `sample` rows of numbers, or one a language
    chosen = F.broadcast(few.select("i", "lang", "h").distinct())
    counts: dict[str, list] = {}
    for r in known.join(chosen, ["i", "lang"]).select("lang", "h", "i", "t").orderBy("lang", "h", "i", "t").toLocalIterator():
        held = counts.setdefault(r["lang"], [])
        held.append(gram_counts(r["t"]))
        if len(held) >= 256:
            counts[r["lang"]] = [_added(held)]
    return Profiles.of({k: top(*_added(v), size) for k, v in counts.items()}, size)


def _added(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    g, where = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
    return g, np.bincount(where, weights=np.concatenate([p[1] for p in parts]), minlength=len(g)).astype(np.int64)


def identify(docs: DataFrame, profiles: Profiles, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, lang_pred, score) for every row, from the whole text; `und` and 0 where it is null or has no letter."""
    small_batches(docs.sparkSession)
    shared = docs.sparkSession.sparkContext.broadcast(profiles)

    def run(batches):
        for b in batches:
            found = [shared.value.predict(t) for t in b.column(1).to_pylist()]
            yield pa.record_batch([b.column(0), pa.array([k for k, _ in found], pa.string()), pa.array([s for _, s in found], pa.float64())], names=["doc_id", "lang_pred", "score"])

    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).alias("t")).mapInArrow(run, "doc_id long, lang_pred string, score double")


def learnable(doc_id: str = "doc_id") -> Column:
    """Rows that may be learned from: crc32 of the id, modulo 5, is not 0."""
    return crc_mod(doc_id, 5) != 0
