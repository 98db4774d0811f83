"""Benchmark decontamination by winnowed k-gram fingerprints, extended to whole shared spans."""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import blocks_of, settle, small_batches

WINDOW = 13  # words a shared span must have; a shorter item counts as one window
GRAM = 8  # words in a fingerprinted k-gram; WINDOW - GRAM + 1 of them stand in a window
BLOCK = 1 << 19  # bytes of text taken at a time
ITEM_BYTES = 32_000_000  # benchmark text that one pass over the documents carries

_CLASS = bytes(c + 32 if 65 <= c <= 90 else c if c >= 128 or 48 <= c <= 57 or 97 <= c <= 122 else 32 for c in range(256))
_ODD, _STEP = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)


def _mix(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(31))) * np.uint64(0xBF58476D1CE4E5B9)
    return h ^ (h >> np.uint64(29))


def _powers_of(base: np.uint64, n: int) -> np.ndarray:
    return np.concatenate([[np.uint64(1)], np.cumprod(np.full(n - 1, base, np.uint64), dtype=np.uint64)])


_POWER = _powers_of(_ODD, BLOCK + 1)
_INVERSE = _powers_of(np.uint64(pow(int(_ODD), -1, 2**64)), BLOCK + 1)  # odd numbers have an inverse modulo 2**64


def word_ids(texts: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """64-bit ids of the words of some texts, one after another, and the index at which each text's words begin.

    An id is a polynomial of the word's bytes, so equal words have equal ids wherever they stand.
    """
    ids, starts = [], [0]
    for t in texts:
        n = 0
        raw = t.translate(_CLASS)
        for part in _pieces(raw):
            x = np.frombuffer(part, np.uint8)
            inside = np.concatenate([[False], x != 32, [False]])
            edge = np.flatnonzero(inside[1:] != inside[:-1])
            a, b = edge[::2], edge[1::2]
            if not len(a):
                continue
            power, inverse = (_POWER, _INVERSE) if len(x) <= BLOCK else (_powers_of(_ODD, len(x)), _powers_of(_INVERSE[1], len(x)))
            total = np.zeros(len(x) + 1, np.uint64)
            np.cumsum((x.astype(np.uint64) + np.uint64(1)) * power[: len(x)], out=total[1:])
            ids.append(_mix((total[b] - total[a]) * inverse[a] + (b - a).astype(np.uint64) * _STEP))
            n += len(a)
        starts.append(starts[-1] + n)
    return (np.concatenate(ids) if ids else np.zeros(0, np.uint64)), np.array(starts)


def _pieces(raw: bytes):
    """raw in pieces of about BLOCK bytes that end between words; a longer word is a piece of its own."""
    at = 0
    while at < len(raw):
        end = min(len(raw), at + BLOCK)
        if end < len(raw):
            cut = raw.rfind(b" ", at, end)
            end = cut + 1 if cut >= at else (raw.find(b" ", end) + 1 or len(raw))
        yield raw[at:end]
        at = end


def grams(ids: np.ndarray, k: int) -> np.ndarray:
    """A hash of the k words from each position on."""
    if len(ids) < k:
        return np.zeros(0, np.uint64)
    h = ids[: len(ids) - k + 1].copy()
    for j in range(1, k):
        h = h * _STEP + ids[j : len(ids) - k + 1 + j]
    return _mix(h)


def winnow(h: np.ndarray, span: int) -> np.ndarray:
    """Positions of the rightmost least hash of each window of `span` hashes, each once."""
    n = len(h) - span + 1
    if n <= 0:
        return np.zeros(0, np.int64)
    low, at = h[:n].copy(), np.arange(n)
    for j in range(1, span):
        take = h[j : j + n] <= low
        low[take] = h[j : j + n][take]
        at[take] = np.arange(j, j + n)[take]
    return np.unique(at)


@dataclass
class Passages:
    """Fingerprints of benchmark items by length class: L words make a window, k-grams of k words are kept."""

    names: list[str | None]  # item ids as strings, by item index
    ids: np.ndarray  # all words of all items
    starts: np.ndarray
    classes: list[tuple[int, int, np.ndarray, np.ndarray]]  # (L, k, sorted fingerprints, word position of each)

    @classmethod
    def of(cls, items: list[tuple[str | None, bytes]]) -> Passages:
        ids, starts = word_ids([t for _, t in items])
        by_class: dict[tuple[int, int], list] = {}
        for i in range(len(items)):
            n = starts[i + 1] - starts[i]
            if n:
                window = min(n, WINDOW)
                k = GRAM if n >= WINDOW else window
                h = grams(ids[starts[i] : starts[i + 1]], k)
                at = winnow(h, window - k + 1)
                by_class.setdefault((int(window), int(k)), []).append((h[at], at + starts[i]))
        classes = []
        for (window, k), found in sorted(by_class.items()):
            h, at = (np.concatenate(x) for x in zip(*found, strict=True))
            order = np.argsort(h, kind="stable")
            classes.append((window, k, h[order], at[order]))
        return cls([n for n, _ in items], ids, starts, classes)

    def spans(self, ids: np.ndarray, starts: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(begin, end, item) of shared spans of at least a window's words in the texts whose words are given."""
        out = [(np.zeros(0, np.int64),) * 3]
        text_of = None
        for window, k, prints, places in self.classes:
            h = grams(ids, k)
            if not len(h):
                continue
            if window > k:
                sel = winnow(h, window - k + 1)
                h = h[sel]
            else:
                sel = np.arange(len(h))
            first = np.searchsorted(prints, h)
            hit = np.flatnonzero(prints[np.minimum(first, len(prints) - 1)] == h)
            if not len(hit):
                continue
            first, last = first[hit], np.searchsorted(prints, h[hit], "right")
            if text_of is None:
                text_of = np.searchsorted(starts, np.arange(len(ids)), "right")
                item_of = np.searchsorted(self.starts, np.arange(len(self.ids)), "right")
            counts = np.cumsum(last - first)
            cut = np.searchsorted(counts, np.arange(1_000_000, counts[-1] + 1_000_000, 1_000_000))
            for lo, hi in zip([0, *cut[:-1] + 1], cut + 1, strict=True):
                f, n = first[lo:hi], (last - first)[lo:hi]
                if not len(f):
                    continue
                p = np.repeat(sel[hit[lo:hi]], n)
                q = places[np.repeat(f - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())]
                out.append(self._extended(ids, text_of, item_of, p, q, k, window))
        return tuple(np.concatenate(x) for x in zip(*out, strict=True))

    def _extended(self, ids, text_of, item_of, p, q, k, window):
        """Grow k-gram matches (p in the texts, q in the items) word by word, within text and item; keep spans of a window."""
        def same(i, j):
            ok = (i >= 0) & (i < len(ids)) & (j >= 0) & (j < len(self.ids))
            i, j = np.where(ok, i, 0), np.where(ok, j, 0)
            return ok & (ids[i] == self.ids[j]) & (text_of[i] == text_of[p]) & (item_of[j] == item_of[q])

        whole = np.ones(len(p), bool)
        for j in range(k):
            whole &= same(p + j, q + j)
        p, q = p[whole], q[whole]
        left, right = np.zeros(len(p), np.int64), np.zeros(len(p), np.int64)
        for side, way in ((left, -1), (right, 1)):
            going = np.ones(len(p), bool)
            for step in range(1, window - k + 1):
                going &= same(p - step, q - step) if way < 0 else same(p + k - 1 + step, q + k - 1 + step)
                side += going
        keep = left + k + right >= window
        return (p - left)[keep], (p + k + right)[keep], item_of[q[keep]] - 1


def scan(texts: list[bytes], passages: Passages) -> list[tuple[int, list[tuple[int, int]], list[str]]]:
    """For each text: its words, the merged word spans that are hit, and the items with occurring windows."""
    ids, starts = word_ids(texts)
    a, b, item = passages.spans(ids, starts)
    out = [(int(n), [], []) for n in np.diff(starts)]
    text = np.searchsorted(starts, a, "right") - 1
    for i in np.unique(text):
        mine = np.flatnonzero(text == i)
        merged: list[tuple[int, int]] = []
        for x, y in sorted(set(zip((a[mine] - starts[i]).tolist(), (b[mine] - starts[i]).tolist(), strict=True))):
            if merged and x <= merged[-1][1]:
                merged[-1] = (merged[-1][0], max(y, merged[-1][1]))
            else:
                merged.append((x, y))
        out[i] = (out[i][0], merged, sorted({passages.names[j] for j in np.unique(item[mine])} - {None}))
    return out


def _item_blocks(benchmark: DataFrame, item_id: str, text: str):
    """Benchmark items in blocks of ITEM_BYTES of text, one block in the driver at a time."""
    rows = benchmark.select(F.col(item_id).cast("string").alias("i"), F.col(text).cast("binary").alias("t")).where("t is not null").toLocalIterator()
    return blocks_of(((r["i"], bytes(r["t"])) for r in rows), lambda r: len(r[1]) + 64, ITEM_BYTES)


_SPAN = "array<struct<begin:long,end:long>>"
_FOUND = f"doc_id long, text_key long, text_key2 long, n_words long, spans {_SPAN}, items array<string>"


def shared_spans(docs: DataFrame, benchmark: DataFrame, doc_id: str = "doc_id", text: str = "text", item_id: str = "item_id", item_text: str = "text", keep_key: bool = False) -> DataFrame:
    """(doc_id, n_words, spans, items) for every row of docs: merged word spans [begin, end) that lie in windows of items.

    A null text has no words. Items without words match nothing; items without an id are matched but
    not listed; repeated items are listed once. An empty benchmark hits nothing. Each block of
    ITEM_BYTES of benchmark text takes a pass over the documents, so no pass carries more than that;
    with several blocks the hits, which are few, are written and merged by document.
    """
    small_batches(docs.sparkSession)
    narrow = docs.select(F.col(doc_id).cast("long").alias("doc_id"), *_named(F.col(text)), F.col(text).cast("binary").alias("t"))
    base, more = None, []
    for block in _item_blocks(benchmark, item_id, item_text):
        found = _pass(narrow, block)
        if base is None:
            base = found
        else:
            more.append(settle(found.where("size(spans) > 0").dropDuplicates(["doc_id", "text_key", "text_key2"]), "spans"))
    if base is None:
        base = _pass(narrow, [])
    if not more:
        return base if keep_key else base.drop("text_key", "text_key2")
    hits = more[0]
    for x in more[1:]:
        hits = hits.unionByName(x)
    hits = hits.groupBy("doc_id", "text_key", "text_key2").agg(F.flatten(F.collect_list("spans")).alias("s2"), F.flatten(F.collect_list("items")).alias("i2")).select(F.col("doc_id").alias("d2"), F.col("text_key").alias("k2"), F.col("text_key2").alias("k3"), "s2", "i2")
    both = base.join(hits, F.col("doc_id").eqNullSafe(F.col("d2")) & (F.col("text_key") == F.col("k2")) & (F.col("text_key2") == F.col("k3")), "left")
    none = F.array().cast(_SPAN)
    merged = F.aggregate(F.array_sort(F.concat("spans", F.coalesce("s2", none))), none, _joined)
    return both.select("doc_id", *["text_key", "text_key2"] * keep_key, "n_words", merged.alias("spans"), F.array_sort(F.array_distinct(F.concat("items", F.coalesce("i2", F.array().cast("array<string>"))))).alias("items"))


def _joined(spans, x):
    """Spans in order, with x joined to the last where they touch."""
    last = F.element_at(spans, -1)
    grown = F.concat(F.slice(spans, 1, F.size(spans) - 1), F.array(F.struct(last["begin"].alias("begin"), F.greatest(last["end"], x["end"]).alias("end"))))
    return F.when((F.size(spans) > 0) & (x["begin"] <= F.try_element_at(spans, F.lit(-1))["end"]), grown).otherwise(F.concat(spans, F.array(x)))


def _named(text) -> list:
    """Two independent hashes of a text, which name it where the text itself would be too long; a null is as an empty text."""
    text = F.coalesce(text.cast("string"), F.lit(""))
    return [F.xxhash64(text).alias("text_key"), F.xxhash64(F.reverse(text), F.lit("second")).alias("text_key2")]


def _pass(narrow: DataFrame, items: list[tuple[str | None, bytes]]) -> DataFrame:
    shared = narrow.sparkSession.sparkContext.broadcast(Passages.of(items))

    def run(batches):
        for b in batches:
            for ids, keys, keys2, held in _held(b):
                found = scan(held, shared.value)
                spans = [[{"begin": x, "end": y} for x, y in s] for _, s, _ in found]
                yield pa.record_batch(
                    [
                        ids,
                        keys,
                        keys2,
                        pa.array([n for n, _, _ in found], pa.int64()),
                        pa.array(spans, pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64())]))),
                        pa.array([i for _, _, i in found], pa.list_(pa.string())),
                    ],
                    names=["doc_id", "text_key", "text_key2", "n_words", "spans", "items"],
                )

    return narrow.mapInArrow(run, _FOUND)


def _held(b: pa.RecordBatch):
    """(ids, first keys, second keys, texts) of a batch in runs of about BLOCK bytes."""
    at = 0
    for held in blocks_of([b"" if t is None else t for t in b.column(3).to_pylist()], len, BLOCK):
        yield *(b.column(k).slice(at, len(held)) for k in range(3)), held
        at += len(held)


def measured(found: DataFrame, share: int = 20) -> DataFrame:
    """Adds n_hit, n_items, items_sha256 and contaminated to the rows of shared_spans.

    contaminated: some word is hit, and at least one word in `share`.
    """
    n_hit = F.aggregate("spans", F.lit(0).cast("long"), lambda n, s: n + s["end"] - s["begin"])
    out = found.withColumn("n_hit", n_hit).withColumn("n_items", F.size("items").cast("long"))
    out = out.withColumn("items_sha256", F.sha2(F.array_join("items", ",").cast("binary"), 256))
    return out.withColumn("contaminated", (F.col("n_hit") > 0) & (share * F.col("n_hit") >= F.col("n_words")))


def without_contaminated(docs: DataFrame, benchmark: DataFrame, text: str = "text", share: int = 20) -> DataFrame:
    """The rows of docs that are not contaminated, all columns kept.

    A benchmark of one block takes a single pass that moves no rows; with more blocks the
    contaminated texts are listed first and left out by a join.
    """
    small_batches(docs.sparkSession)
    blocks = _item_blocks(benchmark, "item_id", "text")
    first, second = next(blocks, []), next(blocks, None)
    if second is not None:
        found = measured(shared_spans(docs, benchmark, text=text, keep_key=True), share).where("contaminated")
        # two hashes name a text: its own and that of its reverse
        whole = docs.select(F.struct(*[F.col(f"`{c}`") for c in docs.columns]).alias("_row"), *_named(F.col(text)))
        bad = settle(found.select("text_key", "text_key2").distinct(), "contaminated")
        return whole.join(bad, ["text_key", "text_key2"], "left_anti").select("_row.*")
    shared, at = docs.sparkSession.sparkContext.broadcast(Passages.of(first)), docs.columns.index(text)

    def run(batches):
        for b in batches:
            start = 0
            for held in blocks_of([b"" if t is None else t.encode() for t in b.column(at).to_pylist()], len, BLOCK):
                keep = []
                for n, spans, _ in scan(held, shared.value):
                    hit = sum(y - x for x, y in spans)
                    keep.append(not (hit and share * hit >= n))
                yield b.slice(start, len(held)).filter(pa.array(keep))
                start += len(held)

    return docs.mapInArrow(run, docs.schema)
