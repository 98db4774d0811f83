"""SimHash fingerprints and exact near-duplicate links by vantage-point trees."""

from __future__ import annotations

from collections.abc import Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import similar
from .common import give_back, settle, small_batches
from .components import connected_components
from .similar import shingle_hashes

SHINGLE = 3  # words, as the query's contract states
RADIUS = 2  # differing bits
SHARD_ROWS = 20_000  # fingerprints a shard should hold
MAX_DEPTH = 16  # of the routing tree
SAMPLE_PER_SHARD = 64  # fingerprints that fit each leaf of the routing tree; at most 2**22 in all
LOST_ROWS = 1 << 22  # ids of copies sent by broadcast, some 128 MB; beyond that the documents are dealt by id
LEAF = 1024  # residents below which a shard compares in blocks


# ---- fingerprints -------------------------------------------------------------------------

def fingerprint(text: bytes | None, shingle: int = SHINGLE) -> int:
    """64-bit SimHash of a text's word shingles; 0 without words. A bit is set if over half of the hashes have it."""
    return _majority(shingle_hashes(text, shingle))


def _majority(blocks: Iterable[bytes]) -> int:
    ones, n = np.zeros(64, np.int64), 0
    for raw in blocks:
        ones += np.unpackbits(np.frombuffer(raw, np.uint8).reshape(-1, 8), axis=1).sum(axis=0, dtype=np.int64)
        n += len(raw) // 8
    return int.from_bytes(np.packbits(2 * ones > n).tobytes(), "big")


def with_fingerprint(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = SHINGLE, sketch: bool = False) -> DataFrame:
    """(doc_id, fp long): one narrow row per document. Null and blank texts have fingerprint 0.

    With `sketch`, also the text's XXH64, the min-hash band keys, the minima's low bytes and the number of shingles; texts without
    words have no sketch.
    """
    small_batches(docs.sparkSession)

    def run(batches):
        for b in batches:
            fps, keys, least, size = [], [], [], []
            for t in b.column(1).to_pylist():
                blocks = list(shingle_hashes(None if t is None else memoryview(t).tobytes(), shingle))
                fps.append(_majority(blocks))
                if sketch:
                    m = similar.minima(np.frombuffer(b"".join(blocks), "<u8")) if blocks else None
                    keys.append([] if m is None else similar.band_keys(m))
                    least.append(b"" if m is None else m.astype(np.uint8).tobytes())
                    size.append(sum(map(len, blocks)) // 8)
            more = [b.column(2), pa.array(keys, pa.list_(pa.int64())), pa.array(least, pa.binary()), pa.array(size, pa.int64())] if sketch else []
            yield pa.record_batch([b.column(0), pa.array(np.array(fps, np.uint64).view(np.int64)), *more], names=["doc_id", "fp", "tid", "keys", "least", "n"][: 2 + len(more)])

    schema = "doc_id long, fp long" + (", tid long, keys array<bigint>, least binary, n long" if sketch else "")
    whole = [similar.text_id(text).alias("tid")] if sketch else []
    return docs.select(F.col(doc_id).cast("long").alias("doc_id"), F.col(text).cast("binary").alias("t"), *whole).mapInArrow(run, schema)


# ---- vantage-point tree -------------------------------------------------------------------

def _distance(fps: np.ndarray, to: np.uint64) -> np.ndarray:
    return np.bitwise_count(fps ^ to).astype(np.int16)


def _vantage(fps: np.ndarray, tries: int = 8) -> tuple[np.uint64, int, np.ndarray] | None:
    """The point, of a few spread over fps, whose distances vary most; the radius near their median that fewest points touch."""
    best = None
    for p in fps[np.linspace(0, len(fps) - 1, min(tries, len(fps))).astype(int)]:
        d = _distance(fps, p)
        if best is None or d.std() > best[2].std():
            best = (p, 0, d)
    p, _, d = best
    counts = np.bincount(d, minlength=65)
    below = np.cumsum(counts)
    can = [r for r in range(64) if 0.3 * len(d) <= below[r] <= 0.7 * len(d)] or [int(np.median(d)) - 1, int(np.median(d))]
    can = [r for r in can if 0 <= r and 0 < below[r] < len(d)]
    if not can:
        return None
    r = min(can, key=lambda r: (counts[max(0, r - RADIUS + 1) : r + 1].sum(), abs(below[r] - len(d) / 2)))
    return p, r, d


def fit_tree(sample: np.ndarray, depth: int) -> list[tuple[int, int] | None]:
    """Heap-ordered (vantage point, radius); None where points can't be parted and all go left."""
    nodes: list = [None] * (2**depth - 1)
    parts = {0: sample}
    for i in range(len(nodes)):
        fps = parts.pop(i, sample[:0])
        got = _vantage(fps) if len(fps) > 1 else None
        if got:
            p, r, d = got
            nodes[i] = (int(p), r)
            parts[2 * i + 1], parts[2 * i + 2] = fps[d <= r], fps[d > r]
        else:
            parts[2 * i + 1] = fps
    return nodes


def route(fps: np.ndarray, nodes: list, depth: int, radius: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, leaf, home): each fingerprint's own leaf, and the leaves to its right that a ball of `radius` around it may reach.

    A pair in two leaves needs to meet once, so points visit from left to right only: a resident
    crosses a boundary rightwards, and a visitor follows both sides that the triangle bound leaves open.
    """
    rows, at, home = np.arange(len(fps)), np.zeros(len(fps), np.int64), np.ones(len(fps), bool)
    for _ in range(depth):
        out = [[], [], []]
        for node in np.unique(at):
            here = at == node
            i, h = rows[here], home[here]
            if nodes[node] is None:
                left, right, right_home = np.ones(len(i), bool), np.zeros(len(i), bool), h
            else:
                p, r = nodes[node]
                d = _distance(fps[i], np.uint64(p))
                left = np.where(h, d <= r, d - radius <= r)
                right, right_home = d + radius > r, h & (d > r)
            for keep, child, own in ((left, 2 * node + 1, h), (right, 2 * node + 2, right_home)):
                out[0].append(i[keep])
                out[1].append(np.full(keep.sum(), child))
                out[2].append(own[keep])
        rows, at, home = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in out)
    return rows, at - (2**depth - 1), home.astype(bool)


# ---- links inside a shard -----------------------------------------------------------------

def _min_labels(n: int, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Smallest index reachable over undirected pairs, by hooking and pointer jumping."""
    lab = np.arange(n)
    while len(a):
        low = np.minimum(lab[a], lab[b])
        new = lab.copy()
        for x in (lab[a], lab[b], a, b):
            np.minimum.at(new, x, low)
        while (new[new] != new).any():
            new = new[new]
        if (new == lab).all():
            break
        lab = new
        open_ = lab[a] != lab[b]
        a, b = a[open_], b[open_]
    return lab


def forest_of_links(fps: np.ndarray, home: np.ndarray, radius: int) -> tuple[np.ndarray, np.ndarray]:
    """A spanning forest (member, root) over all pairs within `radius` of which one is at home here.

    The shard is a vantage-point tree in memory; pairs are folded into a forest as they come, so
    a dense group yields as many rows as it has members.
    """
    a, b, held = [], [], 0

    def fold():
        nonlocal a, b, held
        x, y = (np.concatenate(v) if v else np.zeros(0, np.int64) for v in (a, b))
        lab = _min_labels(len(fps), x, y)
        i = np.flatnonzero(lab != np.arange(len(fps)))
        a, b, held = [i], [lab[i]], 0

    stack = [(np.flatnonzero(home), np.flatnonzero(~home))]
    while stack:
        res, vis = stack.pop()
        if not len(res):
            continue
        got = _vantage(fps[res]) if len(res) > LEAF else None
        if got is None:
            for block in np.array_split(res, max(1, len(res) // 256)):
                for other in (res, vis):
                    for at in range(0, len(other), 1 << 14):
                        o = other[at : at + (1 << 14)]
                        i, j = np.nonzero(np.bitwise_count(fps[block][:, None] ^ fps[o][None, :]) <= radius)
                        keep = block[i] != o[j]
                        a.append(block[i[keep]])
                        b.append(o[j[keep]])
                        held += int(keep.sum())
                        if held > 2_000_000:
                            fold()
            continue
        p, r, d = got
        v = _distance(fps[vis], p)
        stack.append((res[d <= r], vis[v - radius <= r]))
        stack.append((res[d > r], np.concatenate([vis[v + radius > r], res[(d <= r) & (d + radius > r)]])))
    fold()
    return a[0], b[0]


def near_links(points: DataFrame, radius: int = RADIUS, shard_rows: int = SHARD_ROWS) -> DataFrame:
    """(a, b) links that join all points (node long, fp long, distinct) within `radius` bits into their components.

    A routing tree is fitted on a bounded sample (SAMPLE_PER_SHARD a leaf); every point is indexed
    in the leaf it falls into and visits each leaf that its ball overlaps.
    """
    n = points.count()
    depth = 0 if n <= shard_rows else min(MAX_DEPTH, int(np.ceil(np.log2(n / shard_rows))))
    nodes: list = []
    if depth:
        take = min(2**22, SAMPLE_PER_SHARD * 2**depth)
        sample = points.select("fp").orderBy(F.xxhash64("fp"), "fp").limit(take).toArrow().column(0).to_numpy()
        nodes = fit_tree(sample.view(np.uint64), depth)

    def deal(batches):
        for x in batches:
            fps = x.column(1).to_numpy().view(np.uint64)
            rows, leaf, home = route(fps, nodes, depth, radius)
            yield pa.record_batch([pa.array(leaf.astype(np.int32)), x.column(0).take(pa.array(rows)), x.column(1).take(pa.array(rows)), pa.array(home)], names=["shard", "node", "fp", "home"])

    def links(t: pa.Table) -> pa.Table:
        node, fps = t.column("node").to_numpy(), t.column("fp").to_numpy().view(np.uint64)
        i, root = forest_of_links(fps, t.column("home").to_numpy(), radius)
        return pa.table({"a": node[i], "b": node[root]})

    dealt = points.select("node", "fp").mapInArrow(deal, "shard int, node long, fp long, home boolean")
    return dealt.groupBy("shard").applyInArrow(links, "a long, b long")


def near_duplicates(docs: DataFrame, doc_id: str = "doc_id", text: str = "text", shingle: int = SHINGLE, radius: int = RADIUS, similarity: float | None = None) -> DataFrame:
    """(doc_id, fp, component_id) for every row of docs.

    component_id is the smallest doc_id reachable over links of at most `radius` bits. Null and
    blank texts have fingerprint 0 and link like others. Repeated rows each keep their row. A row
    whose doc_id is null takes no part in links: its component_id is null. An empty table gives
    an empty result. Further columns of docs are ignored. With `similarity`, texts whose shingles
    have at least that Jaccard similarity link too: min-hash bands propose them, the texts confirm them.
    """
    fps = settle(with_fingerprint(docs, doc_id, text, shingle, similarity is not None), "fingerprints")
    groups = settle(fps.where("doc_id is not null").groupBy("fp").agg(F.min("doc_id").alias("node")), "groups")
    links = near_links(groups, radius)
    if similarity is None:
        label = connected_components(settle(links, "links"))
    else:
        label = _with_similar(links, fps, groups, docs, similarity, shingle, doc_id, text)
    classes = groups.join(label, "node", "left").select("fp", F.coalesce("component", "node").alias("component_id"))
    return fps.join(classes, "fp", "left").select("doc_id", "fp", F.when(F.col("doc_id").isNotNull(), F.col("component_id")).alias("component_id"))


def _with_similar(links: DataFrame, fps: DataFrame, groups: DataFrame, docs: DataFrame, similarity: float, shingle: int, doc_id: str, text: str) -> DataFrame:
    """(node, component) over the links and the pairs of similar texts; every distinct text is sketched.

    Pairs with the heads of bands join large groups first; then all pairs of a band that still lie apart are tried.
    """
    worded = fps.where("doc_id is not null and size(keys) > 0")
    named = worded.groupBy("tid").agg(F.min_by("fp", "doc_id").alias("fp"), F.min("doc_id").alias("doc"))
    named = named.join(groups, "fp").select("tid", F.col("node").alias("member"), "doc")
    own = worded.select("tid", "doc_id", "keys", "least", "n").join(named, "tid").where("doc_id = doc")  # sketches are dealt once, by text
    held = [F.first(c).alias(c) for c in ("member", "keys", "least", "n")]
    sketches = settle(own.groupBy(F.col("tid").alias("node"), F.col("doc_id").alias("doc")).agg(*held), "sketches")
    shared = similar.shared_bands(sketches)
    give_back(docs.sparkSession)  # here and below: many plans and jobs, few rows for the driver
    docs = docs.where(F.col(text).isNotNull())
    named_by = lambda pairs, kind, of: pairs.join(of.select(F.col("node").alias("a"), F.col(kind).alias("u")), "a").join(of.select(F.col("node").alias("b"), F.col(kind).alias("v")), "b").select(F.col("u").alias("a"), F.col("v").alias("b"))
    first = similar.confirmed(similar.head_cells(similar.to_heads(sketches, shared, similarity), sketches), docs, similarity, shingle, doc_id, text)
    label = settle(connected_components(settle(links.unionByName(named_by(first, "member", sketches)), "links")), "label")
    placed = sketches.join(label.withColumnRenamed("node", "member"), "member", "left").select("node", F.coalesce("component", "member").alias("part"), "keys", "least", "n", "doc")
    placed = settle(placed, "placed")
    give_back(docs.sparkSession)
    more = similar.confirmed(similar.apart(placed, shared, similarity), docs, similarity, shingle, doc_id, text)
    joined = label.select(F.col("node").alias("a"), F.col("component").alias("b")).unionByName(named_by(more, "part", placed))
    joined = settle(joined, "links")
    give_back(docs.sparkSession)
    return connected_components(joined)


def one_of_each(docs: DataFrame, shingle: int = SHINGLE, radius: int = RADIUS, similarity: float | None = None) -> DataFrame:
    """The rows of docs that represent their near-duplicate group; rows without an id all stay.

    Repeated rows of one id count as copies: the one with the least text stays.
    """
    found = settle(near_duplicates(docs, shingle=shingle, radius=radius, similarity=similarity), "members")
    ids = found.where("doc_id is not null").groupBy("doc_id").agg(F.bool_or(F.col("doc_id") == F.col("component_id")).alias("stays"), F.count("*").alias("n"))
    ids = settle(ids, "ids")
    repeated = ids.where("n > 1").limit(1).count() > 0
    lost = ids.where("not stays").select("doc_id")
    if lost.count() <= LOST_ROWS:
        kept = docs.where("doc_id is not null").join(F.broadcast(lost), "doc_id", "left_anti")
    else:
        kept = docs.join(ids.where("stays").select("doc_id"), "doc_id", "left_semi")
    if repeated:
        columns = ["text", *sorted(set(docs.columns) - {"text", "doc_id"})]
        rows = kept.select(F.col("doc_id").alias("_own"), F.struct(*[F.col(f"`{c}`") for c in columns]).alias("_row"))
        order = F.struct("_row.text", F.to_json("_row"))  # any column has a text, maps too
        kept = rows.groupBy("_own").agg(F.min_by("_row", order).alias("_row")).select(*[F.col("_own" if c == "doc_id" else f"_row.`{c}`").alias(c) for c in docs.columns])
    return kept.unionByName(docs.where("doc_id is null"))
