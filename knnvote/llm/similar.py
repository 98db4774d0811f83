"""Links between texts whose word shingles overlap: min-hash candidates, each confirmed on the whole texts.

Pairs of Jaccard similarity 0.8 differ in about ten bits of a 64-bit SimHash, a radius at which no
vantage-point tree prunes. This finds what the fingerprints of `simhash` leave out.

Pairs are never rows of a table: texts travel to cells, a cell holds two sides of bounded size, and a task
compares one side with the other and returns links that join what belongs together.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import settle, small_batches

BANDS, ROWS = 20, 6  # a pair of similarity 0.8 shares a band with probability 0.998
BLOCK_ROWS = 4_000  # sketches of a band in one block
CELL_ROWS = 2_000  # texts on a side of a cell, at most
CELL_SHINGLES = 1_500_000  # and their shingles together, but for a single text of more
SLACK = 0.15  # a pair whose estimated similarity is this much too low isn't compared: four standard errors at 0.8
NEEDED_ROWS = 1 << 21  # texts named by broadcast, two numbers each, some 128 MB; beyond that all texts are dealt by id
HOT = 1_000  # a band that holds more than this fraction of all band rows is joined by broadcast; there are at most so many
_RNG = np.random.default_rng(20)
_MUL = _RNG.integers(1, 2**32, (2, BANDS * ROWS), dtype=np.uint32) | np.uint32(1)


def shingle_hashes(text: bytes | None, shingle: int) -> Iterator[bytes]:
    """XXH64 digests of a text's word shingles, repeats included, in blocks; one of the whole sequence where it is shorter."""
    words = text.lower().split() if text else []
    if words and len(words) <= shingle:
        yield xxhash.xxh64_digest(b" ".join(words), 42)
        return
    digest, n = xxhash.xxh64_digest, len(words) - shingle + 1
    for at in range(0, n, 1 << 16):
        part = words[at : at + (1 << 16) + shingle - 1]
        yield b"".join([digest(b" ".join(t), 42) for t in zip(*(part[i:] for i in range(shingle)), strict=False)])


def minima(hashes: np.ndarray) -> np.ndarray:
    """The least value of some 64-bit hashes under each of BANDS * ROWS mixings."""
    least = np.full(BANDS * ROWS, 2**32 - 1, np.uint32)
    lo, hi = hashes.astype(np.uint32), (hashes >> np.uint64(32)).astype(np.uint32)
    for at in range(0, len(hashes), 1 << 11):
        x = lo[at : at + (1 << 11), None] * _MUL[0] + hi[at : at + (1 << 11), None] * _MUL[1]
        x ^= x >> np.uint32(15)
        x *= np.uint32(0x9E3779B1)
        np.minimum(least, x.min(axis=0), out=least)
    return least


def band_keys(least: np.ndarray) -> list[int]:
    raw, width = least.tobytes(), 4 * ROWS
    return [xxhash.xxh64_intdigest(raw[k * width : (k + 1) * width], k) - 2**63 for k in range(BANDS)]


def shingles(text: str | None, n: int) -> set:
    """The distinct n-word shingles of a whole text; fewer words make one shingle, none make none."""
    words = text.encode().lower().split() if text else []
    return set(zip(*(words[i:] for i in range(n)), strict=False)) if len(words) > n else {tuple(words)} - {()}


def alike(one: set, other: set, similarity: float) -> bool:
    both = len(one & other)
    return both > 0 and both >= similarity * (len(one) + len(other) - both)


def text_id(text: str) -> Column:
    return F.xxhash64(F.col(text).cast("binary"))


# ---- candidates -----------------------------------------------------------------------------

def shared_bands(sketches: DataFrame) -> DataFrame:
    """(key, band, node, first, last): the members of every band of two texts or more, with the band's least and greatest.

    Bands that hold more than one row in HOT, of which there are HOT at most, are joined by broadcast, so no hot band
    lands in one task.
    """
    rows = sketches.select("node", F.posexplode("keys").alias("band", "key"))
    heads = rows.groupBy("key").agg(F.min("node").alias("first"), F.max("node").alias("last"), F.count("*").alias("n")).where("first < last")
    heads = settle(heads, "bands")
    total = BANDS * sketches.count()
    hot = F.broadcast(heads.where(F.col("n") > total / HOT).select("key", "first", "last"))
    cold = rows.join(hot.select("key"), "key", "left_anti").join(heads.select("key", "first", "last"), "key")
    return settle(rows.join(hot, "key").unionByName(cold).select("key", "band", "node", "first", "last"), "shared")


def to_heads(sketches: DataFrame, shared: DataFrame, similarity: float) -> DataFrame:
    """(node, head): for each text the head of a band it shares that agrees best, and the least head that agrees well.

    One or two rows a text, so that large families are joined in linear work; `apart` finds what this leaves out.
    """
    met = shared.select("node", F.explode(F.array("first", "last")).alias("head")).where("node <> head").distinct()
    side = lambda k, c: sketches.select(F.col("node").alias(k), F.col("member").alias(f"of_{k}"), F.col("least").alias(c))
    both = met.join(side("node", "one"), "node").join(side("head", "other"), "head").where("of_node <> of_head").select("node", "head", "one", "other")

    def measure(batches):
        for x in batches:
            a, b = (np.frombuffer(b"".join(x.column(k).to_pylist()), np.uint8).reshape(x.num_rows, -1) for k in ("one", "other"))
            share = (a == b).mean(axis=1)
            yield pa.record_batch([x.column("node"), x.column("head"), pa.array(share)], names=["node", "head", "share"]).filter(pa.array(share >= similarity - SLACK))

    close = both.mapInArrow(measure, "node long, head long, share double")
    best = close.groupBy("node").agg(F.max_by("head", F.struct("share", "head")).alias("best"), F.min(F.when(F.col("share") >= similarity, F.col("head"))).alias("least"))
    return best.select("node", F.explode(F.array_distinct(F.array("best", F.coalesce("least", "best")))).alias("head"))


def head_cells(pairs: DataFrame, sketches: DataFrame) -> DataFrame:
    """Cells of a head and some of its texts: however hot the head, a cell holds about CELL_ROWS at most."""
    pairs = settle(pairs, "pairs")
    spread = max(1, -(-pairs.count() // CELL_ROWS))
    cell = F.xxhash64("head", F.pmod(F.xxhash64("node", F.lit("cell")), F.lit(spread)))
    rows = pairs.select(cell.alias("cell"), "head", "node")
    ends = rows.select("cell", F.lit(0).alias("side"), F.col("head").alias("node")).distinct().unionByName(rows.select("cell", F.lit(1).alias("side"), "node"))
    return ends.withColumn("band", F.lit(0)).join(sketches.select("node", F.col("member").alias("part"), "keys", "least", "doc"), "node")


def apart(placed: DataFrame, shared: DataFrame, similarity: float) -> DataFrame:
    """Cells that hold every pair of texts which share a band, lie in different parts and agree well enough.

    placed: (node, part long, keys, least, n, doc). The members of a band outside its largest part meet all others, in
    blocks of BLOCK_ROWS, two blocks a task; small bands share tasks. Only texts that have a partner there, by their
    sketches, go into a cell, and a pair is looked at in the first band it shares.
    """
    rows = shared.select("key", "band", "node").join(placed.select("node", "part"), "node")
    sizes = rows.groupBy("key", "part").agg(F.count("*").alias("n"))
    bands = sizes.groupBy("key").agg(F.max_by("part", F.struct("n", "part")).alias("main"), F.max("n").alias("most"), F.sum("n").alias("n")).where("most < n")
    blocks = lambda n: F.ceil(n / F.lit(BLOCK_ROWS)).cast("int")
    bands = settle(bands.select("key", "main", blocks(F.col("n") - F.col("most")).alias("others"), blocks(F.col("most")).alias("mains"), "n"), "open")
    tasks = max(1, (bands.agg(F.sum("n")).first()[0] or 0) // BLOCK_ROWS)
    salt = F.xxhash64("node", F.lit("block"))
    own = F.when(F.col("part") == F.col("main"), F.col("others") + F.pmod(salt, F.col("mains"))).otherwise(F.pmod(salt, F.col("others"))).cast("int")
    dealt = rows.join(bands, "key").withColumn("own", own)
    meets = F.explode(F.sequence(F.lit(0), F.when(F.col("own") < F.col("others"), F.col("others") + F.col("mains")).otherwise(F.col("others")) - 1))
    dealt = dealt.withColumn("other", meets).withColumn("i", F.least("own", "other")).withColumn("j", F.greatest("own", "other"))
    task = F.when(F.col("others") + F.col("mains") == 2, F.pmod(F.xxhash64("key"), F.lit(tasks))).otherwise(F.xxhash64("key", "i", "j"))
    side = F.when(F.col("i") == F.col("j"), 2).when(F.col("own") == F.col("i"), 0).otherwise(1)
    dealt = dealt.select(task.alias("task"), F.xxhash64("key", "i", "j").alias("cell"), side.alias("side"), "band", "node")
    dealt = dealt.join(placed, "node").select("task", "cell", "side", "band", "node", "part", "keys", "least", "n", "doc")
    return dealt.groupBy("task").applyInArrow(_partners(similarity - SLACK), _CELL)


_CELL = "cell long, side int, band int, node long, part long, keys array<bigint>, least binary, doc long"


def agreement(one: np.ndarray, other: np.ndarray) -> np.ndarray:
    """Equal places of all rows of two matrices of bytes."""
    if len(one) * len(other) < 1 << 10:
        return (one[:, None] == other[None]).sum(axis=2)
    out, other = np.zeros((len(one), len(other)), np.uint8), np.ascontiguousarray(other.T)
    for k in range(one.shape[1]):
        out += one[:, k, None] == other[k]
    return out


class _Rows:
    """The columns of a group of cells, and the pairs of one cell that are worth a comparison."""

    def __init__(self, t: pa.Table, share: float):
        self.side, self.node, self.part, self.band = (t.column(c).to_numpy() for c in ("side", "node", "part", "band"))
        self.sketch = np.frombuffer(b"".join(t.column("least").to_pylist()), np.uint8).reshape(len(t), -1)
        self.keys = t.column("keys").combine_chunks().flatten().to_numpy().reshape(len(t), -1)
        cell = t.column("cell").to_numpy()
        ends = np.flatnonzero(np.diff(cell)) + 1
        self.cells = list(zip([0, *ends], [*ends, len(t)], strict=True)) if len(t) else []
        self.least = share * BANDS * ROWS

    def pairs(self, lo: int, hi: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """(rows of one side, rows of the other) of the pairs of a cell in different parts that agree, each in the first band it shares."""
        at = np.arange(lo, hi)
        one, other = at[self.side[lo:hi] != 1], at[self.side[lo:hi] != 0]
        band = self.band[lo]
        for x in np.array_split(one, len(one) // 256 + 1):
            m, n = np.nonzero((agreement(self.sketch[x], self.sketch[other]) >= self.least) & (self.part[x][:, None] != self.part[other]))
            a, b = x[m], other[n]
            keep = (self.side[a] != 2) | (self.node[a] < self.node[b])  # a block with itself has each pair twice
            a, b = a[keep], b[keep]
            if band:
                earlier = (self.keys[a, :band] == self.keys[b, :band]).any(axis=1)
                a, b = a[~earlier], b[~earlier]
            yield a, b


_ORDER = [("cell", "ascending"), ("side", "ascending"), ("node", "ascending")]


def _partners(share: float):
    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by(_ORDER)
        rows, n, cell = _Rows(t, share), t.column("n").to_numpy(), t.column("cell").to_numpy()
        at, cells, sides = [], [], []
        for lo, hi in rows.cells:
            chunk = np.zeros(hi - lo, np.int64)  # sides are cut where texts or shingles are too many
            for s in (0, 1, 2):
                mine = np.flatnonzero(rows.side[lo:hi] == s)
                weight = np.cumsum(np.maximum(n[lo:hi][mine] / CELL_SHINGLES, 1 / CELL_ROWS))
                chunk[mine] = weight.astype(np.int64)
            found = [p for p in rows.pairs(lo, hi) if len(p[0])]
            if not found:
                continue
            a, b = (np.concatenate(v) for v in zip(*found, strict=True))
            ca, cb = chunk[a - lo], chunk[b - lo]
            if rows.side[lo] == 2:  # chunks of one block meet once: the lesser is the first side
                swap = ca > cb
                a, b, ca, cb = np.where(swap, b, a), np.where(swap, a, b), np.where(swap, cb, ca), np.where(swap, ca, cb)
            code = ca * (chunk.max() + 1) + cb
            for c in np.unique(code):
                here = code == c
                name = xxhash.xxh64_intdigest(f"{cell[lo]} {c}".encode()) - 2**63
                whole = rows.side[lo] == 2 and ca[here][0] == cb[here][0]
                for s, who in ((2, np.union1d(a[here], b[here])),) if whole else ((0, np.unique(a[here])), (1, np.unique(b[here]))):
                    at.append(who)
                    cells.append(np.full(len(who), name))
                    sides.append(np.full(len(who), s))
        at, cells, sides = (np.concatenate(v).astype(np.int64) if v else np.zeros(0, np.int64) for v in (at, cells, sides))
        out = t.select(["band", "node", "part", "keys", "least", "doc"]).take(pa.array(at))
        return out.append_column("cell", pa.array(cells)).append_column("side", pa.array(sides.astype(np.int32))).select(["cell", "side", "band", "node", "part", "keys", "least", "doc"])

    return run


# ---- confirmation ---------------------------------------------------------------------------

def _texts(cells: DataFrame, docs: DataFrame, doc_id: str, text: str) -> DataFrame:
    """(node, t): the texts that stand in cells, each once; a node is the text's XXH64, doc the least id that has it."""
    needed = settle(cells.select("node", F.col("doc").alias("own_id")).distinct(), "needed")
    if needed.count() <= NEEDED_ROWS:
        needed = F.broadcast(needed)  # so that no other text is shuffled
    held = docs.select(F.col(doc_id).cast("long").alias("own_id"), text_id(text).alias("node"), F.col(text).cast("binary").alias("t"))
    return held.join(needed, ["own_id", "node"], "left_semi").groupBy("node").agg(F.first("t").alias("t"))


def confirmed(cells: DataFrame, docs: DataFrame, similarity: float, shingle: int, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(a, b): links that join the texts of every cell as all its pairs of at least this Jaccard similarity would.

    Shingles are held against each other as 64-bit hashes. Pairs that earlier links of the cell have joined are skipped.
    """
    small_batches(docs.sparkSession)
    cells = settle(cells, "cells")
    tasks = max(1, cells.count() // CELL_ROWS)
    rows = cells.join(settle(_texts(cells, docs, doc_id, text), "texts"), "node")
    rows = rows.select(F.pmod(F.xxhash64("cell", F.lit("task")), F.lit(tasks)).alias("task"), "cell", "side", "band", "node", "part", "keys", "least", "t")

    def run(t: pa.Table) -> pa.Table:
        t = t.sort_by(_ORDER)
        rows, texts, out = _Rows(t, similarity - SLACK), t.column("t"), ([], [])
        for lo, hi in rows.cells:
            held: dict[int, np.ndarray] = {}

            def of(i):
                if i not in held:
                    held[i] = np.unique(np.frombuffer(b"".join(shingle_hashes(texts[i].as_py(), shingle)), "<u8"))
                return held[i]

            label = rows.part[lo:hi].copy()
            for a, b in rows.pairs(lo, hi):
                for i, j in _links(a, b, lo, label, of, similarity):
                    out[0].append(rows.node[i])
                    out[1].append(rows.node[j])
        return pa.table({"a": pa.array(out[0], pa.int64()), "b": pa.array(out[1], pa.int64())})

    return rows.groupBy("task").applyInArrow(run, "a long, b long")


def _links(a: np.ndarray, b: np.ndarray, lo: int, label: np.ndarray, of, similarity: float) -> Iterator[tuple[int, int]]:
    """The pairs (sorted by a) that join labels anew; label, by row from lo on, is kept up to date."""
    many, place = len(a) > 64, None
    if many:  # shingles by number, so that one text meets many by a look-up
        used = np.unique(np.concatenate([a, b]))
        sets = [of(int(i)) for i in used]
        sizes = np.array([len(s) for s in sets])
        names, ids = np.unique(np.concatenate(sets), return_inverse=True)
        begin = np.concatenate([[0], np.cumsum(sizes)])
        place, mark = {int(i): k for k, i in enumerate(used)}, np.zeros(len(names), bool)
    starts = np.flatnonzero(np.concatenate([[True], a[1:] != a[:-1]])) if len(a) else []
    for s, e in zip(starts, [*starts[1:], len(a)], strict=True):
        i, mates = int(a[s]), b[s:e]
        mates = mates[label[mates - lo] != label[i - lo]]
        if not len(mates):
            continue
        if many:
            x = ids[begin[place[i]] : begin[place[i] + 1]]
            mark[x] = True
            at = np.array([place[int(j)] for j in mates])
            n = sizes[at]
            first = np.concatenate([[0], np.cumsum(n)[:-1]])
            flat = ids[np.repeat(begin[at] - first, n) + np.arange(n.sum())]
            both = np.add.reduceat(mark[flat].astype(np.int64), first)
            mark[x] = False
            own = len(x)
        else:
            x = of(i)
            n = np.array([len(of(int(j))) for j in mates])
            both = np.array([len(np.intersect1d(x, of(int(j)), assume_unique=True)) for j in mates])
            own = len(x)
        for j in mates[(both > 0) & (both >= similarity * (own + n - both))]:
            if label[j - lo] != label[i - lo]:
                label[label == label[j - lo]] = label[i - lo]
                yield i, int(j)
