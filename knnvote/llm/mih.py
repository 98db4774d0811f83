"""Exact top-k search over binary codes by multi-index hashing with growing radii."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from .common import settle

BITS, SEGMENTS = 64, 4
CELL_CODES = 500_000  # distinct codes that one task indexes
CELL_QUERIES = 20_000  # queries that one task answers
K = 10


def with_code(points: DataFrame, point_id: str = "vec_id", vec: str = "embedding") -> DataFrame:
    """(id, code): bit i of the code is 1 if component i is above 0.

    Missing components, nulls and NaN give 0; components from the 64th on are ignored. Rows whose vector
    or id is null have no code and are left out.
    """
    def run(batches):
        for b in batches:
            codes = np.zeros(b.num_rows, np.uint64)
            lists = b.column(1)
            values = lists.flatten().fill_null(0).to_numpy(zero_copy_only=False)
            bits = values > 0
            at = np.cumsum(np.concatenate([[0], lists.value_lengths().to_numpy()]))
            for i in range(BITS):
                has = at[:-1] + i < at[1:]
                codes[has] |= bits[at[:-1][has] + i].astype(np.uint64) << np.uint64(i)
            yield pa.record_batch([b.column(0), pa.array(codes.view(np.int64))], names=["id", "code"])

    rows = points.where(F.col(point_id).isNotNull() & F.col(vec).isNotNull())
    return rows.select(F.col(point_id).cast("long").alias("id"), F.col(vec).cast("array<float>").alias("v")).mapInArrow(run, "id long, code long")


def _masks(width: int, radius: int) -> np.ndarray:
    return np.array([sum(1 << b for b in c) for c in combinations(range(width), radius)], np.int64)


class MultiIndex:
    """Tables of codes by the value of each segment; radii of all segments grow together, one bit at a time."""

    def __init__(self, codes: np.ndarray, segments: int = SEGMENTS):
        self.codes, self.segments, self.width = codes, segments, BITS // segments
        self.order, self.first = [], []
        for s in range(segments):
            key = self._key(codes, s)
            order = np.argsort(key, kind="stable")
            self.order.append(order)
            self.first.append(np.searchsorted(key[order], np.arange((1 << self.width) + 1)))
        self.masks = [_masks(self.width, r) for r in range(self.width + 1)]

    def _key(self, codes, s: int):
        return ((codes >> np.uint64(s * self.width)) & np.uint64((1 << self.width) - 1)).astype(np.int64)

    def within_reach(self, query: np.uint64, wanted) -> tuple[np.ndarray, np.ndarray]:
        """(index, distance) of codes, verified, that hold all up to the distance that `wanted` asks for.

        After radius r in every segment, each code within segments * (r + 1) - 1 bits has been met: one that
        differs by more than r bits in every segment differs by segments * (r + 1) in all. The search ends
        when wanted(distances) - the k-th verified distance, or none - is covered.
        """
        seen = np.zeros(len(self.codes), bool)
        index, dist = np.zeros(0, np.int64), np.zeros(0, np.int64)
        for r in range(self.width + 1):
            new = []
            for s in range(self.segments):
                keys = int(self._key(query, s)) ^ self.masks[r]
                a, n = self.first[s][keys], self.first[s][keys + 1] - self.first[s][keys]
                if n.sum():
                    at = np.repeat(a - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())
                    new.append(self.order[s][at])
            if new:
                got = np.unique(np.concatenate(new))
                got = got[~seen[got]]
                seen[got] = True
                index = np.concatenate([index, got])
                dist = np.concatenate([dist, np.bitwise_count(self.codes[got] ^ query).astype(np.int64)])
            kth = wanted(index, dist)
            if len(index) == len(self.codes) or (kth is not None and kth <= self.segments * (r + 1) - 1):
                break
        return index, dist


def search_cell(ids: np.ndarray, codes: np.ndarray, qid: np.ndarray, qcode: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(qid, id, distance): the k nearest of (ids, codes) for each query, ties by the smaller id."""
    codes = codes.view(np.uint64)
    distinct, where = np.unique(codes, return_inverse=True)
    by = np.lexsort((ids, where))
    start = np.searchsorted(where[by], np.arange(len(distinct) + 1))
    held = np.diff(start)
    index = MultiIndex(distinct)
    out = [[], [], []]

    def kth(i, d):
        order = np.argsort(d, kind="stable")
        upto = np.cumsum(held[i[order]])
        at = np.searchsorted(upto, k)
        return int(d[order[at]]) if at < len(order) else None

    for q, c in zip(qid, qcode.view(np.uint64), strict=True):
        i, d = index.within_reach(c, kth)
        last = kth(i, d)
        if last is not None:
            i, d = i[d <= last], d[d <= last]
        n = np.minimum(held[i], k)
        rows = by[np.repeat(start[i] - np.concatenate([[0], np.cumsum(n)[:-1]]), n) + np.arange(n.sum())]
        dd = np.repeat(d, n)
        best = np.lexsort((ids[rows], dd))[:k]
        out[0].append(np.full(len(best), q))
        out[1].append(ids[rows][best])
        out[2].append(dd[best])
    return tuple(np.concatenate(x) if x else np.zeros(0, np.int64) for x in out)


def nearest(points: DataFrame, queries: DataFrame, k: int = K) -> DataFrame:
    """(qid, rank, id, distance): the k codes of least Hamming distance to each query's, ties by the smaller id.

    points (id, code), queries (qid, qcode). Codes are dealt into cells of CELL_CODES and queries into blocks of
    CELL_QUERIES; every cell indexes its codes and answers each block exactly, and the answers meet by
    query. Copies of a code beyond its k smallest ids can't be in an answer and stay out of the cells. With
    fewer than k points an answer has them all. Repeated rows count once each.
    """
    alike = W.partitionBy("code").orderBy("id")
    kept = settle(points.withColumn("_nth", F.row_number().over(alike)).where(F.col("_nth") <= k).select("id", "code"), "codes")
    asked = settle(queries, "queries")
    cells = max(1, -(-kept.count() // CELL_CODES))
    blocks = max(1, -(-asked.count() // CELL_QUERIES))
    spread = max(cells, min(12, -(-kept.count() // 2_000)))  # small tables too use several tasks
    left = kept.select((F.pmod(F.xxhash64("code"), F.lit(spread))).cast("int").alias("cell"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))).alias("block"), "id", "code")
    right = asked.select(F.explode(F.sequence(F.lit(0), F.lit(spread - 1))).alias("cell"), (F.pmod(F.xxhash64("qid"), F.lit(blocks))).cast("int").alias("block"), "qid", "qcode")

    def answer(_, a: pa.Table, b: pa.Table) -> pa.Table:
        col = lambda t, c: t.column(c).to_numpy()
        q, i, d = search_cell(col(a, "id"), col(a, "code"), col(b, "qid"), col(b, "qcode"), k) if len(a) and len(b) else (np.zeros(0, np.int64),) * 3
        return pa.table({"qid": pa.array(q, pa.int64()), "id": pa.array(i, pa.int64()), "distance": pa.array(d.astype(np.int32))})

    # a stated number of partitions stays: adaptive execution would join the cells of small tables into one task
    apart = lambda df: df.repartition(2 * spread * blocks, "cell", "block").groupBy("cell", "block")
    found = apart(left).cogroup(apart(right)).applyInArrow(answer, "qid long, id long, distance int")
    best = W.partitionBy("qid").orderBy("distance", "id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("qid", "rank", "id", "distance")
