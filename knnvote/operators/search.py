"""The query side: routing, vote counting, exact ranking, and the searches made of them."""

from __future__ import annotations

from itertools import combinations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.vectors import METRICS
from .forest import Forest, materialised
from .projection import block, project

BROADCAST_ROWS = 200_000  # rows of queries or routes that may be sent to every executor
BLOCK_QUERIES = 2_000  # queries that one pass over the points answers


# ---- exact ---------------------------------------------------------------------------------

def ranked(pairs: DataFrame, k: int | Column) -> DataFrame:
    """(qid, rank, id, distance, ..) of the k nearest of each query, ties by the smaller id."""
    nth = F.row_number().over(W.partitionBy("qid").orderBy("distance", "id"))
    return pairs.withColumn("rank", nth).where(F.col("rank") <= k)


def query_blocks(queries: DataFrame, size: int = BLOCK_QUERIES):
    """The queries (qid, qvec) in the driver, a bounded block at a time."""
    ids, vecs = [], []
    for r in queries.select("qid", "qvec").orderBy("qid").toLocalIterator():
        ids.append(r["qid"])
        vecs.append(r["qvec"])
        if len(ids) == size:
            yield np.array(ids, np.int64), np.array(vecs, float)
            ids, vecs = [], []
    if ids:
        yield np.array(ids, np.int64), np.array(vecs, float)


_PAIRS = "qid long, id long, distance double"


def brute_force_knn(points: DataFrame, queries: DataFrame, k: int, engine: str = "native", metric: str = "l2", exclude_self: bool = False) -> DataFrame:
    """neighbors (qid, rank, id, distance) by a scan of all points.

    native: every pair's distance as an expression, over a broadcast of the queries, whose number is checked.
    arrow: blocks of points against blocks of queries as matrix products; each task keeps its k best a query, so
    what is shuffled doesn't grow with the points of a task.
    """
    if engine == "arrow" and metric == "l2":
        found = None
        for qid, q in query_blocks(queries):
            part = points.select("id", "vec").mapInArrow(_nearest_of_task(qid, q, k, exclude_self), _PAIRS)
            found = part if found is None else found.unionByName(part)
        if found is None:
            found = points.sparkSession.createDataFrame([], _PAIRS)
    else:
        small = queries.count() <= BROADCAST_ROWS
        pairs = points.crossJoin(F.broadcast(queries) if small else queries)
        if exclude_self:
            pairs = pairs.where("id <> qid")
        found = pairs.select("qid", "id", F.round(METRICS[metric]("vec", "qvec"), 6).alias("distance"))
    return ranked(found, k).select("qid", "rank", "id", "distance")


class Nearest:
    """The k nearest of each query among all points offered so far, ties by the smaller id; a task keeps one over its batches.

    A matrix product ranks roughly; what lies within reach of the k-th found so far is measured exactly, with room for
    the product's rounding and that of distances.
    """

    def __init__(self, qid: np.ndarray, q: np.ndarray, k: int, exclude_self: bool = False):
        self.qid, self.q, self.k, self.exclude_self = qid, q, k, exclude_self
        self.squares = (q * q).sum(1)
        self.dist, self.ids, self.votes = np.full((len(qid), k), np.inf), np.zeros((len(qid), k), np.int64), np.zeros((len(qid), k), np.int32)

    def rough(self, x: np.ndarray) -> np.ndarray:
        """Squared distances of all queries from the rows of x, not below 0."""
        near = self.q @ x.T
        near *= -2
        near += self.squares[:, None]
        near += (x * x).sum(1)
        return np.maximum(near, 0, out=near)

    def steps(self, n: int):
        """Slices of n points: a few first, which bound the reach, then as many as 32 MB of doubles hold."""
        most, at = max(64, (1 << 22) // max(1, len(self.qid), self.q.shape[1])), 0
        size = most if np.isfinite(self.dist[:, -1]).all() else min(most, max(4 * self.k, 256))
        while at < n:
            yield at, min(n, at + size)
            at, size = at + size, most

    def offer(self, ids: np.ndarray, x: np.ndarray, near: np.ndarray, shared=None, least: int = 0) -> None:
        """Points with their rough distances. shared(rows, columns): the votes of pairs; those of fewer than `least` don't count."""
        slack = 1e-9 * (1 + self.squares.max(initial=0) + (x * x).sum(1).max(initial=0))
        rows, cols = np.nonzero(near <= ((self.dist[:, -1] + 2e-6) ** 2 + slack)[:, None])
        votes = None
        if shared is not None:
            votes = shared(rows, cols)
            rows, cols, votes = (c[votes >= least] for c in (rows, cols, votes))
        if self.exclude_self:
            other = ids[cols] != self.qid[rows]
            rows, cols, votes = rows[other], cols[other], None if votes is None else votes[other]
        if not len(rows):
            return
        # of these, none beyond the k-th nearest of their own
        far = near[rows, cols]
        order = np.lexsort((far, rows))
        rows, cols, far = rows[order], cols[order], far[order]
        ends = np.searchsorted(rows, np.arange(len(self.qid) + 1))
        many = np.flatnonzero(np.diff(ends) >= self.k)
        cut = np.full(len(self.qid), np.inf)
        cut[many] = (np.sqrt(far[ends[many] + self.k - 1]) + 2e-6) ** 2 + 2 * slack
        keep = far <= cut[rows]
        votes = np.ones(keep.sum(), np.int32) if votes is None else votes[order][keep]
        rows, cols = rows[keep], cols[keep]
        some = max(1, (1 << 20) // x.shape[1])
        dist = [np.round(np.sqrt(((x[cols[i : i + some]] - self.q[rows[i : i + some]]) ** 2).sum(1)), 6) for i in range(0, len(rows), some)]
        self.merge(rows, np.concatenate(dist), ids[cols], votes)

    def merge(self, rows: np.ndarray, dist: np.ndarray, ids: np.ndarray, votes: np.ndarray) -> None:
        met = np.unique(rows)
        old = np.isfinite(self.dist[met])
        rows = np.concatenate([np.repeat(met, old.sum(1)), rows])
        dist, ids, votes = (np.concatenate([have[met][old], new]) for have, new in ((self.dist, dist), (self.ids, ids), (self.votes, votes)))
        order = np.lexsort((ids, dist, rows))
        nth = np.arange(len(rows)) - np.searchsorted(rows[order], rows[order])
        order, nth = order[nth < self.k], nth[nth < self.k]
        self.dist[met] = np.inf
        for have, new in ((self.dist, dist), (self.ids, ids), (self.votes, votes)):
            have[rows[order], nth] = new[order]

    def rows(self, *more: str) -> pa.RecordBatch:
        """(qid, id, distance, ..), at most k a query."""
        q, nth = np.nonzero(np.isfinite(self.dist))
        columns = {"qid": self.qid[q], "id": self.ids[q, nth], "distance": self.dist[q, nth], "votes": self.votes[q, nth]}
        names = ["qid", "id", "distance", *more]
        return pa.record_batch([pa.array(columns[c]) for c in names], names=names)


def _nearest_of_task(qid: np.ndarray, q: np.ndarray, k: int, exclude_self: bool):
    def run(batches):
        best = Nearest(qid, q, k, exclude_self)
        for b in batches:
            ids, whole = b.column(0).to_numpy(), block(b.column(1), q.shape[1])
            for i, j in best.steps(len(ids)):
                best.offer(ids[i:j], whole[i:j], best.rough(whole[i:j]))
        yield best.rows()

    return run


def within_radius(points: DataFrame, queries: DataFrame, radius: float, metric: str = "l2") -> DataFrame:
    """(qid, id, distance) of all points at most `radius` away."""
    pairs = points.crossJoin(F.broadcast(queries) if queries.count() <= BROADCAST_ROWS else queries)
    return pairs.select("qid", "id", F.round(METRICS[metric]("vec", "qvec"), 6).alias("distance")).where(F.col("distance") <= radius)


def rank_candidates(candidates: DataFrame, points: DataFrame, queries: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """neighbors (qid, rank, id, distance, votes): the k nearest among the candidates (qid, id, votes)."""
    small = queries.count() <= BROADCAST_ROWS
    with_vec = candidates.join(points.select("id", "vec"), "id").join(F.broadcast(queries) if small else queries, "qid")
    return ranked(with_vec.select("qid", "id", "votes", F.round(METRICS[metric]("vec", "qvec"), 6).alias("distance")), k).select("qid", "rank", "id", "distance", "votes")


# ---- routing and votes ------------------------------------------------------------------------

def route(queries: DataFrame, forest: Forest) -> DataFrame:
    """(qid, tree, leaf): the leaf of every query in every tree."""
    coded = forest.coded(queries.select("qid", F.col("qvec").alias("vec")))
    return coded.select("qid", F.posexplode("codes").alias("tree", "leaf"))


def route_with_neighbours(queries: DataFrame, forest: Forest, extra: int) -> DataFrame:
    """(qid, tree, leaf, margin): the own leaf and, of the leaves one wrong turn away, the `extra` of least margin in each tree.

    The margin of a turn at a level is the distance of the projection from the split there; the path below the
    turn follows the splits.
    """
    p, depth = forest.params, forest.params.depth
    rows = project(queries.select("qid", F.col("qvec").alias("vec")), forest.pack, p, forest.d)
    splits = forest.split_literal()

    def path(t: Column, turn: int) -> Column:
        step = lambda s, j: F.struct((s["node"] * 2 + F.when(F.lit(turn) == j, 1 - side(t, s["node"], j)).otherwise(side(t, s["node"], j))).alias("node"), F.when(F.lit(turn) == j, gap(t, s["node"], j)).otherwise(s["margin"]).alias("margin"))
        return F.aggregate(F.sequence(F.lit(0), F.lit(depth - 1)), F.struct(F.lit(0).alias("node"), F.lit(0.0).alias("margin")), step)

    def cut(t, node, j):
        return F.get(F.get(splits, t), F.call_function("shiftleft", F.lit(1), j) - 1 + node)

    def side(t, node, j):
        return (F.get("proj", t * depth + j) > cut(t, node, j)).cast("int")

    def gap(t, node, j):
        return F.abs(F.get("proj", t * depth + j) - cut(t, node, j))

    rows = rows.withColumn("tree", F.explode(F.sequence(F.lit(0), F.lit(p.trees - 1)))).select("qid", "proj", "tree")
    paths = F.array(*[path(F.col("tree"), turn) for turn in range(-1, depth)])
    out = rows.select("qid", "tree", F.posexplode(paths).alias("turn", "s")).select("qid", "tree", F.col("s.node").alias("leaf"), F.round("s.margin", 9).alias("margin"))
    nth = F.row_number().over(W.partitionBy("qid", "tree").orderBy("margin", "leaf"))
    return out.withColumn("nth", nth).where(F.col("nth") <= extra + 1).drop("nth")


def priority_knn(queries: DataFrame, forest: Forest, k: int, votes: int, extra: int) -> DataFrame:
    """neighbors (qid, rank, id, distance, votes) from the own leaf and the `extra` nearest ones of each tree."""
    routes = route_with_neighbours(queries, forest, extra).select("qid", "tree", "leaf").distinct()
    return rank_candidates(count_votes(routes, forest.postings()).where(F.col("votes") >= votes), forest.points, queries, k)


def count_votes(routes: DataFrame, cells: DataFrame, part: str = "tree", cell: str = "leaf") -> DataFrame:
    """(qid, id, votes): in how many partitions a point shares a cell with the query.

    routes (qid, part, cell) and cells (part, cell, id) may come from any family of partitions.
    """
    small = routes.count() <= BROADCAST_ROWS
    return cells.join(F.broadcast(routes) if small else routes, [part, cell]).groupBy("qid", "id").agg(F.count("*").cast("int").alias("votes"))


def candidates(queries: DataFrame, forest: Forest, votes: int, strategy: str = "probe") -> DataFrame:
    """(qid, id, votes) of the points with at least `votes` votes.

    probe: routes meet the postings by (tree, leaf). scan: the codes of every point are held against those of all
    queries in Arrow blocks; nothing is shuffled.
    """
    if strategy == "probe":
        return count_votes(route(queries, forest), forest.postings()).where(F.col("votes") >= votes)
    found = None
    for qid, codes in _coded_blocks(queries, forest):
        part = forest.codes.select("id", "codes").mapInArrow(_votes_of_batch(qid, codes, votes), "qid long, id long, votes int")
        found = part if found is None else found.unionByName(part)
    return found if found is not None else forest.points.sparkSession.createDataFrame([], "qid long, id long, votes int")


def _coded_blocks(queries: DataFrame, forest: Forest):
    coded = forest.coded(queries.select("qid", F.col("qvec").alias("vec"))).select("qid", F.col("codes").alias("qvec"))
    for qid, codes in query_blocks(coded):
        yield qid, codes.astype(np.int32)


def _shared(codes: np.ndarray, q: np.ndarray) -> np.ndarray:
    votes = np.zeros(len(codes), np.int16)
    for t in range(codes.shape[1]):
        votes += codes[:, t] == q[t]
    return votes


def _votes_of_batch(qid: np.ndarray, q: np.ndarray, votes: int):
    def run(batches):
        for b in batches:
            codes = np.asfortranarray(b.column(1).flatten().to_numpy().reshape(-1, q.shape[1]))
            out = [[], [], []]
            for i in range(len(qid)):
                f = _shared(codes, q[i])
                keep = np.flatnonzero(f >= votes)
                out[0].append(np.full(len(keep), qid[i]))
                out[1].append(b.column(0).to_numpy()[keep])
                out[2].append(f[keep].astype(np.int32))
            yield pa.record_batch([pa.array(np.concatenate(c)) for c in out], names=["qid", "id", "votes"])

    return run


def choose_strategy(forest: Forest, queries: int) -> str:
    """scan where leaves of all trees together hold much of the points, or the points are few; else probe."""
    p = forest.params
    return "scan" if queries * p.trees * forest.n / 2**p.depth > 0.1 * queries * forest.n or forest.n <= 100_000 else "probe"


def approximate_knn(queries: DataFrame, forest: Forest, k: int, votes: int, strategy: str = "probe", shortfall: str = "return_fewer", where: Column | None = None) -> DataFrame:
    """neighbors (qid, rank, id, distance, votes): the exact k nearest among points with at least `votes` votes.

    strategy: probe, scan, fused (votes, distance and the best k of each batch in one pass over points and codes) or
    auto. shortfall: return_fewer; lower_votes (queries with fewer than k answers take the points of one
    vote or more); brute (they are answered exactly). where: a condition on the points.
    """
    points = forest.points if where is None else forest.points.where(where)
    if strategy == "auto":
        strategy = "fused" if choose_strategy(forest, queries.count()) == "scan" else "probe"
    if strategy == "fused":
        found = _fused(queries, forest, points, k, votes)
    else:
        found = rank_candidates(candidates(queries, forest, votes, strategy), points, queries, k)
    if shortfall == "return_fewer":
        return found
    found = materialised(found, "found")
    full = found.groupBy("qid").count().where(F.col("count") >= k)
    rest = queries.join(full, "qid", "left_anti")
    if shortfall == "lower_votes":
        more = rank_candidates(candidates(rest, forest, 1, "probe"), points, rest, k)
    else:
        more = brute_force_knn(points, rest, k).withColumn("votes", F.lit(None).cast("int"))
    return found.join(full, "qid", "left_semi").unionByName(more)


def _fused(queries: DataFrame, forest: Forest, points: DataFrame, k: int, votes: int) -> DataFrame:
    router = forest.router()
    held = points.select("id", "vec") if router else points.join(forest.codes, "id").select("id", "vec", "codes")
    found = None
    vectors = {int(i): v for ids, vs in query_blocks(queries) for i, v in zip(ids, vs, strict=True)} if queries.count() <= BROADCAST_ROWS else None
    if vectors is None:
        return rank_candidates(candidates(queries, forest, votes, "scan"), points, queries, k)
    for qid, codes in _coded_blocks(queries, forest):
        q = np.array([vectors[int(i)] for i in qid])
        part = held.mapInArrow(_fused_task(qid, q, codes, k, votes, router), "qid long, id long, distance double, votes int")
        found = part if found is None else found.unionByName(part)
    if found is None:
        found = points.sparkSession.createDataFrame([], "qid long, id long, distance double, votes int")
    return ranked(found, k).select("qid", "rank", "id", "distance", "votes")


def _votes_between(q: np.ndarray, own: np.ndarray):
    """The function of pairs (rows of q, rows of own) to the number of equal codes: all pairs at once where most are asked for."""
    def shared(rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
        if 5 * len(rows) > len(q) * len(own):
            votes = np.zeros((len(q), len(own)), np.int32)
            for t in range(q.shape[1]):
                votes += q[:, t, None] == own[None, :, t]
            return votes[rows, cols]
        votes = np.zeros(len(rows), np.int32)
        for t in range(q.shape[1]):
            votes += q[rows, t] == own[cols, t]
        return votes

    return shared


def _fused_task(qid: np.ndarray, q: np.ndarray, codes: np.ndarray, k: int, votes: int, router):
    """router: leaf codes from vectors; without it, batches bring theirs."""
    def run(batches):
        best = Nearest(qid, q, k)
        for b in batches:
            ids, whole = b.column(0).to_numpy(), block(b.column(1), q.shape[1])
            held = None if router else b.column(2).flatten().to_numpy().reshape(-1, codes.shape[1])
            for i, j in best.steps(len(ids)):
                x = whole[i:j]
                own = router(x) if router else held[i:j]
                best.offer(ids[i:j], x, best.rough(x), _votes_between(codes, np.asfortranarray(own)), votes)
        yield best.rows("votes")

    return run


CELL_ROWS = 4_000  # points of a cell that one task holds against one another; larger cells are dealt out in pairs of parts
COMBINATIONS = 16  # sets of trees by which a join makes its cells, at most


def _tree_sets(trees: int, votes: int) -> list[tuple[int, ...]]:
    """Sets of trees such that two points with `votes` shared leaves share all leaves of a set: of those that share `votes` of
    the trees, each pair shares j of the first trees - votes + j. The largest j with few sets, which makes the least cells."""
    sets = [list(combinations(range(trees - votes + j), j)) for j in range(1, votes + 1)]
    return max((s for s in sets if len(s) <= COMBINATIONS), key=lambda s: len(s[0]), default=sets[0])


def knn_join(forest: Forest, k: int, votes: int) -> DataFrame:
    """Every point's k nearest others among points that share at least `votes` leaves with it.

    Points meet in cells, the leaves of a set of trees; a pair is looked at in the first set that it shares, and each cell
    keeps the k best of a point, so pairs are never rows.
    """
    votes, trees = max(1, votes), forest.params.trees
    if votes > trees:
        return forest.points.sparkSession.createDataFrame([], "qid long, rank int, id long, distance double, votes int")
    sets = _tree_sets(trees, votes)
    key = F.array(*[F.struct(F.lit(n).alias("nth"), F.array(*[F.get("codes", F.lit(t)) for t in s]).alias("leaves")) for n, s in enumerate(sets)])
    coded = forest.points.select("id", "vec").join(forest.codes, "id")
    rows = coded.select(F.explode(key).alias("cell"), "id", "vec", "codes")
    parts = F.ceil(F.col("n") / CELL_ROWS).cast("int")
    large = forest.codes.select(F.explode(key).alias("cell")).groupBy("cell").agg(F.count("*").alias("n")).where(F.col("n") > CELL_ROWS).select("cell", parts.alias("parts"))
    own = F.pmod(F.xxhash64("id"), F.col("parts")).cast("int")
    role = lambda a, b, asks, answers: F.struct(a.alias("a"), b.alias("b"), F.lit(asks).alias("asks"), F.lit(answers).alias("answers"))
    dealt = F.flatten(F.transform(F.sequence(F.lit(0), F.col("parts") - 1), lambda i: F.when(i == F.col("own"), F.array(role(i, i, True, True))).otherwise(F.array(role(F.col("own"), i, True, False), role(i, F.col("own"), False, True)))))
    rows = rows.join(large, "cell", "left").withColumn("parts", F.coalesce("parts", F.lit(1))).withColumn("own", own)
    rows = rows.select("cell", "id", "vec", "codes", F.explode(dealt).alias("s")).select("cell", "s.*", "id", "vec", "codes")
    found = rows.groupBy("cell", "a", "b").applyInArrow(_cell_pairs(sets, forest.d, trees, k, votes), "qid long, id long, distance double, votes int")
    return ranked(found, k).select("qid", "rank", "id", "distance", "votes")


def _cell_pairs(sets: list[tuple[int, ...]], d: int, trees: int, k: int, votes: int):
    def run(t: pa.Table) -> pa.Table:
        nth = t.column("cell")[0].as_py()["nth"]
        column = lambda c: t.column(c).combine_chunks()
        ids, x, codes = t.column("id").to_numpy(), block(column("vec"), d), column("codes").flatten().to_numpy().reshape(-1, trees)
        before = [s for s in sets[:nth]]
        asks, answers = (np.flatnonzero(t.column(c).to_numpy(zero_copy_only=False)) for c in ("asks", "answers"))
        out = []
        for at in range(0, len(asks), 1000):
            q = asks[at : at + 1000]
            best = Nearest(ids[q], x[q], k, exclude_self=True)
            for i, j in best.steps(len(answers)):
                p = answers[i:j]
                best.offer(ids[p], x[p], best.rough(x[p]), _first_met(codes[q], codes[p], before), votes)
            out.append(best.rows("votes"))
        return pa.Table.from_batches(out or [Nearest(ids[:0], x[:0], k).rows("votes")])

    return run


def _first_met(q: np.ndarray, own: np.ndarray, before: list[tuple[int, ...]]):
    """Votes of pairs; -1 of those that share all leaves of an earlier set, where they are looked at."""
    votes = _votes_between(q, own)

    def shared(rows: np.ndarray, cols: np.ndarray) -> np.ndarray:
        out = votes(rows, cols)
        for s in before:
            out[np.logical_and.reduce([q[rows, t] == own[cols, t] for t in s])] = -1
        return out

    return shared


def classify(neighbors: DataFrame, labels: DataFrame) -> DataFrame:
    """(qid, label, share): the majority label of each query's neighbours, ties by the smaller label. labels: (id, label)."""
    counts = neighbors.join(labels, "id").groupBy("qid", "label").agg(F.count("*").alias("n"))
    share = F.col("n") / F.sum("n").over(W.partitionBy("qid"))
    nth = F.row_number().over(W.partitionBy("qid").orderBy(F.desc("n"), "label"))
    return counts.select("qid", "label", F.round(share, 6).alias("share"), nth.alias("nth")).where("nth = 1").drop("nth")


def recommend(neighbors: DataFrame, weights: DataFrame, k: int) -> DataFrame:
    """(qid, rank, item, score): items (id, item, weight) of the neighbours, by weight over one plus distance."""
    score = neighbors.join(weights, "id").groupBy("qid", "item").agg(F.round(F.sum(F.col("weight") / (1 + F.col("distance"))), 6).alias("score"))
    nth = F.row_number().over(W.partitionBy("qid").orderBy(F.desc("score"), "item"))
    return score.withColumn("rank", nth).where(F.col("rank") <= k)
