"""Growing, storing and updating a forest: split values, leaf codes, postings."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.vectors import packed_dot
from ..plans.config import ForestParams
from ..sources.storage import settle
from .blocks import Blocks
from .projection import _ddl, block, descend, directions, matrix, packed, project, route_expression, uniform

LOCAL_ROWS = 2_000_000  # points of a tree that one task may split: 16 MB of doubles a level
SAMPLE_ROWS = 1_000_000  # points that fit the splits of build "sample"
INLINE_SPLITS = 4_096  # split values written into an expression; beyond, blocks of points are routed in Arrow


materialised = settle  # tables that iterations go back to


@dataclass
class Forest:
    """Directions and split values in the driver (their size depends on the parameters alone), points as DataFrames."""

    params: ForestParams
    d: int
    n: int
    pack: dict  # (tree, level, node) -> dims, weights
    splits: np.ndarray  # trees x (2**depth - 1), heap order
    points: DataFrame  # id, vec
    codes: DataFrame  # id, codes array<int>

    def split_literal(self) -> Column:
        return F.from_json(F.lit(json.dumps(self.splits.tolist())), "array<array<double>>")

    def coded(self, vectors: DataFrame) -> DataFrame:
        """vectors (.., vec) with `codes`: the leaf they fall into in every tree."""
        p = self.params
        if p.direction_scope == "node":
            return _coded_by_node(vectors, self)
        if self.splits.size <= INLINE_SPLITS and p.trees * p.depth <= 16:
            return project(vectors, self.pack, p, self.d).withColumn("codes", route_expression("proj", self.split_literal(), p)).drop("proj")
        return _coded_in_blocks(vectors, self)

    def router(self):
        """The function of a matrix of vectors to their leaf codes, where blocks are what made `codes`; else None."""
        p = self.params
        if p.direction_scope == "node" or p.tie == "rank" or self.splits.size <= INLINE_SPLITS and p.trees * p.depth <= 16:
            return None
        return _router(self)

    def split_table(self) -> DataFrame:
        """(tree, level, node, threshold)."""
        rows = [(t, j, i, float(self.splits[t, 2**j - 1 + i])) for t in range(self.params.trees) for j in range(self.params.depth) for i in range(2**j)]
        return self.points.sparkSession.createDataFrame(rows, "tree int, level int, node int, threshold double")

    def postings(self) -> DataFrame:
        """(tree, leaf, id)."""
        return self.codes.select(F.posexplode("codes").alias("tree", "leaf"), "id")

    def slice(self, trees: int, depth: int) -> Forest:
        """The forest that its first trees, cut at a lesser depth, make: no new build."""
        p = self.params
        if trees > p.trees or depth > p.depth:
            raise ValueError("a slice is no larger than the forest")
        pack = {k: v for k, v in self.pack.items() if k[0] < trees and k[1] < depth}
        codes = self.codes.select("id", F.transform(F.slice("codes", 1, trees), lambda c: F.shiftright(c, p.depth - depth)).alias("codes"))
        return Forest(p.but(trees=trees, depth=depth), self.d, self.n, pack, self.splits[:trees, : 2**depth - 1], self.points, codes)

    def save(self, path: str, buckets: int = 16) -> None:
        """Codes, postings (a folder a tree, sorted by leaf) and points as Parquet, the rest as one JSON row."""
        spark = self.points.sparkSession
        self.points.write.mode("overwrite").parquet(f"{path}/points")
        self.codes.write.mode("overwrite").parquet(f"{path}/codes")
        self.postings().repartition(buckets, "tree").sortWithinPartitions("tree", "leaf", "id").write.mode("overwrite").partitionBy("tree").parquet(f"{path}/postings")
        head = {"params": asdict(self.params), "d": self.d, "n": self.n, "pack": [[list(k), *v] for k, v in self.pack.items()], "splits": self.splits.tolist()}
        spark.createDataFrame([(json.dumps(head),)], "manifest string").coalesce(1).write.mode("overwrite").parquet(f"{path}/manifest")

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Forest:
        head = json.loads(spark.read.parquet(f"{path}/manifest").first()[0])
        p = ForestParams(**head["params"])
        splits = np.array(head["splits"], float).reshape(p.trees, 2**p.depth - 1)
        return cls(p, head["d"], head["n"], {tuple(k): (i, w) for k, i, w in head["pack"]}, splits, spark.read.parquet(f"{path}/points"), spark.read.parquet(f"{path}/codes"))

    def insert(self, new: DataFrame) -> Forest:
        """The forest with more points (id, vec), routed by the splits as they are."""
        new = new.select("id", "vec")
        return Forest(self.params, self.d, self.n + new.count(), self.pack, self.splits, self.points.unionByName(new), self.codes.unionByName(self.coded(new).select("id", "codes")))

    def imbalance(self) -> DataFrame:
        """(tree, largest, mean, ratio): how far leaves have drifted from even; a rebuild is due where the ratio is high."""
        sizes = self.postings().groupBy("tree", "leaf").count()
        out = sizes.groupBy("tree").agg(F.max("count").alias("largest"), (F.sum("count") / 2**self.params.depth).alias("mean"))
        return out.withColumn("ratio", F.round(F.try_divide("largest", "mean"), 6))

    def maintained(self, ratio: float = 2.0) -> Forest:
        """This forest while no leaf of a tree exceeds `ratio` mean leaves; else one grown anew on all points."""
        worst = self.imbalance().agg(F.max("ratio")).first()[0]
        return self if worst is None or worst <= ratio else build_forest(self.points, self.params)


def build_forest(points: DataFrame, params: ForestParams, held: Blocks | None = None) -> Forest:
    """Grow all trees on points (id, vec). Vectors must have one length and no nulls. held: the points as blocks, if they have been packed."""
    points = points.select("id", "vec")
    n, d = points.agg(F.count("*"), F.max(F.size("vec"))).first()
    params.validate(n, d)
    pack = packed(directions(points.sparkSession, params, d))
    shape = (params.trees, 2**params.depth - 1)
    forest = Forest(params, d, n, pack, np.full(shape, np.nan), points, points)
    if params.direction_scope == "node":
        return _grow_by_node(forest)
    if held and params.tie == "threshold" and params.split == "median" and params.build in ("auto", "tree_local") and (n <= LOCAL_ROWS or params.build == "tree_local"):
        r = matrix(pack, params, d)
        forest.splits = _grown_by_tree(held.map(lambda blocks: (_by_tree_and_level(np.round(x @ r, 9), params) for _, x in blocks), _tree_schema(params)), params)
        forest.codes = materialised(held.map(_coded_rows(forest), "id long, codes array<int>"), "codes")
        return forest
    proj = materialised(project(points, pack, params, d).select("id", "proj"), "projected")
    if params.tie == "rank":
        return _grow_ranked(forest, proj)
    build = params.build
    if params.split == "fractile":
        build = "level_fractile"
    elif build == "auto":
        build = "tree_local" if n <= LOCAL_ROWS else "level_exact"
    if build == "sample":
        share = params.sample or min(1.0, SAMPLE_ROWS / max(1, n))
        proj = materialised(proj.where(uniform(params.seed, F.col("id"), "sample") < share), "sample")
        build = "tree_local"
    grown = _tree_local if build == "tree_local" else _level_by_level
    forest.splits = grown(proj, params, build)
    forest.codes = materialised(forest.coded(points).select("id", "codes"), "codes")
    return forest


def _tree_local(proj: DataFrame, p: ForestParams, _: str) -> np.ndarray:
    def run(batches):
        for b in batches:
            yield _by_tree_and_level(block(b.column(0), p.trees * p.depth) if p.depth else np.zeros((b.num_rows, 0)), p)

    return _grown_by_tree(proj.select("proj").mapInArrow(run, _tree_schema(p)), p)


def _tree_schema(p: ForestParams) -> str:
    return ", ".join(["tree int", *[f"x{j} binary" for j in range(p.depth)]])


def _by_tree_and_level(proj: np.ndarray, p: ForestParams) -> pa.RecordBatch:
    """A row a tree, with the projections of each level as bytes."""
    x = proj.reshape(len(proj), p.trees, p.depth)
    return pa.record_batch([pa.array(np.arange(p.trees, dtype=np.int32)), *[pa.array([c.tobytes() for c in x[:, :, j].T], pa.binary()) for j in range(p.depth)]], names=["tree", *[f"x{j}" for j in range(p.depth)]])


def _grown_by_tree(rows: DataFrame, p: ForestParams) -> np.ndarray:
    """One shuffle by tree; a task splits its tree through all levels."""
    def grow(t: pa.Table) -> pa.Table:
        out, node = [], None
        for j in range(p.depth):
            x = np.concatenate([np.frombuffer(c.as_buffer()) for c in t.column(f"x{j}")])
            node = np.zeros(len(x), np.int32) if node is None else node
            order = np.lexsort((x, node))
            v, at = x[order], np.searchsorted(node[order], np.arange(2**j + 1))
            cut = np.full(2**j, np.nan)
            for i in np.flatnonzero(np.diff(at)):
                lo, m = at[i], at[i + 1] - at[i]
                cut[i] = (v[lo + (m - 1) // 2] + v[lo + m // 2]) / 2
            out.append(cut)
            node = 2 * node + (x > cut[node])
        return pa.table({"tree": t.column("tree").slice(0, 1), "cuts": pa.array([np.concatenate(out)], pa.list_(pa.float64()))})

    out = np.full((p.trees, 2**p.depth - 1), np.nan)
    if not p.depth:
        return out
    for r in rows.groupBy("tree").applyInArrow(grow, "tree int, cuts array<double>").collect():  # a row a tree
        out[r["tree"]] = r["cuts"]
    return out


def _level_by_level(proj: DataFrame, p: ForestParams, build: str) -> np.ndarray:
    """A round a level: the medians of all nodes of all trees in one aggregation, at most trees x 2**level numbers back."""
    splits = np.full((p.trees, 2**p.depth - 1), np.nan)
    for j in range(p.depth):
        known = F.from_json(F.lit(json.dumps(np.nan_to_num(splits[:, : max(1, 2**j - 1)]).tolist())), "array<array<double>>")
        nodes = _node_codes("proj", known, p, j)
        parts = F.transform(F.sequence(F.lit(0), F.lit(p.trees - 1)), lambda t: F.struct(t.alias("tree"), F.get(nodes, t).alias("node"), F.get("proj", t * p.depth + j).alias("v")))
        long = proj.select("id", F.explode(parts).alias("s")).select("id", "s.*")
        if build == "level_sketch":
            cut = long.groupBy("tree", "node").agg(F.percentile_approx("v", 0.5, 10_000).alias("cut"))
        elif build == "level_fractile":
            cut = _fractile(long, p, j)
        else:
            cut = medians(long, "tree", "node")
        for r in cut.collect():
            splits[r["tree"], 2**j - 1 + r["node"]] = r["cut"]
    return splits


def medians(rows: DataFrame, *keys: str) -> DataFrame:
    """(keys, cut): the exact median of `v` in every group, without a group's values in one task.

    A sketch brackets the median between the ranks of 49 and 51 %, with an error of 0.1 %; only the distinct values of the
    bracket are counted and ranked. All values below it are one count. Groups are nodes, whose number the parameters bound.
    """
    about = rows.groupBy(*keys).agg(F.percentile_approx("v", [0.49, 0.51], 1000).alias("around"), F.count("v").alias("m"))
    near = rows.join(F.broadcast(about), list(keys)).where(F.col("v") <= F.get("around", F.lit(1)))
    value = F.when(F.col("v") >= F.get("around", F.lit(0)), F.col("v")).alias("v")
    counts = near.groupBy(*keys, "m", value).agg(F.count("*").alias("n"))
    upto = counts.withColumn("upto", F.sum("n").over(W.partitionBy(*keys).orderBy(F.asc_nulls_first("v"))))
    at = lambda rank: F.min(F.when(F.col("upto") >= F.expr(rank), F.col("v")))
    missed = F.max(F.col("v").isNull() & (F.col("upto") >= F.expr("(m + 1) div 2")))
    cut = F.when(missed, F.raise_error(F.lit("the sketch missed a median"))).otherwise((at("(m + 1) div 2") + at("m div 2 + 1")) / 2)
    return upto.groupBy(*keys).agg(cut.cast("double").alias("cut"))


def _node_codes(proj: str, splits: Column, p: ForestParams, level: int) -> Column:
    """The node of a level in every tree, from the first `level` projections."""
    return F.transform(F.sequence(F.lit(0), F.lit(p.trees - 1)), lambda t: descend(F.col(proj), splits, t, p.depth, level))


def _fractile(long: DataFrame, p: ForestParams, level: int) -> DataFrame:
    """The value of rank ceil(f n) in each node, f hashed between 1/4 and 3/4."""
    by = W.partitionBy("tree", "node")
    f = 0.25 + 0.5 * uniform(p.seed, F.col("tree"), level, F.col("node"), "f")
    ranked = long.withColumn("nth", F.row_number().over(by.orderBy("v", "id"))).withColumn("m", F.count("*").over(by)).withColumn("f", f)
    return ranked.where(F.col("nth") == F.ceil(F.col("f") * F.col("m"))).select("tree", "node", F.col("v").alias("cut"))


def _grow_ranked(forest: Forest, proj: DataFrame) -> Forest:
    """Halves by rank, so leaves differ by one point at most whatever the ties; medians still route queries."""
    p = forest.params
    long = proj.select("id", F.explode(F.transform(F.sequence(F.lit(0), F.lit(p.trees - 1)), lambda t: F.struct(t.alias("tree"), F.slice("proj", t * p.depth + 1, F.lit(p.depth)).alias("x")))).alias("s")).select("id", "s.tree", "s.x", F.lit(0).alias("node"))
    for j in range(p.depth):
        by = W.partitionBy("tree", "node")
        long = long.withColumn("nth", F.row_number().over(by.orderBy(F.get("x", F.lit(j)), "id"))).withColumn("m", F.count("*").over(by))
        long = materialised(long, "ranked")
        cut = medians(long.select("tree", "node", F.get("x", F.lit(j)).alias("v")), "tree", "node")
        for r in cut.collect():
            forest.splits[r["tree"], 2**j - 1 + r["node"]] = r["cut"]
        long = long.withColumn("node", F.col("node") * 2 + (F.col("nth") > F.ceil(F.col("m") / 2)).cast("int")).drop("nth", "m")
    codes = long.groupBy("id").agg(F.transform(F.array_sort(F.collect_list(F.struct("tree", "node"))), lambda s: s["node"]).alias("codes"))
    forest.codes = materialised(codes, "codes")
    return forest


def _router(forest: Forest):
    """One matrix product, then a comparison a level for all trees at once."""
    p, splits, r = forest.params, forest.splits, matrix(forest.pack, forest.params, forest.d)
    trees = np.arange(p.trees)

    def route(x: np.ndarray) -> np.ndarray:
        x = np.round(x @ r, 9).reshape(len(x), p.trees, p.depth)
        node = np.zeros((len(x), p.trees), np.int64)
        for j in range(p.depth):
            node = 2 * node + (x[:, :, j] > splits[trees, 2**j - 1 + node])
        return node.astype(np.int32)

    return route


def _coded_rows(forest: Forest):
    """(id, codes) of blocks of points."""
    trees, route = forest.params.trees, _router(forest)

    def run(blocks):
        for ids, x in blocks:
            node = route(x)
            codes = pa.ListArray.from_arrays(pa.array(np.arange(0, node.size + 1, trees, dtype=np.int32)), pa.array(node.ravel()))
            yield pa.record_batch([pa.array(ids), codes], names=["id", "codes"])

    return run


def _coded_in_blocks(vectors: DataFrame, forest: Forest) -> DataFrame:
    """Arrow blocks of vectors, each routed at once."""
    d, trees, route = forest.d, forest.params.trees, _router(forest)
    names, at = vectors.columns, vectors.columns.index("vec")

    def run(batches):
        for b in batches:
            node = route(block(b.column(at), d))
            codes = pa.ListArray.from_arrays(pa.array(np.arange(0, node.size + 1, trees, dtype=np.int32)), pa.array(node.ravel()))
            yield pa.record_batch([*b.columns, codes], names=[*names, "codes"])

    return vectors.mapInArrow(run, f"{_ddl(vectors)}, codes array<int>")


# ---- one direction for every node -----------------------------------------------------------

def _node_step(vectors: DataFrame, forest: Forest, level: int) -> DataFrame:
    """(key, tree, node, v): each point's projection on the direction of the node it stands in."""
    p = forest.params
    dirs = {t: [forest.pack.get((t, level, i), ([], [])) for i in range(2**level)] for t in range(p.trees)}
    table = F.from_json(F.lit(json.dumps([[{"i": list(i), "w": list(w)} for i, w in dirs[t]] for t in range(p.trees)])), "array<array<struct<i:array<int>,w:array<double>>>>")
    at = F.get(F.get(table, F.col("tree")), F.col("node"))
    return vectors.withColumn("v", F.round(packed_dot("vec", at), 9))


def _by_tree(vectors: DataFrame, p: ForestParams) -> DataFrame:
    return vectors.withColumn("tree", F.explode(F.sequence(F.lit(0), F.lit(p.trees - 1)))).withColumn("node", F.lit(0))


def _grow_by_node(forest: Forest) -> Forest:
    p = forest.params
    rows = _by_tree(forest.points, p)
    for j in range(p.depth):
        rows = materialised(_node_step(rows, forest, j), "stepped")
        cut = _fractile(rows, p, j) if p.split == "fractile" else medians(rows, "tree", "node")
        for r in cut.collect():
            forest.splits[r["tree"], 2**j - 1 + r["node"]] = r["cut"]
        rows = _descended(rows, forest, j)
    forest.codes = materialised(rows.groupBy("id").agg(F.transform(F.array_sort(F.collect_list(F.struct("tree", "node"))), lambda s: s["node"]).alias("codes")), "codes")
    return forest


def _descended(rows: DataFrame, forest: Forest, level: int) -> DataFrame:
    cut = F.get(F.get(forest.split_literal(), F.col("tree")), F.lit(2**level - 1) + F.col("node"))
    return rows.withColumn("node", F.col("node") * 2 + (F.col("v") > cut).cast("int")).drop("v")


def _coded_by_node(vectors: DataFrame, forest: Forest) -> DataFrame:
    key = vectors.columns[0]
    rows = _by_tree(vectors, forest.params)
    for j in range(forest.params.depth):
        rows = _descended(_node_step(rows, forest, j), forest, j)
    codes = rows.groupBy(key).agg(F.transform(F.array_sort(F.collect_list(F.struct("tree", "node"))), lambda s: s["node"]).alias("codes"))
    return vectors.join(codes, key)
