"""Random directions and the projection of all points onto all of them in one pass."""

from __future__ import annotations

import json

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ..functions.vectors import packed_dot
from ..plans.config import ForestParams

NATIVE = 256  # multiplications a point for built-in expressions; beyond, blocks of points meet a matrix


def uniform(*parts: Column | str | int) -> Column:
    """A number in [0, 1) from the md5 of the parts, colon-joined: the same in any engine and after any retry."""
    text = F.concat_ws(":", *[p if isinstance(p, Column) else F.lit(str(p)) for p in parts])
    return F.conv(F.substring(F.md5(text), 1, 8), 16, 10).cast("long") / F.lit(4294967296.0)


def directions(spark: SparkSession, params: ForestParams, d: int) -> DataFrame:
    """(tree, level, node, dim, weight): the non-zero components of every direction; node is null where a level shares one.

    A direction that would be empty keeps its component of least hash, so that no projection ties all points.
    """
    t, depth = params.trees, params.depth
    if params.direction_scope == "level":
        grid = spark.range(t * depth * d).select(F.expr(f"int(id div {depth * d})").alias("tree"), F.expr(f"int(id div {d} % {depth})").alias("level"), F.lit(None).cast("int").alias("node"), F.expr(f"int(id % {d})").alias("dim"))
        key = [params.seed, F.col("tree"), F.col("level"), F.col("dim")]
    else:
        inner = 2**depth - 1
        grid = spark.range(t * inner * d).select(F.expr(f"int(id div {inner * d})").alias("tree"), F.expr(f"int(id div {d} % {inner})").alias("at"), F.expr(f"int(id % {d})").alias("dim"))
        grid = grid.withColumn("level", F.expr("int(floor(log2(at + 1)))")).withColumn("node", F.expr("int(at + 1 - shiftleft(1, level))")).drop("at")
        key = [params.seed, F.col("tree"), F.col("level"), F.col("node"), F.col("dim")]
    grid = grid.withColumn("u", uniform(*key, "u"))
    nth = F.row_number().over(W.partitionBy("tree", "level", "node").orderBy("u", "dim"))
    kept = F.col("nth") <= params.nonzeros(d) if params.nnz == "exact" else (F.col("u") < params.share(d)) | (F.col("nth") == 1)
    if params.components == "gaussian":
        u1 = uniform(*key, "a") + F.lit(1 / 4294967296.0)
        weight = F.round(F.sqrt(-2 * F.ln(u1)) * F.cos(2 * F.pi() * uniform(*key, "b")), 6)
    else:
        weight = F.when(uniform(*key, "a") < 0.5, 1.0).otherwise(-1.0)
    return grid.withColumn("nth", nth).where(kept).select("tree", "level", "node", "dim", weight.alias("weight"))


def packed(dirs: DataFrame) -> dict[tuple[int, int, int], tuple[list[int], list[float]]]:
    """(tree, level, node or 0) to its dims and weights, in the driver: trees x levels x non-zeros, whatever the points."""
    rows = dirs.groupBy("tree", "level", F.coalesce("node", F.lit(0)).alias("node")).agg(F.array_sort(F.collect_list(F.struct("dim", "weight"))).alias("parts")).collect()
    return {(r["tree"], r["level"], r["node"]): ([p["dim"] for p in r["parts"]], [p["weight"] for p in r["parts"]]) for r in rows}


def matrix(pack: dict, params: ForestParams, d: int) -> np.ndarray:
    """d x (trees x depth): the directions of all levels side by side."""
    out = np.zeros((d, params.trees * params.depth))
    for (tree, level, _), (dims, weights) in pack.items():
        out[dims, tree * params.depth + level] = weights
    return out


def project(points: DataFrame, pack: dict, params: ForestParams, d: int, engine: str = "auto") -> DataFrame:
    """points with `proj`, an array<double> of trees x depth values rounded to 9 decimals.

    native: a built-in sum over the non-zero components of each direction. arrow: Arrow blocks of points
    times the direction matrix. auto: by the number of multiplications a point.
    """
    columns = [(t, j) for t in range(params.trees) for j in range(params.depth)]
    if engine == "auto":
        engine = "native" if sum(len(x[0]) for x in pack.values()) <= NATIVE else "arrow"
    if engine == "native":
        table = json.dumps([{"i": pack[c + (0,)][0], "w": pack[c + (0,)][1]} for c in columns])
        dirs = F.from_json(F.lit(table), "array<struct<i:array<int>,w:array<double>>>")
        return points.withColumn("proj", F.transform(dirs, lambda r: F.round(packed_dot("vec", r), 9)))
    if engine == "relational":
        return _relational(points, pack, params)
    r = matrix(pack, params, d)
    names = points.columns
    at = names.index("vec")

    def run(batches):
        for b in batches:
            x = block(b.column(at), d)
            p = np.round(x @ r, 9)
            proj = pa.ListArray.from_arrays(pa.array((np.arange(len(p) + 1) * p.shape[1]).astype(np.int32)), pa.array(p.ravel()))
            yield pa.record_batch([*b.columns, proj], names=[*names, "proj"])

    return points.mapInArrow(run, f"{_ddl(points)}, proj array<double>")


def _ddl(df: DataFrame) -> str:
    return ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)


def block(column: pa.Array, d: int) -> np.ndarray:
    """Arrow lists of d numbers as an n x d matrix of doubles."""
    return np.asarray(column.flatten().to_numpy(zero_copy_only=False), np.float64).reshape(-1, d)


def _relational(points: DataFrame, pack: dict, params: ForestParams) -> DataFrame:
    """The product as a join on the dimension: a small direction table, whose size the parameters bound, is broadcast."""
    spark = points.sparkSession
    rows = [(t * params.depth + j, dim, w) for (t, j, _), (dims, ws) in pack.items() for dim, w in zip(dims, ws, strict=True)]
    dirs = F.broadcast(spark.createDataFrame(rows, "at int, dim int, weight double"))
    long = points.select("id", F.posexplode("vec").alias("dim", "x")).join(dirs, "dim")
    values = long.groupBy("id", "at").agg(F.round(F.sum(F.col("x").cast("double") * F.col("weight")), 9).alias("v"))
    rows = values.groupBy("id").agg(F.transform(F.array_sort(F.collect_list(F.struct("at", "v"))), lambda x: x["v"]).alias("proj"))
    return points.join(rows, "id")


def route_expression(proj: Column | str, splits: Column, params: ForestParams) -> Column:
    """Leaf codes of all trees from the projections: at or below the split goes left; the root's split is the highest bit."""
    proj = F.col(proj) if isinstance(proj, str) else proj
    depth = params.depth
    if not depth:
        return F.array_repeat(F.lit(0), params.trees)

    return F.transform(F.sequence(F.lit(0), F.lit(params.trees - 1)), lambda t: descend(proj, splits, t, depth, depth))


def descend(proj: Column, splits: Column, t: Column, depth: int, levels: int) -> Column:
    """The node of tree t that `levels` splits lead to; depth is the number of projections a tree has."""
    if not levels:
        return F.lit(0)

    def step(node, j):
        cut = F.get(F.get(splits, t), F.call_function("shiftleft", F.lit(1), j) - 1 + node)
        return node * 2 + (F.get(proj, t * depth + j) > cut).cast("int")

    return F.aggregate(F.sequence(F.lit(0), F.lit(levels - 1)), F.lit(0), step)
