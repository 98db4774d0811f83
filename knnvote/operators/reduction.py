"""Truncated singular vectors: wide count vectors as short dense ones."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .projection import block

MAX_DIMS = 4_096  # the Gram matrix comes to the driver: 128 MB at most
SHUFFLE_BYTES = 8 << 30  # of partial Gram matrices, all tasks together


@dataclass(frozen=True)
class Basis:
    """The k leading right singular vectors, as columns, and their singular values."""

    vectors: np.ndarray
    values: np.ndarray

    def reduced(self, points: DataFrame, vec: str = "vec", unit: bool = True) -> DataFrame:
        """points with `vec` on the basis, at length 1 if unit; a vector that is zero there stays zero."""
        v = self.vectors
        rest = [c for c in points.columns if c != vec]

        def run(batches):
            for b in batches:
                x = block(b.column(b.num_columns - 1), v.shape[0]) @ v
                if unit:
                    size = np.sqrt((x * x).sum(1, keepdims=True))
                    x = np.divide(x, size, out=np.zeros_like(x), where=size > 1e-12)
                flat = pa.array(x.astype(np.float32).ravel())
                lists = pa.ListArray.from_arrays(pa.array(np.arange(0, x.size + 1, x.shape[1], dtype=np.int32)), flat)
                yield pa.record_batch([*b.columns[:-1], lists], names=[*rest, vec])

        schema = ", ".join(f"`{c}` {points.schema[c].dataType.simpleString()}" for c in rest)
        return points.select(*rest, vec).mapInArrow(run, f"{schema}, `{vec}` array<float>")


def gram_matrix(points: DataFrame, d: int) -> np.ndarray:
    """The sum of x x' over all points (.., vec): each task adds up its blocks, rows of the partial sums are added by row.

    Tasks are merged, without a shuffle of the points, until the partial sums fit SHUFFLE_BYTES.
    """
    if d > MAX_DIMS:
        raise ValueError(f"{d} dimensions; at most {MAX_DIMS} have a Gram matrix in the driver")

    def partial(batches):
        g = np.zeros((d, d))
        for b in batches:
            x = block(b.column(0), d)
            g += x.T @ x
        yield pa.record_batch([pa.array(np.arange(d, dtype=np.int32)), pa.array(list(g), pa.list_(pa.float64()))], names=["i", "row"])

    def added(t: pa.Table) -> pa.Table:
        rows = block(t.column("row").combine_chunks(), d)
        return pa.table({"i": t.column("i").slice(0, 1), "row": pa.array([rows.sum(0)], pa.list_(pa.float64()))})

    tasks = max(1, SHUFFLE_BYTES // (8 * d * d))
    rows = points.select("vec").coalesce(tasks).mapInArrow(partial, "i int, row array<double>").groupBy("i").applyInArrow(added, "i int, row array<double>").collect()
    out = np.zeros((d, d))
    for r in rows:
        out[r["i"]] = r["row"]
    return out


def singular_basis(points: DataFrame, k: int) -> Basis:
    """The k leading singular vectors of points (.., vec), of at most MAX_DIMS dimensions; fewer where the rank is less.

    A vector's sign is that of its largest component, so reruns agree.
    """
    d = points.agg(F.max(F.size("vec"))).first()[0]
    if not d:
        raise ValueError("no vectors")
    values, vectors = np.linalg.eigh(gram_matrix(points, d))
    values, vectors = np.sqrt(np.maximum(values[::-1][:k], 0)), vectors[:, ::-1][:, :k]
    keep = values > 1e-9 * max(values[0], 1e-300)
    values, vectors = values[keep], vectors[:, keep]
    top = np.abs(vectors).argmax(0)
    return Basis(vectors * np.sign(vectors[top, np.arange(len(top))]), values)
