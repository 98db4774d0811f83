"""Vector algebra as Column expressions over array<float|double>, and the same as SQL functions."""

from __future__ import annotations

from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

DOUBLES = "array<double>"


def _d(v: Column | str) -> Column:
    return (F.col(v) if isinstance(v, str) else v).cast(DOUBLES)


def _sum(v: Column) -> Column:
    return F.aggregate(v, F.lit(0.0), lambda s, x: s + x)


def dot(a: Column | str, b: Column | str) -> Column:
    return _sum(F.zip_with(_d(a), _d(b), lambda x, y: x * y))


def squared_l2(a: Column | str, b: Column | str) -> Column:
    return _sum(F.zip_with(_d(a), _d(b), lambda x, y: (x - y) * (x - y)))


def l2_distance(a: Column | str, b: Column | str) -> Column:
    return F.sqrt(squared_l2(a, b))


def l1(a: Column | str, b: Column | str) -> Column:
    return _sum(F.zip_with(_d(a), _d(b), lambda x, y: F.abs(x - y)))


def linf(a: Column | str, b: Column | str) -> Column:
    return F.coalesce(F.array_max(F.zip_with(_d(a), _d(b), lambda x, y: F.abs(x - y))), F.lit(0.0))


def norm(a: Column | str) -> Column:
    return F.sqrt(_sum(F.transform(_d(a), lambda x: x * x)))


def cosine_distance(a: Column | str, b: Column | str) -> Column:
    """1 minus the cosine; 1 where either vector is zero."""
    return 1 - F.coalesce(F.try_divide(dot(a, b), norm(a) * norm(b)), F.lit(0.0))


def scale(a: Column | str, by: Column | float) -> Column:
    if not isinstance(by, Column):
        return F.transform(_d(a), lambda x: x * F.lit(float(by)))
    # an outer lambda binds the factor, which would else be computed anew for every component
    return F.get(F.transform(F.array(by), lambda b: F.transform(_d(a), lambda x: x * b)), F.lit(0))


def add(a: Column | str, b: Column | str) -> Column:
    return F.zip_with(_d(a), _d(b), lambda x, y: x + y)


def normalize(a: Column | str) -> Column:
    """The vector at length 1; a zero vector stays as it is."""
    return scale(a, F.coalesce(F.try_divide(F.lit(1.0), norm(a)), F.lit(0.0)))


def sparse_dot(vec: Column | str, idx: list[int], weights: list[float]) -> Column:
    """Sum of the named components by weight: plain arithmetic that is compiled with the stage around it."""
    v = F.col(vec) if isinstance(vec, str) else vec
    out = F.lit(0.0)
    for i, w in zip(idx, weights, strict=True):
        out = out + v[i].cast("double") * F.lit(float(w))
    return out


def packed_dot(vec: Column | str, direction: Column) -> Column:
    """Sum of the components that a struct of indexes i and weights w names, by weight."""
    v = F.col(vec) if isinstance(vec, str) else vec
    parts = F.arrays_zip(direction["i"].alias("i"), direction["w"].alias("w"))
    return F.aggregate(parts, F.lit(0.0), lambda s, x: s + F.get(v, x["i"]).cast("double") * x["w"])


METRICS = {"l2": l2_distance, "squared_l2": squared_l2, "l1": l1, "linf": linf, "cosine": cosine_distance}


def valid(v: Column | str, d: int | None = None) -> Column:
    """No null, no null or NaN component, not empty, and of length d if given."""
    c = F.col(v) if isinstance(v, str) else v
    good = c.isNotNull() & (F.size(c) > 0) & ~F.exists(c, lambda x: x.isNull() | F.isnan(x))
    return F.coalesce(good & (F.size(c) == d) if d is not None else good, F.lit(False))


def register_sql(spark: SparkSession) -> None:
    """dot, l2_distance and l1_distance as temporary SQL functions, which Catalyst inlines."""
    kinds = {
        "dot": ("x * y", "s"),
        "l2_distance": ("(x - y) * (x - y)", "sqrt(s)"),
        "l1_distance": ("abs(x - y)", "s"),
    }
    for name, (each, end) in kinds.items():
        spark.sql(
            f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a ARRAY<DOUBLE>, b ARRAY<DOUBLE>) RETURNS DOUBLE "
            f"RETURN aggregate(zip_with(a, b, (x, y) -> {each}), 0D, (s, x) -> s + x, s -> {end})"
        )
