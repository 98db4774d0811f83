"""Table functions and vector aggregates for SQL users."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.functions import udtf


def vec_mean(df: DataFrame, by: str, vec: str = "vec", d: int = 64) -> DataFrame:
    """(by, vec): the element-wise mean of each group's vectors, by built-in averages, so partial sums leave the map side."""
    parts: list[Column] = [F.avg(F.get(F.col(vec), F.lit(i)).cast("double")).alias(f"c{i}") for i in range(d)]
    return df.groupBy(by).agg(*parts).select(by, F.array(*[f"c{i}" for i in range(d)]).alias(vec))


@udtf(returnType="tree: int, leaf: int")
class ExplodeLeaves:
    """explode_leaves(codes): a row for every tree with the leaf that the codes name."""

    def eval(self, codes: list[int]):
        for tree, leaf in enumerate(codes or []):
            yield tree, leaf


@udtf(returnType="qid: bigint, rank: int, id: bigint, distance: double")
class BestOf:
    """best_of(TABLE(pairs) PARTITION BY (qid), k): the k nearest of a query's (qid, id, distance) rows; memory holds k rows."""

    def __init__(self):
        self.k, self.held = 0, []

    def eval(self, row, k: int):
        import heapq

        self.k = k
        item = (-row["distance"], -row["id"], row["qid"])
        if len(self.held) < k:
            heapq.heappush(self.held, item)
        elif self.held and item > self.held[0]:
            heapq.heapreplace(self.held, item)

    def terminate(self):
        for rank, (distance, i, qid) in enumerate(sorted(self.held, reverse=True), 1):
            yield qid, rank, -i, -distance


def register(spark: SparkSession) -> None:
    """explode_leaves and best_of, for SQL."""
    spark.udtf.register("explode_leaves", ExplodeLeaves)
    spark.udtf.register("best_of", BestOf)
