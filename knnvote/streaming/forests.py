"""Streams of queries and of new points against a forest.

Each micro-batch is written to a folder named by its number, so a batch that is run again after
a failure replaces its rows instead of repeating them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..operators.forest import Forest
from ..operators.search import approximate_knn

CODED = "id long, vec array<float>, codes array<int>"


def started(stream: DataFrame, each, checkpoint: str, trigger: dict | None = None) -> StreamingQuery:
    """A query that hands every micro-batch to each(batch, number); what is there at the start is taken, unless a trigger says otherwise."""
    return stream.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(**(trigger or {"availableNow": True})).start()


def query_stream(queries: DataFrame, forest: Forest, k: int, votes: int, path: str, checkpoint: str, strategy: str = "auto", trigger: dict | None = None) -> StreamingQuery:
    """Answers a stream of queries (qid, qvec) into path: (qid, rank, id, distance, votes), a folder a batch."""
    def answer(batch: DataFrame, number: int) -> None:
        found = approximate_knn(batch.select("qid", "qvec"), forest, k, votes, strategy)
        found.write.mode("overwrite").parquet(f"{path}/batch={number}")

    return started(queries, answer, checkpoint, trigger)


def insert_stream(points: DataFrame, forest: Forest, path: str, checkpoint: str, trigger: dict | None = None) -> StreamingQuery:
    """Routes a stream of points (id, vec) by the splits as they are, and adds them and their leaves to path."""
    def add(batch: DataFrame, number: int) -> None:
        forest.coded(batch.select("id", "vec")).select("id", "vec", "codes").write.mode("overwrite").parquet(f"{path}/batch={number}")

    return started(points, add, checkpoint, trigger)


def with_inserted(forest: Forest, path: str) -> Forest:
    """The forest with all points that insert_stream has written to path."""
    new = forest.points.sparkSession.read.schema(CODED).parquet(path)
    return Forest(
        forest.params, forest.d, forest.n + new.count(), forest.pack, forest.splits,
        forest.points.unionByName(new.select("id", "vec")), forest.codes.unionByName(new.select("id", "codes")),
    )


def as_queries(points: DataFrame) -> DataFrame:
    return points.select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))
