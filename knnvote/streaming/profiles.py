"""Windowed profiles, joins in time and running vectors over the events, for batches and streams alike."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

EVENTS = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
KINDS = ("click", "error", "purchase", "signup", "view")
HOURS = 24
STAMP = "yyyy-MM-dd HH:mm:ss"


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a stream of files."""
    from ..sources.tables import load

    schema = load(spark, sf_dir, "events").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "events.parquet").parquet(sf_dir).withColumn("ts", F.col("ts").cast("timestamp"))


def once(events: DataFrame, late: str = "1 hour") -> DataFrame:
    """Events with their repeats dropped; on a stream, rows later than the watermark go too."""
    if not events.isStreaming:
        return events.dropDuplicates(["event_id"])
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def window_of(kind: str) -> Column:
    return {"tumbling": lambda: F.window("ts", "1 day"), "sliding": lambda: F.window("ts", "1 day", "6 hours"), "session": lambda: F.session_window("ts", "2 hours")}[kind]()


def profiles(events: DataFrame, kind: str, by: str = "user_id", late: str | None = "1 hour") -> DataFrame:
    """(by, start, events, largest): counts and the largest value of each day, of days begun every six hours, or of sessions that two quiet hours end."""
    if events.isStreaming and late:
        events = events.withWatermark("ts", late)
    out = events.groupBy(by, window_of(kind).alias("w")).agg(F.count("*").alias("events"), F.max("value").alias("largest"))
    return out.select(by, F.date_format("w.start", STAMP).alias("start"), "events", "largest")


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, values: list[str]) -> DataFrame:
    """left with the `values` of the last row of right at or before each of its times, per key; null where there is none.

    One shuffle by key: both sides are united and the last right row is carried along. Of right
    rows of one key and time, the greatest counts.
    """
    kept = F.struct(*[F.col(v) for v in values])
    r = right.where(F.col(key).isNotNull() & F.col(at).isNotNull()).groupBy(key, at).agg(F.max(kept).alias("_r"))
    both = left.withColumn("_r", F.lit(None).cast(r.schema["_r"].dataType)).withColumn("_left", F.lit(1)).unionByName(r.withColumn("_left", F.lit(0)), allowMissingColumns=True)
    last = F.last("_r", ignorenulls=True).over(W.partitionBy(key).orderBy(F.col(at), "_left").rowsBetween(W.unboundedPreceding, W.currentRow))
    return both.withColumn("_seen", last).where("_left = 1").select(*left.columns, *[F.col(f"_seen.{v}").alias(f"last_{v}") for v in values])


def followed(events: DataFrame, first: str = "view", then: str = "purchase", within: str = "1 hour", late: str | None = "1 hour") -> DataFrame:
    """(user_id, first_id, then_id): events of one kind that another kind of the same user follows within a time. late is None where the stream has a watermark."""
    if events.isStreaming and late:
        events = events.withWatermark("ts", late)
    a = events.where(F.col("event_type") == first).select(F.col("user_id").alias("u"), F.col("event_id").alias("first_id"), F.col("ts").alias("t1"))
    b = events.where(F.col("event_type") == then).select("user_id", F.col("event_id").alias("then_id"), F.col("ts").alias("t2"))
    near = (F.col("u") == F.col("user_id")) & (F.col("t2") >= F.col("t1")) & (F.col("t2") <= F.col("t1") + F.expr(f"interval {within}"))
    return a.join(b, near).select("user_id", "first_id", "then_id")


def running_vectors(events: DataFrame) -> DataFrame:
    """(user_id, vec, events): each user's counts of kinds by hour so far, a row a user and batch; state is one vector a user."""
    slot = (F.array_position(F.array(*[F.lit(k) for k in KINDS]), F.col("event_type")) - 1) * HOURS + F.hour("ts")
    d = len(KINDS) * HOURS

    def update(key: tuple, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        vec = list(state.get[0]) if state.exists else [0.0] * d
        for f in frames:
            for s, n in f["slot"].value_counts().items():
                vec[int(s)] += float(n)
        state.update((vec,))
        yield pd.DataFrame({"user_id": [key[0]], "vec": [vec], "events": [int(sum(vec))]})

    rows = events.where(F.col("event_type").isin(*KINDS) & F.col("user_id").isNotNull() & F.col("ts").isNotNull()).select("user_id", slot.cast("int").alias("slot"))
    return rows.groupBy("user_id").applyInPandasWithState(update, "user_id long, vec array<double>, events long", "vec array<double>", "update", "NoTimeout")


def collected(stream: DataFrame, folder: str, mode: str = "append") -> DataFrame:
    """All that a stream has to give now, run to its end and read back from folder."""
    out = f"{folder}/out"
    if mode == "append":
        q = stream.writeStream.format("parquet").option("path", out).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    else:
        # a complete result replaces the last one; updates are kept, a folder a batch
        each = lambda batch, number: batch.write.mode("overwrite").parquet(f"{out}/batch={0 if mode == 'complete' else number}")
        q = stream.writeStream.outputMode(mode).foreachBatch(each).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return stream.sparkSession.read.schema(stream.schema).parquet(out).select(stream.columns)
