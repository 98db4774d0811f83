"""Helpers that the training-data operators share."""

from __future__ import annotations

import contextlib
import ctypes
import gc
from collections.abc import Iterable

import pyarrow as pa
from py4j.protocol import Py4JError
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..sources.storage import clean, settle, shared_folder, work_folder  # noqa: F401

#: Rows in one Arrow batch, where whole texts travel. Spark itself ends a batch at 64 MB (spark.sql.execution.arrow.maxBytesPerBatch).
BATCH_ROWS = 1000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def small_batches(spark: SparkSession) -> None:
    """Whole texts cross to Python in batches of BATCH_ROWS rows, unless the session asks for fewer."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if int(spark.conf.get(key, "10000")) > BATCH_ROWS:
        spark.conf.set(key, str(BATCH_ROWS))


def give_back(spark: SparkSession) -> None:
    """Returns the driver's free memory to the system: Python's, the JVM's heap, and what its native allocator holds.

    Both allocators keep the most that a step took, so over the steps of a pipeline a driver of little live data grows all
    the same. What an allocator or a JVM (before 17.0.9) can't give back stays.
    """
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(AttributeError, OSError):  # glibc only
        ctypes.CDLL(None).malloc_trim(0)
    jvm, gateway = spark.sparkContext._jvm, spark.sparkContext._gateway

    def array(kind, *items):
        out = gateway.new_array(kind, len(items))
        for k, x in enumerate(items):
            out[k] = x
        return out

    jvm.System.gc()
    objects, strings, named = jvm.java.lang.Object, jvm.java.lang.String, jvm.java.lang.Class.forName
    with contextlib.suppress(Py4JError):
        # by reflection on the interface, as the server's own class is closed to Py4J
        kinds = "javax.management.ObjectName", "java.lang.String", "[Ljava.lang.Object;", "[Ljava.lang.String;"
        invoke = named("javax.management.MBeanServer").getMethod("invoke", array(jvm.java.lang.Class, *map(named, kinds)))
        commands = jvm.javax.management.ObjectName("com.sun.management:type=DiagnosticCommand")
        invoke.invoke(jvm.java.lang.management.ManagementFactory.getPlatformMBeanServer(), array(objects, commands, "systemTrimNativeHeap", array(objects), array(strings)))


def literal_rows(spark: SparkSession, rows: Iterable[tuple], schema: str) -> DataFrame:
    """A few rows of numbers and plain words as a DataFrame, from one literal; schema as `name type, ...`."""
    text = "\n".join("\t".join(map(str, r)) for r in rows)
    cells = F.split("line", "\t")
    named = [c.split() for c in schema.split(", ")]
    lines = spark.range(1).select(F.explode(F.split(F.lit(text), "\n")).alias("line")).where("line <> ''")
    return lines.select(*[F.get(cells, F.lit(i)).cast(kind).alias(name) for i, (name, kind) in enumerate(named)])


def crc_mod(doc_id: str, n: int) -> Column:
    """crc32 of an id's decimal text, modulo n; null ids take remainder 0."""
    return F.coalesce(F.crc32(F.col(doc_id).cast("string")) % n, F.lit(0))


def seeded_hash(*parts: Column | str | int) -> Column:
    """60 bits of the md5 of the parts, colon-joined, as a long: the same in any SQL engine."""
    cols = [p if isinstance(p, Column) else F.lit(str(p)) for p in parts]
    text = F.concat_ws(":", *[F.coalesce(c.cast("string"), F.lit("")) for c in cols])
    return F.conv(F.substring(F.md5(text), 1, 15), 16, 10).cast("long")


def blocks_of(items: Iterable, weight, most: int):
    """Consecutive items in lists whose weights add up to about `most`."""
    held, total = [], 0
    for x in items:
        held.append(x)
        total += weight(x)
        if total >= most:
            yield held
            held, total = [], 0
    if held:
        yield held
