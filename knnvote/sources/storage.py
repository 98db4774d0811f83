"""Where intermediate tables lie: the folder that driver and executors share."""

from __future__ import annotations

import re
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


GROUP_NUMBERS = 1 << 21  # numbers in a row group of wide rows


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir. Where it is unset, a temporary folder in local mode; on a cluster, which would not share that, an error."""
    sc = spark.sparkContext
    folder = spark.conf.get("spark.checkpoint.dir", None) or sc.getCheckpointDir()
    if not folder:
        if not re.fullmatch(r"local(\[.*\])?", sc.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        folder = tempfile.mkdtemp(prefix="shared-")
        sc.setCheckpointDir(folder)
    return folder.rstrip("/")


def work_folder(spark: SparkSession) -> str:
    """The application's own folder for intermediate tables; `clean` deletes it."""
    return f"{shared_folder(spark)}/work-{spark.sparkContext.applicationId}"


def settle(df: DataFrame, name: str = "table", width: int = 1, **options: str) -> DataFrame:
    """df as Parquet in the application's folder, read again: cuts lineage, and survives lost executors.

    width: the numbers in a row. A reader decodes up to 4,096 rows at once, but no more than a row group has, so groups of
    wide rows get few: 16 MB of doubles. options: of the writer.
    """
    path = f"{work_folder(df.sparkSession)}/{name}-{uuid.uuid4().hex}"
    writer = df.write.options(**options)
    if width > GROUP_NUMBERS // 4_096:
        writer = writer.option("parquet.block.row.count.limit", max(8 if width > GROUP_NUMBERS // 16 else 16, GROUP_NUMBERS // width))
    writer.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def clean(spark: SparkSession) -> bool:
    """Deletes the application's intermediate tables. Results that are not written elsewhere by then can't be read any more."""
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(work_folder(spark))
    return path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
