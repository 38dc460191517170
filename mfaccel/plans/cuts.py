"""Lineage cuts in the shared folder, and global row numbers without a single-task sort."""

from __future__ import annotations

import gc
import os
import tempfile

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, else, where both are one machine, a temporary one."""
    if folder := spark.conf.get("spark.checkpoint.dir", None):
        return folder.rstrip("/")
    if spark.sparkContext.master.partition("[")[0] != "local":
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    return os.path.join(tempfile.gettempdir(), "mfaccel-shared")


def cut(df: DataFrame) -> DataFrame:
    """A reliable checkpoint: it survives lost executors and keeps plans of loops short."""
    spark = df.sparkSession
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(shared_folder(spark))
    return df.checkpoint(eager=True)


def release(spark: SparkSession) -> None:
    """Lets Spark drop the files of shuffles and checkpoints that nothing refers to any more: it does so once the driver has collected their frames."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def numbered(df: DataFrame, *order: Column | str, name: str = "at") -> DataFrame:
    """Adds the position from 1 in a total order: ranges are sorted apart, and only their sizes reach the driver."""
    spark = df.sparkSession
    ranges = df.repartitionByRange(*order).sortWithinPartitions(*order)
    held = cut(ranges.select("*", F.spark_partition_id().alias("_part"), F.monotonically_increasing_id().alias("_row")))
    sizes = held.groupBy("_part").agg(F.count("*").alias("n"), F.min("_row").alias("first")).orderBy("_part").collect()
    offsets, total = [], 0
    for r in sizes:
        offsets.append((r["_part"], total - r["first"] + 1))
        total += r["n"]
    shift = F.broadcast(spark.createDataFrame(offsets, "_part int, _shift long"))  # one row per range
    return held.join(shift, "_part").withColumn(name, F.col("_row") + F.col("_shift")).drop("_part", "_row", "_shift")


def running_sums(df: DataFrame, value: str, *order: Column | str, name: str = "sum") -> DataFrame:
    """Adds the sum of a column over all rows up to each one in a total order, and `total`; ranges are summed apart, and only their sums reach the driver."""
    spark = df.sparkSession
    held = cut(df.repartitionByRange(*order).select("*", F.spark_partition_id().alias("_part")))
    totals = held.groupBy("_part").agg(F.sum(value).alias("s")).orderBy("_part").collect()
    before, rows = 0, []
    for r in totals:
        rows.append((r["_part"], before))
        before += r["s"]
    shift = F.broadcast(spark.createDataFrame(rows, f"_part int, _before {dict(df.dtypes)[value]}"))  # one row per range
    mine = F.sum(value).over(Window.partitionBy("_part").orderBy(*order))
    return held.withColumn(name, mine).join(shift, "_part").withColumn(name, F.col(name) + F.col("_before")).withColumn("total", F.lit(before)).drop("_part", "_before")
