"""Fitted factors as Parquet by side, with a small manifest."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def save(users: DataFrame, items: DataFrame, path: str, **about) -> None:
    both = users.select(F.lit("user").alias("side"), "id", "x").unionByName(items.select(F.lit("item").alias("side"), "id", "x"))
    both.write.mode("overwrite").partitionBy("side").parquet(f"{path}/factors")
    about_row = users.sparkSession.createDataFrame([(json.dumps(about, sort_keys=True),)], "value string")
    about_row.coalesce(1).write.mode("overwrite").text(f"{path}/about")


def load(spark: SparkSession, path: str) -> tuple[DataFrame, DataFrame, dict]:
    factors = spark.read.parquet(f"{path}/factors")
    sides = [factors.where(F.col("side") == s).select("id", "x") for s in ("user", "item")]
    return sides[0], sides[1], json.loads(spark.read.text(f"{path}/about").first().value)
