"""Rating streams from files of events: windowed counts, deduplication, latest values, folding into a model.

The same functions take batch and streaming frames, which is also how they are tested.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.query import StreamingQuery

from mfaccel.operators.recommend import fold_in
from mfaccel.sources.ratings import event_keys

EVENTS = "event_id bigint, ts timestamp, user_id bigint, event_type string, value double, props string"


def events(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(EVENTS).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def ratings(events_df: DataFrame, late: str = "1 hour") -> DataFrame:
    """(user, item, value, ts), each event once, events later than the watermark dropped."""
    return event_keys(events_df.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"]) if events_df.isStreaming else events_df.dropDuplicates(["event_id"]))


def tumbling(events_df: DataFrame, width: str = "1 day") -> DataFrame:
    return events_df.groupBy(F.window("ts", width).alias("w"), F.col("user_id").alias("user")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user", "n")


def sliding(events_df: DataFrame, width: str = "1 day", step: str = "12 hours") -> DataFrame:
    return events_df.groupBy(F.window("ts", width, step).alias("w"), F.col("user_id").alias("user")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user", "n")


def sessions(events_df: DataFrame, gap: str = "6 hours") -> DataFrame:
    return events_df.groupBy(F.session_window("ts", gap).alias("w"), F.col("user_id").alias("user")).agg(F.count("*").alias("n")).select(F.col("w.start").alias("start"), "user", "n")


def latest(rated: DataFrame) -> DataFrame:
    """(user, item, rating): the newest value of each cell of a stream, by state kept for each cell."""

    def keep(key, pdfs: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        best = state.get if state.exists else (pd.Timestamp.min.value, float("nan"))
        for pdf in pdfs:
            row = pdf.sort_values(["ts", "value"]).iloc[-1]
            best = max(best, (int(row.ts.value), float(row.value)))
        state.update(best)
        yield pd.DataFrame({"user": [key[0]], "item": [key[1]], "rating": [best[1]]})

    return rated.groupBy("user", "item").applyInPandasWithState(keep, "user bigint, item bigint, rating double", "at bigint, rating double", "update", "NoTimeout")


def fold_in_stream(rated: DataFrame, items: DataFrame, rank: int, lam: float, history: str, out: str, checkpoint: str) -> StreamingQuery:
    """Each batch appends its cells to `history` and writes new vectors of its users, from all their cells so far."""

    def each(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch.select("user", "item", "value").withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{history}/part={number}")
        mine = spark.read.parquet(history).join(batch.select("user").distinct(), "user", "left_semi")
        cells = mine.groupBy("user", "item").agg(F.avg("value").alias("rating"))
        fold_in(cells, items, rank, lam).withColumn("batch", F.lit(number)).write.mode("overwrite").parquet(f"{out}/part={number}")

    return rated.writeStream.foreachBatch(each).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
