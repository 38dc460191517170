"""Rating views over the given tables, validation, subsets and splits.

A rating table is (user bigint, item bigint, rating double), one row per known cell and nothing for a missing one.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from mfaccel.plans.cuts import numbered

SCHEMA = "user bigint, item bigint, rating double"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _brand(col: str = "p_brand") -> Column:
    return F.regexp_extract(col, r"(\d+)", 1).cast("long")


def _codes(df: DataFrame, col: str) -> DataFrame:
    """(col, code): dense codes from 0 of the few distinct values of a column, in their order."""
    return df.select(col).distinct().select(col, (F.dense_rank().over(Window.orderBy(col)) - 1).cast("long").alias("code"))


def _mean_quantity(lines: DataFrame, user: str, item: Column) -> DataFrame:
    cells = lines.select(F.col(user).cast("long").alias("user"), item.cast("long").alias("item"), "l_quantity")
    return cells.groupBy("user", "item").agg((F.avg("l_quantity") / 10).alias("rating"))


def _bought(spark: SparkSession, sf_dir: str) -> DataFrame:
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    return lines.join(orders, lines.l_orderkey == orders.o_orderkey)


def _with_part(lines: DataFrame, spark: SparkSession, sf_dir: str, *cols: str) -> DataFrame:
    part = table(spark, sf_dir, "part").select("p_partkey", *cols)
    return lines.join(part, lines.l_partkey == part.p_partkey)


def view(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """cust_part, cust_brandtype, cust_brandsize, supp_part, nation_brand, event_key, event_type or given_items."""
    if name == "cust_part":
        return _mean_quantity(_bought(spark, sf_dir), "o_custkey", F.col("l_partkey"))
    if name == "cust_brandtype":
        lines = _with_part(_bought(spark, sf_dir), spark, sf_dir, "p_brand", "p_type")
        codes = F.broadcast(_codes(table(spark, sf_dir, "part"), "p_type"))  # a handful of types
        return _mean_quantity(lines.join(codes, "p_type"), "o_custkey", _brand() * 10 + F.col("code"))
    if name == "cust_brandsize":
        lines = _with_part(_bought(spark, sf_dir), spark, sf_dir, "p_brand", "p_size")
        return _mean_quantity(lines, "o_custkey", _brand() * 50 + F.col("p_size") - 1)
    if name == "supp_part":
        return _mean_quantity(table(spark, sf_dir, "lineitem"), "l_suppkey", F.col("l_partkey"))
    if name == "nation_brand":
        lines = _with_part(_bought(spark, sf_dir), spark, sf_dir, "p_brand")
        customer = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
        return _mean_quantity(lines.join(customer, lines.o_custkey == customer.c_custkey), "c_nationkey", _brand())
    if name == "event_key":
        keyed = event_keys(table(spark, sf_dir, "events"))
        return keyed.groupBy("user", "item").agg(F.avg("value").alias("rating"))
    if name == "event_type":
        events = table(spark, sf_dir, "events").select("user_id", "event_type")
        kinds = F.broadcast(_codes(events, "event_type"))
        return events.join(kinds, "event_type").groupBy(F.col("user_id").alias("user"), F.col("code").alias("item")).agg(F.count("*").cast("double").alias("rating"))
    raise ValueError(name)


def event_keys(events: DataFrame) -> DataFrame:
    """(user, item, value, ts) of events whose JSON property has a key."""
    item = F.get_json_object("props", "$.k").cast("long")
    return events.select(F.col("user_id").alias("user"), item.alias("item"), "value", "ts").where("item IS NOT NULL")


def csv(spark: SparkSession, path: str, sep: str = ",", header: bool = False) -> tuple[DataFrame, DataFrame]:
    """Text ratings: (valid cells, malformed lines)."""
    lines = spark.read.schema(f"{SCHEMA}, bad string").csv(path, sep=sep, header=header, mode="PERMISSIVE", columnNameOfCorruptRecord="bad")
    whole = "user IS NOT NULL AND item IS NOT NULL AND rating IS NOT NULL AND bad IS NULL"
    return lines.where(whole).drop("bad"), lines.where(f"NOT coalesce({whole}, false)").select(F.coalesce("bad", F.concat_ws(sep, "user", "item", "rating")).alias("line"))


def validate(ratings: DataFrame, how: str = "mean", at: str | None = None) -> DataFrame:
    """One finite rating per cell without null keys; repeated cells by "mean" or by the "latest" of a column."""
    fine = ratings.where(F.col("user").isNotNull() & F.col("item").isNotNull() & F.col("rating").isNotNull() & ~F.isnan("rating") & (F.abs("rating") < float("inf")))
    value = F.avg("rating") if how == "mean" else F.max_by("rating", at)
    return fine.groupBy(F.col("user").cast("long").alias("user"), F.col("item").cast("long").alias("item")).agg(value.cast("double").alias("rating"))


def counts(ratings: DataFrame, side: str) -> DataFrame:
    return ratings.groupBy(F.col(side).alias("id")).agg(F.count("*").alias("n"))


def entity_counts(ratings: DataFrame) -> DataFrame:
    sides = [counts(ratings, s).select(F.lit(s).alias("side"), "id", "n") for s in ("user", "item")]
    return sides[0].unionByName(sides[1])


def profile(ratings: DataFrame) -> DataFrame:
    sums = ratings.agg(
        F.count_distinct("user").alias("n_u"), F.count_distinct("item").alias("n_m"), F.count("*").alias("nnz"),
        F.avg("rating").alias("mean"), F.min("rating").alias("low"), F.max("rating").alias("high"),
    )
    return sums.withColumn("density", F.col("nnz") / (F.col("n_u") * F.col("n_m")))


def histogram(ratings: DataFrame) -> DataFrame:
    return ratings.groupBy(F.round("rating", 1).alias("value")).agg(F.count("*").alias("n"))


def _around_median(ratings: DataFrame, side: str, k: int) -> DataFrame:
    """Ids of the k entities around the median by count downwards, ties by id."""
    ordered = numbered(counts(ratings, side), F.desc("n"), F.asc("id"))
    middle = (ordered.count() + 1) // 2
    return ordered.where(F.col("at").between(middle - k // 2, middle + (k + 1) // 2 - 1)).select(F.col("id").alias(side))


def median_subset(ratings: DataFrame, n_u: int, n_m: int) -> DataFrame:
    """Cells of n_u users around the median of ratings a user, then of n_m items chosen likewise among those cells."""
    mine = ratings.join(_around_median(ratings, "user", n_u), "user", "left_semi")
    return mine.join(_around_median(mine, "item", n_m), "item", "left_semi").select("user", "item", "rating")


def minimum_count(ratings: DataFrame, side: str, least: int) -> DataFrame:
    return ratings.join(counts(ratings, side).where(F.col("n") >= least).select(F.col("id").alias(side)), side, "left_semi").select("user", "item", "rating")


def hash_split(ratings: DataFrame, seed: int = 42, tenths: int = 2) -> DataFrame:
    """Adds `held`: true for about `tenths` tenths of the cells, by a hash of seed, user and item."""
    digit = F.conv(F.substring(F.md5(F.concat_ws(":", F.lit(seed), "user", "item").cast("binary")), 1, 8), 16, 10).cast("long") % 10
    return ratings.withColumn("held", digit < tenths)


def temporal_split(spark: SparkSession, sf_dir: str, day: str) -> DataFrame:
    """Cells of customers and parts with `late`: true for cells that were first shipped on the day or after it."""
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_partkey", "l_quantity", "l_shipdate")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    cells = lines.join(orders, lines.l_orderkey == orders.o_orderkey).groupBy(F.col("o_custkey").alias("user"), F.col("l_partkey").alias("item"))
    return cells.agg((F.avg("l_quantity") / 10).alias("rating"), (F.min("l_shipdate") >= F.lit(day).cast("timestamp")).alias("late"))
