"""Synthetic ratings of any number of users by the empirical laws of a table, and ratings planted from known factors.

A law is sampled by picking a row: the count of a random user, the item of a random rating, the value of a random rating.
Rows are numbered once, so a draw is an equi-join on a uniform position: no range join, no table of laws in a task, and
popular items spread evenly over positions.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from mfaccel.functions.vectors import unit_hash
from mfaccel.plans.cuts import numbered, running_sums
from mfaccel.sources.ratings import counts


def law(values: DataFrame, value: str) -> DataFrame:
    """(value, n, cum): cumulative share of a column's distinct values, in order."""
    sizes = values.groupBy(F.col(value).alias("value")).agg(F.count("*").alias("n"))
    return running_sums(sizes, "n", "value", name="cum").select("value", "n", (F.col("cum") / F.col("total")).alias("cum"))


def laws(ratings: DataFrame) -> dict[str, DataFrame]:
    return {"count": law(counts(ratings, "user"), "n"), "item": law(ratings, "item"), "rating": law(ratings.select(F.round("rating", 1).alias("rating")), "rating")}


def expand(ratings: DataFrame, n_u: int, seed: int = 42, spare: int = 4) -> DataFrame:
    """Users 0..n_u-1. Each draws a count, then twice as many items and `spare` more, and keeps the first distinct ones up to
    the count; a rating's value is drawn for each cell kept. Where the draws hold fewer distinct items the user gets fewer ratings:
    shortfall() counts them."""
    valued = _drawn(ratings, n_u, seed, spare).where("k <= count").withColumn("at", _spot(seed, "value", ratings.count(), F.col("user"), F.col("item")))
    return valued.join(numbered(ratings.select("item", "user", "rating"), "item", "user").select("at", "rating"), "at").select("user", "item", "rating")


def shortfall(ratings: DataFrame, n_u: int, seed: int = 42, spare: int = 4) -> DataFrame:
    """(wanted, made, short_users): ratings that expand() draws counts for, those that it makes, and users with fewer than their count."""
    each = _drawn(ratings, n_u, seed, spare).groupBy("user").agg(F.first("count").alias("count"), F.max("k").alias("found"))
    made = F.least("found", "count")
    return each.agg(F.sum("count").alias("wanted"), F.sum(made).cast("long").alias("made"), F.count_if(made < F.col("count")).alias("short_users"))


def _spot(seed: int, what: str, size: int, *keys: Column) -> Column:
    return (F.floor(unit_hash(seed, F.lit(what), *keys) * size) + 1).cast("long")


def _drawn(ratings: DataFrame, n_u: int, seed: int, spare: int) -> DataFrame:
    """(user, item, draw, count, k): distinct items of every user in the order of their draws."""
    spark = ratings.sparkSession
    cells = numbered(ratings.select("item", "user"), "item", "user")
    users = numbered(counts(ratings, "user"), "n", "id")
    n_cells, n_users = cells.count(), users.count()
    spot = lambda *what: _spot(seed, *what)
    new = spark.range(n_u).select(F.col("id").alias("user"), spot("count", n_users, F.col("id")).alias("at"))
    new = new.join(users.select("at", F.col("n").alias("count")), "at").select("user", "count")
    draws = new.select("user", "count", F.explode(F.sequence(F.lit(0), 2 * F.col("count") + (spare - 1))).alias("draw"))
    draws = draws.withColumn("at", spot("item", n_cells, F.col("user"), F.col("draw")))
    items = draws.join(cells.select("at", "item"), "at").groupBy("user", "item").agg(F.min("draw").alias("draw"), F.first("count").alias("count"))
    return items.withColumn("k", F.row_number().over(Window.partitionBy("user").orderBy("draw")))


def planted(pattern: DataFrame, rank: int, noise: float, seed: int = 7) -> DataFrame:
    """Ratings on the pattern's cells from hashed factors, plus noise, rounded to tenths within 0.1 and 5."""
    u = [unit_hash(seed, F.lit("user"), F.col("user"), k) for k in range(rank)]
    m = [unit_hash(seed, F.lit("item"), F.col("item"), k) for k in range(rank)]
    dot = sum((a * b for a, b in zip(u, m, strict=True)), F.lit(0.0)) * (5 / max(1.0, rank / 3))
    shift = (unit_hash(seed, F.lit("noise"), F.col("user"), F.col("item")) - 0.5) * (2 * math.sqrt(3) * noise)
    return pattern.select("user", "item", F.greatest(F.lit(0.1), F.least(F.lit(5.0), F.round(dot + shift, 1))).alias("rating"))
