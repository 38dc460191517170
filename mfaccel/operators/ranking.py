"""Agreement of two rankings on the first t places of a reference, as adjacent swaps.

The swaps that bring the reference's first t items, in order, to the front of another ranking have a closed form: for
the k-th of them its place there less one, less the number of earlier ones that stand before it.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def positions(scores: DataFrame) -> DataFrame:
    """(user, item, rk): places from 1 by score downwards, ties by item."""
    return scores.select("user", "item", F.row_number().over(Window.partitionBy("user").orderBy(F.desc("score"), "item")).alias("rk"))


def distance(reference: DataFrame, other: DataFrame, t: int) -> DataFrame:
    """(user, s): swaps for each user, from two frames of scores."""
    top = positions(reference).where(F.col("rk") <= t).withColumnRenamed("rk", "k")
    placed = top.join(positions(other).withColumnRenamed("rk", "pos"), ["user", "item"]).select("user", "k", "pos")
    ahead = placed.select("user", F.col("k").alias("k2"), F.col("pos").alias("pos2"))
    pairs = placed.join(ahead, "user").where("k2 < k AND pos2 < pos").groupBy("user").agg(F.count("*").alias("ahead"))  # at most t * t a user
    sums = placed.groupBy("user").agg(F.sum(F.col("pos") - 1).alias("moves"))
    return sums.join(pairs, "user", "left").select("user", (F.col("moves") - F.coalesce("ahead", F.lit(0))).alias("s"))


def max_distance(n_m: int, t: int) -> float:
    return t * (2 * n_m - t - 1) / 2


def accuracy(reference: DataFrame, other: DataFrame, t: int) -> DataFrame:
    """Mean over users of 1 less the share of the most swaps possible."""
    sizes = reference.groupBy("user").agg(F.count("*").alias("n_m"))
    most = F.lit(t) * (2 * F.col("n_m") - t - 1) / 2
    return distance(reference, other, t).join(sizes, "user").agg(F.avg(1 - F.col("s") / most).alias("q"))


def stable_top(reference: DataFrame, other: DataFrame, t: int) -> DataFrame:
    """Items that are among the first t of both."""
    tops = [positions(x).where(F.col("rk") <= t).select("user", "item") for x in (reference, other)]
    return tops[0].intersect(tops[1])


def first_places(scores: np.ndarray, t: int) -> np.ndarray:
    """The first t items of every user, ties by item, of a score matrix (users by items) in memory."""
    return np.argsort(-scores, axis=1, kind="stable")[:, :t]


def accuracy_of_places(first: np.ndarray, other: np.ndarray, t: int) -> float:
    """accuracy() of scores in memory against the first t items of a reference."""
    n_m = other.shape[1]
    places = np.empty(other.shape, np.int64)
    np.put_along_axis(places, np.argsort(-other, axis=1, kind="stable"), np.arange(n_m)[None, :], axis=1)
    pos = np.take_along_axis(places, first, axis=1)
    ahead = (pos[:, :, None] > pos[:, None, :]) & np.tri(t, k=-1, dtype=bool)
    swaps = pos.sum(axis=1) - ahead.sum(axis=(1, 2))
    return float((1 - swaps / max_distance(n_m, t)).mean())


def accuracy_dense(reference: np.ndarray, other: np.ndarray, t: int) -> float:
    return accuracy_of_places(first_places(reference, t), other, t)


def distance_by_swaps(reference: list, other: list, t: int) -> int:
    """The definition itself, item by item; for tests."""
    left, swaps = list(other), 0
    for k, item in enumerate(reference[:t]):
        at = left.index(item)
        swaps += at - k
        left.insert(k, left.pop(at))
    return swaps
