"""Vectors as array<double> columns, and block vector operations on frames keyed by (side, id)."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def _col(x: Column | str) -> Column:
    return F.col(x) if isinstance(x, str) else x


def vdot(x: Column | str, y: Column | str) -> Column:
    return F.aggregate(F.zip_with(_col(x), _col(y), lambda a, b: a * b), F.lit(0.0), lambda s, v: s + v)


def vaxpby(a, x: Column | str, b, y: Column | str) -> Column:
    a, b = (F.lit(float(v)) if not isinstance(v, Column) else v for v in (a, b))
    return F.zip_with(_col(x), _col(y), lambda s, t: a * s + b * t)


def vscale(a, x: Column | str) -> Column:
    return F.transform(_col(x), lambda v: v * a)


def vnorm2(x: Column | str) -> Column:
    return F.aggregate(_col(x), F.lit(0.0), lambda s, v: s + v * v)


def vzeros(rank: int) -> Column:
    return F.array_repeat(F.lit(0.0), rank)


def vpack_outer(x: Column | str, rank: int) -> Column:
    """Upper triangle of x xT, row by row."""
    return F.array(*[_col(x)[k] * _col(x)[m] for k in range(rank) for m in range(k, rank)])


def unit_hash(*parts: Column | str | int) -> Column:
    """Uniform in [0, 1) from the MD5 of the parts joined by colons; any engine can replay it."""
    text = F.concat_ws(":", *[F.lit(str(p)) if isinstance(p, int) else _col(p).cast("string") for p in parts])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("double") / F.lit(2.0**32)


def start_vector(side: str, rank: int, seed: int = 42) -> Column:
    """Components uniform in [0, 1) over the square root of the rank, by hashes of seed, side, id and place."""
    return F.array(*[unit_hash(seed, F.lit(side), F.col("id"), k) / math.sqrt(rank) for k in range(rank)])


def hashed_start(ids: DataFrame, side: str, rank: int, seed: int = 42) -> DataFrame:
    """(id, x)"""
    return ids.select("id", start_vector(side, rank, seed).alias("x"))


def random_start(ids: DataFrame, rank: int, seed: int = 42) -> DataFrame:
    return ids.select("id", F.array(*[F.rand(seed + k) / math.sqrt(rank) for k in range(rank)]).alias("x"))


def axpby(a: float, x: DataFrame, b: float, y: DataFrame) -> DataFrame:
    """a x + b y of two block vectors (side, id, x); frames of one partitioning join without an exchange."""
    return x.join(y.select("side", "id", F.col("x").alias("y")), ["side", "id"]).select("side", "id", vaxpby(a, "x", b, "y").alias("x"))


def dot(x: DataFrame, y: DataFrame) -> DataFrame:
    both = x.join(y.select("side", "id", F.col("x").alias("y")), ["side", "id"])
    return both.agg(F.sum(vdot("x", "y")).alias("value"))


def norm(x: DataFrame) -> DataFrame:
    return x.agg(F.sqrt(F.sum(vnorm2("x"))).alias("value"))
