"""What the accelerated method is compared with: Spark ML's estimator, plain conjugate gradients, steepest descent,
stochastic gradient descent, coordinate descent, and the singular value decomposition of a full matrix."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mfaccel.functions.vectors import hashed_start
from mfaccel.operators.distributed import Fit, StopRule, _array, _lists, fit
from mfaccel.plans.blocks import block_of
from mfaccel.plans.cuts import cut


def plain_cg(ratings: DataFrame, rank: int, lam: float, stop: StopRule, **options) -> Fit:
    """Nonlinear conjugate gradients without a preconditioner."""
    return fit(ratings, rank, lam, stop=stop, precond="gradient", rule="pr", **options)


def steepest_descent(ratings: DataFrame, rank: int, lam: float, stop: StopRule, **options) -> Fit:
    return fit(ratings, rank, lam, stop=stop, precond="gradient", rule="zero", **options)


def coordinate_descent(ratings: DataFrame, rank: int, lam: float, stop: StopRule, **options) -> Fit:
    """Passes over single components, without acceleration."""
    return fit(ratings, rank, lam, algo="als", stop=stop, precond="coordinate", **options)


def mllib_als(ratings: DataFrame, rank: int, lam: float, sweeps: int, seed: int = 42, **options):
    """Spark ML's blocked ALS in single precision; its start cannot be given, so compare final losses."""
    from pyspark.ml.recommendation import ALS

    known = ratings.select(F.col("user").cast("int"), F.col("item").cast("int"), F.col("rating").cast("float"))
    model = ALS(rank=rank, regParam=lam, maxIter=sweeps, seed=seed, userCol="user", itemCol="item", ratingCol="rating", **options).fit(known)
    sides = [f.select(F.col("id").cast("bigint").alias("id"), F.col("features").cast("array<double>").alias("x")) for f in (model.userFactors, model.itemFactors)]
    return model, sides[0], sides[1]


def sgd(ratings: DataFrame, rank: int, lam: float, epochs: int = 5, rate: float = 0.05, n_blocks: int = 4, seed: int = 42) -> tuple[DataFrame, DataFrame]:
    """Stochastic gradient descent in strata: in each of n_blocks turns an epoch, user block b meets item block
    (b + turn) mod n_blocks, so that blocks share no vector and run side by side."""
    cells = ratings.select(block_of("user", n_blocks).alias("ublk"), block_of("item", n_blocks).alias("iblk"), "user", "item", "rating").repartition(n_blocks, "ublk").persist()
    users, items = (cut(hashed_start(ratings.select(F.col(s).alias("id")).distinct(), s, rank, seed).withColumn("blk", block_of("id", n_blocks))) for s in ("user", "item"))
    schema = "side int, id bigint, blk int, x array<double>"

    def turn_of(turn: int, step: float):
        def run(left: pa.Table, right: pa.Table) -> pa.Table:
            sides = [right.filter(pa.array(right["side"].to_numpy() == k)).sort_by("id") for k in (0, 1)]
            ids, x = [t["id"].to_numpy() for t in sides], [_array(t["x"], rank).copy() for t in sides]
            u, m = (np.searchsorted(i, left[c].to_numpy()) for i, c in zip(ids, ("user", "item"), strict=True))
            order = np.random.default_rng((seed, turn)).permutation(len(u))
            for k, j, r in zip(u[order], m[order], left["rating"].to_numpy()[order], strict=True):
                a, b = x[0][k], x[1][j]
                e = r - a @ b
                x[0][k], x[1][j] = a + step * (e * b - lam * a), b + step * (e * a - lam * b)
            parts = [pa.Table.from_arrays([t["side"], t["id"], t["blk"], _lists(v)], ["side", "id", "blk", "x"]) for t, v in zip(sides, x, strict=True)]
            return pa.concat_tables([p.cast(parts[0].schema) for p in parts])

        return run

    for epoch in range(epochs):
        for turn in range(n_blocks):
            meets = F.pmod(F.col("blk") - turn, F.lit(n_blocks)).cast("int")
            both = users.select(F.col("blk").alias("to"), F.lit(0).alias("side"), "id", "blk", "x").unionByName(items.select(meets.alias("to"), F.lit(1).alias("side"), "id", "blk", "x"))
            mine = cells.where(F.col("iblk") == F.pmod(F.col("ublk") + turn, F.lit(n_blocks)))
            new = cut(mine.groupBy("ublk").cogroup(both.groupBy("to")).applyInArrow(turn_of(epoch * n_blocks + turn, rate / (1 + epoch)), schema))
            users, items = (new.where(F.col("side") == k).select("id", "blk", "x") for k in (0, 1))
    cells.unpersist()
    return users.select("id", "x"), items.select("id", "x")


def svd_loss(full: np.ndarray, rank: int) -> float:
    """The least squared error of any factorisation of a full matrix."""
    values = np.linalg.svd(full, compute_uv=False)
    return float((values[rank:] ** 2).sum())
