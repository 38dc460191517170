"""Measures over run traces: a frame (run, algo, iter, t_sec, gnorm, ...), one row per iteration of a run.

Traces are small; everything is still a query, so traces of many runs can be appended to a table and measured there.
"""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

SCHEMA = "run int, algo string, iter int, t_sec double, loss double, gnorm double, alpha double, beta double, restart boolean, ckpt boolean"


def frame(spark: SparkSession, rows: Sequence[dict], run: int = 0) -> DataFrame:
    """`ckpt` tells the iterations in which the fit did save its state."""
    data = [(run, r.get("algo", "als"), r["iter"], float(r["t_sec"]), float(r["loss"]), float(r["gnorm"]), float(r["alpha"]), float(r["beta"]), bool(r["restart"]), bool(r.get("ckpt", False))) for r in rows]
    return spark.createDataFrame(data, SCHEMA)


def first_hits(trace: DataFrame, below: float, measure: str = "gnorm", at: str = "iter") -> DataFrame:
    """(algo, run, hit): the first value of `at` at which the measure is below; null if it never is."""
    return trace.groupBy("algo", "run").agg(F.min(F.when(F.col(measure) < below, F.col(at))).alias("hit"))


def _summed(hits: DataFrame, *keys: str) -> DataFrame:
    return hits.groupBy("algo", *keys).agg(
        F.avg("hit").cast("double").alias("mean"), F.stddev("hit").alias("std"), F.count("hit").alias("converged"), F.count_if(F.isnull("hit")).alias("nonconverged"),
    )


def iterations_to(trace: DataFrame, below: float) -> DataFrame:
    """Mean and deviation over the runs that get below, and how many do not."""
    return _summed(first_hits(trace, below))


def time_to(trace: DataFrame, below: float) -> DataFrame:
    return _summed(first_hits(trace, below, at="t_sec"))


def time_to_accuracy(trace: DataFrame, thresholds: Sequence[float]) -> DataFrame:
    """The same for the first time at which the accuracy q reaches each threshold."""
    levels = F.explode(F.array(*[F.lit(float(t)) for t in thresholds])).alias("threshold")
    hits = trace.select("*", levels).groupBy("algo", "run", "threshold").agg(F.min(F.when(F.col("q") >= F.col("threshold"), F.col("t_sec"))).alias("hit"))
    return _summed(hits, "threshold")


def acceleration(summary: DataFrame, *keys: str) -> DataFrame:
    """Mean of plain sweeps over mean of the accelerated method."""
    mean = lambda algo: F.max(F.when(F.col("algo") == algo, F.col("mean")))
    grouped = summary.groupBy(*keys) if keys else summary.groupBy()
    return grouped.agg(mean("als").alias("als"), mean("accelerated").alias("accelerated")).withColumn("factor", F.col("als") / F.col("accelerated"))


def bands(trace: DataFrame, by: str = "iter", width: float = 3) -> DataFrame:
    """Mean and deviation of the gradient norm over all runs in windows that do not overlap."""
    bucket = F.floor(F.col("iter" if by == "iter" else "t_sec") / width)
    return trace.groupBy("algo", bucket.alias("bucket")).agg(F.avg("gnorm").alias("mean"), F.stddev("gnorm").alias("std"))


def resample(trace: DataFrame, step: float, steps: int, value: str = "q") -> DataFrame:
    """(algo, t, mean): at each time of a grid the last value so far, mean over the runs that have one."""
    grid = trace.select("algo", "run").distinct().select("algo", "run", F.explode(F.sequence(F.lit(0), F.lit(steps))).alias("k"))
    points = grid.select("algo", "run", (F.col("k") * step).alias("t"), F.lit(None).cast("double").alias("v"), F.col("k"), F.lit(None).cast("long").alias("iter"))
    both = trace.select("algo", "run", F.col("t_sec").alias("t"), F.col(value).alias("v"), F.lit(None).cast("int").alias("k"), F.col("iter").cast("long").alias("iter")).unionByName(points)
    order = Window.partitionBy("algo", "run").orderBy("t", F.col("k").asc_nulls_first(), "iter").rowsBetween(Window.unboundedPreceding, 0)
    held = both.withColumn("v", F.last("v", ignorenulls=True).over(order)).where("k IS NOT NULL")
    return held.groupBy("algo", "t").agg(F.avg("v").alias("mean"))


def iteration_seconds(trace: DataFrame) -> DataFrame:
    before = F.lag("t_sec").over(Window.partitionBy("algo", "run").orderBy("iter"))
    return trace.withColumn("seconds", F.col("t_sec") - before).where("seconds IS NOT NULL")


def time_per_iteration(trace: DataFrame) -> DataFrame:
    """Mean seconds, with the deviation inside the two groups, iterations with and without a checkpoint."""
    groups = iteration_seconds(trace).groupBy("algo", "ckpt").agg(F.count("*").alias("n"), F.sum("seconds").alias("total"), F.coalesce(F.var_samp("seconds"), F.lit(0.0)).alias("var"))
    return groups.groupBy("algo").agg((F.sum("total") / F.sum("n")).alias("mean"), F.sqrt(F.sum(F.col("n") * F.col("var")) / F.sum("n")).alias("std"))


def linear_fit(points: DataFrame, x: str = "n_u", y: str = "seconds", *keys: str) -> DataFrame:
    return points.groupBy(*keys).agg(F.regr_slope(y, x).alias("slope"), F.regr_intercept(y, x).alias("intercept"), F.regr_r2(y, x).alias("r2"))


def smoothed(trace: DataFrame) -> DataFrame:
    """Adds the mean of the gradient norm and the one before it."""
    return trace.withColumn("smooth", F.avg("gnorm").over(Window.partitionBy("algo", "run").orderBy("iter").rowsBetween(-1, 0)))


def first_reach(trace: DataFrame) -> DataFrame:
    """(run, iter, smooth, hit): for each smoothed accelerated value the first plain iteration that is at or below it.
    Only plain iterations below all before them matter; among those a value's iteration is the one with the largest norm that does not
    exceed it, so one pass in the order of the norms meets each value with its step."""
    fast = smoothed(trace.where("algo = 'accelerated'")).select("run", F.col("smooth").alias("norm"), F.lit(1).alias("turn"), "iter")
    earlier = Window.partitionBy("run").orderBy("iter").rowsBetween(Window.unboundedPreceding, -1)
    steps = trace.where("algo = 'als'").withColumn("least", F.min("gnorm").over(earlier)).where("least IS NULL OR gnorm < least")
    both = steps.select("run", F.col("gnorm").alias("norm"), F.lit(0).alias("turn"), "iter").unionByName(fast)
    order = Window.partitionBy("run").orderBy("norm", "turn").rowsBetween(Window.unboundedPreceding, 0)
    met = both.withColumn("hit", F.last(F.when(F.col("turn") == 0, F.col("iter")), ignorenulls=True).over(order))
    return met.where("turn = 1").select("run", "iter", F.col("norm").alias("smooth"), "hit")


def speedup(trace: DataFrame) -> DataFrame:
    """Adds to first_reach() the factor: ratio of iterations times ratio of mean seconds an iteration."""
    mean = iteration_seconds(trace).groupBy("run").agg(F.avg(F.when(F.col("algo") == "als", F.col("seconds"))).alias("t_als"), F.avg(F.when(F.col("algo") == "accelerated", F.col("seconds"))).alias("t_fast"))
    hits = first_reach(trace).where("iter > 0 AND hit IS NOT NULL")
    return hits.join(mean, "run").select("run", "iter", "smooth", "hit", (F.col("hit") * F.col("t_als") / (F.col("iter") * F.col("t_fast"))).alias("factor"))


def cost_ratio(trace: DataFrame) -> DataFrame:
    mean = iteration_seconds(trace).groupBy().agg(F.avg(F.when(F.col("algo") == "accelerated", F.col("seconds"))).alias("accelerated"), F.avg(F.when(F.col("algo") == "als", F.col("seconds"))).alias("als"))
    return mean.withColumn("ratio", F.col("accelerated") / F.col("als"))
