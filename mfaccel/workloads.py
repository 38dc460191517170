"""The experiments on the given tables: convergence from shared starts, ranking accuracy, scaling, speedup, ablations."""

from __future__ import annotations

import os
import time
from collections.abc import Sequence

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mfaccel.operators import baselines, distributed, ranking, serial, synthetic, trace
from mfaccel.operators.conjugate import RULES
from mfaccel.plans.blocks import layout, routing_volume
from mfaccel.plans.cuts import cut
from mfaccel.sources.ratings import median_subset, view

#: Users, items, and the rating view that has enough cells around its median.
SUBSETS = {"100x40": (100, 40, "cust_part"), "400x80": (400, 80, "cust_brandtype"), "800x160": (800, 160, "cust_brandsize"), "1600x320": (1600, 320, "cust_brandsize"), "3200x640": (3200, 640, "cust_brandsize")}
#: Fixed values of the serial experiments: starts, tolerance, most iterations, places of the ranking, and the accuracies that are timed.
STARTS, TOLERANCE, MOST, TOP, LEVELS = 20, 1e-6, 10_000, 20, (0.7, 0.8, 0.9, 1.0)
_TRACE = "size string, algo string, run int, iter int, t_sec double, loss double, gnorm double, q double, done boolean, alpha double, beta double, restart boolean"


def subset(spark: SparkSession, sf_dir: str, size: str) -> DataFrame:
    n_u, n_m, name = SUBSETS[size]
    return median_subset(view(spark, sf_dir, name), n_u, n_m)


def multi_start(
    cells: DataFrame, size: str, starts: int, rank: int = 10, lam: float = 0.1, gnorm: float = TOLERANCE, iterations: int = MOST, t: int = 0, algos: Sequence[str] = ("als", "accelerated"),
    rule: str = "pr_pre", search: str = "more_thuente", precond: str = "als", seconds: float = float("inf"),
) -> DataFrame:
    """Traces of both methods from the same random starts: one small problem, sent to one task for each (method, start), which computes on one
    thread. With t the ranking accuracy q of each iteration, against the run's own last one if that converged, else null."""
    spark = cells.sparkSession
    held = cells.toPandas()  # a subset of fixed size
    shared = spark.sparkContext.broadcast(tuple(held[c].to_numpy() for c in ("user", "item", "rating")))
    pairs = [(k, a, s) for k, (a, s) in enumerate((a, s) for a in algos for s in range(starts))]
    # One by one: a hash would give some tasks several runs and others none.
    todo = spark.createDataFrame(pairs, "at int, algo string, run int").repartitionById(len(pairs), "at")

    def one(algo: str, run: int) -> pd.DataFrame:
        problem = serial.Serial(*shared.value, rank, lam)
        start, stop = problem.start(run), serial.Stop(gnorm=gnorm, iterations=iterations, seconds=seconds)
        if algo == "als":
            done = problem.fit_als(*start, stop, keep_factors=t > 0)
        else:
            done = problem.fit_accelerated(*start, stop, rule=rule, search=search, precond=precond, keep_factors=t > 0)
        out = pd.DataFrame(done.trace)
        out["q"] = _accuracies(done, t) if t and done.converged else np.nan
        return out.assign(size=size, algo=algo, run=run)[[c.split()[0] for c in _TRACE.split(", ")]]

    def each(frames):
        for pdf in frames:
            for algo, run in zip(pdf.algo, pdf.run, strict=True):
                yield one(algo, int(run))

    return cut(todo.mapInPandas(each, _TRACE))


def _accuracies(done: serial.Run, t: int) -> list[float]:
    score = lambda pair: pair[0].astype(np.float64) @ pair[1].astype(np.float64).T
    final = ranking.first_places(score(done.factors[-1]), t)
    return [ranking.accuracy_of_places(final, score(pair), t) for pair in done.factors]


def convergence(spark: SparkSession, sf_dir: str, size: str = "400x80", starts: int = STARTS, **options) -> DataFrame:
    return multi_start(subset(spark, sf_dir, size), size, starts, **options)


def convergence_table(spark: SparkSession, sf_dir: str, size: str, starts: int = STARTS, **options) -> DataFrame:
    """(size, measure, als, als_std, accelerated, accelerated_std, factor, als_open, accelerated_open): iterations and seconds to the tolerance, over the
    runs that get there; how many do not."""
    runs = convergence(spark, sf_dir, size, starts, **options)
    goal = options.get("gnorm", TOLERANCE)
    both = [f(runs, goal).select(F.lit(size).alias("size"), F.lit(name).alias("measure"), "*") for name, f in (("iterations", trace.iterations_to), ("seconds", trace.time_to))]
    return _side_by_side(both[0].unionByName(both[1]), "size", "measure")


def accuracy_table(spark: SparkSession, sf_dir: str, size: str, starts: int = STARTS, **options) -> DataFrame:
    """(size, threshold, ...): seconds to each ranking accuracy, over the converged runs."""
    runs = convergence(spark, sf_dir, size, starts, t=TOP, **options).where("NOT isnan(q)")
    return _side_by_side(trace.time_to_accuracy(runs, LEVELS).select(F.lit(size).alias("size"), "*"), "size", "threshold")


def accuracy_curve(spark: SparkSession, sf_dir: str, size: str = "400x80", starts: int = STARTS, step: float = 0.05, steps: int = 60, **options) -> DataFrame:
    """(algo, t, mean): mean ranking accuracy over time."""
    return trace.resample(convergence(spark, sf_dir, size, starts, t=TOP, **options).where("NOT isnan(q)"), step, steps)


def _side_by_side(summary: DataFrame, *keys: str) -> DataFrame:
    cols = []
    for algo in ("als", "accelerated"):
        of = lambda c, algo=algo: F.max(F.when(F.col("algo") == algo, F.col(c)))
        cols += [of("mean").alias(algo), of("std").alias(f"{algo}_std"), of("nonconverged").alias(f"{algo}_open")]
    return summary.groupBy(*keys).agg(*cols).withColumn("factor", F.col("als") / F.col("accelerated"))


def ablation(spark: SparkSession, sf_dir: str, iterations: int = 60) -> DataFrame:
    """(kind, name, iterations, loss, gnorm): rules of the weight, searches, and preconditioners on the smallest subset."""
    cells = subset(spark, sf_dir, "100x40")
    kinds = [("rule", r, {"rule": r}) for r in RULES]
    kinds += [("search", s, {"search": s}) for s in ("backtracking", "exact", "more_thuente", "backtracking_direct", "more_thuente_direct")]
    kinds += [("precond", p, {"precond": p}) for p in ("als", "als_items_first", "coordinate", "nonnegative", "gradient")]
    out = None
    for kind, name, options in kinds:
        last = multi_start(cells, "100x40", 1, rank=5, iterations=iterations, algos=("accelerated",), **options)
        row = last.groupBy().agg(F.max("iter").alias("iterations"), F.min("loss").alias("loss"), F.min_by("gnorm", "iter").alias("gnorm_first"), F.max_by("gnorm", "iter").alias("gnorm"))
        row = row.select(F.lit(kind).alias("kind"), F.lit(name).alias("name"), "iterations", "loss", "gnorm")
        out = row if out is None else out.unionByName(row)
    return out


def search_cost(spark: SparkSession, sf_dir: str, iterations: int = 1, rank: int = 5, **options) -> DataFrame:
    """(search, comm, iterations, seconds, loss): the block engine with the quartic's one exchange a search, by the fused and the separate schedule, and
    with an exchange for each trial step."""
    rows = []
    for search, comm in (("backtracking", "fused"), ("backtracking", "paper"), ("backtracking_direct", "fused")):
        done = distributed.fit(subset(spark, sf_dir, "400x80"), rank, 0.1, stop=distributed.StopRule(0.0, iterations), search=search, comm=comm, **options).trace
        rows.append((search, comm, iterations, (done[-1]["t_sec"] - done[0]["t_sec"]) / iterations, done[-1]["loss"]))
    return spark.createDataFrame(rows, "search string, comm string, iterations int, seconds double, loss double")


def both_traces(spark: SparkSession, ratings: DataFrame, rank: int, lam: float, iterations: int, seeds: Sequence[int] = (42,), n_blocks: int | None = None, saves_every: int = 0, **options) -> DataFrame:
    """Traces of both methods in the block engine, from shared starts, with twice as many plain sweeps as accelerated iterations. A start comes
    of hashes, so each method makes it anew rather than holding it through both. With saves_every the state is saved so often, and those iterations are marked."""
    plan = layout(ratings, n_blocks)
    engine = distributed.Engine(plan, rank, lam)
    rows, out = [], None
    folder = f"{spark.sparkContext.getCheckpointDir()}/runs-{os.urandom(8).hex()}"
    for run, seed in enumerate(seeds):
        saves = lambda algo, run=run: distributed.Saves(f"{folder}/{algo}-{run}", saves_every) if saves_every else None
        rows = engine.fit_als(engine.start(seed), distributed.StopRule(0.0, 2 * iterations), saves=saves("als")).trace
        rows += engine.fit_accelerated(engine.start(seed), distributed.StopRule(0.0, iterations), saves=saves("accelerated"), **options).trace
        one = trace.frame(spark, rows, run)
        out = one if out is None else out.unionByName(one)
    plan.close()
    return out


def full_run(spark: SparkSession, sf_dir: str, name: str = "cust_part", rank: int = 100, lam: float = 0.01, iterations: int = 10, seeds: Sequence[int] = (42,), **options) -> DataFrame:
    """The whole view: traces of both methods."""
    return both_traces(spark, view(spark, sf_dir, name), rank, lam, iterations, seeds, **options)


def scaling(spark: SparkSession, sf_dir: str, times: Sequence[int] = (1, 2, 3, 4, 5, 6), rank: int = 10, iterations: int = 3, name: str = "cust_part") -> DataFrame:
    """(algo, n_u, nnz, seconds, std, slope, intercept, r2): seconds an iteration on synthetic ratings of more and more users, the deviation of iterations with and
    without a save, and the line through the means of a method."""
    source = cut(view(spark, sf_dir, name))
    n_u = source.select("user").distinct().count()
    rows = []
    for k in times:
        cells = cut(synthetic.expand(source, k * n_u))
        runs = both_traces(spark, cells, rank, 0.01, iterations, saves_every=max(2, iterations // 2))
        rows += [(r.algo, k * n_u, cells.count(), r["mean"], r["std"]) for r in trace.time_per_iteration(runs).collect()]
    points = spark.createDataFrame(rows, "algo string, n_u long, nnz long, seconds double, std double")
    return points.join(trace.linear_fit(points, "n_u", "seconds", "algo"), "algo")


def speedups(spark: SparkSession, sf_dir: str, times: Sequence[int] = (1, 3, 6), rank: int = 10, iterations: int = 6, name: str = "cust_part") -> DataFrame:
    """(n_u, run, iter, smooth, hit, factor): speedup at equal gradient norm on synthetic ratings of more and more users."""
    source, out = cut(view(spark, sf_dir, name)), None
    n_u = source.select("user").distinct().count()
    for k in times:
        runs = both_traces(spark, cut(synthetic.expand(source, k * n_u)), rank, 0.01, iterations)
        one = trace.speedup(runs).select(F.lit(k * n_u).alias("n_u"), "*")
        out = one if out is None else out.unionByName(one)
    return out


def svd_reference(spark: SparkSession, sf_dir: str, ranks: Sequence[int] = (1, 2, 4), sweeps: int = 300) -> DataFrame:
    """(rank, svd_loss, als_loss): the least squared error on the (nearly) full view of nations and brands, and plain sweeps with next to no ridge."""
    full = view(spark, sf_dir, "nation_brand").toPandas().pivot(index="user", columns="item", values="rating")  # 25 by 25
    full = full.fillna(full.stack().mean()).to_numpy()
    rows = []
    for rank in ranks:
        s = serial.Serial(*[x.ravel() for x in np.indices(full.shape)], full.ravel(), rank, 1e-9)
        rows.append((rank, baselines.svd_loss(full, rank), s.fit_als(*s.start(0), serial.Stop(gnorm=1e-9, iterations=sweeps)).trace[-1]["loss"]))
    return spark.createDataFrame(rows, "rank int, svd_loss double, als_loss double")


def communication(spark: SparkSession, sf_dir: str, name: str = "cust_part", n_blocks: int = 8) -> DataFrame:
    """(schedule, vectors, passes) of an iteration, by the routes of a view."""
    from mfaccel.operators.cost import passes, routed_vectors

    pairs = {r.side: r.pairs for r in routing_volume(view(spark, sf_dir, name), n_blocks, "mod").collect()}  # two rows
    rows = [(s, int(routed_vectors(pairs["user"], pairs["item"], s)), passes(s)) for s in ("als", "paper", "fused")]
    return spark.createDataFrame(rows, "schedule string, vectors long, passes int")


def work(spark: SparkSession, sf_dir: str, name: str = "cust_part", rank: int = 10) -> DataFrame:
    """(part, flops) of an iteration by formula."""
    from mfaccel.operators.cost import gradient_flops, search_flops, solve_flops

    r = view(spark, sf_dir, name).agg(F.count_distinct("user").alias("u"), F.count_distinct("item").alias("m"), F.count("*").alias("n")).first()
    rows = [("sweep", solve_flops(r.u, r.n, rank) + solve_flops(r.m, r.n, rank)), ("gradient", gradient_flops(r.u, r.n, rank) + gradient_flops(r.m, r.n, rank)), ("search", search_flops(r.n, rank))]
    return spark.createDataFrame([(a, float(b)) for a, b in rows], "part string, flops double")
