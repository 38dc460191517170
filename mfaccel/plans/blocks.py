"""Block layout: two copies of the ratings, entity rows with routing lists, and what moves between them.

Ratings are kept by user block and by item block. An entity row carries `dest`, the blocks of the other side that need
its vector; a vector is sent to each of them once, however many ratings there use it. Hot entities cost what
their distinct blocks cost, at most the number of blocks. The cells of an entity with more ratings than a task should hold are
spread over blocks too: sums over its ratings (normal equations, gradient, loss) are added up from its parts.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator, Sequence
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from mfaccel.plans.cuts import cut, release, shared_folder

#: Ratings of one entity that one task takes.
HEAVY = 1_000_000
#: Ratings of a block.
CELLS = 1 << 19
#: Ratings that a task packs at a time, and most of a packed row.
PACKED, ROW = 1 << 20, 1 << 17


def block_of(id_col: str, n_blocks: int, how: str = "hash") -> Column:
    """Block of an entity: of a hash of its id, or the id modulo the number of blocks."""
    key = F.xxhash64(id_col) if how == "hash" else F.col(id_col)
    return F.pmod(key, F.lit(n_blocks)).cast("int")


@lru_cache(maxsize=64)
def labels(spark: SparkSession, n: int, partitions: int | None = None) -> tuple[int, ...]:
    """A number for each of n blocks that the hash of an exchange deals evenly over its partitions (n of them, if not given): plain numbers
    0..n-1 would leave a third of the partitions empty and give others two or three blocks."""
    partitions = partitions or n
    each = -(-n // partitions)
    spots = spark.range(40 * each * partitions + 64).select(F.col("id").cast("int").alias("v"))
    spots = spots.groupBy(F.pmod(F.hash("v"), F.lit(partitions)).alias("p")).agg(F.slice(F.sort_array(F.collect_list("v")), 1, each).alias("v"))
    found = [r.v for r in spots.orderBy("p").collect()]  # one number a block
    return tuple(found[k % partitions][k // partitions] for k in range(n))


def range_of(id_col: str, bounds: Sequence[int], names: Sequence[int]) -> Column:
    """The name of the range that an id lies in; each bound begins a range."""

    def pick(a: int, b: int) -> Column:
        if a == b:
            return F.lit(names[a])
        m = (a + b + 1) // 2
        return F.when(F.col(id_col) < bounds[m - 1], pick(a, m - 1)).otherwise(pick(m, b))

    return pick(0, len(bounds))


@dataclass
class Layout:
    ratings: DataFrame
    n_blocks: int
    how: str
    by_user: DataFrame  # blk, cells, own, other, rating: packed, many ratings a row
    by_item: DataFrame
    users: DataFrame  # id, blk, n, dest, parts, lead: an entity, or each part of one whose ratings lie in several blocks
    items: DataFrame
    n_u: int
    n_m: int
    nnz: int
    split: dict[str, bool]  # whether any entity of a side is in parts
    volume: dict[str, int]  # vectors that a side sends in a pass
    path: str  # where the ratings were written once

    def side(self, side: str) -> tuple[DataFrame, DataFrame]:
        return (self.by_user, self.users) if side == "user" else (self.by_item, self.items)

    def close(self) -> None:
        for df in (self.by_user, self.by_item, self.users, self.items):
            df.unpersist()
        spark = self.by_user.sparkSession
        path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
        release(spark)


def routing(ratings: DataFrame, side: str, n_blocks: int, how: str = "hash") -> DataFrame:
    """Distinct (entity of the side, block of the other side that has a rating of it)."""
    other, name = ("item", "ublk") if side == "item" else ("user", "iblk")
    return ratings.select(F.col(other), block_of("user" if side == "item" else "item", n_blocks, how).alias(name)).distinct()


def routing_volume(ratings: DataFrame, n_blocks: int, how: str = "hash") -> DataFrame:
    """(side, pairs, nnz, bound): vectors sent in a half-step, against one per rating and against all to all."""
    out = None
    for side in ("user", "item"):
        pairs = routing(ratings, side, n_blocks, how).agg(F.count("*").alias("pairs"))
        size = ratings.agg(F.count("*").alias("nnz"), (F.count_distinct(side) * n_blocks).alias("all"))
        one = pairs.crossJoin(size).select(F.lit(side).alias("side"), "pairs", "nnz", F.least("nnz", "all").alias("bound"))
        out = one if out is None else out.unionByName(one)
    return out


def pack(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Ratings (blk, own, other, rating) as few rows of a block's, with the numbers of many ratings in one compressed value each: Spark then moves
    and hands over bytes, where single ratings cost it far more than the computing does."""

    def packed(held: list[pa.RecordBatch]) -> pa.RecordBatch:
        blk, own, other, rating = (np.concatenate([b.column(k).to_numpy(zero_copy_only=False) for b in held]) for k in range(4))
        order = np.lexsort((own, blk))
        blk, columns = blk[order], [c[order].astype(t) for c, t in ((own, np.int64), (other, np.int64), (rating, np.float64))]
        turns = [0, *(np.flatnonzero(np.diff(blk)) + 1).tolist(), len(blk)]
        spans = [(k, min(k + ROW, b)) for a, b in zip(turns, turns[1:], strict=False) for k in range(a, b, ROW)]
        rows = [pa.array(blk[[a for a, _ in spans]], pa.int32()), pa.array([b - a for a, b in spans], pa.int32())]
        rows += [pa.array([pa.compress(c[a:b].tobytes(), "zstd", asbytes=True) for a, b in spans], pa.binary()) for c in columns]
        return pa.RecordBatch.from_arrays(rows, ["blk", "cells", "own", "other", "rating"])

    held, n = [], 0
    for batch in batches:
        if batch.num_rows:
            held.append(batch)
            n += batch.num_rows
        if n >= PACKED:
            yield packed(held)
            held, n = [], 0
    if held:
        yield packed(held)


def unpacked(rows: pa.Table | pa.RecordBatch) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(own, other, rating) of packed rows."""
    kinds, cells = (("own", np.int64), ("other", np.int64), ("rating", np.float64)), rows["cells"].to_pylist()
    return tuple(np.concatenate([np.zeros(0, t), *(_numbers(v, n, t) for v, n in zip(rows[c], cells, strict=True))]) for c, t in kinds)


def _numbers(value: pa.BinaryScalar, n: int, kind: type) -> np.ndarray:
    return np.frombuffer(pa.decompress(value.as_buffer(), 8 * n, "zstd"), kind)


def uses(column: str):
    """(id, blk, n) of packed rows: how often each row has an id."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for blk, cells, value in zip(batch["blk"].to_pylist(), batch["cells"].to_pylist(), batch[column], strict=True):
                ids, n = np.unique(_numbers(value, cells, np.int64), return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(np.full(len(ids), blk, np.int32)), pa.array(n)], ["id", "blk", "n"])

    return run


def layout(ratings: DataFrame, n_blocks: int | None = None, how: str = "range", level: StorageLevel = StorageLevel.MEMORY_AND_DISK, heavy: int = HEAVY) -> Layout:
    """Ratings by user and by item block. Blocks are ranges of ids with about as many ratings each (how "range"), so that a vector goes to few blocks where
    near ids rate near ones, or hashes of ids. An entity of more than `heavy` ratings is kept in parts, by the blocks of the other side's ids, so that no
    block holds all of them; its first part leads: it alone sends the vector and counts in norms and products. The ratings, and packed copies of
    them that a join has made, are written once, as files, so that the exchanges which made them can go."""
    spark = ratings.sparkSession
    path = f"{shared_folder(spark)}/cells-{uuid.uuid4().hex}"
    ratings.select("user", "item", "rating").write.option("compression", "zstd").parquet(f"{path}/cells")
    release(spark)
    rows = spark.read.parquet(f"{path}/cells")
    nnz = rows.count()
    n_blocks = n_blocks or max(spark.sparkContext.defaultParallelism, -(-nnz // CELLS))
    names, bounds = labels(spark, n_blocks), {}
    if how == "range":
        shares = [k / n_blocks for k in range(1, n_blocks)]
        found = rows.agg(*[F.percentile_approx(s, shares, 100 * n_blocks).alias(s) for s in ("user", "item")]).first() if shares else {"user": [], "item": []}
        bounds = {s: [b + 1 for b in found[s] or [0] * len(shares)] for s in ("user", "item")}
    copies, split = {}, {}

    def placed(col: str) -> Column:
        return range_of(col, bounds[col], names) if how == "range" else F.get(F.array(*map(F.lit, names)), block_of(col, n_blocks, how))

    for side, other in (("user", "item"), ("item", "user")):
        large = rows.groupBy(side).agg(F.count("*").alias("n")).where(F.col("n") > heavy).select(side, F.lit(True).alias("large"))
        split[side] = bool(large.limit(1).count())
        cells = rows.join(large, side, "left") if split[side] else rows.withColumn("large", F.lit(None).cast("boolean"))
        blk = F.when(F.col("large"), placed(other)).otherwise(placed(side))
        cells = cells.select(blk.alias("blk"), F.col(side).cast("bigint").alias("own"), F.col(other).cast("bigint").alias("other"), F.col("rating").cast("double").alias("rating"))
        packed = cells.mapInArrow(pack, "blk int, cells int, own binary, other binary, rating binary")
        if split[side]:  # kept as files: the rows behind them would hold the exchanges of the join above, several times as large, as long as the layout lives
            packed.write.option("compression", "none").parquet(f"{path}/{side}")
            packed = spark.read.parquet(f"{path}/{side}")
            release(spark)
        copies[side] = packed.repartition(n_blocks, "blk").persist(level)
    entities = {}
    for side, other in (("user", "item"), ("item", "user")):
        mine = copies[side].select("blk", "cells", "own").mapInArrow(uses("own"), "id bigint, blk int, n bigint").groupBy("id", "blk").agg(F.sum("n").cast("int").alias("n"))
        needed = copies[other].select("blk", "cells", "other").mapInArrow(uses("other"), "id bigint, blk int, n bigint").groupBy("id").agg(F.sort_array(F.collect_set("blk")).alias("dest"))
        if split[side]:
            whole = mine.groupBy("id").agg(F.count("*").cast("int").alias("parts"), F.min("blk").alias("first"))
            mine = mine.join(whole, "id").withColumn("lead", F.col("blk") == F.col("first")).drop("first")
        else:
            mine = mine.withColumn("parts", F.lit(1)).withColumn("lead", F.lit(True))
        none = F.array().cast("array<int>")
        entities[side] = cut(mine.join(needed, "id").select("id", "blk", "n", F.when(F.col("lead"), F.col("dest")).otherwise(none).alias("dest"), "parts", "lead"))
    sums = {s: e.agg(F.count_if("lead").alias("n"), F.sum(F.size("dest")).alias("sent")).first() for s, e in entities.items()}
    release(spark)
    return Layout(rows, n_blocks, how, copies["user"], copies["item"], entities["user"], entities["item"], sums["user"].n, sums["item"].n, nnz, split, {s: sums[s].sent or 0 for s in sums}, path)


def exchanges(df: DataFrame) -> dict[str, int]:
    """How often a plan exchanges, broadcasts, and calls Python, by the nodes of its executed plan."""
    plan = df._jdf.queryExecution().executedPlan().toString()
    lines = [x.split("+-")[-1].strip(" :*()0123456789") for x in plan.splitlines()]
    count = lambda *names: sum(any(x.startswith(n) for n in names) for x in lines)
    return {"exchange": count("Exchange", "ShuffleExchange"), "broadcast": count("BroadcastExchange"), "python": sum("Arrow" in x or "Pandas" in x or "PythonUDF" in x for x in lines)}
