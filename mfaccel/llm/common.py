"""Helpers that the text operators share: Arrow maps, a shared folder, bounded broadcasts."""

from __future__ import annotations

import os
import pickle
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Bytes that separate words once letters are lower-cased: all of ASCII but digits and a-z.
_WORD = {*range(0x30, 0x3A), *range(0x61, 0x7B), *range(0x80, 0x100)}
#: A-Z to a-z, every other non-word byte to a space; bytes of longer code points stay.
LOWER_WORDS = bytes(b + 32 if 65 <= b <= 90 else b if b in _WORD else 32 for b in range(256))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_folder(spark: SparkSession) -> str:
    """The folder that driver and executors share: spark.checkpoint.dir, else, where both are one machine, a temporary one."""
    if folder := spark.conf.get("spark.checkpoint.dir", None):
        return folder
    if spark.sparkContext.master.partition("[")[0] != "local":
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    return os.path.join(tempfile.gettempdir(), "mfaccel-shared")


def fresh_path(spark: SparkSession, what: str) -> str:
    return f"{shared_folder(spark).rstrip('/')}/{what}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Cuts the lineage by a reliable checkpoint in the shared folder."""
    spark = df.sparkSession
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(shared_folder(spark))
    return df.checkpoint(eager=True)


def raw(name: str) -> F.Column:
    """A text column as UTF-8 bytes; null stays null."""
    return F.col(name).cast("string").cast("binary")


def map_batches(
    df: DataFrame, make: Callable[[], Callable[[pa.RecordBatch], Iterable[pa.RecordBatch]]], schema: str
) -> DataFrame:
    """mapInArrow with a worker that is built once per task by `make`."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        work = None
        for batch in batches:
            if batch.num_rows:
                work = work or make()
                yield from work(batch)

    return df.mapInArrow(run, schema)


def slices(batch: pa.RecordBatch, column: int, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Row ranges of a batch whose bytes in a binary column stay near `limit` (a longer text comes alone)."""
    start, held = 0, 0
    sizes = batch.column(column)
    for k in range(batch.num_rows):
        n = len(sizes[k].as_buffer()) if sizes[k].is_valid else 0
        if k > start and held + n > limit:
            yield batch.slice(start, k - start)
            start, held = k, 0
        held += n
    if start < batch.num_rows:
        yield batch.slice(start)


def keep_rows(df: DataFrame, column: str, make: Callable[[], Callable[[list[bytes | None]], list[bool]]]) -> DataFrame:
    """The rows, all columns as they are, whose text passes; texts come as UTF-8 bytes, null as None."""
    at = df.columns.index(column)

    def start():
        passes = make()

        def work(batch):
            for part in slices(_with_bytes(batch, at), at):
                kept = pa.array(passes(part.column(at).to_pylist()), pa.bool_())
                yield pa.RecordBatch.from_arrays([c.cast(f.type) for c, f in zip(part.filter(kept).columns, batch.schema, strict=True)], schema=batch.schema)

        return work

    return map_batches(df, start, df.schema)


def _with_bytes(batch: pa.RecordBatch, at: int) -> pa.RecordBatch:
    columns = list(batch.columns)
    columns[at] = columns[at].cast(pa.binary())
    return pa.RecordBatch.from_arrays(columns, names=[f"c{k}" for k in range(len(columns))])


_SPAN = 1 << 40


def first_by_hash(df: DataFrame, column: str, most: int, count: int | None = None) -> DataFrame:
    """At most `most` rows, the first in the order of a hash of a column. A filter by hash leaves about twice that many before they
    are ordered, so tasks do not each send `most` rows to the driver."""
    count = df.count() if count is None else count
    spot = F.pmod(F.xxhash64(column), F.lit(_SPAN))
    if count > 2 * most:
        df = df.where(spot < int(_SPAN * min(1.0, (2 * most + 100) / count)))
    return df.orderBy(spot, column).limit(most)


def labelled_features(
    docs: DataFrame, labels: DataFrame, label_col: str, where: F.Column, make_codes: Callable[[bytes | None], "object"],
    doc_col: str, text_col: str, most_rows: int, most_codes: int,
) -> DataFrame | None:
    """(id, y, codes), with packed int32 codes, of at most `most_rows` labelled documents in the order of a hash of their ids, with
    at most `most_codes` codes in all; ids whose labels contradict each other are left out. None without any label."""
    spark = docs.sparkSession
    chosen = labels.where(where & F.col(label_col).isNotNull() & F.col(doc_col).isNotNull()).select(F.col(doc_col).alias("id"), F.col(label_col).cast("int").alias("y"))
    rows = first_by_hash(chosen.distinct(), "id", most_rows).collect()
    seen: dict = {}
    for r in rows:
        seen.setdefault(r.id, set()).add(r.y)
    of = {k: next(iter(v)) for k, v in seen.items() if len(v) == 1}
    if not of:
        return None
    kind = docs.schema[doc_col].dataType.simpleString()
    ids = F.broadcast(spark.createDataFrame(list(of.items()), f"id {kind}, y int"))

    def start():
        def work(batch):
            for part in slices(batch, 1):
                packed = [make_codes(t).astype("<i4").tobytes() for t in part.column(1).to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(2), pa.array(packed, pa.binary())], ["id", "y", "codes"])

        return work

    texts = docs.select(F.col(doc_col).alias("id"), raw(text_col).alias("text")).join(ids, "id")
    found = cut(map_batches(texts, start, f"id {kind}, y int, codes binary")).withColumn("h", F.xxhash64("codes"))
    sizes = found.select("id", "h", (F.octet_length("codes") / 4).cast("long").alias("n")).distinct()
    sizes = sizes.orderBy(F.xxhash64("id"), "id", "n", "h").limit(most_rows).collect()
    total, taken = 0, []
    for r in sizes:
        if total and total + r.n > most_codes:
            break
        total += r.n
        taken.append((r.id, r.h))
    many, texts = found.agg(F.count("*"), F.count_distinct("id", "h")).first()
    if len(taken) < texts:  # beyond the bound
        found = found.join(F.broadcast(spark.createDataFrame(taken, f"id {kind}, h bigint")), ["id", "h"])
    if texts < many:  # each text of an id once
        found = found.dropDuplicates(["id", "h"])
    return found.select("id", "y", "codes")


def trained(found: DataFrame | None, train: Callable[[list[np.ndarray], np.ndarray], "object"]):
    """What `train` makes of the codes and labels of labelled_features(), in the order of their ids. It works in one task, as the rows are bounded;
    the driver gets what it returns and none of the rows."""

    def work(batches):
        rows, labels = [], []
        for batch in batches:
            rows += [np.frombuffer(c.as_buffer(), "<i4") for c in batch.column(1)]
            labels += batch.column(0).to_pylist()
        yield pa.RecordBatch.from_arrays([pa.array([pickle.dumps(train(rows, np.array(labels)), 5)], pa.binary())], ["made"])

    if found is not None:
        inorder = found.repartition(1).sortWithinPartitions("id", F.octet_length("codes"), "codes").select("y", "codes")
        if (made := inorder.mapInArrow(work, "made binary").first()) is not None:
            return pickle.loads(made.made)
    return train([], np.array([]))
