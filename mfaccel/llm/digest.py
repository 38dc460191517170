"""Document fingerprints by a quartile bucket digest of hashed byte triplets, and their likeness.

Every position of the UTF-8 bytes counts two triplets of a twelve-byte window in 256 hashed buckets. The
digest holds the length on a log scale, two quartile ratios, and for each bucket in which quarter of the
counts it lies (2 bits). Two digests differ by a bounded score; likeness is 1 less its share of the bound.

Edge cases: null and empty texts count as empty: all buckets in the lowest quarter, length code 0; texts of
one or two bytes have no triplet but a length code; very long texts are counted in blocks; equal texts have
equal digests, and likeness is 1 exactly for equal digests.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.ml.feature import Bucketizer
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mfaccel.llm.common import raw

BUCKETS = 256
#: Offsets of the second and third byte of the triplets that a position counts, each with a multiplier of its hash.
#: Spread bytes tell texts of one language apart better than adjacent ones, and an edit still spoils a few only.
TRIPLETS = ((3, 7, 0x9E3779B1), (5, 11, 0x85EBCA6B))
_BLOCK = 1 << 20
#: Most that the length adds to a score.
LENGTH_MOST = 40
#: The bound of a score: unrelated texts come near it, so likeness uses all of 0 to 1.
SCORE_MOST = 512


def bucket_counts(text: bytes) -> np.ndarray:
    counts = np.zeros(BUCKETS, np.int64)
    for k in range(0, len(text), _BLOCK):
        block = np.frombuffer(text[k : k + _BLOCK + 11], np.uint8).astype(np.uint32)
        for a, b, factor in TRIPLETS:
            n = min(_BLOCK, len(block) - b)
            if n > 0:
                code = block[:n] | (block[a : a + n] << np.uint32(8)) | (block[b : b + n] << np.uint32(16))
                code *= np.uint32(factor)
                counts += np.bincount(code >> np.uint32(24), minlength=BUCKETS)
    return counts


def fingerprint(text: bytes | None) -> str:
    """Hexadecimal: 2 digits of length code, 1 and 1 of quartile ratios, 128 of buckets."""
    text = text or b""
    counts = bucket_counts(text)
    quartiles = np.sort(counts)[[BUCKETS // 4 - 1, BUCKETS // 2 - 1, 3 * BUCKETS // 4 - 1]]
    length = min(255, round(8 * math.log2(1 + len(text)))) if text else 0
    low, mid = (int(16 * int(q) / int(quartiles[2])) % 16 if quartiles[2] else 0 for q in quartiles[:2])
    quarter = (counts[:, None] > quartiles).sum(axis=1).astype(np.uint8).reshape(-1, 4)
    body = (quarter << np.array([6, 4, 2, 0], np.uint8)).sum(axis=1, dtype=np.uint8)
    return f"{length:02x}{low:x}{mid:x}{body.tobytes().hex()}"


_PAIRS = np.array([bin(x).count("1") for x in range(4)])


def score(a: str, b: str) -> int:
    """0 for equal digests only, SCORE_MOST at most. Quarters that are 1, 2 or 3 apart add 1, 2 or 4."""
    left, right = bytes.fromhex(a), bytes.fromhex(b)
    length = min(LENGTH_MOST, abs(left[0] - right[0]))
    ratios = sum(min(d := abs((left[1] >> s & 15) - (right[1] >> s & 15)), 16 - d) for s in (0, 4))
    shift = np.array([6, 4, 2, 0], np.uint8)
    x, y = ((np.frombuffer(v[2:], np.uint8)[:, None] >> shift & 3).astype(np.int64) for v in (left, right))
    apart = np.abs(x - y)
    return min(SCORE_MOST, int(length + ratios + (apart + (apart == 3)).sum()))


def likeness(a: str, b: str) -> float:
    return 1.0 - score(a, b) / SCORE_MOST


def edited(text: str, following: str) -> str:
    """The last third of the code points replaced by as many first ones of the following text, or all it has."""
    n = len(text) // 3
    return text[: len(text) - n] + following[:n]


_FIELDS = [("doc_id", pa.int64()), ("n_chars", pa.int64()), ("edited_sha256", pa.string()), ("fingerprint", pa.string()), ("edited_fingerprint", pa.string()), ("near_edited", pa.float64()), ("near_next", pa.float64())]


def _pairs(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows sorted by shard, guests last, ids downwards: each row of a shard meets the next, its last one a guest."""
    last, out = None, []
    for batch in batches:
        for k in range(0, batch.num_rows, 64):
            for shard, guest, doc, packed in zip(*(c.to_pylist() for c in batch.slice(k, 64).columns), strict=True):
                if guest and (last is None or last[0] != shard):
                    continue
                text, own = (packed or b"").decode(errors="replace"), fingerprint(packed)
                if last is not None and last[0] == shard:
                    new = edited(last[2], text).encode()
                    made = fingerprint(new)
                    out.append((last[1], len(last[2]), hashlib.sha256(new).hexdigest(), last[3], made, likeness(last[3], made), likeness(last[3], own)))
                last = None if guest else (shard, doc, text, own)
            if len(out) >= 512:
                yield _batch(out)
                out = []
    if out:
        yield _batch(out)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, t) for c, (_, t) in zip(zip(*rows, strict=True), _FIELDS, strict=True)], [n for n, _ in _FIELDS])


def against_next(docs: DataFrame, *, doc_col: str = "doc_id", text_col: str = "text", shards: int | None = None) -> DataFrame:
    """Each document's digest, that of its edited text, and its likeness to that and to the next document's, by
    descending id; after the last comes the first. Rows of one id are in the order of a hash of the text;
    rows without id come last.

    Quantiles of the ids cut the table into ranges. The first rows of a range are also sent to the range before
    it, so that each task sees the row after its last one: the texts are shuffled once, and nothing is ordered
    in one task. Bounds and first ids, a few numbers a range, are all that the driver gets.
    """
    spark = docs.sparkSession
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    shards = shards or min(8192, 4 * parts)
    ids = docs.select(F.coalesce(F.col(doc_col).cast("long"), F.lit(-(2**63))).alias("id"))
    found = ids.agg(F.percentile_approx("id", [k / shards for k in range(1, shards)] or [0.5], max(10000, 10 * shards)).alias("q")).first()
    splits = [-math.inf, *sorted({float(x) for x in found.q or [0]}), math.inf]
    cutter = Bucketizer(splits=splits, inputCol="at", outputCol="range")

    def placed(df: DataFrame) -> DataFrame:
        return cutter.transform(df.withColumn("at", F.col("id").cast("double"))).withColumn("shard", F.col("range").cast("int")).drop("at", "range")

    tops = sorted(tuple(r) for r in placed(ids).groupBy("shard").agg(F.max("id").alias("id")).collect())
    before = [(shard, top, tops[(k + 1) % len(tops)][0]) for k, (shard, top) in enumerate(tops)]
    before = F.broadcast(spark.createDataFrame(before, "shard int, id long, dest int"))
    rows = docs.select(F.coalesce(F.col(doc_col).cast("long"), F.lit(-(2**63))).alias("id"), F.col(doc_col).cast("long").alias("doc_id"), raw(text_col).alias("text"))
    own = F.struct(F.col("shard"), F.lit(False).alias("guest"))
    both = F.array(own, F.struct(F.col("dest").alias("shard"), F.lit(True).alias("guest")))
    sent = placed(rows).join(before, ["shard", "id"], "left").select("id", "doc_id", "text", F.xxhash64("text").alias("tie"), F.explode(F.when(F.isnull("dest"), F.array(own)).otherwise(both)).alias("to"))
    sorted_rows = sent.select("to.*", "id", "tie", "doc_id", "text").repartition(parts, "shard").sortWithinPartitions("shard", "guest", F.desc("id"), "tie")
    schema = "doc_id bigint, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    return sorted_rows.select("shard", "guest", "doc_id", "text").mapInArrow(_pairs, schema).withColumnRenamed("doc_id", doc_col)
