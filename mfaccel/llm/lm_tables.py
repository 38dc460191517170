"""Language-model scoring by cross-entropy difference, with exact counts of every word and word pair.

The models and scores are those of `lm_score`, without its bounds: every word is in the vocabulary, and pairs are counted as they are, in
tables that grow with the corpus. Texts are taken in blocks of bounded size. A block counts its distinct words, contexts (a word that
another follows) and pairs, and sends them by hash to buckets; a bucket adds up what all blocks sent and answers each
with the counts over the whole corpus; the block then scores its documents. The number of buckets grows with the text, so neither
a task nor the driver holds a model, and a word or pair that is everywhere is one row a block.

Edge cases: null and empty texts have no words, losses 0 and score 0; documents without a mark, or with a null one, are no target; an
empty target leaves its smoothed uniform model; repeated rows count as often as they occur; empty tables give no rows; other
columns are ignored.
"""

from __future__ import annotations

import math
import pickle
import zlib
from collections import defaultdict

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mfaccel.llm.common import LOWER_WORDS, map_batches, raw, slices
from mfaccel.llm.lm_score import ADDED, SHARE
from mfaccel.plans.blocks import labels

#: Bytes of text and rows of a block, bytes of text for each bucket; and the bytes of text beyond which all three grow.
BLOCK, BLOCK_ROWS, BUCKET, GROWS = 16 << 20, 200_000, 32 << 20, 1 << 40
_SENT = "block string, bucket int, docs boolean, data binary, words bigint, n bigint, n_target bigint"


_LEVEL = 3


def _ints(values: np.ndarray) -> tuple[int, int, bytes]:
    """Numbers from 0 in few bytes: of the least width that holds them, first bytes first, compressed."""
    width = np.min_scalar_type(int(values.max()) if len(values) else 0).itemsize
    planes = np.ascontiguousarray(values.astype(f"<u{width}").view(np.uint8).reshape(-1, width).T)
    return len(values), width, pa.Codec("zstd", compression_level=_LEVEL).compress(planes.tobytes(), asbytes=True)


def _from_ints(packed: tuple[int, int, bytes]) -> np.ndarray:
    many, width, data = packed
    planes = np.frombuffer(pa.Codec("zstd").decompress(data, many * width, asbytes=True), np.uint8).reshape(width, many)
    return np.ascontiguousarray(planes.T).view(f"<u{width}").reshape(-1).astype(np.int64)


def _lines(keys: pa.Array) -> tuple[int, bytes]:
    """Keys, which hold no line feed, as compressed lines."""
    text = b"\n".join(keys.to_pylist())
    return len(text), pa.Codec("zstd", compression_level=_LEVEL).compress(text, asbytes=True)


def _from_lines(packed: tuple[int, bytes]) -> pa.Array:
    size, data = packed
    return pa.array(pa.Codec("zstd").decompress(data, size, asbytes=True).split(b"\n") if size else [], pa.binary())


def _pack_ids(docs: pa.Array) -> bytes:
    batch = pa.RecordBatch.from_arrays([docs], ["doc"])
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write_batch(batch)
    return sink.getvalue().to_pybytes()


def _row(block, bucket, docs, data, words=0, n=0, n_target=0) -> pa.RecordBatch:
    kinds = [pa.string(), pa.int32(), pa.bool_(), pa.binary(), pa.int64(), pa.int64(), pa.int64()]
    names = ["block", "bucket", "docs", "data", "words", "n", "n_target"]
    return pa.RecordBatch.from_arrays([pa.array([x], t) for x, t in zip((block, bucket, docs, data, words, n, n_target), kinds, strict=True)], names)


def _pairs(ids: np.ndarray, sizes: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Word before each word (0 at the start of a document); distinct pairs as numbers, and the place of each word's pair among them."""
    before = np.concatenate([[0], ids[:-1]])[: len(ids)].astype(np.int64)
    starts = np.concatenate([[0], np.cumsum(sizes)[:-1]])[: len(sizes)].astype(np.int64)
    before[starts[sizes > 0]] = 0
    pairs, at = np.unique(before * words + ids, return_inverse=True)
    return before, pairs, at


def _buckets(spots: np.ndarray, first: np.ndarray, second: np.ndarray, buckets: int) -> np.ndarray:
    """Bucket of each pair, then of each word but the first, then of each context, from hashes of the words."""
    spots = spots.astype(np.uint64) + np.uint64(1)
    mixed = np.concatenate([spots[first] * np.uint64(0x9E3779B97F4A7C15) ^ spots[second] * np.uint64(0xC2B2AE3D27D4EB4F), spots[1:] * np.uint64(0xD6E8FEB86659FD93), spots * np.uint64(0xA0761D6478BD642F)])
    mixed = (mixed ^ (mixed >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)
    return ((mixed >> np.uint64(32)) % np.uint64(buckets)).astype(np.int64)


class _Block:
    """Documents of a block: their ids, targets and words, numbered in order of appearance; 0 is the start of a document."""

    def __init__(self):
        self.number: defaultdict[bytes, int] = defaultdict()
        self.number.default_factory = self.number.__len__
        self.number[b""]
        self.docs, self.targets, self.ids, self.bytes, self.rows = [], [], [], 0, 0

    def add(self, docs: pa.Array, targets: list[bool], texts: list[bytes | None]) -> None:
        self.docs.append(docs)
        self.targets += targets
        for text in texts:
            words = text.translate(LOWER_WORDS).split() if text else []
            self.ids.append(np.fromiter(map(self.number.__getitem__, words), np.int64, len(words)))
            self.bytes += len(text or b"")
        self.rows += len(texts)

    def rows_out(self, name: str, buckets: int):
        sizes = np.array([len(x) for x in self.ids], np.int64)
        ids, many = np.concatenate(self.ids), len(self.number)
        often = np.concatenate([[0], 1 + np.argsort(-np.bincount(ids, minlength=many)[1:], kind="stable")])  # small numbers for frequent words
        rank = np.empty(many, np.int64)
        rank[often] = np.arange(many)
        ids = rank[ids]
        target = np.repeat(np.array(self.targets, bool), sizes)
        before, pairs, at = _pairs(ids, sizes, many)
        names = pa.array(list(self.number), pa.binary()).take(pa.array(often))
        first, second = pairs // many, pairs % many
        space = pa.scalar(b" ", pa.binary())
        keys = pa.concat_arrays([
            pc.binary_join_element_wise(names.take(pa.array(first)), names.take(pa.array(second)), space),
            names.slice(1), pc.binary_join_element_wise(names, pa.scalar(b"", pa.binary()), space),
        ])
        n, n_target = (
            np.concatenate([np.bincount(at[w], minlength=len(pairs)), np.bincount(ids[w], minlength=many)[1:], np.bincount(before[w], minlength=many)])
            for w in (slice(None), target)
        )
        spots = (np.fromiter(map(zlib.crc32, self.number), np.int64, many) & 0xFFFF)[often]
        bucket = _buckets(spots, first, second, buckets)
        order = np.argsort(bucket, kind="stable")
        edges = np.searchsorted(bucket[order], np.arange(buckets + 1))
        for k in range(buckets):  # an empty part too: its answer has the bucket's share of the sums over all words
            part = order[edges[k] : edges[k + 1]]
            yield _row(name, k, False, pickle.dumps((_lines(keys.take(pa.array(part))), _ints(n[part]), _ints(n_target[part]))))
        record = pickle.dumps((_pack_ids(pa.concat_arrays(self.docs)), _ints(sizes), _ints(ids), _ints(spots)))
        yield _row(name, zlib.crc32(name.encode()) % buckets, True, record)


def _add_up(table: pa.Table):
    """A bucket: the counts of its keys over all blocks, in the order in which each block sent them."""
    sent = [k for k in range(table.num_rows) if not table["docs"][k].as_py()]
    parts = [pickle.loads(table["data"][k].as_py()) for k in sent]
    if parts:
        coded = pa.concat_arrays([_from_lines(p[0]) for p in parts]).dictionary_encode()
        at, many = coded.indices.to_numpy(zero_copy_only=False), len(coded.dictionary)
        n, n_target = np.zeros(many, np.int64), np.zeros(many, np.int64)
        np.add.at(n, at, np.concatenate([_from_ints(p[1]) for p in parts]))
        np.add.at(n_target, at, np.concatenate([_from_ints(p[2]) for p in parts]))
        word = pc.less(pc.find_substring(coded.dictionary, b" "), 0).to_numpy(zero_copy_only=False).astype(bool)
        sums, start = (int(word.sum()), int(n[word].sum()), int(n_target[word].sum())), 0
        for k, part in zip(sent, parts, strict=True):
            own = at[start : start + part[1][0]]
            start += part[1][0]
            yield _row(table["block"][k].as_py(), table["bucket"][k].as_py(), False, pickle.dumps((_ints(n[own]), _ints(n_target[own]))), *sums)
    for k in range(table.num_rows):
        if table["docs"][k].as_py():
            yield _row(table["block"][k].as_py(), table["bucket"][k].as_py(), True, table["data"][k].as_py())


def _losses(table: pa.Table, buckets: int) -> tuple[pa.Array, np.ndarray, list[np.ndarray]]:
    """Document ids of a block, their numbers of words, and their mean losses under the target and the background."""
    docs = pc.equal(table["docs"], True)
    records, answers = table.filter(docs), table.filter(pc.invert(docs)).sort_by("bucket")
    if records.num_rows != 1 or answers["bucket"].to_pylist() != list(range(buckets)):
        raise RuntimeError("a block of documents lost a part: the input is not the same when it is read again")
    doc, *packed = pickle.loads(records["data"][0].as_py())
    sizes, ids, spots = map(_from_ints, packed)
    many = len(spots)
    sent = [pickle.loads(x.as_py()) for x in answers["data"]]
    _, pairs, at = _pairs(ids, sizes, many)
    first, second = pairs // many, pairs % many
    order = np.argsort(_buckets(spots, first, second, buckets), kind="stable")
    owner, out = np.repeat(np.arange(len(sizes)), sizes), []
    words = sum(answers["words"].to_pylist())
    for k, name in ((1, "n_target"), (0, "n")):
        counts = np.empty(len(order), np.int64)
        counts[order] = np.concatenate([_from_ints(x[k]) for x in sent])
        of_pair, of_word, of_context = counts[: len(pairs)], np.concatenate([[0], counts[len(pairs) : len(pairs) + many - 1]]), counts[len(pairs) + many - 1 :]
        context = of_context[first]
        share = np.where(context > 0, SHARE, 0.0)
        p = share * of_pair / np.maximum(context, 1) + (1 - share) * (of_word[second] + ADDED) / (sum(answers[name].to_pylist()) + ADDED * words)
        out.append(np.bincount(owner, (-np.log(p))[at], minlength=len(sizes)) / np.maximum(sizes, 1))
    return pa.ipc.open_stream(doc).read_all()["doc"].combine_chunks(), sizes, out


def block_sizes(total: int, block: int, least_buckets: int) -> tuple[int, int, int]:
    """Bytes and rows of a block, and the number of buckets, for `total` bytes of text. Each block sends a part to each bucket, so beyond GROWS both
    grow with the square root of the text: the number of parts then grows as the text does, and their size stays."""
    more = max(1.0, math.sqrt(total / GROWS))
    return int(block * more), int(BLOCK_ROWS * more), max(least_buckets, math.ceil(total / (BUCKET * more)))


def score(docs: DataFrame, targets: DataFrame, *, doc_col: str = "doc_id", text_col: str = "text", block: int = BLOCK, least_buckets: int | None = None) -> DataFrame:
    """doc_col, n_tokens, target_loss, background_loss, score (their difference), selected (score < 0) of every document.

    `targets` (doc_col, target) has one row for each marked document. It grows with the corpus and is never broadcast; texts are
    compressed before the join that deals them out."""
    spark, kind = docs.sparkSession, docs.schema[doc_col].dataType.simpleString()
    total = docs.agg(F.sum(F.octet_length(raw(text_col)))).first()[0] or 0
    block, block_rows, buckets = block_sizes(total, block, least_buckets or int(spark.conf.get("spark.sql.shuffle.partitions")))

    def pack():
        codec = pa.Codec("zstd", compression_level=1)

        def work(batch):
            for part in slices(batch, 1):
                texts = part.column(1).to_pylist()
                small = [codec.compress(t, asbytes=True) if t else None for t in texts]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([len(t or b"") for t in texts], pa.int64()), pa.array(small, pa.binary())], [doc_col, "_size", "_small"])

        return work

    packed = map_batches(docs.select(doc_col, raw(text_col).alias("_raw")), pack, f"{doc_col} {kind}, _size bigint, _small binary")
    marks = targets.select(doc_col, F.coalesce(F.col("target"), F.lit(False)).alias("_target"))
    marked = packed.join(marks.hint("merge"), doc_col, "left").select(doc_col, "_small", "_size", F.coalesce("_target", F.lit(False)).alias("_target"))

    def count(batches):
        codec, own, k = pa.Codec("zstd"), _Block(), 0
        partition = TaskContext.get().partitionId()
        for batch in batches:
            for part in slices(batch, 1, 1 << 20):
                texts = [codec.decompress(s, n, asbytes=True) if n else None for s, n in zip(part.column(1).to_pylist(), part.column(2).to_pylist(), strict=True)]
                own.add(part.column(0), part.column(3).to_pylist(), texts)
                if own.bytes >= block or own.rows >= block_rows:
                    yield from own.rows_out(f"{partition}-{k}", buckets)
                    own, k = _Block(), k + 1
        if own.rows:
            yield from own.rows_out(f"{partition}-{k}", buckets)

    def add(table: pa.Table) -> pa.Table:
        return pa.Table.from_batches(list(_add_up(table)))

    def finish(table: pa.Table) -> pa.Table:
        ids, sizes, (target, background) = _losses(table, buckets)
        return pa.table([ids, sizes, target, background, target - background, target < background], [doc_col, "n_tokens", "target_loss", "background_loss", "score", "selected"])

    spots = labels(spark, buckets, int(spark.conf.get("spark.sql.shuffle.partitions")))  # so that no task gets several buckets while another has none
    sent = marked.mapInArrow(count, _SENT).withColumn("spot", F.get(F.array(*map(F.lit, spots)), F.col("bucket")))
    answered = sent.groupBy("spot").applyInArrow(add, _SENT)
    schema = f"{doc_col} {kind}, n_tokens bigint, target_loss double, background_loss double, score double, selected boolean"
    return answered.groupBy("block").applyInArrow(finish, schema)
