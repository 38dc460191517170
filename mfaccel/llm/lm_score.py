"""Language-model scoring by cross-entropy difference, with models of a bounded size (op3_lm_score uses `lm_tables`, which has no bounds).

Two bigram models, of target documents and of all documents (the background), share one vocabulary: the most frequent
words of the whole corpus, all others being one unknown word. Both are made in the same way from all their documents:
unigrams with additive smoothing, and bigrams interpolated with them. Bigrams are counted in hashed cells that both
models share, so a model has a fixed size however large the corpus is. A document's score is its mean loss per
word under the target model less that under the background: the lower, the more like the target.

Tasks add up dense counts and send them in fixed slices; partial sums are added where each slice is gathered, one array
at a time, so neither a task nor the driver holds more than a model.

Edge cases: null and empty texts have no words, losses 0 and score 0; an empty target leaves its smoothed uniform model;
a document's target flag that is null counts as no; repeated rows count as often as they occur; empty tables give no
rows; other columns are ignored.
"""

from __future__ import annotations

from collections import Counter
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mfaccel.llm.common import LOWER_WORDS, cut, map_batches, raw, slices

VOCABULARY, CELL_BITS, SLICE_BITS = 65_536, 20, 14
SHARE, ADDED = 0.7, 0.5
_HELD_WORDS = 400_000


def word_counts(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """(word binary, n) over all texts."""

    def run(batches):
        held: Counter = Counter()

        def out():
            return pa.RecordBatch.from_arrays([pa.array(list(held), pa.binary()), pa.array(list(held.values()), pa.int64())], ["word", "n"])

        for batch in batches:
            for text in batch.column(0):
                if text.is_valid:
                    held.update(text.as_py().translate(LOWER_WORDS).split())
                if len(held) > _HELD_WORDS:
                    yield out()
                    held.clear()
        if held:
            yield out()

    return docs.select(raw(text_col)).mapInArrow(run, "word binary, n bigint").groupBy("word").agg(F.sum("n").alias("n"))


def vocabulary(docs: DataFrame, text_col: str = "text", most: int = VOCABULARY) -> dict[bytes, int]:
    """The most frequent words, numbered from 2; 0 is any other word, 1 the start of a document.

    Words are taken by classes of frequency (sixteen to a doubling), and in the last class that has room by a hash of the word, so
    that two small histograms and the vocabulary itself are all that reaches the driver."""
    words = cut(word_counts(docs, text_col).select("word", "n", F.floor(16 * F.log2("n")).alias("class"), F.pmod(F.xxhash64("word"), F.lit(1 << 16)).alias("spot")))
    room, least, bound = most, 0, 0
    for r in sorted(words.groupBy("class").agg(F.count("*").alias("k")).collect(), key=lambda r: -r["class"]):
        if r.k > room:
            least = r["class"] + 1
            for s in sorted(words.where(F.col("class") == r["class"]).groupBy("spot").agg(F.count("*").alias("k")).collect(), key=lambda s: s.spot):
                if s.k > room:
                    break
                room, bound = room - s.k, s.spot + 1
            break
        room -= r.k
    kept = words.where((F.col("class") >= least) | ((F.col("class") == least - 1) & (F.col("spot") < bound))).collect()
    kept.sort(key=lambda r: (-r.n, bytes(r.word)))
    return {bytes(r.word): k + 2 for k, r in enumerate(kept)}


def _ids(text: bytes | None, vocab: dict[bytes, int]) -> np.ndarray:
    words = text.translate(LOWER_WORDS).split() if text else []
    return np.fromiter(map(vocab.get, words, repeat(0)), np.int64, len(words))


def cells(ids: np.ndarray) -> np.ndarray:
    """Hashed cell of each word with the word before it (the start of the document for the first)."""
    before = np.concatenate([[1], ids[:-1]]).astype(np.uint64)
    h = (before * np.uint64(0x9E3779B97F4A7C15)) ^ (ids.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F))
    return (((h ^ (h >> np.uint64(29))) * np.uint64(0xBF58476D1CE4E5B9)) >> np.uint64(64 - CELL_BITS)).astype(np.int64)


def counts(docs: DataFrame, target: F.Column, vocab: dict[bytes, int], text_col: str = "text") -> np.ndarray:
    """Array of two rows (background, target): contexts and words, then cells. Layout: words, contexts, cells."""
    spark = docs.sparkSession
    width, size = 1 << SLICE_BITS, len(vocab) + 2
    padded = -(-size // width) * width
    total, shared = 2 * padded + (1 << CELL_BITS), spark.sparkContext.broadcast(vocab)

    def gather(batches):
        have = np.zeros((2, total), np.int64)
        for batch in batches:
            for part in slices(batch, 1):
                groups: list[list[np.ndarray]] = [[], []]
                for text, is_target in zip(part.column(1).to_pylist(), part.column(0).to_pylist(), strict=True):
                    ids = _ids(text, shared.value)
                    if len(ids):
                        groups[1 if is_target else 0].append(ids)
                for k, held in enumerate(groups):
                    if held:
                        words = np.concatenate(held)
                        contexts = np.concatenate([np.concatenate([[1], x[:-1]]) for x in held])
                        have[k, :padded] += np.bincount(words, minlength=padded)
                        have[k, padded : 2 * padded] += np.bincount(contexts, minlength=padded)
                        have[k, 2 * padded :] += np.bincount(np.concatenate([cells(x) for x in held]), minlength=1 << CELL_BITS)
        have[0] += have[1]  # the background is every document
        for at in range(0, total, width):
            block = have[:, at : at + width]
            if block.any():
                yield pa.RecordBatch.from_arrays([pa.array([at // width], pa.int32()), pa.array([np.ascontiguousarray(block).tobytes()], pa.binary())], ["slice", "n"])

    def add(batches):
        held: dict[int, np.ndarray] = {}
        for batch in batches:
            for k in range(batch.num_rows):
                at, block = batch.column(0)[k].as_py(), np.frombuffer(batch.column(1)[k].as_py(), np.int64)
                held[at] = held[at] + block if at in held else block
        for at, block in held.items():
            yield pa.RecordBatch.from_arrays([pa.array([at], pa.int32()), pa.array([block.tobytes()], pa.binary())], ["slice", "n"])

    schema = "slice int, n binary"
    parts = docs.select(F.coalesce(target, F.lit(False)).alias("target"), raw(text_col).alias("text")).mapInArrow(gather, schema)
    summed = parts.repartition(int(spark.conf.get("spark.sql.shuffle.partitions")), "slice").mapInArrow(add, schema)
    out = np.zeros((2, total), np.int64)
    for row in summed.collect():
        out[:, row.slice * width : (row.slice + 1) * width] = np.frombuffer(row.n, np.int64).reshape(2, width)
    return np.concatenate([out[:, :size], out[:, padded : padded + size], out[:, 2 * padded :]], axis=1)


class Models:
    """Both models, background first; `losses` of a word given the one before it, in nats."""

    def __init__(self, vocab: dict[bytes, int], counted: np.ndarray):
        size = len(vocab) + 2
        self.vocab = vocab
        words = counted[:, :size] + ADDED
        self.words = (words / words.sum(axis=1, keepdims=True)).astype(np.float32)
        self.contexts = np.maximum(counted[:, size : 2 * size], 1).astype(np.float32)
        self.seen = counted[:, size : 2 * size] > 0
        self.cells = counted[:, 2 * size :].astype(np.float32)

    def losses(self, text: bytes | None) -> tuple[int, float, float]:
        """Number of words; mean loss under the target and under the background."""
        ids = _ids(text, self.vocab)
        if not len(ids):
            return 0, 0.0, 0.0
        before, at, out = np.concatenate([[1], ids[:-1]]), cells(ids), []
        for k in (1, 0):
            share = np.where(self.seen[k, before], SHARE, 0.0)
            p = share * np.minimum(1.0, self.cells[k, at] / self.contexts[k, before]) + (1 - share) * self.words[k, ids]
            out.append(float(-np.log(p).mean()))
        return len(ids), out[0], out[1]


def fit(docs: DataFrame, target: F.Column, *, text_col: str = "text", most_words: int = VOCABULARY) -> Models:
    vocab = vocabulary(docs, text_col, most_words)
    return Models(vocab, counts(docs, target, vocab, text_col))


def score(docs: DataFrame, models: Models, *, doc_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_col, n_tokens, target_loss, background_loss, score (their difference), selected (score < 0)."""
    shared, kind = docs.sparkSession.sparkContext.broadcast(models), docs.schema[doc_col].dataType.simpleString()

    def make():
        own = shared.value

        def work(batch):
            for part in slices(batch, 1):
                n, a, b = (np.array(x) for x in zip(*map(own.losses, part.column(1).to_pylist()), strict=True))
                yield pa.RecordBatch.from_arrays([part.column(0), *map(pa.array, (n, a, b, a - b, a < b))], [doc_col, "n_tokens", "target_loss", "background_loss", "score", "selected"])

        return work

    schema = f"{doc_col} {kind}, n_tokens bigint, target_loss double, background_loss double, score double, selected boolean"
    return map_batches(docs.select(doc_col, raw(text_col).alias("_raw")), make, schema)
