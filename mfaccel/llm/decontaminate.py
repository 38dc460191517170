"""Benchmark decontamination: training documents are scanned for word windows of benchmark items.

Method: the items' windows (`size` consecutive words; a shorter item is one window) form a hash set that
is broadcast in pieces of a checked size. Every document is read once per piece: a rolling hash over
dictionary codes finds candidate windows in a bitmap, and the exact window decides. Nothing is shuffled.

Words: ASCII letters are lower-cased; digits, a-z and all code points from U+0080 on form words.

Edge cases: a null or empty text has no words and no hits; an item with no words makes no window; an item
whose id is null marks words but is not listed, ids that are no whole numbers fail the query; repeated documents are kept as they are, repeated items
count once per id; empty tables work; other columns are ignored.
"""

from __future__ import annotations

import uuid
from itertools import repeat

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mfaccel.llm.common import LOWER_WORDS, cut, keep_rows, map_batches, raw, slices

WINDOW = 10
#: Bytes of item text that one broadcast piece may hold. Its hash set takes about 30 times that in a worker.
PIECE_BYTES = 4 << 20
_BITS = 22


def words_of(text: bytes | None) -> list[bytes]:
    return text.translate(LOWER_WORDS).split() if text else []


class Windows:
    """Distinct windows of a piece of the items, for exact lookups."""

    def __init__(self, items: list[tuple[int | None, bytes | None]], size: int):
        self.vocab: dict[bytes, int] = {}
        self.found: dict[int, dict[bytes, list]] = {}
        for item, text in items:
            words = words_of(text)
            if words:
                codes = np.array([self.vocab.setdefault(w, len(self.vocab) + 1) for w in words], np.int64)
                n = min(size, len(codes))
                known = self.found.setdefault(n, {})
                for k in range(len(codes) - n + 1):
                    owners = known.setdefault(codes[k : k + n].tobytes(), [])
                    if not owners or owners[-1] != item:
                        owners.append(item)
        self.bitmaps = {}
        for n, known in self.found.items():
            grid = np.frombuffer(b"".join(known), np.int64).reshape(-1, n)
            self.bitmaps[n] = np.zeros(1 << _BITS, bool)
            self.bitmaps[n][self._hash(grid.T, grid.shape[0])] = True

    @staticmethod
    def _hash(columns, count: int) -> np.ndarray:
        h = np.zeros(count, np.uint64)
        for column in columns:
            h *= np.uint64(0x9E3779B97F4A7C15)
            h += column.astype(np.uint64)
            h ^= h >> np.uint64(29)
        return (h * np.uint64(0xBF58476D1CE4E5B9)) >> np.uint64(64 - _BITS)

    def scan(self, texts: list[bytes | None]) -> list[tuple[int, list[tuple[int, int]], list]]:
        """Per text: number of words, hit runs [first, end) of words, ids of items with a window in it."""
        all_words = [words_of(t) for t in texts]
        gap = max(self.found, default=1)
        sizes = np.array([len(w) for w in all_words], np.int64)
        starts = np.zeros(len(texts), np.int64)
        np.cumsum(sizes[:-1] + gap, out=starts[1:])
        codes = np.zeros(int(sizes.sum()) + gap * (len(texts) + 1), np.int64)
        get = self.vocab.get
        for at, words in zip(starts.tolist(), all_words, strict=True):
            codes[at : at + len(words)] = np.fromiter(map(get, words, repeat(0)), np.int64, len(words))
        unknown = np.concatenate([[0], np.cumsum(codes == 0)])
        edge = np.zeros(len(codes) + 1, np.int64)
        items: dict[int, set] = {}
        for n, known in self.found.items():
            whole = np.flatnonzero(unknown[n:] == unknown[:-n])
            if not whole.size:
                continue
            near = whole[self.bitmaps[n][self._hash((codes[whole + k] for k in range(n)), whole.size)]]
            owners = np.searchsorted(starts, near, "right") - 1
            for at, doc in zip(near.tolist(), owners.tolist(), strict=True):
                ids = known.get(codes[at : at + n].tobytes())
                if ids is not None:
                    edge[at] += 1
                    edge[at + n] -= 1
                    items.setdefault(doc, set()).update(ids)
        hit = np.cumsum(edge) > 0
        out = []
        for k, (at, n) in enumerate(zip(starts.tolist(), sizes.tolist(), strict=True)):
            runs: list[tuple[int, int]] = []
            if k in items:
                turns = np.flatnonzero(np.diff(np.concatenate([[0], hit[at : at + n].view(np.int8), [0]])))
                runs = list(map(tuple, turns.reshape(-1, 2).tolist()))
            out.append((n, runs, sorted(i for i in items.get(k, ()) if i is not None)))
        return out


def merge_runs(a: list[tuple[int, int]], b: list[tuple[int, int]]) -> list[tuple[int, int]]:
    out: list[list[int]] = []
    for first, end in sorted([*a, *b]):
        if out and first <= out[-1][1]:
            out[-1][1] = max(out[-1][1], end)
        else:
            out.append([first, end])
    return [tuple(x) for x in out]


def without_words(text: bytes, runs: list[tuple[int, int]]) -> bytes:
    """The text without the bytes from the first to the last word of each run."""
    mapped, kept, at, word, runs = text.translate(LOWER_WORDS), [], 0, 0, list(runs)
    pos, n = 0, len(mapped)
    while runs and pos < n:
        while pos < n and mapped[pos] == 32:
            pos += 1
        end = mapped.find(b" ", pos)
        end = n if end < 0 else end
        if word == runs[0][0]:
            kept.append(text[at:pos])
        word += 1
        if word == runs[0][1]:
            at = end
            runs.pop(0)
        pos = end
    return b"".join([*kept, text[at:]])


_RUNS = pa.list_(pa.struct([("first", pa.int64()), ("end", pa.int64())]))


def pieces_of(benchmark: DataFrame, item_col: str, text_col: str, piece_bytes: int) -> list[DataFrame]:
    """The distinct items in pieces of about `piece_bytes` of text at most, by a hash of id and text."""
    items = benchmark.select(F.col(item_col).cast("long").alias("item"), raw(text_col).alias("text")).where("text IS NOT NULL").distinct()
    total = items.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = -(-total // piece_bytes) or 1
    if n == 1:
        return [items]
    bucket = F.pmod(F.xxhash64("item", "text"), F.lit(2 * n))
    return [items.where(bucket == k) for k in range(2 * n)]


def flag(
    docs: DataFrame, benchmark: DataFrame, *, doc_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id",
    item_text_col: str = "text", size: int = WINDOW, piece_bytes: int = PIECE_BYTES, keep_text: bool = False,
) -> DataFrame:
    """One row per document: doc_col, n_words, runs (hit word ranges), items (ids), and with keep_text the text."""
    spark = docs.sparkSession
    out = docs.select(F.col(doc_col).alias("id"), raw(text_col).alias("text"))
    kind, pieces = out.schema["id"].dataType.simpleString(), pieces_of(benchmark, item_col, item_text_col, piece_bytes)
    for turn, piece in enumerate(pieces):
        shared = spark.sparkContext.broadcast(Windows([(r.item, bytes(r.text)) for r in piece.collect()], size))
        last = turn == len(pieces) - 1

        def make(shared=shared, first=not turn, text_out=keep_text or not last):
            windows = shared.value

            def work(batch):
                for part in slices(batch, 1):
                    texts = part.column(1).to_pylist()
                    found = windows.scan(texts)
                    if not first:
                        olds = zip(part.column(3).to_pylist(), part.column(4).to_pylist(), strict=True)
                        found = [
                            (n, merge_runs(runs, [(x["first"], x["end"]) for x in old_runs]), sorted({*ids, *old_ids}))
                            for (n, runs, ids), (old_runs, old_ids) in zip(found, olds, strict=True)
                        ]
                    yield pa.RecordBatch.from_arrays(
                        [
                            part.column(0),
                            part.column(1) if text_out else pa.nulls(part.num_rows, pa.binary()),
                            pa.array([x[0] for x in found], pa.int64()),
                            pa.array([[{"first": a, "end": b} for a, b in x[1]] for x in found], _RUNS),
                            pa.array([x[2] for x in found], pa.list_(pa.int64())),
                        ],
                        ["id", "text", "n_words", "runs", "items"],
                    )

            return work

        schema = f"id {kind}, text binary, n_words bigint, runs array<struct<first: bigint, end: bigint>>, items array<bigint>"
        out = map_batches(out, make, schema)
        if not last:  # one piece in a worker's memory at a time
            out = cut(out)
    return out.withColumnRenamed("id", doc_col) if keep_text else out.drop("text").withColumnRenamed("id", doc_col)


def digest(flagged: DataFrame, doc_col: str = "doc_id") -> DataFrame:
    """The contract's columns from those of flag()."""
    names = F.array_sort(F.transform(F.array_distinct("items"), lambda x: x.cast("string")))
    hits = F.aggregate("runs", F.lit(0).cast("long"), lambda s, x: s + x["end"] - x["first"])
    return flagged.select(
        doc_col, "n_words", hits.alias("n_hit"), F.size("items").cast("long").alias("n_items"),
        F.sha2(F.concat_ws(",", names).cast("binary"), 256).alias("items_sha256"), (hits > 0).alias("contaminated"),
    )


def remove(docs: DataFrame, benchmark: DataFrame, *, mode: str = "documents", text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text", size: int = WINDOW, piece_bytes: int = PIECE_BYTES) -> DataFrame:
    """The documents, all columns kept, without those that hold a window (mode "documents") or without the
    words of the windows themselves (mode "spans"; other texts stay byte for byte)."""
    if mode not in ("documents", "spans"):
        raise ValueError(mode)
    pieces = pieces_of(benchmark, item_col, item_text_col, piece_bytes)
    if mode == "spans" and len(pieces) > 1:  # spans of all pieces go at once: words that one piece removes may belong to another's window
        return _without_found_spans(docs, benchmark, text_col, item_col, item_text_col, size, piece_bytes)
    out = docs
    for turn, piece in enumerate(pieces):
        if turn:  # one piece in a worker's memory at a time
            out = cut(out)
        shared = docs.sparkSession.sparkContext.broadcast(Windows([(r.item, bytes(r.text)) for r in piece.collect()], size))
        out = (_without_documents if mode == "documents" else _without_spans)(out, text_col, shared)
    return out


def _without_found_spans(docs: DataFrame, benchmark: DataFrame, text_col: str, item_col: str, item_text_col: str, size: int, piece_bytes: int) -> DataFrame:
    """Spans by way of flag(): a document's other columns travel as one struct in place of its id."""
    row, names = f"_row_{uuid.uuid4().hex}", docs.columns
    rows = docs.select(F.struct(*[F.col(c) for c in names]).alias(row), F.col(text_col).alias("text"))
    found = flag(rows, benchmark, doc_col=row, item_col=item_col, item_text_col=item_text_col, size=size, piece_bytes=piece_bytes, keep_text=True)
    kind = docs.schema[text_col].dataType

    def make():
        def work(batch):
            texts, runs = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            new = [without_words(t, [(x["first"], x["end"]) for x in r]) if r else t for t, r in zip(texts, runs, strict=True)]
            yield pa.RecordBatch.from_arrays([pa.array(new, pa.binary()), batch.column(2)], ["text", row])

        return work

    new = map_batches(found.select("text", "runs", row), make, f"text binary, {row} {rows.schema[row].dataType.simpleString()}")
    return new.select(*[F.col("text").cast("string").cast(kind).alias(c) if c == text_col else F.col(f"{row}.{c}").alias(c) for c in names])


def _without_documents(docs: DataFrame, text_col: str, shared) -> DataFrame:
    return keep_rows(docs, text_col, lambda: lambda texts: [not runs for _, runs, _ in shared.value.scan(texts)])


def _without_spans(docs: DataFrame, text_col: str, shared) -> DataFrame:
    at = docs.columns.index(text_col)

    def make():
        def work(batch):
            texts = batch.column(at).cast(pa.binary()).to_pylist()
            found = (shared.value.scan([t])[0][1] for t in texts)
            new = [without_words(t, runs) if runs else t for t, runs in zip(texts, found, strict=True)]
            columns = list(batch.columns)
            columns[at] = pa.array(new, pa.binary()).cast(batch.schema.field(at).type)
            yield pa.RecordBatch.from_arrays(columns, schema=batch.schema)

        return work

    return map_batches(docs, make, docs.schema)
