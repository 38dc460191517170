"""Byte-level BPE encoding and decoding with the tokenizers library over Arrow batches.

A rank file (base64 token, rank) is turned into the library's BPE model: bytes become printable characters
by the usual byte-to-character table, and every way to join two known tokens into a third is a merge, by the
third one's rank. A text is split by the pre-tokenizer pattern; each distinct piece is encoded once by the library, and its ids and
offsets stay in a bounded cache of the worker; a text's offsets are those of its pieces, moved to where they stand. Decoding writes
the tokens' characters back as bytes by the table's inverse and joins them, so characters that are split between tokens come
back whole; a cut sequence is decoded with replacement characters. Tokens that hold only a part of a character are counted by their offsets, which overlap.

Edge cases: null and empty texts have no tokens and decode to the empty string; very long texts are encoded
piece by piece; repeated rows stay; no special token is ever made: their strings are ordinary text.
"""

from __future__ import annotations

import base64
import hashlib
from array import array
from itertools import repeat

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from mfaccel.llm.common import map_batches, raw, slices

CACHE_PIECES, CACHED_CHARS = 400_000, 64


def byte_characters() -> list[str]:
    """The printable stand-in of each byte: itself if it prints in Latin-1, else the next character from U+0100 on."""
    printable = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    spare = iter(range(0x100, 0x200))
    return [chr(b) if b in printable else chr(next(spare)) for b in range(256)]


class Codec:
    def __init__(self, rank_lines: bytes, pattern: str):
        from tokenizers import Tokenizer, models, pre_tokenizers

        self.ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, rank_lines.splitlines()) if token}
        stand_in = byte_characters()
        written = {token: "".join(map(stand_in.__getitem__, token)) for token in self.ranks}
        merges = []
        for token, _ in sorted(self.ranks.items(), key=lambda x: x[1]):
            cuts = [(token[:k], token[k:]) for k in range(1, len(token)) if token[:k] in self.ranks and token[k:] in self.ranks]
            merges += [(written[a], written[b]) for a, b in sorted(cuts, key=lambda ab: (self.ranks[ab[0]], self.ranks[ab[1]]))]
        model = {written[token]: rank for token, rank in self.ranks.items()}
        to_bytes = pre_tokenizers.ByteLevel(add_prefix_space=False, use_regex=False)
        self.of_pieces = Tokenizer(models.BPE(vocab=model, merges=merges, ignore_merges=True))
        self.of_pieces.pre_tokenizer = to_bytes
        self.split = regex.compile(pattern).findall
        byte_of = {character: byte for byte, character in enumerate(stand_in)}
        self.bytes_of: list[bytes] = [b""] * (max(self.ranks.values(), default=-1) + 1)
        for token, rank in model.items():
            self.bytes_of[rank] = bytes(map(byte_of.__getitem__, token))
        self.cache: dict[str, bytes] = {}
        self.spans: dict[str, list[tuple[int, int]]] = {}
        self.parts: dict[str, int] = {}

    def _known(self, pieces: list[list[str]]) -> tuple[dict[str, bytes], dict[str, list[tuple[int, int]]]]:
        """Ids of every piece, and offsets (code point ranges within the piece) of those of several tokens that are not ASCII."""
        if len(self.cache) > CACHE_PIECES:
            self.cache.clear()
            self.spans.clear()
            self.parts.clear()
        missing = list({p for own in pieces for p in own if p not in self.cache})
        long = any(len(p) > CACHED_CHARS for p in missing)
        ids_of, spans_of = (dict(self.cache), dict(self.spans)) if long else (self.cache, self.spans)
        for k in range(0, len(missing), 4096):
            block = missing[k : k + 4096]
            for piece, coded in zip(block, self.of_pieces.encode_batch(block, add_special_tokens=False), strict=True):
                ids_of[piece] = ids = array("I", coded.ids).tobytes()
                spans = None if piece.isascii() or len(ids) == 4 else coded.offsets
                if spans:
                    spans_of[piece] = spans
                if len(piece) <= CACHED_CHARS:
                    if long:
                        self.cache[piece] = ids
                    if spans:
                        self.spans[piece] = spans
                        if n := _parts(spans):
                            self.parts[piece] = n
        return ids_of, spans_of

    def packed(self, texts: list[str]) -> tuple[list[bytes], list[int]]:
        """Each text's ids as little-endian unsigned 32-bit integers, and its number of tokens that hold a part of a character."""
        pieces = [self.split(t) for t in texts]
        ids_of, spans_of = self._known(pieces)
        if spans_of is not self.spans:
            spans_of = {p: x for p, x in spans_of.items() if p not in self.spans}
            extra = {p: n for p, x in spans_of.items() if (n := _parts(x))}
            counts = self.parts | extra if extra else self.parts
        else:
            counts = self.parts
        parts = [0 if t.isascii() else sum(map(counts.get, own, repeat(0))) for t, own in zip(texts, pieces, strict=True)]
        return [b"".join(map(ids_of.__getitem__, own)) for own in pieces], parts

    def with_offsets(self, texts: list[str]) -> list[tuple[np.ndarray, np.ndarray]]:
        """Ids, and the code point range of each token; all parts of a split character name the whole of it."""
        pieces, out = [self.split(t) for t in texts], []
        ids_of, spans_of = self._known(pieces)
        for own in pieces:
            ids = np.frombuffer(b"".join(map(ids_of.__getitem__, own)), "<u4").astype(np.int32)
            ends, spans = np.cumsum([len(self.bytes_of[i]) for i in ids], dtype=np.int64), []
            reached = at = 0
            for piece in own:
                n = len(ids_of[piece]) // 4
                if piece in spans_of:
                    spans += [(reached + a, reached + b) for a, b in spans_of[piece]]
                elif n == 1:
                    spans.append((reached, reached + len(piece)))
                else:  # one byte a character: ends of bytes are ends of characters
                    stops = (ends[at : at + n] - (ends[at - 1] if at else 0) + reached).tolist()
                    spans += zip([reached, *stops[:-1]], stops, strict=True)
                reached, at = reached + len(piece), at + n
            out.append((ids, np.array(spans, np.int32).reshape(-1, 2)))
        return out

    def joined(self, packed: bytes) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, np.frombuffer(packed, "<u4").tolist()))


def _parts(spans: list[tuple[int, int]]) -> int:
    """Tokens that hold a part of a character: their ranges overlap."""
    over = [b[0] < a[1] for a, b in zip(spans, spans[1:], strict=False)]
    return sum(x or y for x, y in zip([False, *over], [*over, False], strict=True))


_CODECS: dict[str, Codec] = {}


def codec(rank_lines: bytes, pattern: str) -> Codec:
    """One codec per worker process, so that its cache lasts over tasks."""
    key = hashlib.sha256(rank_lines + pattern.encode()).hexdigest()
    if key not in _CODECS:
        _CODECS[key] = Codec(rank_lines, pattern)
    return _CODECS[key]


def _shared(spark: SparkSession, path: str, pattern: str):
    with open(path, "rb") as f:  # the tokenizer's own file, of fixed size, on the driver
        return spark.sparkContext.broadcast((f.read(), pattern))


def _mapped(docs: DataFrame, columns: list, path: str, pattern: str, schema: str, each) -> DataFrame:
    shared = _shared(docs.sparkSession, path, pattern)

    def make():
        own = codec(*shared.value)

        def work(batch):
            for part in slices(batch, 1):
                yield pa.RecordBatch.from_arrays([part.column(0), *each(own, part.column(1).to_pylist())], schema_names)

        return work

    schema_names = [x.split()[0] for x in schema.split(", ")]
    return map_batches(docs.select(*columns), make, schema)


def encode(docs: DataFrame, path: str, pattern: str, *, doc_col: str = "doc_id", text_col: str = "text", offsets: bool = False) -> DataFrame:
    """doc_col, ids array<int>; with offsets also starts and ends, code point ranges of the tokens."""
    kind = docs.schema[doc_col].dataType.simpleString()

    def each(own: Codec, texts: list[bytes | None]):
        plain = [(t or b"").decode(errors="replace") for t in texts]
        if not offsets:
            return [pa.array([np.frombuffer(p, "<u4").astype(np.int32) for p in own.packed(plain)[0]], pa.list_(pa.int32()))]
        both = own.with_offsets(plain)
        return [pa.array(list(x), pa.list_(pa.int32())) for x in ([ids for ids, _ in both], [spans[:, 0] for _, spans in both], [spans[:, 1] for _, spans in both])]

    schema = f"{doc_col} {kind}, ids array<int>" + ", starts array<int>, ends array<int>" * offsets
    return _mapped(docs, [doc_col, raw(text_col).alias("_raw")], path, pattern, schema, each)


def decode(coded: DataFrame, path: str, pattern: str, *, doc_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """doc_col, decoded (binary) and text, in which incomplete UTF-8 shows as U+FFFD."""
    kind, shared = coded.schema[doc_col].dataType.simpleString(), _shared(coded.sparkSession, path, pattern)

    def make():
        table = codec(*shared.value).bytes_of

        def work(batch):
            for ids, doc in ((batch.column(1).slice(k, 256), batch.column(0).slice(k, 256)) for k in range(0, batch.num_rows, 256)):
                plain = [b"".join(map(table.__getitem__, x or ())) for x in ids.to_pylist()]
                yield pa.RecordBatch.from_arrays([doc, pa.array(plain, pa.binary()), pa.array([p.decode(errors="replace") for p in plain])], [doc_col, "decoded", "text"])

        return work

    return map_batches(coded.select(doc_col, ids_col), make, f"{doc_col} {kind}, decoded binary, text string")


def round_trip(docs: DataFrame, path: str, pattern: str, *, doc_col: str = "doc_id", text_col: str = "text", keep_ids: bool = False) -> DataFrame:
    """doc_col, n_tokens, ids_sha256, decoded_sha256, n_parts (tokens that hold a part of a character), and with keep_ids
    the ids: every text is encoded, then decoded from the ids alone."""
    kind = docs.schema[doc_col].dataType.simpleString()

    def each(own: Codec, texts: list[bytes | None]):
        packed, parts = own.packed([(t or b"").decode(errors="replace") for t in texts])
        ids = [pa.array([np.frombuffer(p, "<i4") for p in packed], pa.list_(pa.int32()))] if keep_ids else []
        return [
            pa.array([len(p) // 4 for p in packed], pa.int64()),
            pa.array([hashlib.sha256(p).hexdigest() for p in packed]),
            pa.array([hashlib.sha256(own.joined(p)).hexdigest() for p in packed]),
            pa.array(parts, pa.int64()),
            *ids,
        ]

    schema = f"{doc_col} {kind}, n_tokens bigint, ids_sha256 string, decoded_sha256 string, n_parts bigint" + ", ids array<int>" * keep_ids
    return _mapped(docs, [F.col(doc_col), raw(text_col).alias("_raw")], path, pattern, schema, each)
