"""Hashed sparse text features that the classifiers share.

Three views of a text give n-gram features: its words (one and two in a row), its shape (runs of upper or
lower case letters, digits, line ends and each punctuation mark, two to five in a row), and repeats (a word that is the
one before it, a line that was there before). Feature codes are hashes of content alone, so every process
gives the same ones. Words keep to ASCII lower case, digits and all code points from U+0080 on.
"""

from __future__ import annotations

import zlib
from itertools import repeat

import numpy as np

from mfaccel.llm.common import LOWER_WORDS

#: Size of the feature space, and of the part of it for each length of shape n-grams (each has two such parts).
BITS, SHAPE_BITS = 20, 14
_SHAPE = bytes(
    65 if 65 <= b <= 90 else 97 if 97 <= b <= 122 or b >= 128 else 48 if 48 <= b <= 57 else 32 if b in (9, 11, 12, 13, 32) else b
    for b in range(256)
)
_MIX, _STEP = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9)
_CACHE: dict[bytes, int] = {}
_CACHED = 64_000


def _fold(h: np.ndarray) -> np.ndarray:
    return (((h ^ (h >> np.uint64(31))) * _STEP) >> np.uint64(64 - BITS)).astype(np.int64)


def word_codes(words: list[bytes]) -> np.ndarray:
    """A number for each word, the same in every process; known words are looked up."""
    if len(_CACHE) > _CACHED:
        _CACHE.clear()
    codes = list(map(_CACHE.get, words, repeat(-1)))
    if -1 in codes:
        for k, code in enumerate(codes):
            if code < 0:
                word = words[k]
                codes[k] = code = zlib.crc32(word) | (zlib.adler32(word) << 32 & 0x7FFFFFFF00000000)
                if len(word) <= 64:
                    _CACHE[word] = code
    return np.array(codes, np.uint64)


#: Lengths in bytes of the word beginnings that stems_view() gives.
STEMS = (4, 5, 6, 7, 8)
_STEM_ROWS: dict[bytes, int] = {}
_STEM_CODES = np.empty((1 << 14, len(STEMS)), np.int32)
_STEMS_CACHED = 64_000


def _stem_row(word: bytes) -> int:
    """Place of a word's codes in the table; words that begin alike, as far as beginnings count, share one."""
    global _STEM_CODES
    short = word[: max(STEMS)]
    row = _STEM_ROWS.get(short, -1)
    if row < 0:
        row = _STEM_ROWS[short] = len(_STEM_ROWS)
        if row == len(_STEM_CODES):
            _STEM_CODES = np.concatenate([_STEM_CODES, np.empty_like(_STEM_CODES)])
        _STEM_CODES[row] = [zlib.crc32(short[:n], n) >> (32 - BITS) if len(short) >= n else -1 for n in STEMS]
    return row


def stems_view(text: bytes) -> np.ndarray:
    """Codes of the beginnings of all words, with repeats; a word gives those that it is longer than or equal to."""
    if len(_STEM_ROWS) > _STEMS_CACHED:
        _STEM_ROWS.clear()
    most = max(STEMS)
    words = [w[:most] for w in text.translate(LOWER_WORDS).split()]
    rows = list(map(_STEM_ROWS.get, words, repeat(-1)))
    if -1 in rows:
        rows = [row if row >= 0 else _stem_row(word) for row, word in zip(rows, words, strict=True)]
    codes = _STEM_CODES[rows].reshape(-1).astype(np.int64) if rows else np.zeros(0, np.int64)
    return codes[codes >= 0]


def words_view(text: bytes, pairs: bool = True) -> list[np.ndarray]:
    codes = word_codes(text.translate(LOWER_WORDS).split()) * _MIX
    out = [_fold(codes + np.uint64(1))]
    if pairs and len(codes) > 1:
        out.append(_fold(codes[:-1] * np.uint64(3) ^ (codes[1:] + np.uint64(2))))
        again = int((codes[1:] == codes[:-1]).sum())
        if again:
            share = int(min(7, 8 * again / len(codes)))
            out.append(_fold(np.arange(share + 1, dtype=np.uint64) * _MIX + np.uint64(77)))
    return out


def shape_view(text: bytes, most: int = 5) -> list[np.ndarray]:
    kinds = np.frombuffer(text.translate(_SHAPE), np.uint8)
    runs = kinds[np.flatnonzero(np.diff(kinds, prepend=np.uint8(0)))].astype(np.uint64)
    out, grams = [], runs * _MIX
    for n in range(2, most + 1):
        if len(runs) < n:
            break
        grams = (grams[:-1] * np.uint64(257)) ^ (runs[n - 1 :] * _MIX + np.uint64(n))
        counts = np.bincount(_fold(grams) >> (BITS - SHAPE_BITS), minlength=1 << SHAPE_BITS)
        codes = np.flatnonzero(counts)
        often = codes[counts[codes] * 16 >= len(runs)]  # also as a mark of what the text is made of
        out += [codes + (2 * n << SHAPE_BITS), often + (2 * n + 1 << SHAPE_BITS)]
    lines = text.split(b"\n")
    repeated = len(lines) - len(set(lines))
    if repeated:
        share = int(min(7, 8 * repeated / len(lines)))
        out.append(_fold(np.arange(share + 1, dtype=np.uint64) * _MIX + np.uint64(99)))
    return out


_SEEN = np.zeros(1 << BITS, np.int32)


def distinct(codes: np.ndarray) -> np.ndarray:
    """Each code once, without sorting: the last place that a code was written to is kept."""
    places = np.arange(len(codes), dtype=np.int32)
    _SEEN[codes] = places
    return codes[_SEEN[codes] == places]


def indicators(text: bytes | None, words: bool = True, shape: bool = True) -> np.ndarray:
    """Distinct feature codes of a text; none for a null or empty one."""
    text = text or b""
    views = (words_view(text) if words else []) + (shape_view(text) if shape and text else [])
    return distinct(np.concatenate(views)) if views else np.zeros(0, np.int64)
