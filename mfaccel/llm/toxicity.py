"""Toxicity by cumulative-link ordinal regression on sparse text features.

Grades are ordered: 0 is clean, and 1 to GRADES - 1 are ever more severe. One weight for each feature is shared by
all thresholds: P(grade <= k) = logistic(threshold_k - w x). The labels say toxic or not, so the training grade of a toxic
document is found from how many marker words it has: 1, 2-3, 4 or more occurrences (markers are the words that the
labels make likely in toxic documents; their pairs and beginnings do not count). Features are the words, word pairs and beginnings of words
whose likelihood ratio against the label exceeds what chance gives over all features that could; their value is
log2(1 + occurrences).

The fit takes a bounded sample of labelled rows (TRAIN_ROWS, TRAIN_CODES); one task chooses the features and counts them, and the
driver fits the weights to these counts. Scoring reads every whole text once with a model of fixed size.

Edge cases: null and empty texts have no features and get the severity of the bias; labels that are null, of no document
or contradictory teach nothing; without both classes, or without a significant feature, every document has the grades'
base rates and none is toxic; repeated rows score alike; empty tables give no rows; other columns are ignored, or
kept by keep_clean().
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mfaccel.llm import features
from mfaccel.llm.common import LOWER_WORDS, keep_rows, labelled_features, map_batches, raw, slices, trained

TRAIN_ROWS, TRAIN_CODES = 8000, 16_000_000
#: Number of grades, most features, and the least probability of any grade over 0 that makes a text toxic.
GRADES, FEATURES, SPLIT = 4, 512, 0.35


def _counted(text: bytes | None) -> np.ndarray:
    """Codes of all words, word pairs and beginnings of words, with repeats."""
    text = text or b""
    return np.concatenate([*features.words_view(text, pairs=True)[:2], features.stems_view(text)])


def _counted_after_size(text: bytes | None) -> np.ndarray:
    """The number of words, then the codes of _counted(), which begin with those of the words."""
    return np.concatenate([[len((text or b"").translate(LOWER_WORDS).split())], _counted(text)])


def _chance_ratio(a: np.ndarray, b: np.ndarray, n1: int, n0: int) -> np.ndarray:
    """Twice the log likelihood ratio of a 2 x 2 table, signed by the direction; a of n1 and b of n0 have the feature."""

    def part(k, n):
        return np.where(k > 0, k * np.log(np.maximum(k, 1e-300) / np.maximum(n, 1e-300)), 0.0)

    both, rest = part(a, n1) + part(n1 - a, n1) + part(b, n0) + part(n0 - b, n0), part(a + b, n1 + n0) + part(n1 + n0 - a - b, n1 + n0)
    return 2 * (both - rest) * np.sign(a * n0 - b * n1)


class Ordinal:
    def __init__(self, rows: list[np.ndarray], toxic: np.ndarray, words: list[int]):
        """`words`: how many codes at the start of each row are those of single words. Chooses and counts the features; fitted() does the rest."""
        self.counts = self.grades = None
        self.place = np.full(1 << features.BITS, -1, np.int16)
        self.weights, self.cuts = np.zeros(0), np.array([30.0] * (GRADES - 1))
        n1, n0 = int((toxic == 1).sum()), int((toxic != 1).sum())
        if not n1 or not n0:
            return
        a, b = np.zeros(1 << features.BITS), np.zeros(1 << features.BITS)
        for codes, y in zip(rows, toxic, strict=True):
            (a if y == 1 else b)[features.distinct(codes.astype(np.int64))] += 1
        able = np.flatnonzero(a + b >= 3)
        gain = _chance_ratio(a[able], b[able], n1, n0)
        best = np.flatnonzero(np.abs(gain) > 2 * np.log(max(2, len(able))) + 3)
        best = best[np.argsort(-np.abs(gain[best]), kind="stable")][:FEATURES]
        strong, gain = able[best], gain[best]
        self.place[strong] = np.arange(len(strong))
        most = max(map(len, rows))
        self.counts = np.empty((len(rows), len(strong)), np.min_scalar_type(most))
        if len(strong):
            for k, codes in enumerate(rows):
                self.counts[k] = self._counts(codes)
        marker = np.zeros(1 << features.BITS, bool)
        marker[strong[gain > 0]] = True
        hits = np.array([int(marker[c[:n]].sum()) for c, n in zip(rows, words, strict=True)])
        self.grades = np.where(toxic == 1, 1 + (hits >= 2).astype(int) + (hits >= 4), 0)

    def fitted(self) -> "Ordinal":
        """With the weights and cuts of what was counted."""
        if self.counts is not None:
            x, grades, self.counts, self.grades = np.log2(1.0 + self.counts, dtype=np.float64), self.grades, None, None
            self._fit(x, grades)
        return self

    def _counts(self, codes: np.ndarray) -> np.ndarray:
        places = self.place[codes]
        return np.bincount(places[places >= 0], minlength=int(self.place.max()) + 1)

    def _values(self, codes: np.ndarray) -> np.ndarray:
        return np.log2(1.0 + self._counts(codes))

    def _fit(self, x: np.ndarray, grades: np.ndarray, ridge: float = 0.003, rounds: int = 800) -> None:
        """Penalised likelihood by gradient steps with step sizes of their own (Adam); cuts stay ordered by log gaps."""
        n, k = x.shape
        share = np.clip([(grades <= g).mean() for g in range(GRADES - 1)], 1e-4, 1 - 1e-4)
        start = np.maximum.accumulate(np.log(share / (1 - share)) + 1e-3 * np.arange(GRADES - 1))
        at = np.concatenate([np.zeros(k), [start[0]], np.log(np.maximum(np.diff(start), 1e-2))])
        first, second = np.zeros_like(at), np.zeros_like(at)
        ones = np.arange(GRADES - 1)
        for step in range(1, rounds + 1):
            gaps = np.exp(np.clip(at[k + 1 :], -20, 5))
            cuts = at[k] + np.concatenate([[0.0], np.cumsum(gaps)])
            below = 1 / (1 + np.exp(-np.clip(cuts[None, :] - (x @ at[:k])[:, None], -30, 30)))
            edges = np.concatenate([np.zeros((n, 1)), below, np.ones((n, 1))], axis=1)
            p = np.maximum(np.diff(edges, axis=1)[np.arange(n), grades], 1e-12)
            slope = below * (1 - below)
            up = np.where(grades[:, None] == ones, slope, 0) / p[:, None]
            down = np.where(grades[:, None] == ones + 1, slope, 0) / p[:, None]
            of_cuts = -(up - down).sum(axis=0) / n
            of_weights = (x.T @ (up - down).sum(axis=1)) / n + ridge / np.sqrt(n) * at[:k]
            later = np.cumsum(of_cuts[::-1])[::-1]
            grade = np.concatenate([of_weights, [later[0]], later[1:] * gaps])
            first, second = 0.9 * first + 0.1 * grade, 0.99 * second + 0.01 * grade**2
            at -= 0.08 * (first / (1 - 0.9**step)) / (np.sqrt(second / (1 - 0.99**step)) + 1e-8)
        self.weights = at[:k]
        self.cuts = at[k] + np.concatenate([[0.0], np.cumsum(np.exp(np.clip(at[k + 1 :], -20, 5)))])

    def grade(self, text: bytes | None) -> np.ndarray:
        """Probability of each grade."""
        lift = float(self._values(_counted(text)) @ self.weights) if len(self.weights) else 0.0
        below = 1 / (1 + np.exp(-np.clip(self.cuts - lift, -30, 30)))
        return np.diff(np.concatenate([[0.0], below, [1.0]]))


def _count(rows: list[np.ndarray], toxic: np.ndarray) -> Ordinal:
    return Ordinal([c[1:] for c in rows], toxic, [int(c[0]) for c in rows])


def fit(docs: DataFrame, labels: DataFrame, *, doc_col: str = "doc_id", text_col: str = "text", label_col: str = "toxic", most_rows: int = TRAIN_ROWS) -> Ordinal:
    found = labelled_features(docs, labels, label_col, F.lit(True), _counted_after_size, doc_col, text_col, most_rows, TRAIN_CODES)
    return trained(found, _count).fitted()


def score(docs: DataFrame, model: Ordinal, *, doc_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_col, severity (expected grade), grade (the likeliest), p_toxic (of any grade over 0), toxic."""
    shared, kind = docs.sparkSession.sparkContext.broadcast(model), docs.schema[doc_col].dataType.simpleString()

    def make():
        own = shared.value

        def work(batch):
            for part in slices(batch, 1):
                p = np.stack([own.grade(t) for t in part.column(1).to_pylist()])
                columns = [p @ np.arange(GRADES), p.argmax(axis=1).astype(np.int32), 1 - p[:, 0], 1 - p[:, 0] >= SPLIT]
                yield pa.RecordBatch.from_arrays([part.column(0), *map(pa.array, columns)], [doc_col, "severity", "grade", "p_toxic", "toxic"])

        return work

    return map_batches(docs.select(doc_col, raw(text_col).alias("_raw")), make, f"{doc_col} {kind}, severity double, grade int, p_toxic double, toxic boolean")


def keep_clean(docs: DataFrame, model: Ordinal, *, text_col: str = "text") -> DataFrame:
    """The documents, all columns kept, that are not toxic."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    return keep_rows(docs, text_col, lambda: lambda texts: [1 - shared.value.grade(t)[0] < SPLIT for t in texts])
