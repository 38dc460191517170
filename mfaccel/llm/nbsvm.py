"""Quality classifier: naive Bayes support vectors.

Indicators of n-grams (of words and of the text's shape) are scaled by the log ratio of their smoothed class
counts; a linear hinge-loss model is fitted to the scaled, unit-length rows by dual coordinate descent, its weights on the
scaled indicators are drawn towards their mean size (a positive number, so that a feature of class 0 speaks for class 0), and a logistic curve through out-of-fold margins makes the score.

The fit takes a bounded sample of labelled rows (TRAIN_ROWS, TRAIN_CODES), in the order of a hash of their ids, and is
done in one task, so that the driver holds the model alone; scoring reads every whole text once, with a model of fixed size.

Edge cases: a null or empty text has no features and gets the score of the bias alone; labels that are null, of
no document, or contradictory teach nothing; with one class only (or none) every score is the smoothed share of
class 1; repeated rows are scored alike; empty tables give no rows; other columns are ignored, or kept by
keep_good().
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from mfaccel.llm import features
from mfaccel.llm.common import keep_rows, labelled_features, map_batches, raw, slices, trained

TRAIN_ROWS, TRAIN_CODES = 8000, 16_000_000
THRESHOLD, FOLDS = 0.3, 5


class NbSvm:
    def __init__(self, rows: list[np.ndarray], labels: np.ndarray, *, alpha: float = 1.0, cost: float = 1.0, beta: float = 0.75, epochs: int = 10, keep: bool = False):
        dim, positive = 1 << features.BITS, labels == 1
        self.share = (positive.sum() + 1) / (len(labels) + 2)
        self.ratio = self.weight = None
        if not positive.any() or positive.all():
            return
        up, down = np.full(dim, alpha), np.full(dim, alpha)
        for codes, is_up in zip(rows, positive, strict=True):
            (up if is_up else down)[codes] += 1
        self.ratio = np.log(up / (alpha + positive.sum())) - np.log(down / (alpha + (~positive).sum()))
        self.ratio[(up == alpha) & (down == alpha)] = 0
        self._descend(rows, np.where(positive, 1.0, -1.0), cost, epochs)
        if not keep:
            self.scaled = self.dual = self.most = None
        self.fitted = self.weight.copy() if keep else None
        size = np.abs(self.weight[self.weight != 0]).mean() if self.weight.any() else 0.0
        self.weight = beta * self.weight + (1 - beta) * size
        self.gain = self.ratio * np.where(self.ratio != 0, self.weight, 0)
        self.square = self.ratio**2
        self.slope, self.shift = 1.0, 0.0

    def _descend(self, rows, signs, cost, epochs):
        """Dual coordinate descent for the hinge loss, whose dual variables lie between 0 and the cost of their row; each class gets the same
        total cost. Rows have length 1 and a constant for the bias, so the curvature of every coordinate is 2."""
        self.weight, self.bias = np.zeros(len(self.ratio)), 0.0
        self.dual, order = np.zeros(len(rows)), np.random.default_rng(7)
        self.scaled = scaled = [(self.ratio[c] / max(1e-9, np.linalg.norm(self.ratio[c]))).astype(np.float32) for c in rows]
        self.most = most = cost * len(signs) / 2 / np.where(signs > 0, (signs > 0).sum(), (signs < 0).sum())
        for _ in range(epochs):
            for k in order.permutation(len(rows)):
                slack = signs[k] * (self.weight[rows[k]] @ scaled[k] + self.bias) - 1
                new = min(max(0.0, self.dual[k] - slack / 2), most[k])
                if new != self.dual[k]:
                    move = (new - self.dual[k]) * signs[k]
                    self.weight[rows[k]] += move * scaled[k]
                    self.bias += move
                    self.dual[k] = new

    def margin(self, codes: np.ndarray) -> float:
        if not len(codes):
            return self.bias
        return float(self.gain[codes].sum() / max(1e-9, np.sqrt(self.square[codes].sum())) + self.bias)

    def calibrate(self, margins: np.ndarray, labels: np.ndarray) -> None:
        """Logistic curve through margins of rows that were not learned from, by damped Newton steps."""
        n1, n0 = (labels == 1).sum(), (labels != 1).sum()
        goal = np.where(labels == 1, (n1 + 1) / (n1 + 2), 1 / (n0 + 2))
        x = np.stack([margins, np.ones(len(margins))], axis=1)
        at = np.array([1.0, 0.0])
        for _ in range(100):
            p = 1 / (1 + np.exp(-np.clip(x @ at, -30, 30)))
            grade = x.T @ (p - goal) + 1e-3 * at
            curve = (x * (p * (1 - p))[:, None]).T @ x + 1e-3 * np.eye(2)
            step = np.linalg.solve(curve, grade)
            at -= step * min(1.0, 5 / max(1e-9, np.abs(step).max()))
        self.slope, self.shift = max(1e-6, float(at[0])), float(at[1])

    def score(self, text: bytes | None) -> float:
        if self.ratio is None:
            return float(self.share)
        return float(1 / (1 + np.exp(-np.clip(self.slope * self.margin(features.indicators(text)) + self.shift, -30, 30))))

    def packed(self) -> "NbSvm":
        """What scoring needs, in single precision."""
        if self.ratio is not None:
            self.gain, self.square = self.gain.astype(np.float32), self.square.astype(np.float32)
            self.ratio, self.weight = True, None
        return self


def fit_rows(rows: list[np.ndarray], labels: np.ndarray) -> NbSvm:
    model = NbSvm(rows, labels)
    if model.ratio is None:
        return model
    fold, margins, used = np.arange(len(rows)) % FOLDS, np.zeros(len(rows)), np.zeros(len(rows), bool)
    for f in range(FOLDS):
        part = NbSvm([r for r, x in zip(rows, fold, strict=True) if x != f], labels[fold != f])
        if part.ratio is not None:
            for k in np.flatnonzero(fold == f):
                margins[k], used[k] = part.margin(rows[k]), True
    if used.any() and len(set(labels[used])) == 2:
        model.calibrate(margins[used], labels[used])
    return model


def _train(rows: list[np.ndarray], labels: np.ndarray) -> NbSvm:
    return fit_rows(rows, labels).packed()


def held_out(doc_col: str) -> F.Column:
    return F.pmod(F.crc32(F.coalesce(F.col(doc_col).cast("string"), F.lit("")).cast("binary")), F.lit(5)) == 0


def fit(docs: DataFrame, labels: DataFrame, *, doc_col: str = "doc_id", text_col: str = "text", label_col: str = "quality", most_rows: int = TRAIN_ROWS) -> NbSvm:
    """Learns from labelled rows whose crc32(id as text) mod 5 is not 0."""
    found = labelled_features(docs, labels, label_col, ~held_out(doc_col), features.indicators, doc_col, text_col, most_rows, TRAIN_CODES)
    return trained(found, _train)


def score(docs: DataFrame, model: NbSvm, *, doc_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_col, held_out, score, predicted for every document."""
    shared, kind = docs.sparkSession.sparkContext.broadcast(model), docs.schema[doc_col].dataType.simpleString()

    def make():
        own = shared.value

        def work(batch):
            for part in slices(batch, 1):
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([own.score(t) for t in part.column(1).to_pylist()], pa.float64())], [doc_col, "score"])

        return work

    scored = map_batches(docs.select(doc_col, raw(text_col).alias("_raw")), make, f"{doc_col} {kind}, score double")
    return scored.select(doc_col, held_out(doc_col).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, model: NbSvm, *, text_col: str = "text") -> DataFrame:
    """The documents, all columns kept, that are predicted to be of class 1."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    return keep_rows(docs, text_col, lambda: lambda texts: [shared.value.score(t) >= THRESHOLD for t in texts])
