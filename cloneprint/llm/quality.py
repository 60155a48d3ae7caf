"""Quality classifier: regularised quadratic discriminant over document statistics.

Statistics of a whole text (counts of byte classes, words, lines, repeats) are turned into logs and
log-odds, so that they come near to normal. Each class gets a mean and a covariance, shrunk towards the pooled
one and then towards its diagonal; scores are differences of Mahalanobis log densities, from Cholesky
factors computed once. The model is fitted on at most ``FIT_ROWS`` labelled rows, chosen by a hash of
their id (the documented bound); everything is scored.

Defined cases: a null text counts as empty; an empty text has the all-zero statistics and is scored like any
other; null labels are not learned from; if several labels of one id differ, each counts. With one class only, every score is that
class's share. With no labelled row, every score is 0.5. Rows come back as often as they occur, but equal ones are learned from once. ``score`` keeps the
columns it is told to, whatever their names; one that is named like its result gives way to it.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, StructField, StructType

from .common import lean, quoted
from .words import text_bytes, word_hashes

FIT_ROWS = 8_000  # labelled rows that the model is fitted on, at most
SHRINK_POOLED, SHRINK_DIAGONAL = 0.2, 0.1
CUT = 0.7
STATISTICS = (
    "log words", "log characters", "log lines", "upper", "lower", "digit", "comma or stop", "other mark", "non-ascii", "blank",
    "word length", "words with marks", "distinct words", "distinct pairs", "most frequent word", "line length", "repeated lines",
)

_CLASS = np.zeros(256, np.uint8)  # 0 other mark, 1 upper, 2 lower, 3 digit, 4 comma or stop, 5 non-ascii, 6 blank, 7 newline, 8 continuation byte
_CLASS[65:91], _CLASS[97:123], _CLASS[48:58] = 1, 2, 3
_CLASS[[44, 46]], _CLASS[128:192], _CLASS[192:] = 4, 8, 5
_CLASS[[9, 11, 12, 13, 32]], _CLASS[10] = 6, 7


def _odds(part: float, whole: float, usual: float, weight: float) -> float:
    """Log-odds of a share, as if ``weight`` more had been seen with the ``usual`` share: short texts stay near it."""
    return float(np.log((part + weight * usual) / (max(whole - part, 0) + weight * (1 - usual))))


def statistics(text: bytes | None) -> list[float]:
    """The transformed statistics of one whole text."""
    text = text or b""
    counts = np.bincount(_CLASS[np.frombuffer(text, np.uint8)], minlength=9)
    other, upper, lower, digit, stops, wide, blank, newline, _ = counts.tolist()
    chars = len(text) - int(counts[8])
    hashed, start, end = word_hashes(text)
    words = len(hashed)
    distinct, often = np.unique(hashed, return_counts=True)
    pairs = len(np.unique(hashed[:-1] * np.uint64(3) + hashed[1:])) if words > 1 else 0
    lines = text.split(b"\n") if text else []
    full = [x for x in lines if x]
    visible = chars - blank - newline
    often_most = int(often.max()) if words else 0
    return [
        np.log1p(words), np.log1p(chars), np.log1p(len(lines)),
        _odds(upper, visible, 0.02, 40), _odds(lower, visible, 0.93, 40), _odds(digit, visible, 0.002, 40), _odds(stops, visible, 0.02, 40),
        _odds(other, visible, 0.002, 40), _odds(wide, visible, 0.03, 40), _odds(blank, chars, 0.15, 40),
        np.log((int((end - start).sum()) + 6.0 * 10) / (words + 10)), _odds(other, words, 0.01, 20), _odds(len(distinct), words, 0.8, 20), _odds(pairs, words - 1, 0.98, 20),
        _odds(often_most, words, 0.1, 20), np.log((words + 10.0) / (len(full) + 1)), _odds(len(full) - len(set(full)), len(full), 0.02, 4),
    ]


class Discriminant:
    """Two normal classes with shrunk covariances; score = posterior of class 1."""

    def __init__(self, x: np.ndarray, y: np.ndarray):
        self.mean, self.chol, self.offset, self.classes = {}, {}, {}, sorted(set(y.tolist()))
        self.share = float(y.mean()) if len(y) else 0.5
        if len(self.classes) < 2:
            return
        self.scale = x.std(axis=0) + 1e-6
        x = x / self.scale
        centred = {c: x[y == c] - x[y == c].mean(axis=0) for c in self.classes}
        pooled = sum(z.T @ z for z in centred.values()) / len(x)
        for c, z in centred.items():
            cov = z.T @ z / len(z)
            cov = (1 - SHRINK_POOLED) * cov + SHRINK_POOLED * pooled
            cov = (1 - SHRINK_DIAGONAL) * cov + SHRINK_DIAGONAL * (np.diag(np.diag(cov)) + 1e-3 * np.eye(len(cov)))
            self.mean[c], self.chol[c] = x[y == c].mean(axis=0), np.linalg.inv(np.linalg.cholesky(cov))
            self.offset[c] = np.log(len(z) / len(x)) + np.log(np.diag(self.chol[c])).sum()

    def scores(self, x: np.ndarray) -> np.ndarray:
        if len(self.classes) < 2:
            return np.full(len(x), self.share)
        x = x / self.scale
        lo, hi = self.classes
        density = {c: self.offset[c] - 0.5 * (((x - self.mean[c]) @ self.chol[c].T) ** 2).sum(axis=1) for c in (lo, hi)}
        return 1 / (1 + np.exp(np.clip(density[lo] - density[hi], -500, 500)))


def _measure(batches):
    for batch in batches:
        got = [statistics(t) for t in text_bytes(batch.column(2))]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(got, pa.list_(pa.float64()))], ["doc_id", "y", "x"])


def fold(id_col: str | Column, folds: int) -> Column:
    return F.crc32(F.col(id_col).cast("string") if isinstance(id_col, str) else id_col) % folds


def fit(docs: DataFrame, labels: DataFrame, held_out: Column | None = None, label_col: str = "quality", rows: int = FIT_ROWS) -> Discriminant:
    """Learns from the labelled rows outside ``held_out``, at most ``rows`` of them, drawn by a hash of doc_id."""
    known = labels.select("doc_id", F.col(label_col).cast("int").alias("y")).where("y in (0, 1) and doc_id is not null").distinct()
    if held_out is not None:
        known = known.where(~held_out)
    n = known.count()
    if n > 2 * rows:  # by a share first, so that few rows meet in the task that puts them in order
        known = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 40)) < int((1 << 40) * min(1.0, 1.5 * rows / n)))
    drawn = F.broadcast(known.orderBy(F.xxhash64("doc_id"), "doc_id", "y").limit(rows))  # bounded by `rows`
    measured = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).join(drawn, "doc_id").select("doc_id", "y", "text").mapInArrow(lean(_measure), "doc_id long, y int, x array<double>")
    # repeated rows count once; an id with many texts cannot exceed the bound
    got = measured.distinct().orderBy(F.xxhash64("doc_id"), F.xxhash64("x"), "y").limit(rows).select("y", "x").toPandas()
    x = np.array(got["x"].tolist(), float).reshape(-1, len(STATISTICS))
    order = np.lexsort((*x.T, got["y"].to_numpy(int)))  # the same sums whatever order rows arrive in
    return Discriminant(x[order], got["y"].to_numpy(int)[order])


def _scored(model: Discriminant):
    def run(batches):
        for batch in batches:
            x = np.array([statistics(t) for t in text_bytes(batch.column(batch.num_columns - 1))], float).reshape(-1, len(STATISTICS))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(model.scores(x))], [*batch.schema.names[:-1], "score"])

    return run


def score(docs: DataFrame, model: Discriminant, keep: list[str], score_col: str = "score") -> DataFrame:
    """The columns of ``keep`` with the score of each whole text; they travel in one struct, so that no name can clash."""
    chosen = docs.select(F.struct(*[F.col(quoted(c)) for c in keep]).alias("kept"), F.col("text").cast("string").alias("text"))
    scored = chosen.mapInArrow(lean(_scored(model)), StructType([chosen.schema["kept"], StructField("score", DoubleType())]))
    return scored.select(*[F.col("kept")[c].alias(c) for c in keep if c != score_col], F.col("score").alias(score_col))


def classify(docs: DataFrame, labels: DataFrame, cut: float = CUT) -> DataFrame:
    """doc_id, held_out, score, predicted of every document; learned outside crc32(doc_id) mod 4 = 2."""
    model = fit(docs, labels, fold("doc_id", 4) == 2)
    out = score(docs, model, ["doc_id"])
    return out.select("doc_id", F.coalesce(fold("doc_id", 4) == 2, F.lit(False)).alias("held_out"), "score", (F.col("score") >= cut).cast("int").alias("predicted"))
