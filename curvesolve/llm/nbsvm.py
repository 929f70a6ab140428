"""Quality classifier: a linear hinge-loss model over naive-Bayes-weighted n-gram indicators.

Features are indicators of words, adjacent word pairs, and the shapes of words (their marks without
letters and digits) alone, paired and immediately repeated; hashed to a fixed number of columns. Each
column is scaled by the log ratio of its smoothed frequency in the two classes, rows are brought to
unit length, and the hinge-loss model is fitted by dual coordinate descent. Scores are a logistic
function of the margin, fitted on a part of the training rows kept out of the descent.

Training takes at most ``sample`` labelled rows, those of smallest hash; scoring covers all rows.
Inputs of a score are the text alone.

Defined results: null and empty texts get the score of a row without features; labels that are null
are not learned from; with labels of one class every score is about that class's, without labels 1; repeated rows count as they
stand; other columns are ignored.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass
from zlib import crc32

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

COLUMNS = 1 << 18
_SHAPE = re.compile(rb"[0-9A-Za-z\x80-\xff]+").sub
_shapes: dict[bytes, bytes] = {}


def shape(word: bytes) -> bytes:
    got = _shapes.get(word)
    if got is None:
        if len(_shapes) > 300_000:
            _shapes.clear()
        got = _shapes[word] = _SHAPE(b"a", word)[:12]
    return got


def features(text: str | None) -> np.ndarray:
    """Sorted distinct columns of a whole text."""
    words = (text or "").encode("utf-8", "surrogatepass").split()
    forms = [shape(w) for w in words]
    grams = {b"w" + w for w in set(words)}
    grams.update([b"p" + a + b" " + b for a, b in set(zip(words, words[1:]))])
    grams.update([b"s" + f for f in set(forms)])
    grams.update([b"t" + a + b" " + b for a, b in set(zip(forms, forms[1:]))])
    grams.update([b"r" + f for f in {f for a, b, f in zip(words, words[1:], forms) if a == b}])
    grams.add(b"n%d" % len(words).bit_length())
    return np.unique(np.fromiter(map(crc32, grams), np.uint32, len(grams)) % COLUMNS).astype(np.int32)


@dataclass
class Model:
    """weights: per column, already times its log ratio; ratios: for the length of a row."""

    weights: np.ndarray
    ratios: np.ndarray
    bias: float
    slope: float
    shift: float

    def score(self, cols: np.ndarray) -> float:
        length = float(np.sqrt((self.ratios[cols] ** 2).sum())) or 1.0
        margin = float(self.weights[cols].sum()) / length + self.bias
        return float(1 / (1 + np.exp(-np.clip(self.slope * margin + self.shift, -30, 30))))


def log_ratios(rows: list[np.ndarray], y: np.ndarray, smooth: float = 1.0, least: int = 5) -> np.ndarray:
    """Log ratio of a column's share among documents of class 1 to that in class 0; 0 for rare columns."""
    pos, neg = (np.zeros(COLUMNS) for _ in range(2))
    for cols, label in zip(rows, y):
        (pos if label > 0 else neg)[cols] += 1
    n1, n0 = max(1, (y > 0).sum()), max(1, (y <= 0).sum())
    ratio = np.log((pos + smooth) / (n1 + 2 * smooth)) - np.log((neg + smooth) / (n0 + 2 * smooth))
    return np.where(pos + neg >= least, ratio, 0.0)


def descend(rows: list[np.ndarray], y: np.ndarray, ratio: np.ndarray, cost: float = 1.0, rounds: int = 12, seed: int = 3) -> tuple[np.ndarray, float]:
    """Dual coordinate descent for the hinge loss; the bias is a constant column of value 1."""
    w, bias, alpha = np.zeros(COLUMNS), 0.0, np.zeros(len(rows))
    values = [ratio[c] for c in rows]
    values = [v / (np.sqrt((v * v).sum()) or 1.0) for v in values]
    share = max(1e-9, float((y > 0).mean()))
    caps = np.where(y > 0, cost * 0.5 / share, cost * 0.5 / max(1e-9, 1 - share))
    square = np.array([(v * v).sum() + 1.0 for v in values])
    rng = np.random.default_rng(seed)
    for _ in range(rounds):
        moved = 0.0
        for i in rng.permutation(len(rows)):
            grad = y[i] * (w[rows[i]] @ values[i] + bias) - 1
            new = min(max(alpha[i] - grad / square[i], 0.0), caps[i])
            if (d := new - alpha[i]) != 0.0:
                w[rows[i]] += d * y[i] * values[i]
                bias += d * y[i]
                alpha[i] = new
                moved = max(moved, abs(d))
        if moved < 1e-3:
            break
    return w, bias


def fit(rows: list[np.ndarray], y: np.ndarray, seed: int = 3) -> Model:
    """``y``: 1 or -1. A fifth of the rows calibrates the score."""
    if len(set(y.tolist())) < 2:
        return Model(np.zeros(COLUMNS), np.zeros(COLUMNS), 0.0, 0.0, 30.0 if not len(y) or y[0] > 0 else -30.0)
    kept = np.random.default_rng(seed).random(len(rows)) < 0.8
    if len(set(y[kept].tolist())) < 2:
        kept[:] = True
    part = [r for r, k in zip(rows, kept) if k]
    ratio = log_ratios(part, y[kept])
    w, bias = descend(part, y[kept], ratio)
    model = Model(w * ratio, ratio, bias, 1.0, 0.0)
    out = [i for i in range(len(rows)) if not kept[i]] or list(range(len(rows)))
    margin = np.array([float(model.weights[rows[i]].sum()) / (float(np.sqrt((ratio[rows[i]] ** 2).sum())) or 1.0) + bias for i in out])
    target = (y[out] > 0).astype(float)
    target = np.where(target > 0, (target.sum() + 1) / (target.sum() + 2), 1 / (len(out) - target.sum() + 2))
    a, b = 2.0, 0.0
    for _ in range(100):  # Newton steps on the two parameters
        p = 1 / (1 + np.exp(-np.clip(a * margin + b, -30, 30)))
        g = np.array([((p - target) * margin).sum() + 1e-3 * a, (p - target).sum()])
        q = p * (1 - p)
        h = np.array([[(q * margin * margin).sum() + 1e-3, (q * margin).sum()], [(q * margin).sum(), q.sum() + 1e-6]])
        step = np.linalg.solve(h, g)
        a, b = max(a - float(np.clip(step[0], -5, 5)), 0.0), b - float(np.clip(step[1], -5, 5))
        if abs(step).max() < 1e-6:
            break
    model.slope, model.shift = a, b
    return model


def fold(doc_id: Column) -> Column:
    return F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(5))


def train(docs: DataFrame, labels: DataFrame, sample: int = 6000) -> Model:
    """Fit on at most ``sample`` labelled rows outside the held-out fold."""
    chosen = labels.where(F.col("quality").isNotNull() & (fold(F.col("doc_id")) != 0)).select(
        F.col("doc_id").cast("long").alias("_id"), (F.col("quality") * 2 - 1).cast("int").alias("_y")).orderBy(F.xxhash64("_id"), "_y").limit(sample)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows = [features(t.as_py()).tobytes() for t in b.column(2)]
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1), pa.array(rows, pa.binary())], names=["id", "y", "x"])

    # At most ``sample`` narrow rows are broadcast.
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    picked = src.join(F.broadcast(chosen), F.col("doc_id") == F.col("_id")).select("_id", "_y", "text")
    got = sorted(picked.mapInArrow(run, "id long, y int, x binary").collect(), key=lambda r: (r["id"], r["y"], bytes(r["x"])))
    return fit([np.frombuffer(r["x"], np.int32) for r in got], np.array([r["y"] for r in got], float))


def score_documents(docs: DataFrame, model: Model) -> DataFrame:
    """(doc_id, held_out, score, predicted at 0.3) of every document."""
    sent = docs.sparkSession.sparkContext.broadcast(model)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            scores = [sent.value.score(features(t.as_py())) for t in b.column(1)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(scores, pa.float64())], names=["doc_id", "score"])

    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return src.mapInArrow(run, "doc_id long, score double").select(
        "doc_id", F.coalesce(fold(F.col("doc_id")) == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))


def keep_good(docs: DataFrame, labels: DataFrame, least: float = 0.3, **options) -> DataFrame:
    """The documents whose score reaches ``least``, columns unchanged."""
    model = docs.sparkSession.sparkContext.broadcast(train(docs, labels, **options))

    @F.pandas_udf("double")
    def score(text: pd.Series) -> pd.Series:
        return text.map(lambda t: model.value.score(features(t)))

    return docs.where(score(F.col("text").cast("string")) >= least)
