"""Quality classifier: n-gram indicators scaled by naive Bayes log-count ratios under a linear hinge-loss model."""

from __future__ import annotations

import re
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import DoubleType, IntegerType, StructField, StructType

from .common import crc_mod, load, slices, small_batches

_TOKEN = re.compile(r"[^\W\d_]+|\d+|[^\w\s]+|_+")
_BITS = 18


def _shape(token: str) -> str:
    if token[0].isalpha():
        return "x" if token.islower() else "X" if token.isupper() and len(token) > 1 else "T"
    return "9" if token[0].isdigit() else token[:3]


class Features:
    """Hashed indicators of a text: words, and runs of one to four shapes (case, digits, the marks themselves, or that the word before is repeated)."""

    def __init__(self, limit: int = 50_000):
        self.known: dict[str, tuple[int, int]] = {}
        self.limit = limit

    def of(self, text: str) -> np.ndarray:
        tokens = _TOKEN.findall(text)
        if not tokens:
            return np.zeros(1, np.int64)  # the empty text has an indicator of its own
        known = self.known
        if len(known) > self.limit:
            known.clear()
        pairs = []
        for t in tokens:
            p = known.get(t)
            if p is None:
                p = known[t] = (xxhash.xxh32_intdigest(t.lower()), xxhash.xxh32_intdigest(_shape(t), 1))
            pairs.append(p)
        both = np.array(pairs, np.uint64)
        word, shape = both[:, 0], both[:, 1].copy()
        again = np.flatnonzero(word[1:] == word[:-1]) + 1
        shape[again] = 0x9E3779B9
        out, run = [word * np.uint64(0x9E3779B97F4A7C15)], np.zeros(len(shape), np.uint64)
        for n in range(1, 5):
            if len(shape) < n:
                break
            run = (run[: len(shape) - n + 1] + shape[n - 1 :]) * np.uint64(0xD6E8FEB86659FD93) + np.uint64(n)
            run ^= run >> np.uint64(29)
            out.append(run * np.uint64(0x9E3779B97F4A7C15))
            run = run[:-1] if len(run) > 1 else run
        return np.unique(np.concatenate(out) >> np.uint64(64 - _BITS)).astype(np.int64)


@dataclass
class Model:
    weights: np.ndarray
    bias: float
    slope: float
    shift: float

    def score(self, features: np.ndarray) -> float:
        margin = (self.weights[features].sum() / np.sqrt(len(features))) + self.bias
        return float(1 / (1 + np.exp(-np.clip(self.slope * margin + self.shift, -30, 30))))


def _descend(rows: list[np.ndarray], y: np.ndarray, ratio: np.ndarray, c: float, epochs: int, seed: int) -> tuple[np.ndarray, float]:
    """Dual coordinate descent for the hinge loss with an L2 penalty; each row is scaled by one over the root of its length."""
    values = [ratio[r] / np.sqrt(len(r)) for r in rows]
    curve = np.array([v @ v + 1 for v in values])
    alpha, w, bias, rng = np.zeros(len(rows)), np.zeros(len(ratio)), 0.0, np.random.default_rng(seed)
    for _ in range(epochs):
        moved = 0.0
        for i in rng.permutation(len(rows)):
            gradient = y[i] * (values[i] @ w[rows[i]] + bias) - 1
            new = min(max(alpha[i] - gradient / curve[i], 0), c)
            if (step := (new - alpha[i]) * y[i]) != 0:
                w[rows[i]] += step * values[i]
                bias += step
                moved = max(moved, abs(step))
                alpha[i] = new
        if moved < 1e-3:
            break
    return w * ratio, bias


def fit(rows: list[np.ndarray], labels: np.ndarray, c: float = 1.0, epochs: int = 20, seed: int = 5) -> Model:
    """Fit on indicator rows and 0/1 labels; margins of five held-out folds give the probability's slope and shift.

    With one class alone, or none, the score is that class's smoothed share for every text.
    """
    size, y = 1 << _BITS, np.where(labels > 0, 1.0, -1.0)
    share = (float((y > 0).sum()) + 1) / (len(y) + 2)
    prior = float(np.log(share / (1 - share)))
    if len(set(y.tolist())) < 2:
        return Model(np.zeros(size), 0.0, 0.0, prior)

    def one(at: np.ndarray) -> tuple[np.ndarray, float]:
        counts = [np.bincount(np.concatenate([rows[i] for i in at if y[i] == s] or [np.zeros(0, np.int64)]), minlength=size) + 1.0 for s in (1, -1)]
        ratio = np.log(counts[0] / counts[0].sum()) - np.log(counts[1] / counts[1].sum())
        return _descend([rows[i] for i in at], y[at], ratio, c, epochs, seed)

    fold = np.random.default_rng(seed).integers(0, 5, len(y))
    margins = np.zeros(len(y))
    for k in range(5):
        w, bias = one(np.flatnonzero(fold != k))
        for i in np.flatnonzero(fold == k):
            margins[i] = w[rows[i]].sum() / np.sqrt(len(rows[i])) + bias
    slope, shift = 1.0, 0.0
    for _ in range(50):  # Newton's method for the logistic map from margin to probability, lightly penalised
        p = 1 / (1 + np.exp(-np.clip(slope * margins + shift, -30, 30)))
        g = np.array([((p - (y > 0)) * margins).sum() + 1e-2 * slope, (p - (y > 0)).sum() + 1e-2 * shift])
        v = p * (1 - p)
        h = np.array([[(v * margins**2).sum() + 1e-2, (v * margins).sum()], [(v * margins).sum(), v.sum() + 1e-2]])
        step = np.linalg.solve(h, g)
        slope, shift = slope - step[0], shift - step[1]
        if not np.isfinite([slope, shift]).all():
            slope, shift = 1.0, 0.0
            break
    w, bias = one(np.arange(len(y)))
    return Model(w, bias, float(max(slope, 1e-3)), float(shift))


def train(docs: DataFrame, labels: DataFrame, label_column: str = "quality", id_column: str = "doc_id", text_column: str = "text", bound: int = 6000, **how) -> Model:
    """Fit on at most ``bound`` labelled documents, those whose ids' hashes are smallest: the documented bound of the sample.

    The ids, ``bound`` rows of numbers, are broadcast to the documents; their indicators come to
    the driver, where the model is fitted. Of several labels of an id the mean counts, halves as 1;
    null labels and ids don't.
    """
    chosen = labels.select(F.col(id_column).cast("long").alias("id"), F.col(label_column).cast("double").alias("label")).dropna().groupBy("id").agg((F.avg("label") >= 0.5).cast("int").alias("label")).orderBy(F.xxhash64("id"), "id").limit(bound)

    def featurise(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made = Features()
        for batch in slices(batches):
            rows = [made.of(x or "").astype("<i4").tobytes() for x in batch.column("text").to_pylist()]
            yield pa.RecordBatch.from_arrays([batch.column("label"), pa.array(rows, pa.binary()), batch.column("id")], ["label", "features", "id"])

    small_batches(docs.sparkSession)
    texts = docs.select(F.col(id_column).cast("long").alias("id"), F.col(text_column).cast("string").alias("text"))
    found = texts.join(F.broadcast(chosen), "id").select("id", "label", "text").mapInArrow(featurise, "label int, features binary, id long").toArrow().to_pylist()
    found.sort(key=lambda r: (r["id"], r["features"]))
    return fit([np.frombuffer(r["features"], "<i4").astype(np.int64) for r in found], np.array([r["label"] for r in found]), **how)


def score(docs: DataFrame, model: Model, text_column: str = "text") -> DataFrame:
    """Add ``score`` (probability of label 1) and ``predicted`` (1 from 0.5 on) to ``docs``; null is the empty text; columns of those names are replaced."""
    docs = docs.drop("score", "predicted")
    spark = docs.sparkSession
    small_batches(spark)
    shared = spark.sparkContext.broadcast(Model(model.weights.astype(np.float32), model.bias, model.slope, model.shift))

    def judge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        made, m = Features(), shared.value
        for batch in slices(batches, column=text_column):
            scores = [m.score(made.of(x or "")) for x in batch.column(text_column).to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(scores, pa.float64()), pa.array([int(x >= 0.5) for x in scores], pa.int32())], [*batch.schema.names, "score", "predicted"])

    return docs.mapInArrow(judge, StructType([*docs.schema.fields, StructField("score", DoubleType()), StructField("predicted", IntegerType())]))


def op6_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = load(spark, sf_dir, "documents").select("doc_id", "text")
    labels = load(spark, sf_dir, "labels").filter(crc_mod("doc_id", 3) != 1)
    held = (crc_mod("doc_id", 3) == 1).alias("held_out")
    return score(docs.select("doc_id", held, "text"), train(docs, labels)).select("doc_id", "held_out", "score", "predicted")
