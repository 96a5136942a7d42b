"""Quality scores from preference pairs: a Bradley-Terry model on features of the whole text.

A document marked good is preferred to one marked bad.  The score is linear in the features, and is
learned by logistic loss on the difference of the features of the two documents of a pair.  The
threshold is the quantile of the learned scores at the share of bad documents among those learned
from; scores are then mapped to 0..1 so that the threshold falls on ``accept``.

Features: how often each pair of character classes follow each other, of the whole text and as
roots of shares, shares of odd word shapes, and lengths.  Labels, language, source and id are no
features.  The model is fitted on at most ``max_labels`` labelled documents, taken in the order of
a hash of the id; that is the only bounded part.

Defined results: null text is empty text and gets a score; several labels of one document count
as their lowest; without labels of both kinds every score is ``accept``, so nothing is rejected;
repeated rows get equal scores; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from dpcluster.llm import scratch
from dpcluster.llm.tokens import forget, small_batches

ACCEPT = 0.3
MAX_LABELS = 20_000
FOLDS = 5

_GROUPS = (b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b" \t", b"\n\r", b".", b",;:", b"!?", b"|", b"#*", b"$&%@", b"()[]{}<>", b"'\"-_", b"/\\=+~^`")
_CLASS = np.full(256, len(_GROUPS), np.uint8)
_CLASS[128:] = len(_GROUPS) + 1
for _i, _g in enumerate(_GROUPS):
    _CLASS[list(_g)] = _i
_N = 16
N_FEATURES = _N * _N + _N + 8


def features(text: bytes) -> np.ndarray:
    out = np.zeros(N_FEATURES, np.float32)
    n = len(text)
    if n == 0:
        return out
    at = _CLASS[np.frombuffer(text, np.uint8)]
    pairs = np.bincount(at[:-1].astype(np.int32) * _N + at[1:], minlength=_N * _N)
    alone = np.bincount(at, minlength=_N)
    out[: _N * _N] = np.sqrt(pairs / n)
    out[_N * _N : _N * _N + _N] = alone / n
    words, lines = text.split(), [x for x in text.split(b"\n") if x]
    few = max(1, len(words))
    rest = np.array([np.log1p(n) / 12, np.log1p(len(words)) / 10, n / few / 20, len(set(words)) / few, len(set(lines)) / max(1, len(lines)), min(1, len(lines) / few), sum(len(w) > 18 for w in words) / few, max(map(len, words), default=0) / 100], np.float32)
    out[-8:] = np.minimum(rest, 3)
    return out


@dataclass(frozen=True)
class Model:
    weights: np.ndarray
    mean: np.ndarray
    scale: np.ndarray
    threshold: float
    accept: float = ACCEPT

    def scores(self, x: np.ndarray) -> np.ndarray:
        raw = ((x - self.mean) / self.scale) @ self.weights - self.threshold
        return 1 / (1 + np.exp(-np.clip(raw + np.log(self.accept / (1 - self.accept)), -40, 40)))


def fit(x: np.ndarray, good: np.ndarray, accept: float = ACCEPT, steps: int = 1500, pairs: int = 512, penalty: float = 1e-4, seed: int = 5) -> Model:
    """Adam on random preference pairs; every good and bad document can be drawn."""
    mean, scale = (x.mean(0), x.std(0) + 1e-3) if len(x) else (np.zeros(N_FEATURES, np.float32), np.ones(N_FEATURES, np.float32))
    yes, no = np.flatnonzero(good == 1), np.flatnonzero(good == 0)
    w = np.zeros(x.shape[1] if len(x) else N_FEATURES, np.float64)
    if not len(yes) or not len(no):
        return Model(w, mean, scale, 0.0, accept)
    z, rng = (x - mean) / scale, np.random.default_rng(seed)
    first, second = np.zeros_like(w), np.zeros_like(w)
    for t in range(1, steps + 1):
        diff = z[rng.choice(yes, pairs)] - z[rng.choice(no, pairs)]
        grad = -(diff * (1 / (1 + np.exp(np.clip(diff @ w, -40, 40))))[:, None]).mean(0) + penalty * w
        first, second = 0.9 * first + 0.1 * grad, 0.999 * second + 0.001 * grad * grad
        w = w - 0.02 * (1 - t / (steps + 1)) * (first / (1 - 0.9**t)) / (np.sqrt(second / (1 - 0.999**t)) + 1e-8)
    raw = np.sort(z @ w)
    cut = len(no)  # as many fall below as are marked bad
    return Model(w, mean, scale, float((raw[cut - 1] + raw[min(cut, len(raw) - 1)]) / 2), accept)


def held_out(doc_id: Column, folds: int = FOLDS) -> Column:
    return F.coalesce(F.pmod(F.crc32(doc_id.cast("string").cast("binary")), F.lit(folds)) == 0, F.lit(False))


def _featured(batches):
    forget()
    for batch in small_batches(batches):
        texts = batch.column("text").cast(pa.binary()).to_pylist()
        rows = [features(t or b"").tobytes() for t in texts]
        yield pa.RecordBatch.from_arrays([batch.column("good"), pa.array(rows, pa.binary())], names=["good", "x"])


def learn(docs: DataFrame, labels: DataFrame, max_labels: int = MAX_LABELS, accept: float = ACCEPT) -> Model:
    """Fits on labelled documents outside the held-out fold."""
    marks = labels.where(F.col("quality").isin(0, 1) & ~held_out(F.col("doc_id"))).groupBy(F.col("doc_id").cast("long").alias("__doc")).agg(F.min("quality").cast("int").alias("good"))
    marks = marks.orderBy(F.xxhash64("__doc"), "__doc").limit(max_labels)  # bounded: a row is an id and a mark
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(marks), F.col("doc_id") == F.col("__doc"))
    scratch.share_code(docs.sparkSession)
    got = texts.select("good", "text").mapInArrow(_featured, "good int, x binary").toArrow()
    x = np.frombuffer(b"".join(got.column("x").to_pylist()), np.float32).reshape(-1, N_FEATURES)
    good = np.asarray(got.column("good").to_pylist(), int)
    order = np.lexsort((*x.T[:4], good)) if len(x) else []
    return fit(x[order], good[order], accept)


def _scorer(model: Model, threshold: float):
    def run(batches):
        forget()
        for batch in small_batches(batches):
            texts = batch.column("text").cast(pa.binary()).to_pylist()
            x = np.stack([features(t or b"") for t in texts]) if texts else np.zeros((0, N_FEATURES), np.float32)
            s = model.scores(x)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), batch.column("held_out"), pa.array(s), pa.array((s >= threshold).astype(np.int32))], names=["doc_id", "held_out", "score", "predicted"])

    return run


def classify(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """Per document: doc_id, held_out, score, predicted."""
    model = learn(docs, labels, **options)
    source = docs.select(F.col("doc_id").cast("long").alias("doc_id"), held_out(F.col("doc_id")).alias("held_out"), "text")
    return source.mapInArrow(_scorer(model, model.accept), "doc_id long, held_out boolean, score double, predicted int")


def with_scores(docs: DataFrame, labels: DataFrame, column: str = "quality", **options) -> DataFrame:
    """The documents with their score beside the other columns."""
    from pyspark.sql.types import DoubleType, StructField, StructType

    model = learn(docs, labels, **options)

    def run(batches):
        forget()
        for batch in small_batches(batches):
            texts = batch.column("text").cast(pa.binary()).to_pylist()
            x = np.stack([features(t or b"") for t in texts]) if texts else np.zeros((0, N_FEATURES), np.float32)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(model.scores(x), pa.float64())], names=[*batch.schema.names, column])

    return docs.mapInArrow(run, StructType([*docs.schema.fields, StructField(column, DoubleType())]))


def accepted(docs: DataFrame, labels: DataFrame, **options) -> DataFrame:
    """The documents that are not rejected, with their columns as they were."""
    model = learn(docs, labels, **options)

    def run(batches):
        forget()
        for batch in small_batches(batches):
            texts = batch.column("text").cast(pa.binary()).to_pylist()
            x = np.stack([features(t or b"") for t in texts]) if texts else np.zeros((0, N_FEATURES), np.float32)
            yield batch.filter(pa.array(model.scores(x) >= model.accept))

    return docs.mapInArrow(run, docs.schema)
