"""Quality classifier: regularised quadratic discriminant over transformed document statistics.

Each class has a mean and a covariance that is shrunk towards a multiple of the pooled covariance's
diagonal; a score is the logistic of the difference of the two log densities (squared Mahalanobis lengths by cached
Cholesky factors, and log determinants) plus the log prior odds.

Training needs sums only (counts, first and second moments), which one aggregation gathers over all
labelled rows; they are a few hundred numbers, whatever the input. Statistics are taken once per document.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from supportbounds.llm.common import keep, text_of
from supportbounds.llm.quality_rules import slices

FEATURES = ("log_words", "word_length", "symbols", "upper", "digits", "marks", "bars", "breaks", "distinct", "top_word", "stops", "repeats", "other")
_CLASS = np.full(256, 8, dtype=np.uint8)  # 8: letters that are not ASCII, and control characters
for _i, _chars in enumerate((b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b"#$%&*<>^~=+\\{}[]@_", b"!?", b"|", b"\n", b" \t\r\x0b\x0c")):
    _CLASS[np.frombuffer(_chars, dtype=np.uint8)] = _i
_CLASS[np.frombuffer(b".,;:'\"()-/`", dtype=np.uint8)] = 9
_CLASS[128:192] = 10  # continuation bytes: no characters of their own


def statistics(text: str) -> list[float]:
    """Shares are square-rooted or logged, so that each class is closer to a bell shape."""
    raw = text.encode("utf-8", "surrogatepass")
    n = np.bincount(_CLASS[np.frombuffer(raw, dtype=np.uint8)], minlength=11)
    chars = max(1, len(raw) - int(n[10]))
    words = raw.split()
    k = max(1, len(words))
    counts: dict[bytes, int] = {}
    for w in words:
        counts[w] = counts.get(w, 0) + 1
    repeats = sum(a == b for a, b in zip(words, words[1:], strict=False))
    root = lambda x: float(np.sqrt(x))
    return [
        float(np.log1p(len(words))), float(np.log1p((chars - n[6] - n[7]) / k)), root(n[3] / chars), root(n[1] / chars), root(n[2] / chars), root(n[4] / chars), root(n[5] / chars),
        root(n[6] / chars), float(np.log((len(counts) + 1) / (k + 1))), root(max(counts.values(), default=0) / k), root(n[9] / chars), root(repeats / k), root(n[8] / chars),
    ]


@dataclass(frozen=True)
class Discriminant:
    """Means, inverse Cholesky factors and log determinants of both classes."""

    means: np.ndarray
    factors: np.ndarray
    log_dets: np.ndarray
    log_odds: float

    def scores(self, x: np.ndarray) -> np.ndarray:
        density = [-0.5 * (((x - m) @ f.T) ** 2).sum(axis=1) - 0.5 * d for m, f, d in zip(self.means, self.factors, self.log_dets, strict=True)]
        return 1 / (1 + np.exp(-np.clip(density[1] - density[0] + self.log_odds, -500, 500)))


def fit(counts: np.ndarray, sums: np.ndarray, products: np.ndarray, shrink: float = 0.1, floor: float = 1e-4) -> Discriminant:
    """From per-class counts (2), sums (2, d) and sums of products (2, d, d). A class without rows has the pooled moments."""
    d = sums.shape[1]
    total = max(1.0, counts.sum())
    pooled_mean = sums.sum(axis=0) / total
    pooled = products.sum(axis=0) / total - np.outer(pooled_mean, pooled_mean)
    target = np.diag(np.maximum(np.diag(pooled), floor))
    means, factors, dets = [], [], []
    for c in range(2):
        mean = sums[c] / counts[c] if counts[c] else pooled_mean
        own = products[c] / counts[c] - np.outer(mean, mean) if counts[c] else pooled
        a = (shrink * total + d) / (total + d)  # few rows: closer to the target
        lower = np.linalg.cholesky((1 - a) * own + a * target + floor * np.eye(d))
        means.append(mean)
        factors.append(np.linalg.inv(lower))
        dets.append(2 * np.log(np.diag(lower)).sum())
    return Discriminant(np.array(means), np.array(factors), np.array(dets), float(np.log((counts[1] + 1) / (counts[0] + 1))))


def with_statistics(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """key and x (array of the statistics), one row per document."""
    plain = docs.select(F.col(key).alias("key"), text_of(docs, text).alias("text"))
    kind = plain.schema["key"].dataType.simpleString()

    def add(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part in slices(batch, "text"):
                x = [statistics(t) for t in part.column("text").to_pylist()]
                yield pa.RecordBatch.from_arrays([part.column("key"), pa.array(x, pa.list_(pa.float64()))], names=["key", "x"])

    return plain.mapInArrow(add, f"key {kind}, x array<double>")


def held_out(key: Column) -> Column:
    """Every fifth document, by the checksum of its key; rows without a key are not held out."""
    return F.coalesce(F.crc32(key.cast("string").cast("binary")) % 5 == 0, F.lit(False))


def train(rows: DataFrame, labels: DataFrame, label: str = "quality") -> Discriminant:
    """Fits on all labelled rows that are not held out; only sums reach the driver."""
    d = len(FEATURES)
    known = labels.select(F.col("doc_id").alias("key"), F.col(label).cast("int").alias("y")).where("key IS NOT NULL AND y IN (0, 1)")
    joined = rows.where(~held_out(F.col("key"))).join(known, "key")

    def sums(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n, s, p = np.zeros(2), np.zeros((2, d)), np.zeros((2, d, d))
        for batch in batches:
            x, y = batch.column("x").flatten().to_numpy().reshape(-1, d), batch.column("y").to_numpy()
            for c in range(2):
                own = x[y == c]
                n[c] += len(own)
                s[c] += own.sum(axis=0)
                p[c] += own.T @ own
        yield pa.RecordBatch.from_arrays([pa.array([np.concatenate([n, s.ravel(), p.ravel()])], pa.list_(pa.float64()))], names=["v"])

    parts = joined.select("x", "y").mapInArrow(sums, "v array<double>")
    one = parts.select(F.posexplode("v").alias("i", "v")).groupBy("i").agg(F.sum("v").alias("v"))
    v = np.zeros(2 + 2 * d + 2 * d * d)
    for r in one.collect():  # 2 + 2 d + 2 d^2 rows
        v[r.i] = r.v
    return fit(v[:2], v[2 : 2 + 2 * d].reshape(2, d), v[2 + 2 * d :].reshape(2, d, d))


def classify(docs: DataFrame, labels: DataFrame, text: str = "text", key: str = "doc_id", threshold: float = 0.3) -> DataFrame:
    """key, held_out, score, predicted for every row of ``docs``.

    Null texts count as empty and get a score like any other; repeated rows get equal scores; without any labels the score is
    one half; texts of any length are measured whole; keys keep their type (rows without one are scored, and not held out); further columns do not matter; an
    empty table gives an empty result.
    """
    rows = keep(with_statistics(docs, text, key), "document-statistics")
    model = train(rows, labels)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            x = batch.column("x").flatten().to_numpy().reshape(-1, len(FEATURES))
            yield pa.RecordBatch.from_arrays([batch.column("key"), pa.array(model.scores(x))], names=["key", "score"])

    kind = rows.schema["key"].dataType.simpleString()
    scored = rows.mapInArrow(score, f"key {kind}, score double")
    return scored.select(F.col("key").alias(key), held_out(F.col("key")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))
