"""Quality classifier: logistic regression on hashed word n-grams, trained by follow-the-regularised-leader.

Features of a text are its word unigrams and bigrams and the unigrams and
bigrams of its words' shapes (letters, digits and case collapsed to classes,
other bytes kept), hashed to ``2**BITS`` coordinates.  A bigram of equal words
is one shared feature, so repetition is visible whatever the word is.  A
coordinate's value is its count over the square root of the sum of squared
counts, and the score is the logistic of a sparse dot product.

Training reads a bounded sample of labelled documents (``max_train``, drawn by
hash of the identifier, so it does not depend on file order); scoring covers
every row and every whole text.

Defined results: a null text counts as empty, an empty text has only the bias
feature; rows with a null label or identifier are not trained on; without any
training row every score is 0.5; other columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from entlink.storage import release_memory

BITS = 18
MASK = (1 << BITS) - 1
MAX_TRAIN = 6000
EPOCHS = 3

_CLASS = bytearray(range(256))
for _c in range(256):
    if 65 <= _c <= 90:
        _CLASS[_c] = ord("X")
    elif 97 <= _c <= 122 or _c >= 128:
        _CLASS[_c] = ord("x")
    elif 48 <= _c <= 57:
        _CLASS[_c] = ord("9")
_CLASS = bytes(_CLASS)


def _grams(words: list[bytes], salt: int) -> list[np.ndarray]:
    crc = zlib.crc32
    h = np.fromiter(map(crc, words), np.uint64, len(words)) * np.uint64(0x9E3779B97F4A7C15) + np.uint64(salt)
    one = h >> np.uint64(64 - BITS)
    if len(words) < 2:
        return [one]
    left, right = h[:-1], h[1:]
    pair = (left * np.uint64(3) + right + np.uint64(salt)) * np.uint64(0xC2B2AE3D27D4EB4F)
    pair = np.where(left == right, np.uint64((salt + 1) * 0xD6E8FEB86659FD93 % 2**64), pair)
    return [one, pair >> np.uint64(64 - BITS)]


def features(text: str | None) -> tuple[np.ndarray, np.ndarray]:
    """Sorted coordinates and their values; coordinate 0 also carries the bias."""
    raw = (text or "").encode("utf-8")
    words = raw.split()
    parts = [np.zeros(0, np.uint64)]
    if words:
        kinds = np.frombuffer(raw.translate(_CLASS), np.uint8)
        run = np.concatenate(([True], kinds[1:] != kinds[:-1]))
        parts = _grams(words, 1) + _grams(kinds[run].tobytes().split(), 7)
    idx, n = np.unique(np.concatenate(parts).astype(np.int64), return_counts=True)
    val = n / max(1.0, np.sqrt(float((n * n).sum())))
    return np.concatenate(([0], idx)), np.concatenate(([0.3], val))


def train(rows, alpha: float = 0.5, beta: float = 1.0, l1: float = 1e-4, l2: float = 1e-3, epochs: int = EPOCHS) -> np.ndarray:
    """Weights after FTRL-proximal passes over ``rows`` of ((coordinates, values), label)."""
    z, n = np.zeros(MASK + 1), np.zeros(MASK + 1)
    for _ in range(epochs):
        for (idx, val), label in rows:
            zi, ni = z[idx], n[idx]
            w = np.where(np.abs(zi) <= l1, 0.0, -(zi - np.sign(zi) * l1) / ((beta + np.sqrt(ni)) / alpha + l2))
            g = (1.0 / (1.0 + np.exp(-np.clip(w @ val, -35, 35))) - label) * val
            s = (np.sqrt(ni + g * g) - np.sqrt(ni)) / alpha
            z[idx] = zi + g - s * w
            n[idx] = ni + g * g
    return np.where(np.abs(z) <= l1, 0.0, -(z - np.sign(z) * l1) / ((beta + np.sqrt(n)) / alpha + l2)).astype(np.float32)


def score(weights: np.ndarray, feats: tuple[np.ndarray, np.ndarray]) -> float:
    idx, val = feats
    return float(1.0 / (1.0 + np.exp(-np.clip(weights[idx] @ val, -35, 35))))


def fit(docs: DataFrame, labels: DataFrame, label_col: str = "quality", id_col: str = "doc_id", text_col: str = "text",
        max_train: int = MAX_TRAIN) -> np.ndarray:
    """Train on at most ``max_train`` labelled rows whose crc32(id as text) mod 3 is not 1."""
    key = F.col(id_col)
    usable = labels.where(key.isNotNull() & F.col(label_col).isNotNull() & (F.pmod(F.crc32(key.cast("string").cast("binary")), F.lit(3)) != 1))
    chosen = usable.select(key.alias("_id"), F.col(label_col).cast("double").alias("_label")).orderBy(F.xxhash64("_id"), "_id", "_label").limit(max_train)
    texts = docs.select(key.alias("_id"), F.col(text_col).alias("_text"))
    sample = texts.join(F.broadcast(chosen), "_id")  # chosen has max_train rows at most
    sample = sample.groupBy("_id").agg(F.max("_label").alias("_label"), F.min("_text").alias("_text"))

    def learn(batches):
        got = [r for b in batches for r in b.to_pylist()]
        got.sort(key=lambda r: (zlib.crc32(str(r["_id"]).encode()), r["_id"], r["_text"] or ""))
        if got:
            w = train([(features(r["_text"]), r["_label"]) for r in got])
            yield pa.RecordBatch.from_arrays([pa.array([w.tobytes()])], ["weights"])

    found = sample.repartition(1).mapInArrow(learn, "weights binary").collect()
    return np.frombuffer(found[0].weights, np.float32) if found else np.zeros(MASK + 1, np.float32)


def scored(docs: DataFrame, weights: np.ndarray, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """``(id, score)`` of every document."""
    shared = docs.sparkSession.sparkContext.broadcast(weights)  # 2**BITS floats

    def run(batches):
        w = shared.value
        for b in batches:
            s = np.fromiter((score(w, features(t)) for t in b.column(1).to_pylist()), np.float64, b.num_rows)
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(s)], ["id", "score"])
        release_memory()

    slim = docs.select(F.col(id_col).cast("long").alias("id"), F.col(text_col).alias("text"))
    return slim.mapInArrow(run, "id long, score double").withColumnRenamed("id", id_col)


def with_score(docs: DataFrame, weights: np.ndarray, text_col: str = "text", score_col: str = "score") -> DataFrame:
    """All columns of ``docs`` and the score; only the text goes through Python."""
    shared = docs.sparkSession.sparkContext.broadcast(weights)

    @F.pandas_udf("double")
    def run(batches: Iterator[pd.Series]) -> Iterator[pd.Series]:
        w = shared.value
        for texts in batches:
            yield pd.Series([score(w, features(t)) for t in texts], dtype=float)
        release_memory()

    return docs.withColumn(score_col, run(F.coalesce(F.col(text_col), F.lit(""))))
