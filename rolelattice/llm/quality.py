"""Quality: logistic regression on hashed word n-grams, fitted by follow-the-regularised-leader updates."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import chunks, crc_mod4, extend, lower_table, mix, table, word_hashes
from .toxicity import sample

BITS = 18
#: The bound of the labelled sample that a model is fitted on: rows, each with its whole text.
SAMPLE_ROWS = 5000
THRESHOLD = 0.7


@dataclass
class Model:
    weight: np.ndarray
    bias: float


def kinds() -> np.ndarray:
    """1 letters, digits and bytes beyond ASCII; 2 punctuation; 0 white space and controls."""
    t = np.zeros(256, np.uint8)
    t[33:127] = 2
    for a, b in ((48, 58), (65, 91), (97, 123), (128, 256)):
        t[a:b] = 1
    return t


def features(raw: np.ndarray, offs: np.ndarray, kind: np.ndarray, low: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(row, feature, value): uni- and bigrams of word and punctuation runs, damped counts of unit length within a row."""
    h, first, _, _ = word_hashes(raw, offs, kind, low)
    row = np.repeat(np.arange(len(first) - 1), np.diff(first))
    pair = mix(h[:-1] * np.uint64(3) + h[1:])[row[1:] == row[:-1]] if len(h) > 1 else h[:0]
    rows = np.concatenate([row, row[1:][row[1:] == row[:-1]] if len(h) > 1 else row[:0]]).astype(np.int64)
    ids = (np.concatenate([h, pair]) >> np.uint64(64 - BITS)).astype(np.int64)
    key = rows << BITS | ids
    key.sort()
    at = np.flatnonzero(np.append(True, key[1:] != key[:-1])) if len(key) else np.zeros(0, np.int64)
    value = np.sqrt(np.diff(np.append(at, len(key))))
    key = key[at]
    rows = key >> BITS
    norm = np.sqrt(np.bincount(rows, value**2, len(offs) - 1))
    return rows, key & ((1 << BITS) - 1), value / norm[rows] if len(rows) else value


def encode(raw: np.ndarray) -> bytes:
    """The features of a text and their values."""
    _, i, x = features(raw, np.array([0, len(raw)]), kinds(), lower_table())
    return i.astype(np.int64).tobytes() + x.astype(np.float64).tobytes()


def decode(data: bytes) -> tuple[np.ndarray, np.ndarray]:
    n = len(data) // 16
    return np.frombuffer(data, np.int64, n), np.frombuffer(data, np.float64, n, 8 * n)


def fit(texts: list[bytes], y: np.ndarray, alpha: float = 0.3, beta: float = 1.0, l1: float = 0.02, l2: float = 0.05, passes: int = 3) -> Model:
    """Per-coordinate FTRL, one text (as encoded) at a time."""
    size = 1 << BITS
    z, n, zb, nb = np.zeros(size), np.zeros(size), 0.0, 0.0

    def weights(zi: np.ndarray, ni: np.ndarray) -> np.ndarray:
        return np.where(np.abs(zi) <= l1, 0.0, -(zi - np.sign(zi) * l1) / ((beta + np.sqrt(ni)) / alpha + l2))

    order = np.random.default_rng(7)
    for _ in range(passes):
        for k in order.permutation(len(texts)):
            i, x = decode(texts[k])
            x = x * 4
            w = weights(z[i], n[i])
            b = -zb / ((beta + np.sqrt(nb)) / alpha)
            g = 1 / (1 + np.exp(-np.clip((w * x).sum() + b, -30, 30))) - y[k]
            gi = g * x
            z[i] += gi - (np.sqrt(n[i] + gi**2) - np.sqrt(n[i])) / alpha * w
            n[i] += gi**2
            zb += g - (np.sqrt(nb + g**2) - np.sqrt(nb)) / alpha * b
            nb += g**2
    return Model((4 * weights(z, n)).astype(np.float32), -zb / ((beta + np.sqrt(nb)) / alpha))


def score_all(docs: DataFrame, model: Model, name: str = "score") -> DataFrame:
    """docs with one more column: the probability of label 1 from the whole text (null: empty)."""
    docs, schema = extend(docs, name, "double")
    shared = docs.sparkSession.sparkContext.broadcast((model.weight, model.bias))  # of fixed size: 2**BITS weights

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (weight, bias), kind, low = shared.value, kinds(), lower_table()
        for rows, raw, offs in chunks(batches):
            r, i, x = features(raw, offs, kind, low)
            total = bias + np.bincount(r, weight[i] * x, rows.num_rows)
            p = 1 / (1 + np.exp(-np.clip(total, -30, 30)))
            yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(p)], [*rows.schema.names, name])

    return docs.mapInArrow(run, schema)


def fit_labelled(docs: DataFrame, labels: DataFrame, label: str = "quality", rows: int = SAMPLE_ROWS) -> Model:
    return fit(*sample(docs, labels, label, rows, encode))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nulls and empty texts get the score of a text without words; repeated rows are scored alike; an empty table gives no rows."""
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    scored = score_all(docs.select("doc_id", "text"), fit_labelled(docs, labels))
    return scored.select("doc_id", (crc_mod4() == 2).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))
