"""Toxicity: logistic regression on hashed character n-grams whose indicators are scaled by naive Bayes log-count ratios."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import chunks, crc_mod4, cut, extend, lower_table, table

BITS = 18
SIZES = (4, 5)
#: The bound of the labelled sample that a model is fitted on: rows, each with its whole text.
SAMPLE_ROWS = 5000


@dataclass
class Model:
    weight: np.ndarray
    bias: float


def gram_ids(raw: np.ndarray, low: np.ndarray) -> list[np.ndarray]:
    """Hashed n-gram of each start, for each of SIZES."""
    b = low[raw].astype(np.uint64)
    out = []
    for n in SIZES:
        if len(b) < n:
            out.append(np.zeros(0, np.int64))
            continue
        h = np.full(len(b) - n + 1, n, np.uint64)
        for j in range(n):
            h = (h << np.uint64(8)) | b[j : len(b) - n + 1 + j]
        out.append(((h * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(64 - BITS)).astype(np.int64))
    return out


def encode(raw: np.ndarray) -> bytes:
    """The distinct n-grams of a text, as numbers or as bits, whichever is shorter: 2**BITS bits at most, however long the text."""
    ids = np.unique(np.concatenate(gram_ids(raw, lower_table()))).astype(np.int32)
    if 32 * len(ids) <= 1 << BITS:
        return b"i" + ids.tobytes()
    bits = np.zeros(1 << BITS, bool)
    bits[ids] = True
    return b"b" + np.packbits(bits).tobytes()


def decode(data: bytes) -> np.ndarray:
    if data[:1] == b"i":
        return np.frombuffer(data, np.int32, offset=1)
    return np.flatnonzero(np.unpackbits(np.frombuffer(data, np.uint8, offset=1))).astype(np.int32)


def fit(texts: list[bytes], y: np.ndarray, alpha: float = 1.0, least_gain: float = 12.0, l2: float = 0.5, rounds: int = 120) -> Model:
    """Log-count ratios from all given texts (as encoded); of the features, those whose presence is far from independent of the label; then a regularised logistic fit."""
    size = 1 << BITS
    if len(y) == 0 or y.min() == y.max():
        p = (y.sum() + 0.5) / (len(y) + 1)
        return Model(np.zeros(size, np.float32), float(np.log(p / (1 - p))))
    pos, neg = np.zeros(size), np.zeros(size)
    for d, t in zip(texts, y, strict=True):
        (pos if t else neg)[decode(d)] += 1
    ratio = np.log((pos + alpha) / (y.sum() + 2 * alpha)) - np.log((neg + alpha) / ((1 - y).sum() + 2 * alpha))
    n1, n0 = y.sum(), (1 - y).sum()
    both = pos + neg
    with np.errstate(divide="ignore", invalid="ignore"):  # likelihood ratio statistic of presence against label
        gain = 2 * sum(np.nan_to_num(c * np.log(c * len(y) / (m * n))) for c, m, n in ((pos, both, n1), (neg, both, n0), (n1 - pos, len(y) - both, n1), (n0 - neg, len(y) - both, n0)))
    used = np.flatnonzero(gain >= least_gain)
    slot = np.full(size, -1)
    slot[used] = np.arange(len(used))
    rows = [(at := slot[decode(d)])[at >= 0] for d in texts]
    idx = np.concatenate(rows) if rows else np.zeros(0, np.int64)
    row = np.repeat(np.arange(len(rows)), [len(r) for r in rows])
    r = ratio[used]
    w, b = np.zeros(len(used)), float(np.log(y.mean() / (1 - y.mean())))
    m, v, mb, vb = np.zeros_like(w), np.zeros_like(w), 0.0, 0.0
    for k in range(1, rounds + 1):  # Adam on the full sample
        p = 1 / (1 + np.exp(-np.clip(np.bincount(row, (w * r)[idx], len(rows)) + b, -30, 30)))
        g = (p - y) / len(y)
        gw, gb = np.bincount(idx, g[row], len(w)) * r + l2 * w / len(y), g.sum()
        m, v, mb, vb = 0.9 * m + 0.1 * gw, 0.99 * v + 0.01 * gw**2, 0.9 * mb + 0.1 * gb, 0.99 * vb + 0.01 * gb**2
        w -= 0.02 * (m / (1 - 0.9**k)) / (np.sqrt(v / (1 - 0.99**k)) + 1e-8)
        b -= 0.02 * (mb / (1 - 0.9**k)) / (np.sqrt(vb / (1 - 0.99**k)) + 1e-8)
    weight = np.zeros(size, np.float32)
    weight[used] = w * r
    return Model(weight, b)


def sample(docs: DataFrame, labels: DataFrame, label: str, rows: int, encode: Callable[[np.ndarray], bytes]) -> tuple[list[bytes], np.ndarray]:
    """At most `rows` labelled texts outside the held-out fold, in the order of a hash, as encoded from the whole text; equal texts once.

    Repeats are dropped by hashes of whole texts before the bound on rows. Executors encode, so that no text reaches the driver."""
    text = F.coalesce("text", F.lit(""))
    name = F.struct(F.xxhash64(text).alias("a"), F.xxhash64(F.lit(1), text).alias("b"), F.length(text).alias("n"))
    lab = labels.where(F.col(label).isNotNull() & (crc_mod4() != 2)).groupBy("doc_id").agg(F.max(label).alias("_y"))
    named = docs.where(crc_mod4() != 2).select("doc_id", name.alias("_t")).join(lab, "doc_id")
    one = named.groupBy("doc_id").agg(F.min("_t").alias("_t"), F.first("_y").alias("_y")).withColumn("_o", F.xxhash64("doc_id"))
    first = one.groupBy("_t").agg(F.min(F.struct("_o", "doc_id", "_y")).alias("_f")).select("_f.*", "_t")
    chosen = cut(first.orderBy("_o", "doc_id").limit(rows))
    held = docs.select("doc_id", text.alias("text")).join(F.broadcast(chosen), "doc_id").where(F.col("_t") == name)  # at most `rows` ids, hashes and labels
    keys = ["doc_id", "_y", "_o"]
    schema = T.StructType([*held.select(*keys).schema.fields, T.StructField("_x", T.BinaryType())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part, raw, offs in chunks(batches):
            x = pa.array([encode(raw[a:b]) for a, b in zip(offs[:-1], offs[1:], strict=True)], pa.binary())
            yield pa.RecordBatch.from_arrays([*(part.column(part.schema.get_field_index(c)) for c in keys), x], [*keys, "_x"])

    got = (
        held.select(*keys, "text").mapInArrow(run, schema)
        .groupBy("doc_id").agg(F.min("_x").alias("_x"), F.first("_y").alias("_y"), F.first("_o").alias("_o"))
        .toPandas()
        .sort_values(["_o", "doc_id"])
    )
    return [bytes(x) for x in got["_x"]], got["_y"].to_numpy(np.float64)


def score_all(docs: DataFrame, model: Model, name: str = "score") -> DataFrame:
    """docs with one more column: the probability of label 1 from the whole text (null: empty)."""
    docs, schema = extend(docs, name, "double")
    shared = docs.sparkSession.sparkContext.broadcast((model.weight, model.bias))  # of fixed size: 2**BITS weights

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        (weight, bias), low = shared.value, lower_table()
        for rows, raw, offs in chunks(batches):
            total = np.full(rows.num_rows, bias)
            for n, ids in zip(SIZES, gram_ids(raw, low), strict=True):
                at = np.flatnonzero(weight[ids] != 0)
                doc = np.searchsorted(offs, at, "right") - 1
                inside = at + n <= offs[doc + 1]
                pairs = np.unique(doc[inside].astype(np.int64) << BITS | ids[at[inside]])
                np.add.at(total, pairs >> BITS, weight[pairs & ((1 << BITS) - 1)])
            p = 1 / (1 + np.exp(-np.clip(total, -30, 30)))
            yield pa.RecordBatch.from_arrays([*rows.columns, pa.array(p)], [*rows.schema.names, name])

    return docs.mapInArrow(run, schema)


def fit_labelled(docs: DataFrame, labels: DataFrame, label: str = "toxic", rows: int = SAMPLE_ROWS) -> Model:
    return fit(*sample(docs, labels, label, rows, encode))


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nulls and empty texts get the score of a text without features; repeated rows are scored alike; an empty table gives no rows."""
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels")
    scored = score_all(docs.select("doc_id", "text"), fit_labelled(docs, labels))
    return scored.select("doc_id", (crc_mod4() == 2).alias("held_out"), "score", (F.col("score") >= 0.3).cast("int").alias("predicted"))
