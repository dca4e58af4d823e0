"""Quality classifier: logistic regression over hashed word n-grams, trained by follow-the-regularised-leader.

A text's tokens are its runs of letters and digits and its runs of marks; its features are hashed single tokens and
pairs (and, for a token that follows itself, one feature shared by all tokens), each with its share of the text's n-grams as value, so a score is a sparse dot product. Weights are learnt in one
task from a bounded sample of labelled rows (`TRAIN_ROWS`, the same at every size of the corpus) and sent to
all tasks as one array of fixed size. Only the text is ever an input.

Defined results: a text without tokens (null, empty, white space) scores by the bias alone. A row of `labels` with a null
id or label is left out; of several labels for one id the largest counts, of several texts for one id the one with the
least SHA-256 is learnt from. Rows are learnt in the order of a hash of their id, whatever the partitioning. Without any label all
weights are zero and every score is 0.5. Repeated rows are scored each.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

#: Labelled rows that a model is fitted on, at most: those of the least hashed ids.
TRAIN_ROWS = 12_000
BITS, EPOCHS = 18, 4
ALPHA, BETA, L1, L2, SCALE = 0.5, 1.0, 1e-4, 1e-4, 10.0
THRESHOLD = 0.3
#: The feature of a token that follows itself.
REPEAT = 0

_WORD = np.zeros(256, np.uint8)
_WORD[list(b"abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789")] = 1
_WORD[128:] = 1
_WORD[list(b"!\"#$%&'()*+,-./:;<=>?@[\\]^_`{|}~")] = 2


def grams(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Feature numbers of all texts' n-grams, and each one's row."""
    n = len(data)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64)
    kind = _WORD[data]
    edge = np.zeros(n + 1, bool)
    edge[0] = edge[n] = True
    edge[1:n] = kind[1:] != kind[:-1]
    edge[off] = True
    at = np.flatnonzero(edge)
    start, end = at[:-1], at[1:]
    real = kind[start] > 0
    start, end = start[real], end[real]
    row = np.searchsorted(off, start, side="right") - 1
    one = common.span_hash(common.prefix_hash(data), start, end)
    near = row[:-1] == row[1:]
    two = common.mix(one[:-1] * np.uint64(31) + one[1:])[near]
    same = row[:-1][near & (one[:-1] == one[1:])]
    shift = np.uint64(64 - BITS)
    feature = np.concatenate([one >> shift, two >> shift, np.full(len(same), REPEAT, np.uint64)]).astype(np.int64)
    return feature, np.concatenate([row, row[:-1][near], same])


def scores(weights: np.ndarray, data: np.ndarray, off: np.ndarray) -> np.ndarray:
    """One score a text; weights ends with the bias."""
    feature, row = grams(data, off)
    n = len(off) - 1
    total = np.bincount(row, weights[feature], n)
    count = np.maximum(np.bincount(row, minlength=n), 1)
    return 1 / (1 + np.exp(-(SCALE * total / count + weights[-1])))


def follow_the_leader(rows: list[tuple[np.ndarray, np.ndarray]], labels: np.ndarray, size: int) -> np.ndarray:
    """Weights by per-coordinate follow-the-regularised-leader updates; rows hold feature numbers and values."""
    z, n = np.zeros(size), np.zeros(size)

    def weights(i):
        zi = z[i]
        return np.where(np.abs(zi) <= L1, 0, -(zi - np.sign(zi) * L1) / ((BETA + np.sqrt(n[i])) / ALPHA + L2))

    for _ in range(EPOCHS):
        for (i, x), y in zip(rows, labels, strict=True):
            w = weights(i)
            g = (1 / (1 + np.exp(-np.clip(w @ x, -30, 30))) - y) * x
            step = (np.sqrt(n[i] + g * g) - np.sqrt(n[i])) / ALPHA
            z[i] += g - step * w
            n[i] += g * g
    return weights(np.arange(size))


def train(docs: DataFrame, labels: DataFrame, text: str = "text", key: str = "doc_id", label: str = "quality", rows: int = TRAIN_ROWS) -> np.ndarray:
    """Weights learnt from the labelled rows whose id's CRC-32 is no multiple of 5."""
    spark = docs.sparkSession
    common.importable(spark)
    some = (
        labels.select(common.col(key).cast("long").alias("i"), common.col(label).cast("int").alias("y"))
        .filter("i IS NOT NULL AND y IS NOT NULL AND crc32(CAST(i AS STRING)) % 5 <> 0")
        .groupBy("i")
        .agg(F.max("y").alias("y"))
        .orderBy(F.xxhash64("i"), "i")
        .limit(rows)
    )
    chosen = docs.select(common.col(key).cast("long").alias("i"), common.clean_text(common.col(text)).alias("t")).join(F.broadcast(some), "i")
    one = F.min_by("t", F.sha2(F.col("t").cast("binary"), 256))
    chosen = chosen.groupBy("i").agg(one.alias("t"), F.first("y").alias("y"))  # the bound holds where ids repeat

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        size = (1 << BITS) + 1
        seen = []
        for whole in batches:
            for b in common.slices(whole, 1):
                data, off = common.raw(b.column(1))
                feature, row = grams(data, off)
                order = np.argsort(row, kind="stable")
                cut = np.searchsorted(row[order], np.arange(b.num_rows + 1))
                for r, (i, y) in enumerate(zip(b.column(0).to_pylist(), b.column(2).to_pylist(), strict=True)):
                    f, c = np.unique(feature[order[cut[r] : cut[r + 1]]], return_counts=True)
                    seen.append((int(common.mix(np.array([i], np.int64).view(np.uint64))[0]), y, np.r_[f, size - 1].astype(np.int32), np.r_[SCALE * c / max(1, c.sum()), 1.0].astype(np.float32)))
        seen.sort(key=lambda s: s[0])
        w = follow_the_leader([(f, x.astype(float)) for *_, f, x in seen], np.array([s[1] for s in seen], float), size)
        yield pa.RecordBatch.from_arrays([pa.array([w.astype("<f4").tobytes()], pa.binary())], ["w"])

    got = chosen.select("i", "t", "y").repartition(1).mapInArrow(run, "w binary").collect()
    return np.frombuffer(bytes(got[0].w), "<f4").astype(float) if got else np.zeros((1 << BITS) + 1)


def scorer(spark: SparkSession, weights: np.ndarray):
    """A column function from text to score."""
    common.importable(spark)
    held = spark.sparkContext.broadcast(weights.astype(np.float32))  # of fixed size

    @F.arrow_udf("double")
    def score(texts: pa.Array) -> pa.Array:
        w = held.value.astype(float)
        batch = pa.RecordBatch.from_arrays([texts], ["t"])
        out = [scores(w, *common.raw(b.column(0))) for b in common.slices(batch, 0)]
        return pa.array(np.concatenate(out) if out else np.zeros(0), pa.float64())

    return lambda text: score(common.clean_text(text))


def accepted(score: Column) -> Column:
    return score >= F.lit(THRESHOLD)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet")
    score = scorer(spark, train(docs, labels))
    return docs.select(
        "doc_id", (F.crc32(F.col("doc_id").cast("string").cast("binary")) % 5 == 0).alias("held_out"), score(F.col("text")).alias("score")
    ).withColumn("predicted", accepted(F.col("score")).cast("int"))
