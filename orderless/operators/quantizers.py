"""Vector quantizers: k-means centroids, product codes with look-up tables, residual codes with re-ranking."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import arrow
from .search import Scorer

#: Centroids and codebooks are broadcast; they may have this many bytes.
MODEL_BYTES = 256 << 20
#: Training rows per centroid, at most; the sample's bound doesn't depend on the corpus.
ROWS_PER_CENTROID = 256
#: Bytes of a training sample, at most, but for one row a centroid.
SAMPLE_BYTES = 256 << 20
#: Distances that are held at a time.
CELLS = 1 << 22


def closest(x: np.ndarray, c: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Number of the closest centroid, the lower of equals, and the distance but for the row's own length."""
    length, step = (c * c).sum(1), max(1, CELLS // max(1, len(c)))
    at, least = np.zeros(len(x), np.int64), np.zeros(len(x))
    for lo in range(0, len(x), step):
        d = length - 2 * (x[lo : lo + step] @ c.T)
        at[lo : lo + step] = d.argmin(1)
        least[lo : lo + step] = d[np.arange(len(d)), at[lo : lo + step]]
    return at, least


def nearest(x: np.ndarray, c: np.ndarray) -> np.ndarray:
    return closest(x, c)[0]


def sample_rows(db: DataFrame, clusters: int) -> int:
    """Rows to train on: some for each centroid, within a bound of bytes, and one for each at least."""
    dim = db.select(F.size("vec").alias("d")).first()
    return min(clusters * ROWS_PER_CENTROID, max(clusters, SAMPLE_BYTES // (8 * max(1, dim.d if dim else 1))))


def sample(db: DataFrame, rows: int, init: str = "first", seed: int = 0) -> np.ndarray:
    """At most `rows` vectors as a matrix: of the least ids, or of the least seeded hashes of ids."""
    order = [F.col("id")] if init == "first" else [F.xxhash64(F.col("id"), F.lit(seed)), F.col("id")]
    t = db.orderBy(*order).limit(rows).select(F.col("vec").cast("array<double>").alias("vec")).toArrow().combine_chunks()
    return arrow.vectors(t["vec"].chunk(0)) if t.num_rows else np.zeros((0, 0))


def lloyd(x: np.ndarray, c: np.ndarray, iters: int) -> np.ndarray:
    """Lloyd's steps on a matrix; a centroid without rows stays where it is."""
    c = c.copy()
    for _ in range(iters):
        at = nearest(x, c)
        n = np.bincount(at, minlength=len(c))
        total = np.zeros_like(c)
        np.add.at(total, at, x)
        c[n > 0] = total[n > 0] / n[n > 0][:, None]
    return c


def assign(db: DataFrame, centroids: np.ndarray) -> DataFrame:
    """Adds k, the nearest centroid's number, to (id, vec). Centroids over the broadcast's bound go in blocks, each a narrow pass."""
    arrow.importable(db.sparkSession)
    step = max(1, MODEL_BYTES // (8 * max(1, centroids.shape[1]))) if centroids.size else 1
    out = db.withColumn("near", F.lit(None).cast("struct<k: bigint, d: double>"))
    for lo in range(0, len(centroids), step):
        out = out.withColumn("near", _nearer(db.sparkSession.sparkContext.broadcast(centroids[lo : lo + step]), lo)("vec", "near"))
    return out.withColumn("k", F.col("near.k")).drop("near")


def _nearer(held, lo: int):
    """A column function: the best so far, or a centroid of this block, numbered from lo, that is nearer."""

    @F.arrow_udf("struct<k: bigint, d: double>")
    def nearer(vec: pa.Array, near: pa.Array) -> pa.Array:
        at, d = closest(arrow.vectors(vec).astype(np.float64), held.value)
        at = at + lo
        if lo:
            old, k = near.field("d").to_numpy(), near.field("k").to_numpy()
            at, d = np.where(old <= d, k, at), np.minimum(old, d)
        return pa.StructArray.from_arrays([pa.array(at), pa.array(d)], ["k", "d"])

    return nearer


def kmeans(db: DataFrame, clusters: int, iters: int = 5, init: str = "first", seed: int = 0, full: bool = False) -> np.ndarray:
    """Centroids of (id, vec): on a bounded sample, or by distributed Lloyd's steps over all rows with full=True."""
    if not full:
        x = sample(db, sample_rows(db, clusters), init, seed)
        return lloyd(x, x[:clusters], iters)
    c = sample(db, clusters, init, seed)
    for _ in range(iters):
        c = lloyd_step(db, c)
    return c


def lloyd_step(db: DataFrame, c: np.ndarray) -> np.ndarray:
    """One step over all rows: tasks send a sum per cluster and dimension, not rows."""
    if c.nbytes > MODEL_BYTES:
        raise ValueError(f"centroids of {c.nbytes} bytes are over the broadcast bound of {MODEL_BYTES}; train on a sample")
    held = db.sparkSession.sparkContext.broadcast(c)
    arrow.importable(db.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c, total, n = held.value, np.zeros_like(held.value), np.zeros(len(held.value), np.int64)
        for b in batches:
            x = arrow.vectors(b.column(0)).astype(np.float64)
            at = nearest(x, c)
            np.add.at(total, at, x)
            n += np.bincount(at, minlength=len(c))
        k = np.flatnonzero(n)
        yield pa.RecordBatch.from_arrays([pa.array(k), pa.array(n[k]), pa.array(list(total[k]), pa.list_(pa.float64()))], ["k", "n", "total"])

    part = db.select("vec").mapInArrow(run, "k long, n long, total array<double>")
    sums = part.select("k", "n", F.posexplode("total").alias("d", "v")).groupBy("k", "d").agg(F.sum("n").alias("n"), F.sum("v").alias("v"))
    out = c.copy()
    t = sums.toArrow()  # a row per cluster and dimension
    out[t["k"].to_numpy(), t["d"].to_numpy()] = t["v"].to_numpy() / t["n"].to_numpy()
    return out


class ProductQuantizer(Scorer):
    """m sub-vectors, each replaced by one of 2**bits centroids.

    The distance to a code is that to the vector it stands for: a sum over tables that a query fills once, with
    one entry per sub-vector and centroid. No vector is decoded.
    """

    column = "code"
    #: Bytes of tables held at a time.
    TABLE_BYTES = 32 << 20

    def __init__(self, books: np.ndarray):
        self.books = books  # m, 2**bits, width
        self.m, self.size, self.width = books.shape

    @classmethod
    def train(cls, db: DataFrame, m: int, bits: int = 8, iters: int = 4, init: str = "first", seed: int = 0) -> ProductQuantizer:
        size = 1 << bits
        x = sample(db, size if iters == 0 else sample_rows(db, size), init, seed)
        if len(x) < size or x.shape[1] % m:
            raise ValueError(f"{len(x)} vectors of {x.shape[1] if x.ndim == 2 else 0} dimensions can't train {m} x {size} centroids")
        parts = x.reshape(len(x), m, -1)
        return cls(np.stack([lloyd(parts[:, j], parts[:size, j], iters) for j in range(m)]))

    def encode_rows(self, x: np.ndarray) -> np.ndarray:
        parts = x.reshape(len(x), self.m, self.width)
        return np.stack([nearest(parts[:, j], self.books[j]) for j in range(self.m)], 1)

    def decode_rows(self, code: np.ndarray) -> np.ndarray:
        return np.concatenate([self.books[j][code[:, j]] for j in range(self.m)], 1)

    def rows(self, column: pa.Array) -> np.ndarray:
        return arrow.vectors(column).astype(np.int64)

    @property
    def step(self) -> int:
        return max(1, self.TABLE_BYTES // (8 * self.m * self.size))

    def prepare(self, q: np.ndarray) -> np.ndarray:
        return self.tables(q)

    def score(self, ready: np.ndarray, mine: np.ndarray, code: np.ndarray) -> np.ndarray:
        return np.round(self.look_up(ready[mine], code), 9)

    def distances(self, q: np.ndarray, code: np.ndarray) -> np.ndarray:
        every = [self.tables(q[lo : lo + self.step]) for lo in range(0, len(q), self.step)]
        return np.round(np.concatenate([self.look_up(t, code) for t in every]), 9) if every else np.zeros((0, len(code)))

    def tables(self, q: np.ndarray) -> np.ndarray:
        """Squared distances of each query's sub-vectors to all centroids: queries, m, 2**bits."""
        parts = q.reshape(len(q), self.m, self.width)
        out = np.empty((len(q), self.m, self.size))
        for j in range(self.m):
            x, c = parts[:, j], self.books[j]
            out[:, j] = (x * x).sum(1)[:, None] + (c * c).sum(1) - 2 * (x @ c.T)
        return np.maximum(out, 0, out=out)

    def look_up(self, tables: np.ndarray, code: np.ndarray) -> np.ndarray:
        out = np.zeros((len(tables), len(code)))
        for j in range(self.m):
            out += tables[:, j].take(code[:, j], 1)
        return out


class ResidualQuantizer(Scorer):
    """Codes that add up: each step quantizes what the steps before left over."""

    column = "code"

    def __init__(self, books: np.ndarray):
        self.books = books  # steps, 2**bits, dim

    @classmethod
    def train(cls, db: DataFrame, steps: int = 8, bits: int = 8, iters: int = 4, init: str = "first", seed: int = 0) -> ResidualQuantizer:
        size = 1 << bits
        x, books = sample(db, sample_rows(db, size), init, seed).copy(), []
        for _ in range(steps):
            c = lloyd(x, x[:size], iters)
            books.append(c)
            x = x - c[nearest(x, c)]
        return cls(np.stack(books))

    def encode_rows(self, x: np.ndarray) -> np.ndarray:
        out, x = [], x.copy()
        for c in self.books:
            at = nearest(x, c)
            out.append(at)
            x = x - c[at]
        return np.stack(out, 1)

    def decode_rows(self, code: np.ndarray) -> np.ndarray:
        return sum(c[code[:, j]] for j, c in enumerate(self.books))

    def rows(self, column: pa.Array) -> np.ndarray:
        return self.decode_rows(arrow.vectors(column).astype(np.int64))

    def distances(self, q: np.ndarray, x: np.ndarray) -> np.ndarray:
        return np.maximum((q * q).sum(1)[:, None] + (x * x).sum(1) - 2 * (q @ x.T), 0)


def encode(db: DataFrame, quantizer) -> DataFrame:
    """Adds code (array<short>) to rows with vec."""
    arrow.importable(db.sparkSession)
    held = db.sparkSession.sparkContext.broadcast(quantizer)

    @F.arrow_udf("array<short>")
    def code(vec: pa.Array) -> pa.Array:
        x = arrow.vectors(vec).astype(np.float64)
        if not len(x):
            return pa.array([], pa.list_(pa.int16()))
        c = held.value.encode_rows(x).astype(np.int16)
        return pa.ListArray.from_arrays(pa.array(np.arange(len(c) + 1, dtype=np.int32) * c.shape[1]), pa.array(c.ravel()))

    return db.withColumn("code", code("vec"))
