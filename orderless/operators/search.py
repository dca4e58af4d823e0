"""Nearest-neighbour search over all rows or over probed clusters, for a stated batch of queries.

The query batch is held on the driver and broadcast, in blocks of a checked size. Rows stay where they are: every Arrow batch gives its
own best k per query, and only those meet in the final ranking.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import arrow

#: Bytes of queries broadcast at once, at most.
BLOCK_BYTES = 32 << 20
#: Distances of an exact search computed at a time, and answers a task of it holds, at most.
CELLS = 1 << 21


class Scorer:
    """What a scan asks of a scorer: what it needs of some queries, made once for all clusters of a batch, and distances from that."""

    #: Queries made ready at a time.
    step = 1 << 30

    def prepare(self, q: np.ndarray) -> np.ndarray:
        return q

    def score(self, ready: np.ndarray, mine: np.ndarray, rows: np.ndarray) -> np.ndarray:
        return self.distances(ready[mine], rows)


class Flat(Scorer):
    """Exact distances to full vectors: squared Euclidean, cosine distance or negative inner product."""

    column = "vec"

    def __init__(self, metric: str = "l2"):
        if metric not in ("l2", "cosine", "ip"):
            raise ValueError(f"no metric {metric!r}")
        self.metric = metric

    def rows(self, column: pa.Array) -> np.ndarray:
        return arrow.vectors(column).astype(np.float64)

    def distances(self, q: np.ndarray, x: np.ndarray) -> np.ndarray:
        if self.metric == "ip":
            return -(q @ x.T)
        if self.metric == "cosine":
            return 1 - (q @ x.T) / np.maximum(np.linalg.norm(q, axis=1)[:, None] * np.linalg.norm(x, axis=1), 1e-300)
        return np.maximum((q * q).sum(1)[:, None] + (x * x).sum(1) - 2 * (q @ x.T), 0)


def query_blocks(q: DataFrame) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(qid, matrix) in blocks that fit a broadcast, brought to the driver one at a time; q has qid and qvec."""
    rows = q.select(F.col("qid").cast("long").alias("qid"), F.col("qvec").cast("array<double>").alias("qvec"))
    size = rows.agg(F.sum(F.size("qvec").cast("long")).alias("s")).first().s or 0
    blocks = max(1, -(-8 * size // BLOCK_BYTES))
    for b in range(blocks):
        t = (rows if blocks == 1 else rows.filter(F.pmod(F.xxhash64("qid"), F.lit(blocks)) == b)).toArrow().combine_chunks()
        if t.num_rows:
            yield t["qid"].to_numpy(), arrow.vectors(t["qvec"].chunk(0))


def best(dist: np.ndarray, tie: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """Row and column numbers of each row's k least distances, ties by the lesser tie value."""
    n = dist.shape[1]
    if n > 4 * k:
        part = np.argpartition(dist, k - 1, 1)[:, :k]
        edge = np.take_along_axis(dist, part, 1).max(1)
        row, col = np.nonzero(dist <= edge[:, None])  # ties at the edge stay
    else:
        row, col = (x.ravel() for x in np.indices(dist.shape))
    order = np.lexsort((tie[col], dist[row, col], row))
    row, col = row[order], col[order]
    place = np.arange(len(row)) - np.searchsorted(row, row)
    return row[place < k], col[place < k]


def _merged(found: list[tuple[np.ndarray, np.ndarray, np.ndarray]], k: int) -> tuple[np.ndarray, ...]:
    """The k least of each query among (query number, id, distance), ties by id."""
    row, tie, dist = (np.concatenate(x) for x in zip(*found, strict=True))
    order = np.lexsort((tie, dist, row))
    row = row[order]
    keep = np.arange(len(row)) - np.searchsorted(row, row) < k
    order = order[keep]
    return row[keep], tie[order], dist[order]


def nearest_of(q: tuple[np.ndarray, np.ndarray], batches: Iterator[pa.RecordBatch], k: int, scorer: Scorer) -> Iterator[pa.RecordBatch]:
    """qid, id, dist: a task's own best k per query, told once it has seen its rows; distances are computed in tiles of `CELLS`."""
    ids, mat = q
    none = np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0)
    told = lambda x: pa.RecordBatch.from_arrays([pa.array(ids[x[0]]), pa.array(x[1]), pa.array(x[2])], ["qid", "id", "dist"])
    kept = none
    for b in batches:
        for lo in range(0, b.num_rows, 4096):
            part = b.slice(lo, 4096)
            tie, rows = part.column(0).to_numpy(), scorer.rows(part.column(1))
            step, found = max(1, CELLS // len(tie)), [kept]
            for at in range(0, len(ids), step):
                dist = scorer.distances(mat[at : at + step], rows)
                row, col = best(dist, tie, k)
                found.append((row + at, tie[col], dist[row, col]))
            kept = _merged(found, k)
            if len(kept[0]) > CELLS:  # many answers to many queries: the ranking sorts them out
                yield told(kept)
                kept = none
    yield told(kept)


def ranked(rows: DataFrame, k: int, tie: list[str]) -> DataFrame:
    """The k least distances per query with their rank from 1."""
    w = Window.partitionBy("qid").orderBy("dist", *tie)
    return rows.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def exact(q: DataFrame, db: DataFrame, k: int, metric: str = "l2") -> DataFrame:
    """qid, rank, id, dist over all rows of db (id, vec); ties by id."""
    spark, scorer, out = db.sparkSession, Flat(metric), None
    arrow.importable(spark)
    for qid, qmat in query_blocks(q):
        held = spark.sparkContext.broadcast((qid, qmat))

        def run(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            yield from nearest_of(held.value, batches, k, scorer)

        got = db.select(F.col("id").cast("long").alias("id"), "vec").mapInArrow(run, "qid long, id long, dist double")
        out = got if out is None else out.union(got)
    if out is None:
        return spark.createDataFrame([], "qid long, rank int, id long, dist double")
    return ranked(out, k, ["id"]).select("qid", "rank", "id", "dist")


def scan(codes: DataFrame, q: tuple[np.ndarray, np.ndarray], probes: np.ndarray, k: int, scorer, carry: str = "off") -> DataFrame:
    """Best k per query among the clusters it probes: qid, k, carry (off or id), dist; codes (k, off|id, column of the scorer)."""
    spark = codes.sparkSession
    arrow.importable(spark)
    held = spark.sparkContext.broadcast((*q, probes, scorer))
    wanted = sorted({int(c) for c in probes.ravel()})
    if len(wanted) <= 256:  # few enough for the filter to reach the files
        near = codes.filter(F.col("k").isin(wanted))
    else:  # a number per cluster that the block probes
        near = codes.join(F.broadcast(spark.createDataFrame(pa.table({"k": pa.array(wanted, pa.int64())}))), "k", "left_semi")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, mat, probed, score = held.value
        for b in batches:
            cluster, tie = b.column(0).to_numpy(), b.column(1).to_numpy()
            rows = score.rows(b.column(2))
            for lo in range(0, len(ids), score.step):
                ready, part, own = score.prepare(mat[lo : lo + score.step]), probed[lo : lo + score.step], ids[lo : lo + score.step]
                for c in np.unique(cluster).tolist():
                    here, mine = np.flatnonzero(cluster == c), np.flatnonzero((part == c).any(1))
                    if not len(mine):
                        continue
                    dist = score.score(ready, mine, rows[here])
                    row, col = best(dist, tie[here], k)
                    yield pa.RecordBatch.from_arrays([pa.array(own[mine][row]), pa.array(np.full(len(row), c)), pa.array(tie[here][col]), pa.array(dist[row, col])], ["qid", "k", carry, "dist"])

    cols = [F.col("k").cast("long").alias("k"), F.col(carry).cast("long").alias(carry), scorer.column]
    return near.select(*cols).mapInArrow(run, f"qid long, k long, {carry} long, dist double")


def recall(result: DataFrame, truth: DataFrame) -> DataFrame:
    """Share of true neighbours found; both (qid, id)."""
    hit = truth.select("qid", "id").join(result.select("qid", "id"), ["qid", "id"], "left_semi").agg(F.count(F.lit(1)).alias("h"))
    return hit.crossJoin(truth.agg(F.count(F.lit(1)).alias("t"))).select(F.round(F.col("h") / F.col("t"), 6).alias("recall"))


def empty(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], "qid long, rank int, id long, dist double")
