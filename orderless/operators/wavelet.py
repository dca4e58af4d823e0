"""Wavelet trees over cluster labels: any id of any cluster by its offset, without decoding a list.

The label sequence S[id] = k over dense ids is cut into shards of 2**shard_bits ids. A shard keeps, per level, one bit a label (which
half of the vocabulary it goes to), nodes side by side, as flat or block-compressed bit strings. A directory holds, for each label
met in a shard, how many came before: it leads (k, offset) to its shard.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.bitvec import RRR, Flat
from . import arrow, ops


class UnsupportedError(ValueError):
    """Asked of a structure that can't hold it, such as lists that overlap."""


def levels_of(vocabulary: int) -> int:
    return max(1, (max(vocabulary, 1) - 1).bit_length())


class Tree:
    """One shard's tree; vectorised access, rank and select."""

    def __init__(self, levels: int, labels: np.ndarray, counts: np.ndarray, bits: list):
        self.levels, self.labels, self.counts, self.bits = levels, labels, counts, bits
        self.below = np.r_[0, np.cumsum(counts)]

    @classmethod
    def of(cls, seq: np.ndarray, levels: int, kind: str = "flat", block: int = 63) -> Tree:
        labels, counts = np.unique(seq, return_counts=True)
        bits, order = [], seq
        for level in range(levels):
            if level:  # nodes side by side: stable by the bits above this level
                order = seq[np.argsort(seq >> (levels - level), kind="stable")]
            b = (order >> (levels - level - 1)) & 1
            bits.append(Flat.of(b) if kind == "flat" else RRR.of(b, block))
        return cls(levels, labels, counts, bits)

    def _start(self, prefix: np.ndarray, level: int) -> np.ndarray:
        """Where the node of a prefix begins at its level."""
        return self.below[np.searchsorted(self.labels, prefix << (self.levels - level))]

    def select(self, k: np.ndarray, o: np.ndarray) -> np.ndarray:
        """Place in the sequence of the o-th (from 0) label k; it must exist."""
        at = np.asarray(o, np.int64)
        k = np.asarray(k, np.int64)
        for level in range(self.levels - 1, -1, -1):
            bit = (k >> (self.levels - level - 1)) & 1
            start = self._start(k >> (self.levels - level), level)
            out = np.empty(len(k), np.int64)
            for v in (0, 1):
                m = np.flatnonzero(bit == v)
                if len(m):
                    base = self.bits[level].rank(start[m], v)
                    out[m] = self.bits[level].select(base + at[m], v) - start[m]
            at = out
        return at

    def access(self, i: np.ndarray) -> np.ndarray:
        at, prefix = np.asarray(i, np.int64), np.zeros(len(i), np.int64)
        for level in range(self.levels):
            start = self._start(prefix, level)
            v = self.bits[level]
            bit = v.access(start + at).astype(np.int64)
            ones = v.rank(start + at) - v.rank(start)
            at = np.where(bit == 1, ones, at - ones)
            prefix = prefix * 2 + bit
        return prefix

    def rank(self, k: np.ndarray, i: np.ndarray) -> np.ndarray:
        """How many of the first i labels are k."""
        at, k = np.asarray(i, np.int64), np.asarray(k, np.int64)
        for level in range(self.levels):
            start = self._start(k >> (self.levels - level), level)
            v, bit = self.bits[level], (k >> (self.levels - level - 1)) & 1
            ones = v.rank(start + at) - v.rank(start)
            at = np.where(bit == 1, ones, at - ones)
        return at

    def size_bits(self, directory: bool = True) -> int:
        return sum(b.bits(directory) for b in self.bits)


INDEX = "shard int, levels int, kind string, n long, labels array<long>, counts array<long>, payload array<binary>, bits long, payload_bits long"


def build(df: DataFrame, id: str, k: str, vocabulary: int, kind: str = "flat", shard_bits: int = 20, block: int = 63) -> DataFrame:
    """Index rows of a partition: every id of a shard's range must occur exactly once, or an error says so."""
    arrow.importable(df.sparkSession)
    levels = levels_of(vocabulary)
    if kind not in ("flat", "rrr"):
        raise UnsupportedError(f"no bit strings of kind {kind!r}")
    rows = df.select(F.shiftright(F.col(id).cast("long"), shard_bits).cast("int").alias("shard"), F.col(id).cast("long").alias("id"), F.col(k).cast("long").alias("k"))
    rows = rows.repartition("shard").sortWithinPartitions("shard", "id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in arrow.whole_groups(batches, 1):
            at = arrow.edges([b.column(0)])
            ids, seq, shard = b.column(1).to_numpy(), b.column(2).to_numpy(), b.column(0).to_numpy()
            for lo, hi in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
                first = int(shard[lo]) << shard_bits
                if (ids[lo:hi] != first + np.arange(hi - lo)).any():
                    raise UnsupportedError("a wavelet tree needs dense ids with one label each; overlapping lists and graphs have none")
                t = Tree.of(seq[lo:hi], levels, kind, block)
                yield pa.RecordBatch.from_pylist(
                    [{"shard": int(shard[lo]), "levels": levels, "kind": kind, "n": hi - lo, "labels": t.labels.tolist(), "counts": t.counts.tolist(), "payload": [v.to_bytes() for v in t.bits], "bits": t.size_bits(), "payload_bits": t.size_bits(False)}],
                    schema=_SCHEMA,
                )

    return rows.mapInArrow(run, INDEX)


_SCHEMA = pa.schema([("shard", pa.int32()), ("levels", pa.int32()), ("kind", pa.string()), ("n", pa.int64()), ("labels", pa.list_(pa.int64())), ("counts", pa.list_(pa.int64())), ("payload", pa.list_(pa.binary())), ("bits", pa.int64()), ("payload_bits", pa.int64())])


def directory(index: DataFrame) -> DataFrame:
    """(k, shard, cum, count): how many k came in earlier shards, for shards that have any."""
    each = index.select("shard", F.explode(F.arrays_zip("labels", "counts")).alias("x")).select("shard", F.col("x.labels").alias("k"), F.col("x.counts").alias("count"))
    before = Window.partitionBy("k").orderBy("shard").rowsBetween(Window.unboundedPreceding, -1)
    return each.withColumn("cum", F.coalesce(F.sum("count").over(before), F.lit(0)))


def _open(row) -> Tree:
    kind = Flat if row["kind"] == "flat" else RRR
    return Tree(row["levels"], np.array(row["labels"], np.int64), np.array(row["counts"], np.int64), [kind.from_bytes(bytes(p)) for p in row["payload"]])


def _by_shard(asked: DataFrame, index: DataFrame, read, schema: str, shard_bits: int) -> DataFrame:
    """Runs read(tree, table, first id) for each shard's questions, beside the shard's tree."""
    arrow.importable(index.sparkSession)

    def run(key: tuple, q: pa.Table, shard: pa.Table) -> pa.Table:
        if not shard.num_rows or not q.num_rows:
            return q.slice(0, 0).append_column("got", pa.array([], pa.int64())).drop(["shard", "local"])
        got = read(_open(shard.slice(0, 1).to_pylist()[0]), q, key[0].as_py() << shard_bits)
        return q.append_column("got", pa.array(got, pa.int64())).drop(["shard", "local"])

    own = index.select(*[F.col(c).alias(c) for c in index.columns])  # asked may stem from the same index
    own = own.join(asked.select("shard").distinct(), "shard", "left_semi")  # payloads of asked shards alone are moved
    return asked.groupBy("shard").cogroup(own.groupBy("shard")).applyInArrow(run, schema)


#: Offsets that one bin of the directory's look-up covers.
BIN = 4096


def located(index: DataFrame, asked: DataFrame) -> DataFrame:
    """asked (k, off, ...) with shard and local, the offset within the shard: one shard a row, by bins of offsets."""
    d = directory(index).withColumn("end", F.col("cum") + F.col("count")).select("k", "shard", "cum", "end")
    return ops.range_join(asked, "off", d, "cum", "end", BIN, ["k"]).withColumn("local", F.col("off") - F.col("cum")).drop("cum", "end")


def select(index: DataFrame, asked: DataFrame, shard_bits: int = 20) -> DataFrame:
    """asked (k, off, ...) with id: the off-th id of cluster k, found in logarithmic time per row. Other columns are kept."""
    keep = [c for c in asked.columns if c not in ("k", "off")]
    types = dict(asked.dtypes)
    rows = located(index, asked).select("k", "off", *keep, "shard", "local")
    schema = ", ".join(f"`{c}` {types[c]}" for c in ["k", "off", *keep]) + ", got long"
    read = lambda t, q, first: first + t.select(q["k"].to_numpy(), q["local"].to_numpy())
    return _by_shard(rows, index, read, schema, shard_bits).withColumnRenamed("got", "id")


def access(index: DataFrame, ids: DataFrame, shard_bits: int = 20) -> DataFrame:
    """ids (id) with k, the cluster that holds each."""
    rows = ids.select("id", F.shiftright("id", shard_bits).cast("int").alias("shard"), F.col("id").alias("local"))
    return _by_shard(rows, index, lambda t, q, first: t.access(q["id"].to_numpy() - first), "id long, got long", shard_bits).withColumnRenamed("got", "k")


def rank(index: DataFrame, asked: DataFrame, shard_bits: int = 20) -> DataFrame:
    """asked (k, pos) with rank: how many ids under pos are in cluster k, 0 for a cluster that has none.

    What stands in earlier shards is the directory's sum up to the position's shard, found by bins of shards: no pairs.
    """
    of_k = Window.partitionBy("k").orderBy("shard")
    d = directory(index)
    after = d.select("k", (F.col("cum") + F.col("count")).alias("before"), F.col("shard").cast("long").alias("from"), F.lead("shard").over(of_k).alias("to"))
    start = d.groupBy("k").agg(F.min("shard").alias("to")).select("k", F.lit(0).cast("long").alias("before"), F.lit(-1).cast("long").alias("from"), "to")
    rows = asked.select("k", "pos", F.shiftright("pos", shard_bits).cast("long").alias("shard"))
    shards = index.agg(F.max("shard").cast("long") + 1).first()[0] or 0
    spans = after.withColumn("to", F.coalesce("to", F.lit(shards))).union(start)
    spans = spans.withColumns({"from": F.col("from") + 1, "to": F.col("to").cast("long") + 1})
    met = ops.range_join(rows, "shard", spans, "from", "to", 64, ["k"]).select("k", "pos", F.col("shard").cast("int").alias("shard"), "before", F.col("pos").alias("local"))
    read = lambda t, q, first: q["before"].to_numpy() + t.rank(q["k"].to_numpy(), q["pos"].to_numpy() - first)
    got = _by_shard(met, index, read, "k long, pos long, before long, got long", shard_bits).select("k", "pos", F.col("got").alias("rank"))
    unknown = rows.join(start.select("k"), "k", "left_anti").select("k", "pos", F.lit(0).cast("long").alias("rank"))
    return got.union(unknown)
