"""Id lists as compressed rows: encode, decode, point reads and set operations.

A row is a list, or a segment of one: k, seg, n, lo, universe, codec, payload, bits. One exchange deals rows by (k, seg); a task
codes all lists of an Arrow batch together. Segments bound a list's memory and let one long list be coded by many tasks.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import listcodecs
from . import arrow, ops

#: Ids that a task decodes at a time, at most, but for a longer list.
DECODE_IDS = 1 << 18
#: Cells of the matrix that lists coded in step share; longer lists go alone.
CELLS = 1 << 21


def encode_lists(df: DataFrame, key: str, id: str, codec: str, universe: int, segment_bits: int | None = None) -> DataFrame:
    """Codes (key, id) rows, repeated ones once; ids lie in 0..universe-1, nulls and others raise an error.

    With segment_bits, ids are cut into ranges of 2**segment_bits and coded within their range.
    """
    arrow.importable(df.sparkSession)
    kind = dict(df.dtypes)[key]
    own = universe if segment_bits is None else 1 << segment_bits
    ids = F.col(id).cast("long")
    checked = F.when(ids.isNull() | F.col(key).isNull() | (ids < 0) | (ids >= universe), F.raise_error(F.lit("ids must be present and inside the universe"))).otherwise(ids)
    seg = F.lit(0) if segment_bits is None else F.shiftright(ids, segment_bits).cast("int")
    rows = df.select(F.col(key).alias("k"), seg.alias("seg"), checked.alias("id"))
    rows = rows.repartition("k", "seg").sortWithinPartitions("k", "seg", "id")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        c = listcodecs.codec(codec, own)
        for b in arrow.whole_groups(batches, 2):
            first = arrow.edges([b.column(0), b.column(1), b.column(2)])[:-1]
            if len(first) < b.num_rows:  # rows that repeat stand side by side
                b = b.take(pa.array(first))
            at = arrow.edges([b.column(0), b.column(1)])
            lo = b.column(1).to_numpy().astype(np.int64)[at[:-1]] * (0 if segment_bits is None else own)
            ids = b.column(2).to_numpy() - np.repeat(lo, np.diff(at))
            payload, bits = _in_portions(c, ids, at)
            pick = pa.array(at[:-1])
            n = len(at) - 1
            yield pa.RecordBatch.from_arrays(
                [b.column(0).take(pick), b.column(1).take(pick), pa.array(np.diff(at)), pa.array(lo), pa.array(np.full(n, own)), pa.array([codec] * n), pa.array(payload, pa.binary()), pa.array(bits.astype(np.int64))],
                ["k", "seg", "n", "lo", "universe", "codec", "payload", "bits"],
            )

    return rows.mapInArrow(run, f"k {kind}, seg int, n long, lo long, universe long, codec string, payload binary, bits long")


def _in_portions(c, ids: np.ndarray, at: np.ndarray) -> tuple[list[bytes], np.ndarray]:
    """Codes lists of like length together, so that the shared matrix stays bounded."""
    size = np.diff(at)
    order = np.argsort(-size, kind="stable")
    payload: list[bytes] = [b""] * len(size)
    bits = np.zeros(len(size), np.int64)
    lo = 0
    while lo < len(order):
        width = max(1, int(size[order[lo]]))
        some = order[lo : lo + max(1, CELLS // width)]
        n = size[some]
        cut = np.r_[0, np.cumsum(n)]
        flat = ids[np.repeat(at[:-1][some] - cut[:-1], n) + np.arange(int(cut[-1]))]
        got, b = c.encode(flat, cut)
        for i, p in zip(some.tolist(), got, strict=True):
            payload[i] = p
        bits[some] = b
        lo += len(some)
    return payload, bits


def decode_lists(encoded: DataFrame) -> DataFrame:
    """(k, id) of encoded rows; filter by k before, since nothing is pushed below the decoder."""
    arrow.importable(encoded.sparkSession)
    kind = dict(encoded.dtypes)["k"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            name, universe, n = b.column(3).to_pylist(), b.column(4).to_numpy(), b.column(1).to_numpy()
            lo, payload = b.column(2).to_numpy(), b.column(5).to_pylist()
            for kind_of in sorted({*zip(name, universe.tolist(), strict=True)}):
                mine = np.array([i for i, x in enumerate(zip(name, universe.tolist(), strict=True)) if x == kind_of])
                mine = mine[np.argsort(-n[mine], kind="stable")]
                c, at = listcodecs.codec(kind_of[0], kind_of[1]), 0
                while at < len(mine):
                    width = max(1, int(n[mine[at]]))
                    some = mine[at : at + max(1, min(CELLS // width, DECODE_IDS // width))]
                    ids = c.decode([payload[i] for i in some.tolist()], n[some]) + np.repeat(lo[some], n[some])
                    yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(np.repeat(some, n[some]))), pa.array(ids)], ["k", "id"])
                    at += len(some)

    return encoded.select("k", "n", "lo", "codec", "universe", "payload").mapInArrow(run, f"k {kind}, id long")


#: Places, or ids, that one bin of a look-up for segments covers.
BIN = 4096


def places(encoded: DataFrame) -> DataFrame:
    """(k, seg, first, end): which places of its list each segment holds; reads sizes alone."""
    before = Window.partitionBy("k").orderBy("seg").rowsBetween(Window.unboundedPreceding, -1)
    first = F.coalesce(F.sum("n").over(before), F.lit(0))
    return encoded.select("k", "seg", "n").withColumn("first", first).select("k", "seg", "first", (F.col("first") + F.col("n")).alias("end"))


def _grouped(rows: DataFrame, keys: list[str], keep: list[str], read, got: str = "long") -> DataFrame:
    """Adds got: read(codec, payload, n, batch of one list's rows); rows are brought together by list, so a payload is opened once."""
    arrow.importable(rows.sparkSession)
    types = dict(rows.dtypes)
    rows = rows.select(*keys, *keep, "n", "lo", "codec", "universe", "payload").repartition(*keys).sortWithinPartitions(*keys)
    n = len(keys)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            at = arrow.edges([b.column(k) for k in range(n)])
            for x, y in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
                part = b.slice(x, y - x)
                size, lo, name, universe, payload = (part.column(part.num_columns - 5 + k)[0].as_py() for k in range(5))
                value = read(listcodecs.codec(name, universe), payload, size, part, lo)
                yield pa.RecordBatch.from_arrays([*(part.column(k) for k in range(n + len(keep))), value], [*keys, *keep, "got"])

    return rows.mapInArrow(run, ", ".join(f"`{c}` {types[c]}" for c in [*keys, *keep]) + f", got {got}")


def get(encoded: DataFrame, asked: DataFrame) -> DataFrame:
    """id at a place of a list, for asked rows (k, off), whatever the number of segments; places that a list lacks give no row.

    Fixed width, raw and Elias-Fano lists are read at the place alone; of others the segment that holds it is decoded.
    """
    at = ops.range_join(asked.select("k", "off"), "off", places(encoded), "first", "end", BIN, ["k"]).withColumn("place", F.col("off") - F.col("first"))
    rows = at.select("k", "seg", "off", "place").join(encoded, ["k", "seg"])

    def read(c, payload: bytes, n: int, part: pa.RecordBatch, lo: int) -> pa.Array:
        return pa.array(listcodecs.get_many(c, payload, n, part.column(3).to_numpy()) + lo)

    return _grouped(rows, ["k", "seg"], ["off", "place"], read).select("k", "off", F.col("got").alias("id"))


def next_geq(encoded: DataFrame, asked: DataFrame) -> DataFrame:
    """The least id not under a value, for asked rows (k, value) of lists that exist; Elias-Fano lists of any number of segments; null where there is none.

    The first segment that isn't under the value's range is asked for it, and the segment after for its first id; the lesser answer counts. Both
    are found from the segments' numbers alone, by a merge join on bins, and no list is opened but these; the coded rows are read three times.
    """
    ef = encoded.filter(F.col("codec").isin("ef", "ef_dir")).withColumn("seg", F.col("seg").cast("long"))
    own = ef.groupBy("k").agg(F.max("universe").alias("own"))  # of one size within a list
    rows = asked.groupBy("k", "value").agg(F.count(F.lit(1)).cast("int").alias("times")).join(own.hint("merge"), "k")
    at = F.greatest("value", F.lit(0)).cast("long")
    rows = rows.withColumn("at", at).withColumn("place", F.floor(at / F.col("own")).cast("long"))
    # each segment answers for the missing ones before it
    of_k = Window.partitionBy("k").orderBy("seg")
    gaps = ef.select("k", "seg", F.coalesce(F.lag("seg").over(of_k) + 1, F.lit(0)).alias("from"), (F.col("seg") + 1).alias("to"), F.lead("seg").over(of_k).alias("after"))
    met = ops.range_join(rows.select("k", "value", "at", "place"), "place", gaps, "from", "to", BIN, ["k"])
    both = met.select("k", "value", F.explode(F.array(F.struct("seg", "at"), F.struct(F.col("after").alias("seg"), F.lit(0).cast("long").alias("at")))).alias("x"))
    both = both.select("k", "value", "x.seg", "x.at").filter("seg IS NOT NULL")

    def read(c, payload: bytes, n: int, part: pa.RecordBatch, lo: int) -> pa.Array:
        got = c.open(payload, n).next_geq(np.maximum(part.column(2).to_numpy() - lo, 0))
        return pa.array(got + lo, mask=got < 0)

    found = _grouped(both.join(ef.hint("merge"), ["k", "seg"]), ["k", "seg"], ["at", "value"], read)
    found = found.groupBy("k", "value").agg(F.min("got").alias("id"))
    told = rows.select("k", "value", "times").join(found.hint("merge"), ["k", "value"], "left")
    return told.select("k", "value", "id", F.explode(F.array_repeat(F.lit(0), F.col("times")))).select("k", "value", "id")


def intersect(encoded: DataFrame, pairs: DataFrame) -> DataFrame:
    """Common ids of two lists, for pairs (a, b), by jumps on the compressed forms (Elias-Fano); segments meet segments of the same range."""
    arrow.importable(encoded.sparkSession)
    side = encoded.filter(F.col("codec").isin("ef", "ef_dir")).select("k", "lo", "n", "universe", "codec", "payload")
    left = side.select(F.col("k").alias("a"), "lo", F.col("n").alias("n1"), "universe", "codec", F.col("payload").alias("p1"))
    right = side.select(F.col("k").alias("b"), "lo", F.col("n").alias("n2"), "universe", "codec", F.col("payload").alias("p2"))

    @F.arrow_udf("array<long>")
    def both(lo: pa.Array, u: pa.Array, codec: pa.Array, p1: pa.Array, n1: pa.Array, p2: pa.Array, n2: pa.Array) -> pa.Array:
        rows = zip(*(c.to_pylist() for c in (lo, u, codec, p1, n1, p2, n2)), strict=True)
        return pa.array([listcodecs.codec(name, x).intersect(a, n, b, m) + first for first, x, name, a, n, b, m in rows], pa.list_(pa.int64()))

    met = pairs.join(left, "a").join(right, ["b", "lo", "universe", "codec"])
    return met.select("a", "b", F.explode(both("lo", "universe", "codec", "p1", "n1", "p2", "n2")).alias("id"))


def unite(a: DataFrame, b: DataFrame, codec: str, universe: int, segment_bits: int | None = None) -> DataFrame:
    """The lists of two encoded frames put together key by key, coded anew; ids in both once."""
    return encode_lists(decode_lists(a).unionByName(decode_lists(b)), "k", "id", codec, universe, segment_bits)


def append(encoded: DataFrame, more: DataFrame, key: str, id: str, codec: str, universe: int, segment_bits: int | None = None) -> DataFrame:
    """Encoded lists with further (key, id) rows: only segments that gain ids are coded anew; parameters as they were encoded with."""
    new = more.select(F.col(key).alias("k"), F.col(id).cast("long").alias("id"))
    seg = F.lit(0) if segment_bits is None else F.shiftright("id", segment_bits).cast("int")
    touched = new.select("k", seg.alias("seg")).distinct()
    again = decode_lists(encoded.join(touched, ["k", "seg"], "left_semi")).unionByName(new)
    return encoded.join(touched, ["k", "seg"], "left_anti").unionByName(encode_lists(again, "k", "id", codec, universe, segment_bits))


def bits_per_id(encoded: DataFrame) -> DataFrame:
    """One row: codec, ids, lists, bits per id; reads no payload."""
    return encoded.groupBy("codec").agg(F.sum("n").cast("long").alias("ids"), F.count(F.lit(1)).cast("long").alias("lists"), F.round(F.sum("bits") / F.sum("n"), 4).alias("bits_per_id"))


def lost_or_added(original: DataFrame, decoded: DataFrame) -> DataFrame:
    """Rows that only one side has; none for a lossless codec."""
    return original.exceptAll(decoded).unionByName(decoded.exceptAll(original))
