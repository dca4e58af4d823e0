"""What the text operators share: shared-folder staging, batch cutting, vectorised word hashes."""

from __future__ import annotations

import gc
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.arrow import _delete, importable, shared_dir, stage  # noqa: F401


def col(name: str) -> Column:
    """A top-level column by its literal name, dots and backticks included."""
    return F.col("`" + name.replace("`", "``") + "`")


def unstage(df: DataFrame) -> None:
    """Deletes a staged table that nothing reads any more."""
    _delete(df.sparkSession, df._staged_path)  # type: ignore[attr-defined]


def sweep(spark: SparkSession) -> None:
    """Lets Spark's cleaner drop the shuffle files of finished steps."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def parts(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions", "200"))


def clean_text(text: Column) -> Column:
    return F.coalesce(text.cast("string"), F.lit(""))


def slices(batch: pa.RecordBatch, text: int, most: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """Cuts a batch so that each piece holds about `most` bytes of text; a longer text stands alone."""
    arr = batch.column(text)
    n = batch.num_rows
    if n == 0:
        return
    size = np.frombuffer(arr.buffers()[1], dtype=np.int32 if pa.types.is_string(arr.type) or pa.types.is_binary(arr.type) else np.int64)
    off = size[arr.offset : arr.offset + n + 1]
    lo = 0
    while lo < n:
        hi = int(np.searchsorted(off, off[lo] + most, side="right")) - 1
        hi = min(n, max(hi, lo + 1))
        yield batch.slice(lo, hi - lo)
        lo = hi


def raw(arr: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """The bytes of a string column and its n+1 offsets into them (nulls must be filled)."""
    if arr.type not in (pa.string(), pa.binary()):
        arr = arr.cast(pa.string() if pa.types.is_large_string(arr.type) else pa.binary())
    n = len(arr)
    off = np.frombuffer(arr.buffers()[1], dtype=np.int32, count=arr.offset + n + 1)[arr.offset :].astype(np.int64)
    buf = arr.buffers()[2]
    data = np.frombuffer(buf, dtype=np.uint8) if buf is not None and buf.size else np.zeros(0, np.uint8)
    data = data[off[0] : off[-1]]
    return data, off - off[0]


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scrambling of 64-bit words (the finaliser of splitmix64)."""
    x = x.astype(np.uint64, copy=True)
    x ^= x >> np.uint64(30)
    x *= np.uint64(0xBF58476D1CE4E5B9)
    x ^= x >> np.uint64(27)
    x *= np.uint64(0x94D049BB133111EB)
    x ^= x >> np.uint64(31)
    return x


BASE = 0x9E3779B97F4A7C15 | 1
_POW: dict[int, np.ndarray] = {}


def powers(n: int, base: int = BASE) -> np.ndarray:
    """base**i mod 2**64 for i in 0..n-1, kept and grown by doubling."""
    have = _POW.get(base)
    if have is None or len(have) < n:
        size = max(n, 1 << 12)
        have = np.ones(1, np.uint64)
        while len(have) < size:
            step = np.uint64(pow(base, len(have), 1 << 64))
            have = np.concatenate([have, have * step])
        _POW[base] = have
    return have[:n]


INV = pow(BASE, -1, 1 << 64)


def inverse(base: int) -> int:
    return pow(base, -1, 1 << 64)


def prefix_hash(data: np.ndarray, base: int = BASE) -> np.ndarray:
    """P[i] = sum of (byte + 1) * base**j over j < i, modulo 2**64; base is odd."""
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum((data.astype(np.uint64) + np.uint64(1)) * powers(len(data), base), out=out[1:])
    return out


def span_hash(prefix: np.ndarray, start: np.ndarray, end: np.ndarray, base: int = BASE) -> np.ndarray:
    """Polynomial hash of bytes start..end, moved to a common exponent, then scrambled."""
    return mix((prefix[end] - prefix[start]) * powers(len(prefix), inverse(base))[start] + (end - start).astype(np.uint64))


_SPACE = np.zeros(256, bool)
_SPACE[[9, 10, 11, 12, 13, 32]] = True


def word_spans(data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of words (runs between ASCII white space), and each word's row."""
    n = len(data)
    if n == 0:
        z = np.zeros(0, np.int64)
        return z, z, z
    solid = ~_SPACE[data]
    first = solid.copy()
    first[1:] &= ~solid[:-1]
    edge = off[(off > 0) & (off < n)]
    first[edge] = solid[edge]
    start = np.flatnonzero(first)
    last = solid.copy()
    last[:-1] &= ~solid[1:]
    last[edge - 1] = solid[edge - 1]
    end = np.flatnonzero(last) + 1
    row = np.searchsorted(off, start, side="right") - 1
    return start, end, row


def whole_groups(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.RecordBatch]:
    """Regroups sorted batches so that none cuts a group; the first `keys` columns, integers, name the group."""
    held: list[pa.RecordBatch] = []

    def joined(some: list[pa.RecordBatch]) -> pa.RecordBatch:
        return some[0] if len(some) == 1 else pa.Table.from_batches(some).combine_chunks().to_batches()[0]

    for b in batches:
        if not b.num_rows:
            continue
        key = [b.column(k).to_numpy(zero_copy_only=False) for k in range(keys)]
        last = np.ones(b.num_rows, bool)
        for k in key:
            last &= k == k[-1]
        cut = int(np.flatnonzero(~last)[-1]) + 1 if not last.all() else 0
        same = bool(held) and all(held[-1].column(k)[-1].as_py() == int(key[k][0]) for k in range(keys))
        if held and not (cut == 0 and same):
            # the held group ends within this batch or before it
            end = cut if same else 0
            yield joined([*held, *([b.slice(0, end)] if end else [])])
            if end:
                b, cut = b.slice(end), 0
            held = []
        if cut:
            yield b.slice(0, cut)
            b = b.slice(cut)
        held.append(b)
    if held:
        yield joined(held)


def star_edges(p: np.ndarray, q: np.ndarray, n: int) -> np.ndarray:
    """Least member of each of n local nodes' components under the links p-q."""
    label = np.arange(n)
    while True:
        low = np.minimum(label[p], label[q])
        new = label.copy()
        np.minimum.at(new, label[p], low)
        np.minimum.at(new, label[q], low)
        new = new[new]
        new = np.minimum(new, label)
        if (new == label).all():
            return label
        label = new


def components(edges: DataFrame) -> DataFrame:
    """node, comp (the least node reachable) of every node in edges (a long, b long); distributed, any size.

    Labels fall to the least neighbour's and then jump to their label's label, until none changes.
    """
    spark = edges.sparkSession
    both = stage(edges.select("a", "b").union(edges.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct(), "cc-edges")
    label = stage(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("l")).withColumnRenamed("a", "v"), "cc-labels")
    while True:
        near = both.join(label, both["b"] == label["v"]).groupBy("a").agg(F.min("l").alias("m"))
        fell = label.join(near, label["v"] == near["a"]).select("v", F.col("l").alias("was"), F.least("l", "m").alias("l"))
        step = stage(fell, "cc-step")
        to = step.select(F.col("v").alias("t"), F.col("l").alias("tl"))
        new = stage(step.join(to, step["l"] == to["t"], "left").select("v", "was", F.least("l", F.coalesce("tl", "l")).alias("l")), "cc-labels")
        done = new.filter("l <> was").isEmpty()
        unstage(label)
        unstage(step)
        label = stage(new.select("v", "l"), "cc-labels") if not done else new.select("v", "l")
        if done:
            unstage(both)
            sweep(spark)
            return label.select(F.col("v").alias("node"), F.col("l").alias("comp"))


def identified(docs: DataFrame, key: str, keep: list[str]) -> DataFrame:
    """uid (unique and stable), ord (the key as a long, null last) and the columns named.

    Where keys are unique, as they should be, the key itself is the uid. Otherwise rows are numbered and written to the
    shared folder, since a number given anew at each read could change when executors come and go.
    """
    k = col(key).cast("long")
    order = F.coalesce(k, F.lit((1 << 63) - 1))
    again = docs.select(k.alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n")).filter("n > 1 OR k IS NULL")
    if again.isEmpty():
        return docs.select(k.alias("uid"), order.alias("ord"), *[col(c) for c in keep])
    return stage(docs.select(F.monotonically_increasing_id().alias("uid"), order.alias("ord"), *[col(c) for c in keep]), "identified")


#: Bits of a sieve, in bitmaps of 2**15 bits. All of them together are 4 MiB, which is what a sieve broadcasts at most.
SIEVE = 1 << 25


def _place(key: str) -> Column:
    return F.pmod(F.xxhash64(col(key)), F.lit(SIEVE))


def sieve(wanted: DataFrame, key: str) -> DataFrame:
    """A bit for each hash of the wanted keys, as at most 1,024 bitmaps of 4 KiB: a broadcast of a fixed bound, pre-aggregated by each task.

    With more than some ten million keys most bits are set and fewer rows are held back: the join after it then shuffles up to all
    rows once, in proportion to the input, and its result stays the same.
    """
    place = _place(key)
    return F.broadcast(wanted.groupBy(F.bitmap_bucket_number(place).alias("map")).agg(F.bitmap_construct_agg(F.bitmap_bit_position(place)).alias("bits")))


def sifted(rows: DataFrame, key: str, bits: DataFrame, how: str = "left_semi") -> DataFrame:
    """Rows whose bit is set (left_semi) or isn't (left_anti) in a `sieve`: a filter before a shuffle, not a result."""
    place = F.bitmap_bit_position(_place(key))
    byte = F.conv(F.hex(F.substring(bits["bits"], (F.shiftright(place, 3) + 1).cast("int"), F.lit(1))), 16, 10).cast("int")
    set_ = F.call_function("getbit", byte, place.bitwiseAND(F.lit(7)).cast("int")) == 1
    return rows.join(bits, (F.bitmap_bucket_number(_place(key)) == bits["map"]) & set_, how)
