"""Relational operators around id lists, thin where the DataFrame API already says it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def lists(df: DataFrame, key: str, id: str) -> DataFrame:
    """(k, n, ids) with ids ascending; for lists known to be bounded, otherwise encode in segments."""
    return df.groupBy(F.col(key).alias("k")).agg(F.count(F.lit(1)).cast("long").alias("n"), F.array_sort(F.collect_list(id)).alias("ids"))


def unnest(df: DataFrame) -> DataFrame:
    return df.select("k", F.explode("ids").alias("id"))


def with_offsets(df: DataFrame, key: str, id: str) -> DataFrame:
    """Adds off, the place of an id in its list."""
    return df.withColumn("off", (F.row_number().over(Window.partitionBy(key).orderBy(id)) - 1).cast("long"))


def allow(df: DataFrame, ids: DataFrame, on: str) -> DataFrame:
    return df.join(ids, on, "left_semi")


def deny(df: DataFrame, ids: DataFrame, on: str) -> DataFrame:
    return df.join(ids, on, "left_anti")


def merge_join(a: DataFrame, b: DataFrame, on, how: str = "inner") -> DataFrame:
    return a.join(b.hint("merge"), on, how)


def hash_join(a: DataFrame, b: DataFrame, on, how: str = "inner") -> DataFrame:
    """Shuffled hash join, building on b."""
    return a.join(b.hint("shuffle_hash"), on, how)


def range_join(points: DataFrame, at: str, intervals: DataFrame, lo: str, hi: str, width: int, by: list[str] | None = None) -> DataFrame:
    """points whose `at` lies in [lo, hi), within the keys `by`: an equality join on these and bins of `width`, then the exact condition.

    A merge join: intervals derived from coded rows pass for small by the size of their files, and would be sent through the driver.
    """
    p = points.withColumn("_bin", F.floor(F.col(at) / width).cast("long"))
    first, last = F.floor(F.col(lo) / width), F.floor((F.col(hi) - 1) / width)
    i = intervals.filter(F.col(hi) > F.col(lo)).withColumn("_bin", F.explode(F.sequence(first.cast("long"), last.cast("long"))))
    return p.join(i.hint("merge"), [*(by or []), "_bin"]).filter((F.col(at) >= F.col(lo)) & (F.col(at) < F.col(hi))).drop("_bin")


def asof(left: DataFrame, right: DataFrame, on: str, at: str, value: str) -> DataFrame:
    """Each left row with the right side's last value at or before its time; one sort per key, no pairs.

    left has on, at and others; right on, at, value. At equal times the right row counts as earlier.
    """
    cols = [c for c in left.columns if c not in (on, at)]
    l_ = left.select(on, at, F.lit(1).alias("_side"), *cols, F.lit(None).cast(dict(right.dtypes)[value]).alias("_v"), F.lit(None).cast(dict(left.dtypes)[at]).alias("_t"))
    r_ = right.select(on, at, F.lit(0).alias("_side"), *[F.lit(None).cast(dict(left.dtypes)[c]).alias(c) for c in cols], F.col(value).alias("_v"), F.col(at).alias("_t"))
    w = Window.partitionBy(on).orderBy(at, "_side", F.col("_v")).rowsBetween(Window.unboundedPreceding, 0)
    both = l_.unionByName(r_).withColumn(value, F.last("_v", True).over(w)).withColumn("matched_at", F.last("_t", True).over(w))
    return both.filter("_side = 1").drop("_side", "_v", "_t")


def interval_join(a: DataFrame, b: DataFrame, by: str, at_a: str, at_b: str, seconds: int) -> DataFrame:
    """Pairs of one key with at_b in (at_a, at_a + seconds]; times as long seconds; binned equality join."""
    x = a.withColumn("_bin", F.explode(F.array(F.floor(F.col(at_a) / seconds), F.floor(F.col(at_a) / seconds) + 1)))
    y = b.withColumn("_bin", F.floor(F.col(at_b) / seconds))
    return x.join(y, [by, "_bin"]).filter((F.col(at_b) > F.col(at_a)) & (F.col(at_b) <= F.col(at_a) + seconds)).drop("_bin")


def degrees(edges: DataFrame, end: str = "src") -> DataFrame:
    return edges.groupBy(end).agg(F.count(F.lit(1)).cast("long").alias("degree"))


def gaps(df: DataFrame, key: str, id: str) -> DataFrame:
    """Adds gap to the id before (the id itself for the first) and next, the id after."""
    w = Window.partitionBy(key).orderBy(id)
    return df.withColumn("gap", F.col(id) - F.coalesce(F.lag(id).over(w), F.lit(0))).withColumn("next", F.lead(id).over(w))


def running_count(df: DataFrame, by: str, order: str, sym: str) -> DataFrame:
    """Adds seen, how often the symbol came before in its group: the adaptive coder's weight less one."""
    w = Window.partitionBy(by, sym).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    return df.withColumn("seen", F.count(sym).over(w))


def top_per_key(df: DataFrame, by: str, order: list[Column], k: int) -> DataFrame:
    return df.withColumn("rank", F.row_number().over(Window.partitionBy(by).orderBy(*order))).filter(F.col("rank") <= k)


def sample_hash(df: DataFrame, id: str, share: float) -> DataFrame:
    """The same rows at every run and in every engine: by the first 28 bits of the id's MD5."""
    return df.filter(F.conv(F.substring(F.md5(F.col(id).cast("string").cast("binary")), 1, 7), 16, 10).cast("long") < int(share * (1 << 28)))


def remap(df: DataFrame, ext: str) -> DataFrame:
    """(ext, id): dense ids in order of ext, by counts of ranges instead of one sort of all rows in a task."""
    keys = df.select(ext).distinct().withColumn("_p", F.substring(F.md5(F.col(ext).cast("string").cast("binary")), 1, 2))
    local = keys.withColumn("_r", F.row_number().over(Window.partitionBy("_p").orderBy(ext)))
    before = local.groupBy("_p").agg(F.count(F.lit(1)).alias("_n")).withColumn("_before", F.coalesce(F.sum("_n").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    return local.join(F.broadcast(before), "_p").select(ext, (F.col("_before") + F.col("_r") - 1).cast("long").alias("id"))  # 256 rows


def choose_codec(sizes: DataFrame) -> DataFrame:
    """Rate-first choice from list lengths alone: packed for very short lists, Elias-Fano for short ones, random order beyond."""
    return sizes.withColumn("codec", F.when(F.col("n") < 2, "packed").when(F.col("n") < 64, "ef").otherwise("roc"))
