"""Sizes, bounds and rates in bits: as numbers, as Spark columns, and as SQL text for the independent oracle.

n is a list's length, u the universe its ids come from. Lengths are in bits throughout.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

LOG2E = math.log2(math.e)


def log2_factorial(n: float) -> float:
    return math.lgamma(n + 1) * LOG2E


def log2_factorial_col(n: Column) -> Column:
    """log2 of n! by Stirling's series at n + 8; Spark has no log-gamma. Absolute error under 1e-9."""
    n = n.cast("double")
    x = n + 8.0
    product = F.lit(1.0)
    for i in range(1, 9):
        product = product * (n + float(i))
    series = x * F.log(x) - x + 0.5 * F.log(2 * math.pi * x) + 1 / (12 * x) - 1 / (360 * x * x * x) + 1 / (1260 * x * x * x * x * x)
    return (series - F.log(product)) * LOG2E


def width_col(u: Column) -> Column:
    """Bits of an id in fixed width: the length of u - 1 in binary."""
    return F.when(u <= 1, F.lit(0)).otherwise(F.length(F.bin(u - 1))).cast("long")


def low_col(n: Column, u: Column, ceil: bool = False) -> Column:
    """Low bits of Elias-Fano: floor (or ceil) of log2(u / n), never negative."""
    ratio = F.greatest(F.floor(u / F.greatest(n, F.lit(1))), F.lit(1)).cast("long")
    low = (F.length(F.bin(ratio)) - 1).cast("int")
    if ceil:
        low = F.when((u > n) & (n * F.pow(F.lit(2.0), low) < u), low + 1).otherwise(low).cast("int")
    return low


def ef_bits_col(n: Column, u: Column, ceil: bool = False) -> Column:
    low = low_col(n, u, ceil)
    return F.when(n > 0, n * low + n + F.floor(u / F.pow(F.lit(2.0), low)) + 1).otherwise(F.lit(0)).cast("long")


def set_bound_col(n: Column, u: Column) -> Column:
    """Bits of n draws from the universe less their order."""
    return n * F.log2(u.cast("double")) - log2_factorial_col(n)


def comb_bound_col(n: Column, u: Column) -> Column:
    """Bits to name one of the sets of n distinct ids."""
    return log2_factorial_col(u) - log2_factorial_col(n) - log2_factorial_col(u - n)


def list_sizes(df: DataFrame, key: str, id: str) -> DataFrame:
    return df.groupBy(key).agg(F.count(F.lit(1)).cast("long").alias("n"))


def rates(sizes: DataFrame, universe: int) -> DataFrame:
    """One row: ids, lists, and bits per id of every closed form, from list sizes alone."""
    n, u = F.col("n"), F.lit(universe).cast("long")
    total = F.sum("n")
    per = lambda c: F.round(F.sum(c) / total, 4)
    return sizes.agg(
        total.cast("long").alias("ids"),
        F.count(F.lit(1)).cast("long").alias("lists"),
        F.lit(64.0).alias("raw"),
        per(n * width_col(u)).alias("packed"),
        per(ef_bits_col(n, u)).alias("ef"),
        per(ef_bits_col(n, u, ceil=True)).alias("ef_ceil"),
        per(set_bound_col(n, u)).alias("set_bound"),
        per(comb_bound_col(n, u)).alias("comb_bound"),
        F.round((log2_factorial_col(total) - F.sum(log2_factorial_col(n))) / total, 4).alias("partition_bound"),
        per(log2_factorial_col(n)).alias("order_saving"),
    )


def rates_sql(source: str, key: str, universe: str) -> str:
    """The same row for the oracle; source is SQL giving (key, id) rows, universe an SQL scalar."""
    f = "(lgamma({0} + 1) / ln(2))"
    low = "CAST(floor(log2(greatest(u // greatest(n, 1), 1))) AS BIGINT)"
    high = f"(CASE WHEN u > n AND n * pow(2, {low}) < u THEN {low} + 1 ELSE {low} END)"
    ef = "(n * {0} + n + floor(u / pow(2, {0})) + 1)"
    return f"""
WITH src AS ({source}), s AS (SELECT {key}, count(*) AS n, ({universe})::BIGINT AS u FROM src GROUP BY {key})
SELECT CAST(sum(n) AS BIGINT) AS ids, count(*) AS lists, CAST(64.0 AS DOUBLE) AS raw,
  round(sum(n * ceil(log2(u))) / sum(n), 4) AS packed,
  round(sum({ef.format(low)}) / sum(n), 4) AS ef,
  round(sum({ef.format(high)}) / sum(n), 4) AS ef_ceil,
  round(sum(n * log2(u) - {f.format("n")}) / sum(n), 4) AS set_bound,
  round(sum({f.format("u")} - {f.format("n")} - {f.format("(u - n)")}) / sum(n), 4) AS comb_bound,
  round(({f.format("sum(n)")} - sum({f.format("n")})) / sum(n), 4) AS partition_bound,
  round(sum({f.format("n")}) / sum(n), 4) AS order_saving
FROM s"""


def entropy(df: DataFrame, sym: str, by: str | None = None) -> DataFrame:
    """Empirical bits a symbol, within groups (weighted by size) or over all rows."""
    keys = [by] if by else []
    counts = df.groupBy(*keys, sym).agg(F.count(F.lit(1)).alias("c"))
    totals = counts.groupBy(*keys).agg(F.sum("c").alias("t"), F.sum(F.col("c") * F.log2(F.col("c").cast("double"))).alias("cl"))
    return totals.agg(F.round(F.sum(F.col("t") * F.log2(F.col("t").cast("double")) - F.col("cl")) / F.sum("t"), 6).alias("bits"))


def cross_entropy(counts: DataFrame, model: DataFrame, sym: str) -> DataFrame:
    """Bits a symbol when counts (sym, c) are coded by model (sym, p); never under the entropy."""
    return counts.join(model, sym).agg(F.round(-F.sum(F.col("c") * F.log2("p")) / F.sum("c"), 6).alias("bits"))


def adaptive_code_bits(df: DataFrame, by: list[str], code: str, alphabet: int = 256) -> DataFrame:
    """by, n, bits of each group's codes under the running-count model; their order doesn't matter."""
    c = df.groupBy(*by, code).agg(F.count(F.lit(1)).alias("c"))
    g = c.groupBy(*by).agg(F.sum("c").cast("long").alias("n"), F.sum(log2_factorial_col(F.col("c"))).alias("lf"))
    bits = log2_factorial_col(F.col("n") + alphabet - 1) - log2_factorial_col(F.lit(alphabet - 1)) - F.col("lf")
    return g.select(*by, "n", bits.alias("bits"))


def rec_bits(edges: DataFrame, vertices: int, bias: int = 1, directed: bool = True) -> DataFrame:
    """One row: edges, bits per edge of the edge coder under the urn model, from degrees alone."""
    deg = edges.select(F.explode(F.array("src", "dst")).alias("v")).groupBy("v").agg(F.count(F.lit(1)).alias("d"))
    if bias != 1:
        raise ValueError("the closed form is written for a bias of 1")
    per = deg.agg(F.sum(log2_factorial_col(F.col("d"))).alias("lf"))
    loops = edges.agg(F.count(F.lit(1)).alias("e"), F.sum((F.col("src") == F.col("dst")).cast("int")).alias("loops"))
    e = F.col("e")
    order = log2_factorial_col(e) + (F.lit(0) if directed else e - F.col("loops"))
    bits = log2_factorial_col(2 * e + vertices - 1) - log2_factorial_col(F.lit(vertices - 1)) - F.col("lf") - order
    return loops.crossJoin(per).select(e.cast("long").alias("edges"), F.round(bits / e, 4).alias("bits_per_edge"))


def project(n: int, clusters: int) -> dict[str, float]:
    """Bits per id of a balanced index of n vectors, from the closed forms."""
    size = n / clusters
    low = max(0, math.floor(math.log2(clusters)))
    return {
        "raw": 64.0,
        "packed": float((n - 1).bit_length()),
        "ef": low + 1 + (n / 2**low + 1) / size,
        "roc": math.log2(n) - log2_factorial(size) / size,
        "partition": (log2_factorial(n) - clusters * log2_factorial(size)) / n,
        "relabel_gain": log2_factorial(clusters) / n,
    }


def redundancy(bits: float, model_bits: float, steps: int) -> float:
    """Bits per step over what the model asks for."""
    return (bits - model_bits) / max(1, steps)


def initial_bits_overhead(bits: float, n: int, universe: int) -> float:
    """Bits per id of one list over its set bound: what the first draws cost, spread over the list."""
    return (bits - (n * math.log2(universe) - log2_factorial(n))) / max(1, n)


def slowdown(seconds: float, base: float) -> float:
    return seconds / base
