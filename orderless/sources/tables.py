"""The given tables with pruned columns, and the id lists and graphs derived from them."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None, where: str | Column | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if where is not None:
        df = df.filter(where)
    return df.select(*cols) if cols else df


#: name -> (table, key column, id column): lists of ids (k, id). The first group partitions its ids, the second overlaps.
PARTITIONS = {
    "nation_customer": ("customer", "c_nationkey", "c_custkey"),
    "type_part": ("part", "p_type", "p_partkey"),
    "brand_part": ("part", "p_brand", "p_partkey"),
    "customer_order": ("orders", "o_custkey", "o_orderkey"),
    "user_event": ("events", "user_id", "event_id"),
    "type_event": ("events", "event_type", "event_id"),
    "source_document": ("documents", "source", "doc_id"),
    "label_vec": ("embeddings", "label", "vec_id"),
}
OVERLAPS = {"part_order": ("lineitem", "l_partkey", "l_orderkey"), "supplier_order": ("lineitem", "l_suppkey", "l_orderkey")}
LISTS = PARTITIONS | OVERLAPS


def id_lists(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    t, k, i = LISTS[name]
    out = table(spark, sf_dir, t, [k, i]).select(F.col(k).alias("k"), F.col(i).cast("long").alias("id"))
    return out.distinct() if name in OVERLAPS else out


def lists_sql(name: str) -> str:
    t, k, i = LISTS[name]
    return f"SELECT {'DISTINCT ' * (name in OVERLAPS)}{k} AS k, CAST({i} AS BIGINT) AS id FROM {t}"


def universe(df: DataFrame, id: str = "id") -> int:
    """One more than the largest id."""
    return int(df.agg(F.coalesce(F.max(id), F.lit(-1))).first()[0]) + 1


GRAPHS = {
    # name -> (SQL for src, dst over the tables; vertices)
    "part_supplier": ("SELECT DISTINCT l_partkey AS src, l_suppkey + (SELECT count(*) FROM part) AS dst FROM lineitem", "(SELECT count(*) FROM part) + (SELECT count(*) FROM supplier)"),
    "customer_part": ("SELECT DISTINCT o_custkey AS src, l_partkey + (SELECT count(*) FROM customer) AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey", "(SELECT count(*) FROM customer) + (SELECT count(*) FROM part)"),
    "order_part": ("SELECT DISTINCT l_orderkey AS src, l_partkey + (SELECT count(*) FROM orders) AS dst FROM lineitem", "(SELECT count(*) FROM orders) + (SELECT count(*) FROM part)"),
}


def graph(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, int]:
    """Edges (src, dst) of a relational graph and its number of vertices; the second side is numbered after the first."""
    first, key, other, size = {
        "part_supplier": ("part", "l_partkey", "l_suppkey", "supplier"), "order_part": ("orders", "l_orderkey", "l_partkey", "part"), "customer_part": ("customer", "o_custkey", "l_partkey", "part"),
    }[name]
    left, right = table(spark, sf_dir, first).count(), table(spark, sf_dir, size).count()
    if name == "customer_part":
        lines = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]).join(table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"]), F.col("o_orderkey") == F.col("l_orderkey"))
    else:
        lines = table(spark, sf_dir, "lineitem", [key, other])
    edges = lines.select(F.col(key).cast("long").alias("src"), (F.col(other) + left).cast("long").alias("dst")).distinct()
    return edges, left + right


def event_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, vec) of events: hour and weekday on the circle, kind, value (logarithm), a hashed place of the user in four dimensions."""
    e = table(spark, sf_dir, "events", ["event_id", "ts", "user_id", "event_type", "value"])
    turn = lambda c, n: [f(c * (2 * 3.141592653589793 / n)) for f in (F.sin, F.cos)]
    user = [F.pmod(F.xxhash64("user_id", F.lit(i)), F.lit(1000)) / 500.0 - 1 for i in range(4)]
    kind = [F.pmod(F.xxhash64("event_type", F.lit(i)), F.lit(1000)) / 500.0 - 1 for i in range(3)]
    parts = [*turn(F.hour("ts"), 24), *turn(F.dayofweek("ts"), 7), *kind, F.log1p(F.abs(F.coalesce("value", F.lit(0.0)))), *user]
    return e.select(F.col("event_id").cast("long").alias("id"), F.array(*[p.cast("double") for p in parts]).alias("vec"))
