"""Queries of the relational surface around id lists: joins, windows, set operations, functions, sources."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.measures import log2_factorial_col
from ..operators import arrow, frames, ops
from ..sources import store, tables
from . import sqlext

Q: dict = {}
SQL: dict[str, str] = {}


def query(sql: str):
    def add(f):
        Q[f.__name__], SQL[f.__name__] = f, sql
        return f

    return add


def t(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    return tables.table(spark, sf_dir, name, list(cols) or None)


@query("SELECT l_orderkey, l_partkey FROM lineitem WHERE l_quantity >= 40 AND l_shipdate >= TIMESTAMP '1995-06-01'")
def op_scan_pruned(spark, sf_dir):
    return tables.table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"], "l_quantity >= 40 AND l_shipdate >= TIMESTAMP_NTZ '1995-06-01'")


def _roundtrip(fmt: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts written in a format and read back with an explicit schema."""
    df = t(spark, sf_dir, "part", "p_partkey", "p_name", "p_size")
    path = arrow.fresh(spark, "format")
    store.write(df, fmt, path)
    return store.read(spark, fmt, path, df.schema)


for _fmt in ("csv", "json", "orc", "parquet"):
    Q[f"op_{_fmt}_roundtrip"], SQL[f"op_{_fmt}_roundtrip"] = partial(_roundtrip, _fmt), "SELECT p_partkey, p_name, p_size FROM part"


@query("SELECT o_custkey AS k, o_orderkey AS id FROM orders WHERE o_custkey IN (7, 100, 1000)")
def op_index_reopen(spark, sf_dir):
    """Lists saved in key buckets; three read back with bucket and key pruning."""
    df = tables.id_lists(spark, sf_dir, "customer_order")
    path = arrow.fresh(spark, "index")
    store.save_index(frames.encode_lists(df, "k", "id", "roc", tables.universe(df)), path)
    return frames.decode_lists(store.open_index(spark, path, [7, 100, 1000]))


@query("SELECT user_id AS k, count(*) AS n, list_sort(list(event_id)) AS ids FROM events GROUP BY user_id")
def op_lists_collect(spark, sf_dir):
    return ops.lists(t(spark, sf_dir, "events"), "user_id", "event_id")


@query("SELECT user_id AS k, event_id AS id FROM events")
def op_lists_unnest(spark, sf_dir):
    return ops.unnest(ops.lists(t(spark, sf_dir, "events"), "user_id", "event_id"))


@query("SELECT o_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_orderkey) - 1 AS off FROM orders")
def op_offsets(spark, sf_dir):
    return ops.with_offsets(t(spark, sf_dir, "orders", "o_custkey", "o_orderkey"), "o_custkey", "o_orderkey")


@query("SELECT c_custkey FROM customer WHERE c_custkey IN (SELECT o_custkey FROM orders WHERE o_orderpriority = '1-URGENT')")
def op_semi(spark, sf_dir):
    urgent = tables.table(spark, sf_dir, "orders", ["o_custkey"], "o_orderpriority = '1-URGENT'").select(F.col("o_custkey").alias("c_custkey"))
    return ops.allow(t(spark, sf_dir, "customer", "c_custkey"), urgent, "c_custkey")


@query("SELECT o_orderkey FROM orders WHERE o_orderkey NOT IN (SELECT l_orderkey FROM lineitem)")
def op_anti(spark, sf_dir):
    return ops.deny(t(spark, sf_dir, "orders", "o_orderkey"), t(spark, sf_dir, "lineitem", "l_orderkey").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey")


_JOINED = "SELECT o_orderkey, o_custkey, l_partkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey"


def _join(how, spark, sf_dir):
    lines = t(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").withColumnRenamed("l_orderkey", "o_orderkey")
    return how(lines, t(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), "o_orderkey").select("o_orderkey", "o_custkey", "l_partkey")


Q["op_join_merge"], SQL["op_join_merge"] = partial(_join, ops.merge_join), _JOINED
Q["op_join_hash"], SQL["op_join_hash"] = partial(_join, ops.hash_join), _JOINED


@query("SELECT c_custkey, n_name FROM customer JOIN nation ON c_nationkey = n_nationkey")
def op_join_broadcast(spark, sf_dir):
    """Nations are 25 rows at any scale."""
    return t(spark, sf_dir, "customer", "c_custkey", "c_nationkey").join(F.broadcast(t(spark, sf_dir, "nation", "n_nationkey", "n_name")), F.col("c_nationkey") == F.col("n_nationkey")).select("c_custkey", "n_name")


@query("SELECT coalesce(p_partkey, l_partkey) AS part, p_partkey IS NULL AS unknown, l_partkey IS NULL AS unsold FROM part FULL JOIN (SELECT DISTINCT l_partkey FROM lineitem WHERE l_quantity > 48) ON p_partkey = l_partkey")
def op_full_outer(spark, sf_dir):
    sold = tables.table(spark, sf_dir, "lineitem", ["l_partkey"], "l_quantity > 48").distinct()
    return t(spark, sf_dir, "part", "p_partkey").join(sold, F.col("p_partkey") == F.col("l_partkey"), "full").select(F.coalesce("p_partkey", "l_partkey").alias("part"), F.col("p_partkey").isNull().alias("unknown"), F.col("l_partkey").isNull().alias("unsold"))


@query("SELECT c_custkey, count(o_orderkey) AS orders FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey")
def op_left_outer(spark, sf_dir):
    return t(spark, sf_dir, "customer", "c_custkey").join(t(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"), "left").groupBy("c_custkey").agg(F.count("o_orderkey").alias("orders"))


@query("SELECT a.r_regionkey AS a, b.r_regionkey AS b FROM region a JOIN region b ON a.r_regionkey < b.r_regionkey")
def op_theta(spark, sf_dir):
    """Five regions: the one place for a nested loop."""
    r = t(spark, sf_dir, "region", "r_regionkey")
    return r.select(F.col("r_regionkey").alias("a")).join(r.select(F.col("r_regionkey").alias("b")), F.col("a") < F.col("b"))


@query("SELECT event_id, CAST(event_id // 1000 AS BIGINT) AS shard FROM events")
def op_range_join(spark, sf_dir):
    """Every event with the shard whose interval of ids holds it."""
    e = t(spark, sf_dir, "events", "event_id")
    shards = e.select(F.floor(F.col("event_id") / 1000).alias("shard")).distinct().select("shard", (F.col("shard") * 1000).alias("lo"), (F.col("shard") * 1000 + 1000).alias("hi"))
    return ops.range_join(e, "event_id", shards, "lo", "hi", 512).select("event_id", "shard")


_SIDES = "SELECT user_id, event_id, ts FROM events WHERE event_type = '{}'"


@query(f"WITH e AS ({_SIDES.format('error')}), c AS (SELECT user_id, ts, max(event_id) AS click FROM ({_SIDES.format('click')}) GROUP BY ALL) SELECT e.event_id, c.click AS last_click FROM e ASOF LEFT JOIN c ON e.user_id = c.user_id AND e.ts >= c.ts")
def op_asof(spark, sf_dir):
    """The user's last click at or before each error."""
    e = t(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type")
    errors = e.filter("event_type = 'error'").select("user_id", "ts", "event_id")
    clicks = e.filter("event_type = 'click'").select("user_id", "ts", F.col("event_id").alias("last_click"))
    return ops.asof(errors, clicks, "user_id", "ts", "last_click").select("event_id", "last_click")


@query("SELECT a.event_id AS click, b.event_id AS purchase FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND epoch(b.ts)::BIGINT > epoch(a.ts)::BIGINT AND epoch(b.ts)::BIGINT <= epoch(a.ts)::BIGINT + 3600")
def op_interval_join(spark, sf_dir):
    e = t(spark, sf_dir, "events", "event_id", "ts", "user_id", "event_type").withColumn("s", F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1000000))
    a = e.filter("event_type = 'click'").select("user_id", F.col("s").alias("sa"), F.col("event_id").alias("click"))
    b = e.filter("event_type = 'purchase'").select("user_id", F.col("s").alias("sb"), F.col("event_id").alias("purchase"))
    return ops.interval_join(a, b, "user_id", "sa", "sb", 3600).select("click", "purchase")


SQL["op_interval_join"] = SQL["op_interval_join"].replace("epoch(a.ts)::BIGINT", "(epoch_us(a.ts) // 1000000)").replace("epoch(b.ts)::BIGINT", "(epoch_us(b.ts) // 1000000)")


@query("SELECT src, count(*) AS degree FROM (SELECT DISTINCT l_partkey AS src, l_suppkey FROM lineitem) GROUP BY src")
def op_degrees(spark, sf_dir):
    return ops.degrees(tables.graph(spark, sf_dir, "part_supplier")[0])


@query("SELECT DISTINCT l_partkey, l_suppkey FROM lineitem")
def op_distinct_edges(spark, sf_dir):
    return t(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey").distinct()


@query("SELECT l_suppkey, count(DISTINCT l_partkey) AS parts FROM lineitem GROUP BY l_suppkey")
def op_count_distinct(spark, sf_dir):
    return t(spark, sf_dir, "lineitem", "l_partkey", "l_suppkey").groupBy("l_suppkey").agg(F.countDistinct("l_partkey").alias("parts"))


@query("SELECT true AS close")
def op_approx_distinct(spark, sf_dir):
    """A sketch's count of parts lies within a tenth of the exact one."""
    return t(spark, sf_dir, "lineitem", "l_partkey").agg((F.abs(F.approx_count_distinct("l_partkey", 0.02) / F.countDistinct("l_partkey") - 1) < 0.1).alias("close"))


@query("SELECT p_type, p_brand, count(*) AS n, CAST(grouping_id(p_type, p_brand) AS BIGINT) AS gid FROM part GROUP BY CUBE (p_type, p_brand)")
def op_cube(spark, sf_dir):
    return t(spark, sf_dir, "part", "p_type", "p_brand").cube("p_type", "p_brand").agg(F.count(F.lit(1)).alias("n"), F.grouping_id().cast("long").alias("gid"))


@query("SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY ROLLUP (c_mktsegment, c_nationkey)")
def op_rollup(spark, sf_dir):
    return t(spark, sf_dir, "customer", "c_mktsegment", "c_nationkey").rollup("c_mktsegment", "c_nationkey").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey))")
def op_grouping_sets(spark, sf_dir):
    return t(spark, sf_dir, "customer", "c_mktsegment", "c_nationkey").groupingSets([["c_mktsegment"], ["c_nationkey"]], "c_mktsegment", "c_nationkey").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'purchase') AS purchase FROM events GROUP BY user_id")
def op_pivot(spark, sf_dir):
    got = t(spark, sf_dir, "events", "user_id", "event_type").groupBy("user_id").pivot("event_type", ["click", "purchase"]).agg(F.count(F.lit(1)))
    return got.select("user_id", F.coalesce("click", F.lit(0)).cast("long").alias("click"), F.coalesce("purchase", F.lit(0)).cast("long").alias("purchase"))


@query("SELECT p_partkey, 'size' AS what, p_size::DOUBLE AS value FROM part UNION ALL SELECT p_partkey, 'price', p_retailprice FROM part")
def op_unpivot(spark, sf_dir):
    return t(spark, sf_dir, "part", "p_partkey", "p_size", "p_retailprice").select("p_partkey", F.col("p_size").cast("double").alias("size"), F.col("p_retailprice").alias("price")).unpivot("p_partkey", ["size", "price"], "what", "value")


@query("SELECT quantile_cont(n, 0.5) AS p50, quantile_cont(n, 0.9) AS p90, quantile_cont(n, 0.99) AS p99 FROM (SELECT o_custkey, count(*) AS n FROM orders GROUP BY o_custkey)")
def op_percentiles(spark, sf_dir):
    n = t(spark, sf_dir, "orders", "o_custkey").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n"))
    return n.agg(*[F.percentile("n", p).alias(f"p{int(p * 100)}") for p in (0.5, 0.9, 0.99)])


_SHARES = ("percent_rank", "cume_dist")
_RANKS = {"row_number": "o_totalprice, o_orderkey", "rank": "o_orderpriority", "dense_rank": "o_orderpriority", "percent_rank": "o_orderpriority", "cume_dist": "o_orderpriority"}


def _rank(kind: str, order: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("o_custkey").orderBy(*order.split(", "))
    v = getattr(F, kind)().over(w)
    return t(spark, sf_dir, "orders", "o_custkey", "o_orderkey", "o_totalprice", "o_orderpriority").select("o_orderkey", (F.round(v, 6) if kind in _SHARES else v.cast("long")).alias("r"))


for _kind, _order in _RANKS.items():
    Q[f"op_{_kind}"] = partial(_rank, _kind, _order)
    _cast = "round({}, 6)" if _kind in _SHARES else "{}"
    SQL[f"op_{_kind}"] = f"SELECT o_orderkey, {_cast.format(f'{_kind}() OVER (PARTITION BY o_custkey ORDER BY {_order})')} AS r FROM orders"


@query("SELECT o_orderkey, ntile(4) OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice, o_orderkey) AS q FROM orders")
def op_ntile(spark, sf_dir):
    return t(spark, sf_dir, "orders", "o_orderkey", "o_orderstatus", "o_totalprice").select("o_orderkey", F.ntile(4).over(Window.partitionBy("o_orderstatus").orderBy("o_totalprice", "o_orderkey")).cast("long").alias("q"))


@query("SELECT o_custkey, o_orderkey, o_orderkey - coalesce(lag(o_orderkey) OVER w, 0) AS gap, lead(o_orderkey) OVER w AS next FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderkey)")
def op_gaps(spark, sf_dir):
    return ops.gaps(t(spark, sf_dir, "orders", "o_custkey", "o_orderkey"), "o_custkey", "o_orderkey")


@query("SELECT p_partkey, round((1 + count(*) OVER (PARTITION BY p_brand, p_size ORDER BY p_partkey ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)) / (256 + row_number() OVER (PARTITION BY p_brand ORDER BY p_partkey) - 1), 9) AS p FROM part")
def op_adaptive_probability(spark, sf_dir):
    """What the adaptive coder gives each part's size, brand by brand."""
    df = ops.running_count(t(spark, sf_dir, "part", "p_partkey", "p_brand", "p_size"), "p_brand", "p_partkey", "p_size")
    return ops.with_offsets(df, "p_brand", "p_partkey").select("p_partkey", F.round((1 + F.col("seen")) / (256 + F.col("off")), 9).alias("p"))


@query("SELECT event_id, sum(event_id) OVER (PARTITION BY user_id ORDER BY event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW)::BIGINT AS s FROM events")
def op_rows_frame(spark, sf_dir):
    return t(spark, sf_dir, "events", "event_id", "user_id").select("event_id", F.sum("event_id").over(Window.partitionBy("user_id").orderBy("event_id").rowsBetween(-2, 0)).alias("s"))


@query("SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY event_id RANGE BETWEEN 100 PRECEDING AND CURRENT ROW) AS n FROM events")
def op_range_frame(spark, sf_dir):
    return t(spark, sf_dir, "events", "event_id", "user_id").select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("event_id").rangeBetween(-100, 0)).alias("n"))


@query("SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 10")
def op_topk_global(spark, sf_dir):
    return t(spark, sf_dir, "orders", "o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(10)


@query("SELECT o_custkey, o_orderkey, CAST(r AS BIGINT) AS rank FROM (SELECT *, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 3")
def op_topk_per_key(spark, sf_dir):
    return ops.top_per_key(t(spark, sf_dir, "orders", "o_custkey", "o_orderkey", "o_totalprice"), "o_custkey", [F.desc("o_totalprice"), F.col("o_orderkey")], 3).select("o_custkey", "o_orderkey", F.col("rank").cast("long").alias("rank"))


_SETS = {"union": "UNION ALL", "intersect": "INTERSECT", "except": "EXCEPT", "intersect_all": "INTERSECT ALL", "except_all": "EXCEPT ALL"}


def _set_op(kind: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    side = lambda k: tables.table(spark, sf_dir, "lineitem", ["l_orderkey"], f"l_suppkey = {k}")
    f = {"union": "unionAll", "intersect": "intersect", "except": "subtract", "intersect_all": "intersectAll", "except_all": "exceptAll"}[kind]
    return getattr(side(1), f)(side(2))


for _kind, _word in _SETS.items():
    Q[f"op_{_kind}"] = partial(_set_op, _kind)
    SQL[f"op_{_kind}"] = f"SELECT l_orderkey FROM lineitem WHERE l_suppkey = 1 {_word} SELECT l_orderkey FROM lineitem WHERE l_suppkey = 2"


@query("SELECT event_id FROM events WHERE ('0x' || substr(md5(CAST(event_id AS VARCHAR)), 1, 7))::BIGINT < 26843545")
def op_sample_hash(spark, sf_dir):
    return ops.sample_hash(t(spark, sf_dir, "events", "event_id"), "event_id", 0.1)


@query("SELECT url, row_number() OVER (ORDER BY substr(md5(url), 1, 2), url) - 1 AS id FROM (SELECT DISTINCT url FROM pages)")
def op_remap_ids(spark, sf_dir):
    return ops.remap(t(spark, sf_dir, "pages", "url"), "url")


@query("SELECT o_custkey, count(*) AS n, CASE WHEN count(*) < 2 THEN 'packed' WHEN count(*) < 64 THEN 'ef' ELSE 'roc' END AS codec FROM orders GROUP BY o_custkey")
def op_choose_codec(spark, sf_dir):
    return ops.choose_codec(t(spark, sf_dir, "orders", "o_custkey").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n")))


@query("SELECT page_id, length(url) AS n, lower(split_part(url, '/', 3)) AS host, md5(url) AS digest, regexp_replace(url, '[0-9]+', '#', 'g') AS shape, upper(substr(url, 1, 4)) AS scheme FROM pages")
def fn_string(spark, sf_dir):
    u = F.col("url")
    return t(spark, sf_dir, "pages").select("page_id", F.length(u).cast("long").alias("n"), F.lower(F.split(u, "/")[2]).alias("host"), F.md5(u.cast("binary")).alias("digest"), F.regexp_replace(u, "[0-9]+", "#").alias("shape"), F.upper(F.substring(u, 1, 4)).alias("scheme"))


@query("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, day(o_orderdate) AS d, CAST(date_trunc('month', o_orderdate) AS DATE) AS first, date_diff('day', DATE '1992-01-01', CAST(o_orderdate AS DATE)) AS days FROM orders")
def fn_date(spark, sf_dir):
    d = F.col("o_orderdate")
    return t(spark, sf_dir, "orders", "o_orderkey", "o_orderdate").select("o_orderkey", F.year(d).cast("long").alias("y"), F.month(d).cast("long").alias("m"), F.day(d).cast("long").alias("d"), F.date_trunc("month", d).cast("date").alias("first"), F.datediff(d.cast("date"), F.lit("1992-01-01").cast("date")).cast("long").alias("days"))


@query("SELECT k, n, round(log2(n), 6) AS l, ceil(log2(n)) AS c, CAST(n << 3 AS BIGINT) AS s, CAST(bit_count(n) AS BIGINT) AS ones, round(lgamma(n + 1) / ln(2), 6) AS f FROM (SELECT o_custkey AS k, count(*) AS n FROM orders GROUP BY 1)")
def fn_math(spark, sf_dir):
    n = F.col("n")
    s = t(spark, sf_dir, "orders", "o_custkey").groupBy(F.col("o_custkey").alias("k")).agg(F.count(F.lit(1)).alias("n"))
    return s.select("k", "n", F.round(F.log2(n), 6).alias("l"), F.ceil(F.log2(n)).cast("double").alias("c"), F.shiftleft(n, 3).alias("s"), F.bit_count(n).cast("long").alias("ones"), F.round(log2_factorial_col(n), 6).alias("f"))


@query("SELECT k, list_transform(ids, lambda x: x % 7) AS mods, list_filter(ids, lambda x: x % 2 = 0) AS even, CAST(list_sum(ids) AS BIGINT) AS total, ids[1:3] AS head FROM (SELECT user_id AS k, list_sort(list(event_id)) AS ids FROM events GROUP BY 1)")
def fn_array(spark, sf_dir):
    ids = F.col("ids")
    return ops.lists(t(spark, sf_dir, "events"), "user_id", "event_id").select("k", F.transform(ids, lambda x: x % 7).alias("mods"), F.filter(ids, lambda x: x % 2 == 0).alias("even"), F.aggregate(ids, F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.slice(ids, 1, 3).alias("head"))


@query("SELECT event_id, CAST(json_extract(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json(spark, sf_dir):
    return t(spark, sf_dir, "events", "event_id", "props").select("event_id", F.from_json("props", "k long")["k"].alias("k"))


@query("SELECT user_id, count(*) FILTER (event_type = 'click') AS clicks, count(DISTINCT event_type) AS kinds FROM events GROUP BY user_id")
def fn_map(spark, sf_dir):
    """A map of counts per user, read back by key."""
    per = t(spark, sf_dir, "events", "user_id", "event_type").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    m = per.groupBy("user_id").agg(F.map_from_entries(F.collect_list(F.struct("event_type", "n"))).alias("m"))
    return m.select("user_id", F.coalesce(F.col("m")["click"], F.lit(0)).cast("long").alias("clicks"), F.size(F.map_keys("m")).cast("long").alias("kinds"))


@query("SELECT event_id, coalesce(nullif(event_type, 'click'), 'none') AS kind, CASE WHEN value < 10 THEN 'low' WHEN value < 50 THEN 'mid' ELSE 'high' END AS class FROM events")
def fn_conditional(spark, sf_dir):
    v = F.col("value")
    return t(spark, sf_dir, "events", "event_id", "event_type", "value").select("event_id", F.coalesce(F.nullif("event_type", F.lit("click")), F.lit("none")).alias("kind"), F.when(v < 10, "low").when(v < 50, "mid").otherwise("high").alias("class"))


@query("SELECT o_custkey AS k, count(*) AS n, min(o_orderkey) AS first, true AS held FROM orders GROUP BY o_custkey")
def sql_scalar_functions(spark, sf_dir):
    """ids_encode, ids_count, ids_get and ids_contains from SQL."""
    sqlext.register(spark)
    ops.lists(t(spark, sf_dir, "orders"), "o_custkey", "o_orderkey").createOrReplaceTempView("order_lists")
    return spark.sql("SELECT k, ids_count(d) AS n, ids_get(d, 0L) AS first, ids_contains(d, ids_get(d, n - 1)) AS held FROM (SELECT k, n, ids_encode(ids, 1L << 40, 'ef') AS d FROM order_lists)")


@query("SELECT user_id AS k, event_id AS id FROM events")
def sql_aggregate_and_table_function(spark, sf_dir):
    """Lists aggregated to compressed form and unnested by a table function."""
    sqlext.register(spark)
    t(spark, sf_dir, "events").createOrReplaceTempView("event_rows")
    return spark.sql("SELECT k, u.id FROM (SELECT user_id AS k, ids_encode_agg(event_id, 1L << 40) AS d FROM event_rows GROUP BY user_id), LATERAL ids_unnest(d) u")


@query("SELECT o_custkey AS k, o_orderkey AS id FROM orders WHERE o_custkey = 7")
def source_idlists(spark, sf_dir):
    """One list decoded while scanning, by the data source's own key filter."""
    df = tables.id_lists(spark, sf_dir, "customer_order")
    path = arrow.fresh(spark, "index")
    store.save_index(frames.encode_lists(df, "k", "id", "roc", tables.universe(df)), path)
    store.register(spark)
    arrow.importable(spark)
    return spark.read.format("idlists").option("path", path).load().filter("k = 7")
