"""Queries that encode, decode and give the ids back: their SQL is the source table's own rows."""

from __future__ import annotations

from functools import partial

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import setcodec
from ..operators import arrow, codecodec, edgecodec, frames, graph, ops, reflist, wavelet
from ..sources import tables

Q: dict = {}
SQL: dict[str, str] = {}
#: Ids of a shard of the wavelet index, as a power of two; small here so that several shards take part.
SHARD_BITS = 12


def _lists(name: str, codec: str, segment: int | None, spark: SparkSession, sf_dir: str) -> DataFrame:
    df = tables.id_lists(spark, sf_dir, name)
    return frames.decode_lists(frames.encode_lists(df, "k", "id", codec, tables.universe(df), segment))


for _codec in ("raw", "packed", "ef", "ef_dir", "ef_ceil", "roc", "roc_seeded"):
    for _name in ("customer_order", "part_order", "user_event", "label_vec"):
        Q[f"roundtrip_{_codec}_{_name}"] = partial(_lists, _name, _codec, None)
for _name in ("supplier_order", "type_event", "type_part"):
    Q[f"roundtrip_roc_segmented_{_name}"] = partial(_lists, _name, "roc", 8)
for _codec in ("roc_exact", "roc_distinct", "roc_buckets", "roc_falling"):
    Q[f"roundtrip_{_codec}_customer_order"] = partial(_lists, "customer_order", _codec, None)
for _q in list(Q):
    SQL[_q] = tables.lists_sql(next(n for n in sorted(tables.LISTS, key=len, reverse=True) if _q.endswith(n)))


def roundtrip_roc_multiset(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts of each order with repeats, coded as multisets."""
    df = tables.table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"])
    u = tables.universe(df, "l_partkey")
    arrow.importable(spark)

    @F.arrow_udf("array<long>")
    def through(parts):
        import pyarrow as pa

        out = []
        for p in parts.to_pylist():
            state = setcodec.ExactState(0)
            setcodec.encode_multiset(state, p, u)
            out.append(setcodec.decode_multiset(setcodec.ExactState.from_bytes(state.to_bytes()), len(p), u))
        return pa.array(out, pa.list_(pa.int64()))

    sets = df.groupBy("l_orderkey").agg(F.collect_list("l_partkey").alias("parts"))  # an order's lines, few
    back = sets.select(F.col("l_orderkey").alias("k"), F.explode(through("parts")).alias("value"))
    return back.groupBy("k", "value").agg(F.count(F.lit(1)).cast("long").alias("count"))


Q["roundtrip_roc_multiset"] = roundtrip_roc_multiset
SQL["roundtrip_roc_multiset"] = "SELECT l_orderkey AS k, l_partkey AS value, count(*) AS count FROM lineitem GROUP BY ALL"


def _tree(name: str, kind: str, spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    df = tables.id_lists(spark, sf_dir, name).select(F.col("k").cast("long").alias("k"), "id")
    return df, wavelet.build(df, "id", "k", int(df.agg(F.max("k")).first()[0]) + 1, kind, SHARD_BITS)


def _select(name: str, kind: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every (cluster, offset) resolved to its id."""
    df, ix = _tree(name, kind, spark, sf_dir)
    ix = arrow.stage(ix, "tree")  # built once, read for its directory and for its bits
    return wavelet.select(ix, ops.with_offsets(df, "k", "id").select("k", "off"), SHARD_BITS)


def _access(name: str, kind: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    df, ix = _tree(name, kind, spark, sf_dir)
    return wavelet.access(ix, df.select("id"), SHARD_BITS)


def wavelet_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many of a user's events come before each of them."""
    df, ix = _tree("user_event", "flat", spark, sf_dir)
    return wavelet.rank(ix, df.select("k", F.col("id").alias("pos")), SHARD_BITS)


for _kind in ("flat", "rrr"):
    for _name in ("user_event", "customer_order"):
        Q[f"wavelet_select_{_kind}_{_name}"] = partial(_select, _name, _kind)
        SQL[f"wavelet_select_{_kind}_{_name}"] = f"SELECT k, row_number() OVER (PARTITION BY k ORDER BY id) - 1 AS off, id FROM ({tables.lists_sql(_name)})"
        Q[f"wavelet_access_{_kind}_{_name}"] = partial(_access, _name, _kind)
        SQL[f"wavelet_access_{_kind}_{_name}"] = tables.lists_sql(_name)
Q["wavelet_rank"] = wavelet_rank
SQL["wavelet_rank"] = f"SELECT k, id AS pos, row_number() OVER (PARTITION BY k ORDER BY id) - 1 AS rank FROM ({tables.lists_sql('user_event')})"


def _edges(name: str, directed: bool, model: str, shards: int, spark: SparkSession, sf_dir: str) -> DataFrame:
    edges, n = tables.graph(spark, sf_dir, name)
    edges = arrow.stage(edges, "graph")  # counted, cut by quantiles and coded
    return edgecodec.decode(edgecodec.encode(edges, n, directed=directed, shards=shards, model=model))


for _q, _args in {
    "roundtrip_rec_part_supplier": ("part_supplier", True, "urn", 8),
    "roundtrip_rec_whole": ("part_supplier", True, "urn", 1),
    "roundtrip_rec_customer_part": ("customer_part", True, "urn", 8),
    "roundtrip_rec_order_part": ("order_part", True, "urn", 8),
    "roundtrip_rec_undirected": ("part_supplier", False, "urn", 8),
    "roundtrip_rec_uniform": ("part_supplier", True, "uniform", 8),
}.items():
    Q[_q], SQL[_q] = partial(_edges, *_args), tables.GRAPHS[_args[0]][0]


def roundtrip_rec_hyper(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as hyperedges over their parts; the result counts equal hyperedges by size and least and greatest part."""
    df = tables.table(spark, sf_dir, "lineitem", ["l_orderkey", "l_partkey"])
    got = edgecodec.decode_hypergraph(edgecodec.encode_hypergraph(df, "l_orderkey", "l_partkey", tables.universe(df, "l_partkey"), shards=8))
    n = got.select(F.size("nodes").cast("long").alias("size"), F.array_min("nodes").alias("least"), F.array_max("nodes").alias("most"), F.aggregate("nodes", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"))
    return n.groupBy("size", "least", "most", "total").agg(F.count(F.lit(1)).cast("long").alias("edges"))


Q["roundtrip_rec_hyper"] = roundtrip_rec_hyper
SQL["roundtrip_rec_hyper"] = """WITH e AS (SELECT l_orderkey, count(*) AS size, min(l_partkey) AS least, max(l_partkey) AS most, CAST(sum(l_partkey) AS BIGINT) AS total FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) GROUP BY 1)
SELECT size, least, most, total, count(*) AS edges FROM e GROUP BY ALL"""


def _reflist(choice: str, entropy: str, intervals: bool, spark: SparkSession, sf_dir: str) -> DataFrame:
    edges, n = tables.graph(spark, sf_dir, "part_supplier")
    edges = arrow.stage(edges, "graph")
    return reflist.decode(reflist.encode(edges, n, entropy=entropy, ref_choice=choice, shards=8, intervals=intervals))


for _q, _args in {"greedy": ("greedy", "ans", False), "overlap": ("overlap", "ans", False), "plain": ("greedy", "none", True), "plain_runs": ("greedy", "none", False), "intervals": ("greedy", "ans", True)}.items():
    Q[f"roundtrip_reflist_{_q}"], SQL[f"roundtrip_reflist_{_q}"] = partial(_reflist, *_args), tables.GRAPHS["part_supplier"][0]


def roundtrip_friend_roc(spark: SparkSession, sf_dir: str) -> DataFrame:
    edges, n = tables.graph(spark, sf_dir, "part_supplier")
    return frames.decode_lists(graph.friends(edges, "roc", n)).select(F.col("k").alias("src"), F.col("id").alias("dst"))


Q["roundtrip_friend_roc"], SQL["roundtrip_friend_roc"] = roundtrip_friend_roc, tables.GRAPHS["part_supplier"][0]


def roundtrip_adaptive_codes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Line quantities by supplier, coded under running counts and back; rows as counts per (supplier, quantity)."""
    df = tables.table(spark, sf_dir, "lineitem", ["l_suppkey", "l_orderkey", "l_quantity"])
    codes = df.selectExpr("l_suppkey AS k", "0 AS sub", "l_orderkey AS id", "CAST(l_quantity AS INT) AS code")
    return codecodec.decode(codecodec.encode(codes)).groupBy("k", "code").agg(F.count(F.lit(1)).cast("long").alias("n"))


Q["roundtrip_adaptive_codes"] = roundtrip_adaptive_codes
SQL["roundtrip_adaptive_codes"] = "SELECT l_suppkey AS k, CAST(l_quantity AS INT) AS code, count(*) AS n FROM lineitem GROUP BY ALL"


def roundtrip_adaptive_order(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Planted codes come back in their order within the cluster."""
    codes = tables.table(spark, sf_dir, "events").selectExpr("user_id % 16 AS k", "0 AS sub", "event_id AS id", "CAST(((user_id % 16) * 37 + (event_id * 7919) % 8) % 256 AS INT) AS code")
    return codecodec.decode(codecodec.encode(codes)).select("k", "off", "code")


Q["roundtrip_adaptive_order"] = roundtrip_adaptive_order
SQL["roundtrip_adaptive_order"] = "SELECT user_id % 16 AS k, row_number() OVER (PARTITION BY user_id % 16 ORDER BY event_id) - 1 AS off, CAST(((user_id % 16) * 37 + (event_id * 7919) % 8) % 256 AS INT) AS code FROM events"


def roundtrip_code_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two-column codes of each supplier's lines (quantity, line number) as multisets, and back; counts per code."""
    df = tables.table(spark, sf_dir, "lineitem", ["l_suppkey", "l_quantity", "l_linenumber"])
    rows = df.select(F.col("l_suppkey").alias("k"), F.array(F.col("l_quantity").cast("int"), F.col("l_linenumber").cast("int")).alias("code"))
    back = codecodec.decode_sets(codecodec.encode_sets(rows, 64))
    return back.groupBy("k", F.col("code")[0].alias("quantity"), F.col("code")[1].alias("line")).agg(F.count(F.lit(1)).cast("long").alias("n"))


Q["roundtrip_code_sets"] = roundtrip_code_sets
SQL["roundtrip_code_sets"] = "SELECT l_suppkey AS k, CAST(l_quantity AS INT) AS quantity, l_linenumber AS line, count(*) AS n FROM lineitem GROUP BY ALL"


def _get(codec: str, segment: int | None, spark: SparkSession, sf_dir: str) -> DataFrame:
    """The middle order of each customer, read from the compressed list alone."""
    df = tables.id_lists(spark, sf_dir, "customer_order")
    enc = frames.encode_lists(df, "k", "id", codec, tables.universe(df), segment)
    return frames.get(enc, enc.groupBy("k").agg(F.floor(F.sum("n") / 2).cast("long").alias("off")))


for _codec in ("raw", "packed", "ef", "ef_dir", "roc"):
    for _q, _segment in ((f"get_{_codec}", None), (f"get_{_codec}_segmented", 8)):
        Q[_q] = partial(_get, _codec, _segment)
        SQL[_q] = f"""WITH l AS ({tables.lists_sql("customer_order")}), o AS (SELECT k, id, row_number() OVER (PARTITION BY k ORDER BY id) - 1 AS off, count(*) OVER (PARTITION BY k) AS n FROM l) SELECT k, off, id FROM o WHERE off = n // 2"""


def _next_geq(codec: str, segment: int | None, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each user's first event from some numbers on: before all, within, and beyond all of them."""
    df = tables.id_lists(spark, sf_dir, "user_event")
    enc = arrow.stage(frames.encode_lists(df, "k", "id", codec, tables.universe(df), segment), "lists")  # coded once, read three times
    asked = df.select("k").distinct().select(F.col("k"), F.explode(F.array(*[F.lit(v).cast("long") for v in VALUES])).alias("value"))
    return frames.next_geq(enc, asked)


VALUES = (-5, 0, 300, 5000, 1 << 40)
for _codec in ("ef", "ef_dir"):
    for _q, _segment in ((_codec, None), (f"{_codec}_segmented", 6)):
        Q[f"next_geq_{_q}"] = partial(_next_geq, _codec, _segment)
        SQL[f"next_geq_{_q}"] = f"SELECT user_id AS k, v AS value, min(CASE WHEN event_id >= v THEN event_id END) AS id FROM events, (SELECT unnest({list(VALUES)}::BIGINT[]) AS v) GROUP BY user_id, v"


def _intersect(codec: str, segment: int | None, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders that two neighbouring suppliers share, by jumps on the compressed lists."""
    df = tables.id_lists(spark, sf_dir, "supplier_order")
    enc = frames.encode_lists(df, "k", "id", codec, tables.universe(df), segment)
    return frames.intersect(enc, enc.select(F.col("k").alias("a"), (F.col("k") + 1).alias("b")).distinct())


for _q, _args in {"ef_intersect": ("ef", None), "ef_intersect_segmented": ("ef", 9), "ef_dir_intersect": ("ef_dir", None)}.items():
    Q[_q] = partial(_intersect, *_args)
    SQL[_q] = f"WITH l AS ({tables.lists_sql('supplier_order')}) SELECT x.k AS a, y.k AS b, x.id FROM l x JOIN l y ON y.k = x.k + 1 AND y.id = x.id"


def lists_united(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders of each supplier and of the one after, put together from two compressed frames."""
    df = tables.id_lists(spark, sf_dir, "supplier_order")
    u = tables.universe(df)
    a, b = frames.encode_lists(df, "k", "id", "ef", u), frames.encode_lists(df.withColumn("k", F.col("k") - 1), "k", "id", "roc", u)
    return frames.decode_lists(frames.unite(a, b, "roc", u, 14))


Q["lists_united"] = lists_united
SQL["lists_united"] = f"WITH l AS ({tables.lists_sql('supplier_order')}) SELECT k, id FROM l UNION SELECT k - 1, id FROM l"


def _appended(codec: str, segment: int | None, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Users' events in two deliveries: the second goes onto the compressed lists of the first."""
    df = tables.id_lists(spark, sf_dir, "user_event")
    u = tables.universe(df)
    first = frames.encode_lists(df.filter("id % 3 > 0"), "k", "id", codec, u, segment)
    return frames.decode_lists(frames.append(first, df.filter("id % 3 = 0"), "k", "id", codec, u, segment))


for _q, _args in {"lists_appended_ef": ("ef", None), "lists_appended_roc_segmented": ("roc", 8)}.items():
    Q[_q], SQL[_q] = partial(_appended, *_args), tables.lists_sql("user_event")


def roundtrip_codes_1024(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Symbols of 10 bits (part numbers modulo 1,024) by supplier, coded under running counts and back."""
    df = tables.table(spark, sf_dir, "lineitem", ["l_suppkey", "l_orderkey", "l_partkey"])
    codes = df.selectExpr("l_suppkey AS k", "0 AS sub", "l_orderkey AS id", "CAST(l_partkey % 1024 AS INT) AS code")
    return codecodec.decode(codecodec.encode(codes, alphabet=1024)).groupBy("k", "code").agg(F.count(F.lit(1)).cast("long").alias("n"))


Q["roundtrip_codes_1024"] = roundtrip_codes_1024
SQL["roundtrip_codes_1024"] = "SELECT l_suppkey AS k, CAST(l_partkey % 1024 AS INT) AS code, count(*) AS n FROM lineitem GROUP BY ALL"
