"""Queries that search: exact, through compressed indexes, with product codes and on graphs."""

from __future__ import annotations

from concurrent.futures import ThreadPoolExecutor
from functools import partial, reduce

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import measures
from ..operators import arrow, codecodec, edgecodec, frames, graph, ivf, quantizers, reflist, search, wavelet
from ..sources import tables
from . import sqlext

Q: dict = {}
SQL: dict[str, str] = {}
CLUSTERS, NEAREST = 8, 10
#: Clusters probed of the eight: a recall at 10 of 0.90 to 0.92 on the given vectors (ivf_recall_by_probes measures it).
PROBES = 6


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tables.table(spark, sf_dir, "embeddings", ["vec_id", "embedding"]).select(F.col("vec_id").cast("long").alias("id"), F.col("embedding").alias("vec"))


def batch(db: DataFrame) -> DataFrame:
    """The query batch: every tenth vector."""
    return db.filter("id % 10 = 0").select(F.col("id").alias("qid"), F.col("vec").alias("qvec"))


def first_rows(db: DataFrame, n: int) -> np.ndarray:
    """The vectors of the n least ids, as fixed centroids."""
    return quantizers.sample(db, n)


def _told(r: DataFrame) -> DataFrame:
    return r.select("qid", F.col("rank").cast("long").alias("rank"), "id", F.round("dist", 6).alias("dist"))


_V = "v AS (SELECT vec_id AS id, CAST(embedding AS DOUBLE[]) AS x FROM embeddings)"
_DIST = {"l2": "list_distance(q.x, v.x) ** 2", "cosine": "1 - list_cosine_similarity(q.x, v.x)", "ip": "-list_inner_product(q.x, v.x)"}


def _exact_sql(metric: str) -> str:
    return f"""WITH {_V}, d AS (SELECT q.id AS qid, v.id, {_DIST[metric]} AS dist FROM v q, v WHERE q.id % 10 = 0),
r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rank FROM d) SELECT qid, rank, id, round(dist, 6) AS dist FROM r WHERE rank <= {NEAREST}"""


def _exact(metric: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    db = vectors(spark, sf_dir)
    return _told(search.exact(batch(db), db, NEAREST, metric))


for _metric in _DIST:
    Q[f"exact_knn_{_metric}"], SQL[f"exact_knn_{_metric}"] = partial(_exact, _metric), _exact_sql(_metric)


def ivf_assign(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The nearest of fixed centroids for every vector."""
    db = vectors(spark, sf_dir)
    return quantizers.assign(db, first_rows(db, CLUSTERS)).select("id", "k")


_ASSIGNED = f"{_V}, a AS (SELECT v.id, v.x, arg_min(c.id, list_distance(v.x, c.x)) AS k FROM v, v c WHERE c.id < {CLUSTERS} GROUP BY v.id, v.x)"
Q["ivf_assign"] = ivf_assign
SQL["ivf_assign"] = f"WITH {_ASSIGNED} SELECT id, k FROM a"


def ivf_lloyd_step(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Centroids after one distributed step, as rows (k, d, value)."""
    db = vectors(spark, sf_dir)
    c = quantizers.lloyd_step(db, first_rows(db, CLUSTERS))
    rows = [(int(k), int(d), float(c[k, d])) for k in range(c.shape[0]) for d in range(c.shape[1])]  # clusters x dimensions
    return spark.createDataFrame(rows, "k long, d long, value double").withColumn("value", F.round("value", 6))


Q["ivf_lloyd_step"] = ivf_lloyd_step
SQL["ivf_lloyd_step"] = f"WITH {_ASSIGNED}, e AS (SELECT k, unnest(x) AS value, generate_subscripts(x, 1) - 1 AS d FROM a) SELECT k, d, round(avg(value), 6) AS value FROM e GROUP BY k, d"

_PROBED = f"""{_ASSIGNED}, c AS (SELECT * FROM v WHERE id < {CLUSTERS}),
p AS (SELECT q.id AS qid, q.x, c.id AS k, row_number() OVER (PARTITION BY q.id ORDER BY list_distance(q.x, c.x), c.id) AS pr FROM v q, c WHERE q.id % 10 = 0),
d AS (SELECT p.qid, a.id, a.k, list_distance(p.x, a.x) ** 2 AS dist FROM p JOIN a USING (k) WHERE pr <= {PROBES}),
r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY dist, id) AS rank FROM d)"""


def _ivf(codec: str, ids: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Six of eight clusters probed; results don't depend on how ids are stored."""
    db = vectors(spark, sf_dir)
    ix = ivf.build(db, first_rows(db, CLUSTERS), codec, shard_bits=8)
    return _told(ivf.find(batch(db), ix, NEAREST, PROBES, ids))


for _codec in ("raw", "packed", "ef", "roc", "wt", "wt1"):
    for _ids in ("deferred", "eager"):
        if _codec[0] == "w" and _ids == "eager":
            continue
        _q = f"ivf_search_{_ids}_{_codec}"
        Q[_q] = partial(_ivf, _codec, _ids)
        SQL[_q] = f"WITH {_PROBED} SELECT qid, rank, id, round(dist, 6) AS dist FROM r WHERE rank <= {NEAREST}"


def ivf_search_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same search where queries meet their clusters in a join, for batches that no broadcast holds."""
    db = vectors(spark, sf_dir)
    return _told(ivf.find_by_join(batch(db), ivf.build(db, first_rows(db, CLUSTERS), "roc"), NEAREST, PROBES))


def ivf_search_centroid_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same search with clusters chosen by beam search on a graph over the centroids; a beam of 64 reaches all eight."""
    db = vectors(spark, sf_dir)
    return _told(ivf.find_by_join(batch(db), ivf.build(db, first_rows(db, CLUSTERS), "roc"), NEAREST, PROBES, 64))


def sql_ivf_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same search as a table function over a saved index."""
    db = vectors(spark, sf_dir)
    path = arrow.fresh(spark, "index")
    ivf.save(ivf.build(db, first_rows(db, CLUSTERS), "ef"), path)
    sqlext.register(spark)
    batch(db).createOrReplaceTempView("query_vectors")
    return _told(spark.sql(f"SELECT * FROM ivf_search(TABLE(SELECT qid, qvec FROM query_vectors), '{path}', {NEAREST}, {PROBES})"))


for _f in (ivf_search_join, ivf_search_centroid_graph, sql_ivf_search):
    Q[_f.__name__], SQL[_f.__name__] = _f, SQL["ivf_search_deferred_roc"]


def centroid_graph_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall with 64 trained clusters and 32 probes, clusters chosen by all distances and by beams of 32 and 64 on their graph."""
    db, out = vectors(spark, sf_dir), None
    truth, ix = search.exact(batch(db), db, NEAREST), ivf.build(db, quantizers.kmeans(db, 64, 4), "roc")
    for explore in (0, 32, 64):
        r = search.recall(ivf.find_by_join(batch(db), ix, NEAREST, 32, explore), truth).select(F.lit(explore).cast("long").alias("explore"), "recall")
        out = r if out is None else out.union(r)
    return out


Q["centroid_graph_recall"] = centroid_graph_recall


def ivf_full_probe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All clusters probed: the exact answer."""
    db = vectors(spark, sf_dir)
    return _told(ivf.find(batch(db), ivf.build(db, quantizers.kmeans(db, CLUSTERS, 3), "roc"), NEAREST, CLUSTERS))


Q["ivf_full_probe"], SQL["ivf_full_probe"] = ivf_full_probe, _exact_sql("l2")


def ivf_recall_by_probes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall against the exact answer as more clusters are probed."""
    db, out = vectors(spark, sf_dir), None
    truth, ix = search.exact(batch(db), db, NEAREST), ivf.build(db, first_rows(db, CLUSTERS), "roc")
    for n in (1, 3, PROBES, CLUSTERS):
        r = search.recall(ivf.find(batch(db), ix, NEAREST, n), truth).select(F.lit(n).cast("long").alias("probes"), "recall")
        out = r if out is None else out.union(r)
    return out


Q["ivf_recall_by_probes"] = ivf_recall_by_probes
SQL["ivf_recall_by_probes"] = " UNION ALL ".join(
    f"SELECT {n}::BIGINT AS probes, round(count(t.id) / (SELECT count(*) FROM ({_exact_sql('l2')})), 6) AS recall FROM (WITH {_PROBED.replace(f'pr <= {PROBES}', f'pr <= {n}')} SELECT qid, id FROM r WHERE rank <= {NEAREST}) s JOIN ({_exact_sql('l2')}) t USING (qid, id)"
    for n in (1, 3, PROBES, CLUSTERS)
)


def permutation_invariance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distances of results that differ after ids are renumbered: none."""
    db = vectors(spark, sf_dir)
    n = db.count()
    other = ivf.permute(db, 7 if n % 7 else 11, n)
    c = first_rows(db, CLUSTERS)
    key = lambda r: r.select("qid", F.col("rank").cast("long").alias("rank"), F.round("dist", 6).alias("dist"))
    q = batch(db)
    return frames.lost_or_added(key(ivf.find(q, ivf.build(db, c, "roc"), NEAREST, PROBES)), key(ivf.find(q, ivf.build(other, c, "roc"), NEAREST, PROBES)))


Q["permutation_invariance"] = permutation_invariance
SQL["permutation_invariance"] = "SELECT 0::BIGINT AS qid, 0::BIGINT AS rank, 0::DOUBLE AS dist WHERE false"

M, BITS = 4, 4


def _fixed_pq(db: DataFrame, m: int = M, bits: int = BITS) -> quantizers.ProductQuantizer:
    return quantizers.ProductQuantizer.train(db, m, bits, iters=0)


def pq_encode(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Codes under codebooks of the first rows' sub-vectors."""
    db = vectors(spark, sf_dir)
    return quantizers.encode(db, _fixed_pq(db)).select("id", F.posexplode("code").alias("sub", "code")).select("id", F.col("sub").cast("long").alias("sub"), F.col("code").cast("long").alias("code"))


def _pq_sql(m: int, bits: int) -> str:
    width = 64 // m
    return f"""{_V}, s AS (SELECT id, j AS sub, x[j * {width} + 1 : j * {width} + {width}] AS y FROM v, (SELECT unnest(range({m})) AS j)),
code AS (SELECT s.id, s.sub, arg_min(b.id, list_distance(s.y, b.y)) AS code FROM s JOIN s b ON b.sub = s.sub AND b.id < {1 << bits} GROUP BY s.id, s.sub)"""


_PQ = _pq_sql(M, BITS)
Q["pq_encode"] = pq_encode
SQL["pq_encode"] = f"WITH {_PQ} SELECT id, sub, code FROM code"


def _pq_search(m: int, bits: int, store: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ten nearest by look-up tables over all codes, one cluster, ids from one of the stores."""
    db = vectors(spark, sf_dir)
    ix = ivf.build(db, first_rows(db, 1), store, _fixed_pq(db, m, bits))
    return _told(ivf.find(batch(db), ix, NEAREST, 1))


def _pq_search_sql(m: int, bits: int) -> str:
    return f"""WITH {_pq_sql(m, bits)}, t AS (SELECT q.id AS qid, q.sub, b.id AS code, list_distance(q.y, b.y) ** 2 AS d FROM s q JOIN s b ON b.sub = q.sub AND b.id < {1 << bits} WHERE q.id % 10 = 0),
d AS (SELECT t.qid, c.id, sum(t.d) AS dist FROM code c JOIN t ON t.sub = c.sub AND t.code = c.code GROUP BY ALL), r AS (SELECT *, row_number() OVER (PARTITION BY qid ORDER BY round(dist, 9), id) AS rank FROM d)
SELECT qid, rank, id, round(round(dist, 9), 6) AS dist FROM r WHERE rank <= {NEAREST}"""


Q["pq_search"], SQL["pq_search"] = partial(_pq_search, M, BITS, "roc"), _pq_search_sql(M, BITS)
STORES = ("raw", "packed", "ef", "wt", "wt1", "roc")
for _m in (4, 16, 32):
    for _store in STORES:
        Q[f"pq_search_{_m}_{_store}"], SQL[f"pq_search_{_m}_{_store}"] = partial(_pq_search, _m, 8, _store), _pq_search_sql(_m, 8)


def pq_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of product codes by sub-quantizers, and of residual codes with a re-ranked short list."""
    db, out = vectors(spark, sf_dir), None
    truth, q, c = search.exact(batch(db), db, NEAREST), batch(db), quantizers.kmeans(db, CLUSTERS, 3)
    for m in (4, 8, 16, 32):
        found = ivf.find(q, ivf.build(db, c, "roc", quantizers.ProductQuantizer.train(db, m, 8, iters=2)), NEAREST, CLUSTERS)
        r = search.recall(found, truth).select(F.lit(f"pq{m}").alias("codes"), "recall")
        out = r if out is None else out.union(r)
    found = ivf.find(q, ivf.build(db, c, "roc", quantizers.ResidualQuantizer.train(db, 4, 6, iters=2)), 50, CLUSTERS)
    return out.union(search.recall(ivf.rerank(found, q, db, NEAREST), truth).select(F.lit("rq4 reranked").alias("codes"), "recall"))


Q["pq_recall"] = pq_recall


def pq_ids_unchanged(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits per id of the flat index and of one with product codes: the ids don't notice."""
    db = vectors(spark, sf_dir)
    c = first_rows(db, CLUSTERS)
    a, b = ivf.id_bits(ivf.build(db, c, "ef")), ivf.id_bits(ivf.build(db, c, "ef", _fixed_pq(db)))
    return a.select(F.lit("flat").alias("index"), "ids", "bits_per_id").union(b.select(F.lit("pq"), "ids", "bits_per_id"))


Q["pq_ids_unchanged"] = pq_ids_unchanged
_EFN = "(n * CAST(floor(log2(greatest(u // n, 1))) AS BIGINT) + n + floor(u / pow(2, CAST(floor(log2(greatest(u // n, 1))) AS BIGINT))) + 1)"
SQL["pq_ids_unchanged"] = f"WITH {_ASSIGNED}, s AS (SELECT k, count(*) AS n, (SELECT max(id) + 1 FROM v) AS u FROM a GROUP BY k), r AS (SELECT CAST(sum(n) AS BIGINT) AS ids, round(sum({_EFN}) / sum(n), 4) AS bits_per_id FROM s) SELECT 'flat' AS index, * FROM r UNION ALL SELECT 'pq', * FROM r"


def knn_graph(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Eight nearest others of every vector."""
    db = vectors(spark, sf_dir)
    near = search.exact(db.select(F.col("id").alias("qid"), F.col("vec").alias("qvec")), db, 9).filter("id <> qid")
    return search.ranked(near.drop("rank"), 8, ["id"]).select(F.col("qid").alias("src"), F.col("id").alias("dst"))


Q["knn_graph"] = knn_graph
SQL["knn_graph"] = f"WITH {_V}, d AS (SELECT a.id AS src, b.id AS dst, row_number() OVER (PARTITION BY a.id ORDER BY list_distance(a.x, b.x), b.id) AS r FROM v a JOIN v b ON a.id <> b.id) SELECT src, dst FROM d WHERE r <= 8"


DEGREES = (4, 8, 16, 32, 64)


def _side_by_side(jobs: dict, at_once: int) -> dict:
    """What each of the jobs gives, by its name; they are begun in the order given. A graph of few shards is few tasks, so many graphs go side by side."""
    with ThreadPoolExecutor(at_once) as pool:
        got = {k: pool.submit(f) for k, f in jobs.items()}
        return {k: f.result() for k, f in got.items()}


def _by_degree(one) -> dict:
    """Jobs one(kind, most) of every kind of graph and degree, by (kind, most), the dearest first."""
    keys = [(kind, most) for kind in ("monotone", "layered") for most in DEGREES]
    return {k: partial(one, *k) for k in sorted(keys, key=lambda k: -k[1])}


def _told_by_degree(got: dict) -> dict:
    """The results in the order in which they are told."""
    return {k: got[k] for k in sorted(got, key=lambda k: (k[0] != "monotone", k[1]))}


def graph_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Beam search on pruned graphs with compressed friend lists: recall, measured bits per edge, and their share of 32-bit words."""
    db, out = vectors(spark, sf_dir), None
    truth, u = arrow.stage(search.exact(batch(db), db, NEAREST), "truth"), tables.universe(db)

    def one(kind: str, most: int) -> tuple[DataFrame, DataFrame]:
        edges = arrow.stage(graph.build(db, most, kind), "graph")
        found = graph.find(batch(db), db, graph.friends(edges, "roc", u), NEAREST, 32, upper=edges if kind == "layered" else None)
        return edges, arrow.stage(search.recall(found, truth), "recall")  # one figure: the search is the same for every store

    for (kind, most), (edges, recall) in _told_by_degree(_side_by_side(_by_degree(one), 2 * len(DEGREES))).items():
        for codec in ("raw32", "packed", "ef", "roc"):
            r = recall.crossJoin(frames.bits_per_id(graph.friends(edges, codec, u)).select("bits_per_id"))
            r = r.select(F.lit(f"{kind}{most}").alias("graph"), F.lit(codec).alias("codec"), F.col("bits_per_id").alias("bits_per_edge"), F.round(F.col("bits_per_id") / 32, 4).alias("of_raw"), "recall")
            out = r if out is None else out.union(r)
    return out


Q["graph_search"] = graph_search


def graph_search_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Beam search over one graph by joins of frontiers, beside the search within tasks: recall of both."""
    db = vectors(spark, sf_dir)
    truth, u = search.exact(batch(db), db, NEAREST), tables.universe(db)
    lists = arrow.stage(graph.friends(graph.build(db, 16), "roc", u), "lists")
    joined = graph.find_by_join(batch(db), db, lists, db.orderBy("id").limit(4), NEAREST, 32)
    out = search.recall(joined, truth).select(F.lit("joins").alias("by"), "recall")
    return out.union(search.recall(graph.find(batch(db), db, lists, NEAREST, 32), truth).select(F.lit("tasks"), "recall"))


Q["graph_search_join"] = graph_search_join


#: Graphs that are coded side by side: each one's plans take memory of the driver.
CODED_AT_ONCE = 4


def graph_offline(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits per edge of whole graphs: edge coding beside the reference-list baseline in both its forms, closed forms, and the share of 32-bit words."""
    db = vectors(spark, sf_dir)
    u, shards = tables.universe(db), graph.shards_for(db.count())
    coders = {"edge_coding": lambda e, n: edgecodec.encode(e, n, shards=1), "reference_lists": reflist.encode, "reference_lists_older": partial(reflist.encode, entropy="none", intervals=True)}

    def sizes(name: str, edges: DataFrame, n: int) -> DataFrame:
        edges, out = arrow.stage(edges, "graph"), None
        lists = measures.list_sizes(edges, "src", "dst")
        form = measures.rec_bits(edges, n).crossJoin(lists.agg(F.round(F.sum(measures.set_bound_col(F.col("n"), F.lit(n))) / F.sum("n"), 4).alias("set_bound")))
        form = form.select(F.col("bits_per_edge").alias("closed_form"), "set_bound")
        for how, code in coders.items():
            r = code(edges, n).select(F.lit(how).alias("coder"), "n_edges", "bits")
            out = r if out is None else out.union(r)
        out = out.groupBy("coder").agg(F.sum("n_edges").cast("long").alias("edges"), F.round(F.sum("bits") / F.sum("n_edges"), 4).alias("bits_per_edge"))
        out = out.crossJoin(form).select(F.lit(name).alias("graph"), "coder", "edges", "bits_per_edge", F.round(F.col("bits_per_edge") / 32, 4).alias("of_raw"), "closed_form", "set_bound")
        return arrow.stage(out, "sizes")

    built = _by_degree(lambda kind, most: sizes(f"{kind}{most}", graph.base(graph.build(db, most, kind, shards=shards)), u))
    given = {name: partial(lambda name: sizes(name, *tables.graph(spark, sf_dir, name)), name) for name in ("part_supplier", "customer_part", "order_part")}
    got = _side_by_side(given | built, CODED_AT_ONCE)  # coding, too: one stream is one task, the longest of the given graphs
    return reduce(DataFrame.union, [*_told_by_degree({k: got[k] for k in built}).values(), *(got[k] for k in given)])


Q["graph_offline"] = graph_offline


def _bits_table(db: DataFrame, clusters: tuple[int, ...]) -> DataFrame:
    """Bits per id by number of clusters and codec on trained clusters, and their shares of raw and of fixed-width ids."""
    out, u = None, tables.universe(db)
    for n in clusters:
        rows = arrow.stage(ivf.placed(db, quantizers.kmeans(db, n, 4)).select("id", "k", "off"), "placed")
        for codec in ("raw", "packed", "ef", "wt", "wt1", "roc", "roc_exact"):
            lists, tree = ivf.stored_ids(rows, codec, u, n)
            r = (lists if tree is None else tree).agg(F.lit(n).cast("long").alias("clusters"), F.lit(codec).alias("codec"), F.round(F.sum("bits") / F.sum("n"), 4).alias("bits_per_id"))
            r = r.withColumn("of_raw", F.round(F.col("bits_per_id") / 64, 4)).withColumn("of_packed", F.round(F.col("bits_per_id") / (u - 1).bit_length(), 4))
            out = r if out is None else out.union(r)
    return out


def ivf_bits_table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fewer, longer lists cost less an id."""
    return _bits_table(vectors(spark, sf_dir), (8, 16, 32, 64))


def ivf_bits_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same on feature vectors of events, up to 512 clusters."""
    return _bits_table(tables.event_vectors(spark, sf_dir), (32, 128, 512))


Q["ivf_bits_table"], Q["ivf_bits_events"] = ivf_bits_table, ivf_bits_events


def index_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bytes of a whole index with raw and with coded ids, vectors as 8-byte residual codes."""
    db, out = vectors(spark, sf_dir), None
    c, rq = quantizers.kmeans(db, CLUSTERS, 3), quantizers.ResidualQuantizer.train(db, 8, 8, iters=1)
    for codec in ("raw", "packed", "ef", "roc"):
        r = ivf.size(ivf.build(db, c, codec, rq))
        out = r if out is None else out.union(r)
    return out


Q["index_size"] = index_size


def regimes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What access costs: bits per id of events by user, read at random, per list, or only as a whole."""
    df, out = tables.id_lists(spark, sf_dir, "user_event").select(F.col("k").cast("long").alias("k"), "id"), None
    u, k = tables.universe(df), tables.universe(df, "k")
    rows = [("random", "packed"), ("random", "wt"), ("random", "wt1"), ("per list", "ef"), ("per list", "roc"), ("per list", "roc_exact")]
    for regime, codec in rows:
        e = wavelet.build(df, "id", "k", k, "flat" if codec == "wt" else "rrr") if codec[0] == "w" else frames.encode_lists(df, "k", "id", codec, u)
        r = e.agg(F.round(F.sum("bits") / F.sum("n"), 4).alias("bits_per_id")).select(F.lit(regime).alias("regime"), F.lit(codec).alias("codec"), "bits_per_id")
        out = r if out is None else out.union(r)
    edges = df.select(F.col("k").alias("src"), (F.col("id") + k).alias("dst"))
    whole = edgecodec.encode(edges, k + u).agg(F.round(F.sum("bits") / F.sum("n_edges"), 4).alias("bits_per_id"))
    return out.union(whole.select(F.lit("whole").alias("regime"), F.lit("edge_coding").alias("codec"), "bits_per_id"))


Q["regimes"] = regimes


def pq_code_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Product codes under running counts, conditioned on the cluster and not, measured and by the closed form."""
    db, out = vectors(spark, sf_dir), None
    c = quantizers.kmeans(db, CLUSTERS, 3)
    for m in (4, 16):
        ix = ivf.build(db, c, "packed", quantizers.ProductQuantizer.train(db, m, 4, iters=2))
        long = ix.codes.select("k", F.col("off").alias("id"), F.posexplode("code").alias("sub", "code"))
        for name, rows in (("conditioned", long), ("unconditioned", long.withColumn("id", F.col("k") * (1 << 40) + F.col("id")).withColumn("k", F.lit(0)))):
            coded = codecodec.encode(rows, alphabet=16).agg(F.sum("bits").alias("bits"), F.sum("n").alias("n"))
            form = measures.adaptive_code_bits(rows, ["k", "sub"], "code", 16).agg(F.sum("bits").alias("form"))
            r = coded.crossJoin(form).select(F.lit(f"pq{m}x4").alias("codes"), F.lit(name).alias("model"), F.round(F.col("bits") / F.col("n"), 4).alias("measured"), F.round(F.col("form") / F.col("n"), 4).alias("closed_form"))
            out = r if out is None else out.union(r)
    return out


Q["pq_code_bits"] = pq_code_bits


#: Added to every coordinate; the coordinates of the given vectors deviate by 0.125.
SHIFTS = (0.0, 0.0625, 0.125, 0.25, 0.5)


def shifted_code_bits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Bits a product code of vectors that have moved away from those its codebooks come from, under running counts."""
    db = vectors(spark, sf_dir)
    moved = db.select("id", F.explode(F.array(*map(F.lit, SHIFTS))).alias("shift"), "vec")
    moved = moved.withColumn("vec", F.transform(F.col("vec").cast("array<double>"), lambda x: x + F.col("shift")))
    long = quantizers.encode(moved, _fixed_pq(db)).select("shift", F.posexplode("code").alias("sub", "code"))
    bits = measures.adaptive_code_bits(long, ["shift", "sub"], "code", 1 << BITS)
    return bits.groupBy("shift").agg(F.sum("n").cast("long").alias("codes"), F.round(F.sum("bits") / F.sum("n"), 4).alias("bits_per_code"))


Q["shifted_code_bits"] = shifted_code_bits
SQL["shifted_code_bits"] = f"""WITH {_PQ}, w AS (SELECT id, shift, sub, list_transform(y, lambda z: z + shift) AS y FROM s, (SELECT CAST(unnest([{", ".join(map(str, SHIFTS))}]) AS DOUBLE) AS shift)),
e AS (SELECT w.id, w.shift, w.sub, arg_min(b.id, list_distance(w.y, b.y)) AS code FROM w JOIN s b ON b.sub = w.sub AND b.id < {1 << BITS} GROUP BY w.id, w.shift, w.sub),
c AS (SELECT shift, sub, code, count(*) AS c FROM e GROUP BY ALL), g AS (SELECT shift, sub, sum(c) AS n, sum(lgamma(c + 1)) AS lf FROM c GROUP BY shift, sub)
SELECT shift, CAST(sum(n) AS BIGINT) AS codes, round(sum(lgamma({1 << BITS} + n) - lgamma({1 << BITS}) - lf) / ln(2) / sum(n), 4) AS bits_per_code FROM g GROUP BY shift"""


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An index with random-order coded ids, searched with ids resolved for the winners only."""
    db = vectors(spark, sf_dir)
    return _told(ivf.find(batch(db), ivf.build(db, first_rows(db, CLUSTERS), "roc"), NEAREST, PROBES))
