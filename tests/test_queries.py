"""Registered queries against the SQL that restates them, on the smallest tables; plan shapes; guards."""

import duckdb
import pytest
from pyspark.errors import PySparkException
from pyspark.sql import functions as F

from orderless.functions import measures
from orderless.operators import frames, ivf, ops, quantizers, search, wavelet
from orderless.plans import catalog, searches
from orderless.sources import store, tables

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SLOW = {"graph_search", "graph_offline", "pq_recall", "ivf_bits_table", "ivf_bits_events", "index_size", "centroid_graph_recall", "graph_search_join"}
SLOW |= {f"pq_search_{m}_{store}" for m in (4, 16) for store in ("packed", "ef", "wt")}


@pytest.fixture(scope="session")
def oracle(sf):
    c = duckdb.connect()
    for t in TABLES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def norm(v):
    if isinstance(v, float):
        return round(v, 6) + 0.0
    return tuple(map(norm, v)) if isinstance(v, (list, tuple)) else v


@pytest.mark.parametrize("name", sorted(n for n in catalog.QUERIES if n not in SLOW))
def test_query(spark, sf, oracle, name):
    df = catalog.QUERIES[name](spark, sf)
    cols = sorted(df.columns)
    got = sorted((tuple(norm(r[c]) for c in cols) for r in df.collect()), key=repr)
    if name not in catalog.ORACLES:
        assert got
        return
    r = oracle.sql(catalog.ORACLES[name])
    assert sorted(r.columns) == cols
    at = [r.columns.index(c) for c in cols]
    assert got == sorted((tuple(norm(x[i]) for i in at) for x in r.fetchall()), key=repr)


def test_scan_is_pruned(spark, sf):
    plan = catalog.QUERIES["op_scan_pruned"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity)" in plan and "l_comment" not in plan
    assert "l_extendedprice" not in plan


def test_rates_read_no_payload(spark, sf):
    df = tables.id_lists(spark, sf, "customer_order")
    plan = measures.rates(measures.list_sizes(df, "k", "id"), 2000)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "MapInArrow" not in plan


def test_late_ids_keep_lists_below_the_winners(spark, sf):
    db = searches.vectors(spark, sf)
    ix = ivf.build(db, searches.first_rows(db, 8), "roc")
    q = next(search.query_blocks(searches.batch(db)))
    plan = search.scan(ix.codes, q, ivf.probe(q[1], ix.centroids, 3), 10, ix.scorer)._jdf.queryExecution().optimizedPlan().toString()
    assert "payload" not in plan


def test_ids_outside_the_universe_fail(spark):
    df = spark.createDataFrame([(1, 5), (1, 10)], "k long, id long")
    with pytest.raises(PySparkException):
        frames.encode_lists(df, "k", "id", "roc", 10).collect()
    with pytest.raises(PySparkException):
        frames.encode_lists(spark.createDataFrame([(1, None)], "k long, id long"), "k", "id", "ef", 10).collect()


def test_empty_and_repeated_lists(spark):
    none = spark.createDataFrame([], "k string, id long")
    for codec in ("packed", "ef", "roc"):
        assert frames.decode_lists(frames.encode_lists(none, "k", "id", codec, 10)).count() == 0
        df = spark.createDataFrame([("a", 3), ("a", 3), ("b", 9), ("a", 0)], "k string, id long")
        assert sorted(map(tuple, frames.decode_lists(frames.encode_lists(df, "k", "id", codec, 10)).collect())) == [("a", 0), ("a", 3), ("b", 9)]


def test_one_giant_list_is_cut(spark):
    df = spark.range(0, 60000, 2).select(F.lit("x").alias("k"), F.col("id"))
    enc = frames.encode_lists(df, "k", "id", "roc", 60000, 10)
    assert enc.count() == 59
    assert frames.lost_or_added(df, frames.decode_lists(enc)).count() == 0


def test_wavelet_refuses_overlap(spark):
    df = spark.createDataFrame([(0, 1), (0, 2), (1, 1)], "id long, k long")
    with pytest.raises(PySparkException, match="dense ids"):
        wavelet.build(df, "id", "k", 3).collect()
    with pytest.raises(wavelet.UnsupportedError):
        wavelet.build(df, "id", "k", 3, "other")


def test_search_without_queries_or_rows(spark, sf):
    db = searches.vectors(spark, sf)
    ix = ivf.build(db, searches.first_rows(db, 4), "ef")
    assert ivf.find(searches.batch(db).filter("false"), ix, 5).count() == 0
    assert search.exact(searches.batch(db), db.filter("false"), 5).count() == 0


def test_product_codes_agree_with_tables(spark, sf):
    db = searches.vectors(spark, sf)
    pq = quantizers.ProductQuantizer.train(db, 8, 4, iters=1)
    x = quantizers.sample(db, 50)
    code = pq.encode_rows(x)
    assert abs(pq.look_up(pq.tables(x[:5]), code) - search.Flat().distances(x[:5], pq.decode_rows(code))).max() < 1e-8
    assert abs(pq.look_up(pq.tables(x[:5]), code) - pq.distances(x[:5], code)).max() < 1e-8


def test_range_join_has_no_cross_product(spark):
    p = spark.createDataFrame([(i,) for i in range(0, 100, 7)], "at long")
    i = spark.createDataFrame([(0, 20), (15, 60), (60, 60)], "lo long, hi long")
    got = ops.range_join(p, "at", i, "lo", "hi", 8)
    assert sorted(map(tuple, got.collect())) == sorted((a, lo, hi) for a in range(0, 100, 7) for lo, hi in ((0, 20), (15, 60)) if lo <= a < hi)
    assert "CartesianProduct" not in got._jdf.queryExecution().executedPlan().toString()


def test_reads_of_a_tree_move_asked_shards_only(spark, sf):
    """The index is cut down to the shards that are asked before its payloads are exchanged, and a place finds its shard by an equality join."""
    df = tables.id_lists(spark, sf, "user_event").select(F.col("k").cast("long").alias("k"), "id")
    ix = wavelet.build(df, "id", "k", 200, "flat", 6)
    asked = spark.createDataFrame([(3, 0), (5, 1)], "k long, off long")
    assert wavelet.located(ix, asked).select("shard").distinct().count() <= 2 < ix.count()
    plan = wavelet.select(ix, asked, 6)._jdf.queryExecution().optimizedPlan().toString()
    assert "LeftSemi" in plan and "Join Cross" not in plan
    assert "payload" not in wavelet.located(ix, asked)._jdf.queryExecution().optimizedPlan().toString().split("MapInArrow")[0]


def test_reads_over_segments(spark):
    """Places and values in the first, a middle and the last segment, in missing ones, and beyond; ids of several codecs."""
    ids = [*range(0, 300, 3), 5000, 5001, 9000]
    df = spark.createDataFrame([("a", i) for i in ids] + [("b", 7)], "k string, id long")
    for codec in ("raw", "packed", "ef", "ef_dir", "roc"):
        enc = frames.encode_lists(df, "k", "id", codec, 10_000, 7)
        asked = spark.createDataFrame([("a", o) for o in (0, 60, 99, 100, 102, 103, -1)] + [("b", 0), ("b", 1), ("c", 0)], "k string, off long")
        got = {(r.k, r.off): r.id for r in frames.get(enc, asked).collect()}
        assert got == {("a", o): ids[o] for o in (0, 60, 99, 100, 102)} | {("b", 0): 7}
    for codec in ("ef", "ef_dir"):
        enc = frames.encode_lists(df, "k", "id", codec, 10_000, 7)
        values = [-9, 0, 1, 297, 298, 4000, 5001, 5002, 9000, 9001, 20_000]
        asked = spark.createDataFrame([("a", v) for v in values] + [("b", 7), ("b", 8), ("c", 1)], "k string, value long")
        got = {(r.k, r.value): r.id for r in frames.next_geq(enc, asked).collect()}
        assert got == {("a", v): next((i for i in ids if i >= v), None) for v in values} | {("b", 7): 7, ("b", 8): None}


def test_many_centroids_fit_in_memory(spark, monkeypatch):
    """65,536 centroids in blocks under the broadcast's bound: the nearest is the nearest."""
    import numpy as np

    r = np.random.default_rng(5)
    c, x = r.normal(size=(1 << 16, 8)), r.normal(size=(400, 8))
    monkeypatch.setattr(quantizers, "MODEL_BYTES", 1 << 20)
    db = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>")
    got = {row.id: row.k for row in quantizers.assign(db, c).select("id", "k").collect()}
    want = np.concatenate([((x[i : i + 50, None] - c[None]) ** 2).sum(2).argmin(1) for i in range(0, 400, 50)])
    assert [got[i] for i in range(400)] == want.tolist()


def test_search_by_join_in_parts(spark, sf, monkeypatch):
    """Clusters scanned in parts, and as many queries as rows: the answers of the other way."""
    db = searches.vectors(spark, sf)
    ix = ivf.build(db, searches.first_rows(db, 8), "ef")
    q = db.selectExpr("id AS qid", "vec AS qvec")
    want = ivf.find(q, ix, 5, 4).select("qid", "rank", "id")
    monkeypatch.setattr(ivf, "PART_ROWS", 16)
    assert frames.lost_or_added(want, ivf.find_by_join(q, ix, 5, 4).select("qid", "rank", "id")).count() == 0


def test_query_blocks_come_one_at_a_time(spark, sf, monkeypatch):
    db = searches.vectors(spark, sf)
    monkeypatch.setattr(search, "BLOCK_BYTES", 8 * 64 * 20)
    blocks = list(search.query_blocks(searches.batch(db)))
    assert len(blocks) > 1 and sorted(i for ids, _ in blocks for i in ids.tolist()) == sorted(r.qid for r in searches.batch(db).select("qid").collect())


def test_saved_index_opens_by_key(spark, sf, tmp_path):
    df = tables.id_lists(spark, sf, "customer_order")
    store.save_index(frames.encode_lists(df, "k", "id", "ef", tables.universe(df)), f"{tmp_path}/ix")
    got = frames.decode_lists(store.open_index(spark, f"{tmp_path}/ix", [3, 4]))
    assert frames.lost_or_added(df.filter("k IN (3, 4)"), got).count() == 0


def test_vector_files(spark, tmp_path):
    import numpy as np

    rows = np.arange(12, dtype="<f4").reshape(3, 4)
    (tmp_path / "a.fvecs").write_bytes(b"".join(np.array([4], "<i4").tobytes() + r.tobytes() for r in rows))
    got = store.vector_files(spark, f"{tmp_path}/a.fvecs").orderBy("pos").collect()
    assert [r.vec for r in got] == rows.tolist()


def test_findings_of_the_paper(spark, sf):
    """Which method wins, and how sizes move."""
    r = {n: catalog.QUERIES[f"rates_{n}"](spark, sf).first() for n in ("supplier_order", "customer_order", "user_event")}
    assert all(x.packed > x.ef > x.set_bound for x in r.values())
    assert r["user_event"].partition_bound < r["user_event"].set_bound
    sweep = {x.keyed_by: x.set_bound for x in catalog.QUERIES["list_length_sweep"](spark, sf).collect()}
    assert sweep["all"] < sweep["type"] < sweep["hour"] < sweep["id"]
    assert catalog.QUERIES["adaptive_code_bits_conditioned_planted"](spark, sf).first().bits_per_code < catalog.QUERIES["adaptive_code_bits_unconditioned_planted"](spark, sf).first().bits_per_code


def test_projection_reads_given_lists(spark, sf):
    """ids and clusters are counted in the tables; the closed forms at published sizes stay as they were."""
    from orderless.plans import sizes

    plan = catalog.QUERIES["projection"](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert all(f"{t}.parquet" in plan for t in ("orders", "events", "part", "customer"))
    got = sizes.balanced(spark.createDataFrame([(10**9, 1 << 20)], "n long, clusters long")).first()
    assert (got.roc, got.ef) == (21.436, 22.0)


def test_entry(spark):
    import __spark_entry__ as e

    df = e.entry(spark)
    assert df.columns == ["qid", "rank", "id", "dist"] and df.count() > 0
    assert set(e.oracle_sql()) <= set(e.queries())
