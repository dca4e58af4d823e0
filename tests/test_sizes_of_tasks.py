"""What a task or the driver holds at a time stays bounded as tables grow."""

import re
import threading

import numpy as np
import pyarrow as pa
import pytest

from orderless.functions import listcodecs, setcodec
from orderless.functions.ans import ExactState, WordState
from orderless.functions.bitvec import RRR, Flat
from orderless.operators import arrow, edgecodec, edgelanes, frames, graph, ivf, reflist, search, wavelet
from orderless.plans import catalog, searches


@pytest.mark.parametrize("cells", [1 << 21, 40])
def test_exact_search_in_tiles(spark, monkeypatch, cells):
    """distances are computed for some queries at a time; answers are those of all at once."""
    r = np.random.default_rng(2)
    x = r.integers(0, 4, (300, 3)).astype(float)  # many ties
    db = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "id long, vec array<double>").repartition(3)
    monkeypatch.setattr(search, "CELLS", cells)
    dist = search.Flat().distances(x, x)
    got = {(row.qid, row["rank"]): row.id for row in search.exact(db.selectExpr("id AS qid", "vec AS qvec"), db, 5).collect()}
    order = np.lexsort((np.broadcast_to(np.arange(300), dist.shape), dist), axis=1)[:, :5]
    assert got == {(q, k + 1): int(i) for q, some in enumerate(order) for k, i in enumerate(some)}


def test_tiles_of_distances_are_bounded(monkeypatch):
    """all queries of a block against 4,096 rows were one matrix."""
    sizes, near = [], search.best
    monkeypatch.setattr(search, "best", lambda d, *a: sizes.append(d.size) or near(d, *a))
    r = np.random.default_rng(3)
    q, x = r.normal(size=(3000, 4)), r.normal(size=(4096, 4))
    b = pa.RecordBatch.from_arrays([pa.array(np.arange(4096)), pa.array(x.tolist())], ["id", "vec"])
    found = list(search.nearest_of((np.arange(3000), q), iter([b]), 3, search.Flat()))
    assert max(sizes) <= search.CELLS and sum(sizes) == 3000 * 4096 and [f.num_rows for f in found] == [9000]


def _plan(df) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def test_values_find_their_segments_without_a_broadcast(spark):
    """segments' numbers aren't sent through the driver, however small their files; lists are opened in one step."""
    df = spark.createDataFrame([("a", i) for i in (3, 70, 71, 900)] + [("b", 5)], "k string, id long")
    asked = spark.createDataFrame([("a", v) for v in (0, 4, 4, 72, 901)] + [("b", -1)], "k string, value long")
    for codec in ("ef", "ef_dir"):
        enc = arrow.stage(frames.encode_lists(df, "k", "id", codec, 1000, 6), "lists")
        got = frames.next_geq(enc, asked)
        assert "Broadcast" not in _plan(got) and _plan(got).count("MapInArrow") == 1
        assert sorted(map(tuple, got.collect()), key=repr) == sorted([("a", 0, 3), ("a", 4, 70), ("a", 4, 70), ("a", 72, 900), ("a", 901, None), ("b", -1, 5)], key=repr)


@pytest.mark.parametrize("kind", ["flat", "rrr"])
def test_places_find_their_shards_without_a_broadcast(spark, sf, kind):
    """F3 (flat), F4 (rrr): a tree's directory isn't sent through the driver, and the tree is built once."""
    plan = _plan(catalog.QUERIES[f"wavelet_select_{kind}_user_event"](spark, sf))
    assert not re.search(r"BroadcastHashJoin \[k#\d+L?, _bin", plan)
    assert "MapInArrow" not in plan


@pytest.mark.parametrize("kind, opener, size", [("flat", (Flat, "_block"), Flat.EVERY), ("rrr", (RRR, "_blocks"), 63)])
def test_blocks_of_a_tree_are_opened_once(monkeypatch, kind, opener, size):
    """F3 (flat), F4 (rrr): every place asked opened the blocks of its own bits, 4,096 times the 8 or 66 that a level has."""
    seq = np.random.default_rng(8).integers(0, 300, 4096)
    order = np.argsort(seq, kind="stable")
    off = np.empty(4096, np.int64)
    off[order] = np.arange(4096) - np.searchsorted(seq[order], seq[order])
    tree = wavelet.Tree.of(seq, 9, kind)
    opened, real = [], getattr(*opener)
    monkeypatch.setattr(*opener, lambda self, k, *a: opened.append(len(k)) or real(self, k, *a))
    assert (tree.select(seq, off) == np.arange(4096)).all() and (tree.access(np.arange(4096)) == seq).all()
    assert (tree.rank(seq, np.arange(4096)) == off).all()
    assert max(opened) <= -(-4096 // size)


def _graph(spark, n: int = 6000):
    r = np.random.default_rng(4)
    rows = {(int(a), int(b)) for a, b in r.integers(0, 500, (n, 2))}
    return spark.createDataFrame(sorted(rows), "src long, dst long"), rows


@pytest.mark.parametrize("directed", [True, False])
@pytest.mark.parametrize("model", ["urn", "uniform"])
def test_shards_grow_in_number_not_in_size(spark, monkeypatch, directed, model):
    """F8 to F11, F18: a number of shards is the least; a task codes about as many edges however large the graph."""
    monkeypatch.setattr(edgecodec, "SHARD_EDGES", 100)
    df, rows = _graph(spark)
    if not directed:
        df, rows = df.filter("src < dst"), {(a, b) for a, b in rows if a < b}
    blobs = edgecodec.encode(df, 500, directed=directed, shards=8, model=model)
    size = [r.n_edges for r in blobs.select("n_edges").collect()]
    assert len(size) > len(rows) / 200 and max(size) < 300 and sum(size) == len(rows)
    assert sorted(map(tuple, edgecodec.decode(blobs).collect())) == sorted(rows)
    assert edgecodec.encode(df, 500, directed=directed, shards=1, model=model).count() == 1


@pytest.mark.parametrize("choice, entropy, intervals", [("greedy", "none", True), ("greedy", "none", False), ("greedy", "ans", False), ("greedy", "ans", True), ("overlap", "ans", False)])
def test_reference_lists_in_bounded_shards(spark, monkeypatch, choice, entropy, intervals):
    """F5 (plain), F6 (plain_runs), F7 (greedy), F17 (intervals), F19 (overlap)."""
    monkeypatch.setattr(edgecodec, "SHARD_EDGES", 100)
    df, rows = _graph(spark)
    blobs = reflist.encode(df, 500, entropy=entropy, ref_choice=choice, shards=8, intervals=intervals)
    size = [r.n_edges for r in blobs.select("n_edges").collect()]
    assert max(size) < 300 and sum(size) == len(rows)
    assert sorted(map(tuple, reflist.decode(blobs).collect())) == sorted(rows)


@pytest.mark.parametrize("state", [WordState, ExactState])
def test_one_stream_in_machine_words(monkeypatch, state):
    """a large stream's edges, trees and words are held as machine words, with the same bits; edges come back in parts."""
    r = np.random.default_rng(5)
    for edges in (sorted({(int(a), int(b)) for a, b in r.integers(0, 60, (400, 2))}), [(int(a), int(b)) for a, b in r.integers(0, 9, (300, 2))]):
        small, large = state(), state()
        edgecodec.encode_edges(small, edges, 60)
        monkeypatch.setattr(edgecodec, "PLAIN", 10)
        monkeypatch.setattr(edgecodec, "TOLD", 50)
        edgecodec.encode_edges(large, edges, 60)
        assert small.to_bytes() == large.to_bytes()
        parts = list(edgecodec.decode_parts(state.from_bytes(large.to_bytes()), len(edges), 60))
        assert len(parts) > 3 and [(a, b) for x in parts for a, b in zip(*(c.tolist() for c in x), strict=True)] == sorted(edges)
        monkeypatch.undo()
    assert getattr(WordState(), "stack").itemsize == 4


def test_long_lists_of_an_index_on_exact_states(spark):
    """F16: a cluster with more ids than an exact state takes was an error."""
    rows = spark.range(140_000).selectExpr("0L AS k", "id * 40 AS id")
    lists, _ = ivf.stored_ids(rows, "roc_exact", 5_600_000, 1)
    got = lists.selectExpr("sum(n) AS n", "sum(bits) AS bits", "max(n) AS most").first()
    # at most what the whole list would take: the segments' sizes aren't in the payload
    assert got.n == 140_000 and got.most <= 1 << 17 and got.bits / got.n < 6.9
    assert lists.select("seg").distinct().count() == lists.count() > 1


@pytest.mark.parametrize("universe", [50_000, 1 << 27])
def test_long_lists_alone_have_the_bits_of_lists_in_step(monkeypatch, universe):
    """F16: coded in step, a list takes time with the square of its length."""
    r = np.random.default_rng(6)
    sets = [np.sort(r.choice(50_000, n, replace=False)) for n in (3, 700, 0, 64, 65, 1)]
    flat, at = np.concatenate(sets), np.r_[0, np.cumsum([len(x) for x in sets])]
    monkeypatch.setattr(listcodecs, "STEP_IDS", 64)
    c = listcodecs.codec("roc", universe)
    alone, bits = c.encode(flat, at)
    step, same = setcodec.encode_sets(flat, at, universe)
    assert alone == step and (bits == same).all()
    assert (c.decode(alone, np.diff(at)) == flat).all()
    assert (c.decode([alone[1]], np.array([700])) == sets[1]).all()


def test_a_long_list_takes_no_square_of_time():
    """F16: 60,000 ids in step moved 60,000 numbers an id."""
    moved, real = [], setcodec.encode_sets
    c, ids = listcodecs.codec("roc", 1 << 20), np.arange(0, 1 << 20, 17)
    try:
        setcodec.encode_sets = lambda flat, *a: moved.append(len(flat)) or real(flat, *a)
        payload, _ = c.encode(ids, np.array([0, len(ids)]))
    finally:
        setcodec.encode_sets = real
    assert sum(moved) == 0 and (c.decode(payload, np.array([len(ids)])) == ids).all()


def test_occlusion_never_meets_all_candidates(monkeypatch):
    """distances are taken from the links chosen alone; the links are those of the plain rule."""
    x = np.random.default_rng(7).normal(size=(400, 6))
    cand = np.arange(1, 400)
    d, between = graph.squared(x[:1], x)[0], graph.squared(x, x)
    want: list[int] = []
    for j in sorted(cand.tolist(), key=lambda j: (d[j], j)):
        if len(want) < 9 and all(between[j, t] >= d[j] for t in want):
            want.append(j)
    cells, real = [], graph.squared
    monkeypatch.setattr(graph, "squared", lambda a, b: cells.append(len(a) * len(b)) or real(a, b))
    assert graph.occlude(x, 0, cand, 9) == want and max(cells) < 400
    assert graph.occlude(x, 0, cand[:0], 9) == []


def test_occlusion_goes_on_with_what_is_left():
    """distances from every link chosen went to all candidates, those already out included."""
    work = []

    class Counted(np.ndarray):
        def __matmul__(self, other):
            work.append(len(self))
            return np.asarray(self) @ np.asarray(other)

    x = np.random.default_rng(9).normal(size=(2000, 6))
    cand, d, between = np.arange(1, 2000), graph.squared(x[:1], x)[0], graph.squared(x, x)
    want: list[int] = []
    for j in sorted(cand.tolist(), key=lambda j: (d[j], j)):
        if len(want) < 64 and all(between[j, t] >= d[j] for t in want):
            want.append(j)
    assert graph.occlude(x.view(Counted), 0, cand, 64) == want
    assert len(want) > 6 and sum(work[1:]) < len(want) * len(cand) / 2


def test_graphs_are_coded_side_by_side(spark, sf, monkeypatch):
    """graphs were built side by side, but counted and coded one after the other; a driver holds the plans of a few."""
    monkeypatch.setattr(searches, "DEGREES", (4, 8))
    begun, real = [], edgecodec.encode
    monkeypatch.setattr(edgecodec, "encode", lambda *a, **b: begun.append(threading.current_thread().name) or real(*a, **b))
    got = searches.graph_offline(spark, sf).collect()
    assert "MainThread" not in begun and len(begun) == 7 and 1 < len(set(begun)) <= searches.CODED_AT_ONCE
    names = {f"{kind}{most}" for kind in ("monotone", "layered") for most in (4, 8)} | {"part_supplier", "customer_part", "order_part"}
    assert len(got) == 21 and {r.graph for r in got} == names
    assert all(abs(r.bits_per_edge - r.closed_form) < 0.1 for r in got if r.coder == "edge_coding")


@pytest.mark.parametrize("directed, model, sources", [(True, "urn", None), (True, "uniform", None), (True, "urn", (100, 400)), (False, "urn", None), (False, "uniform", None)])
def test_states_of_one_stream_step_together(monkeypatch, directed, model, sources):
    """F1, F2 of round 3: a whole graph was one state's work, edge by edge."""
    monkeypatch.setattr(edgelanes, "LANE_EDGES", 500)
    r = np.random.default_rng(11)
    for n, dst in ((6000, 300), (40, 3), (1, 1), (600, 1)):
        src, dst = r.integers(*(sources or (0, 500)), n), r.integers(0, dst, n)
        keys = np.unique((src if directed else np.minimum(src, dst)) * 500 + (dst if directed else np.maximum(src, dst)))
        payload, bits = edgelanes.encode(keys, 500, 1, directed, model, sources)
        assert (edgelanes.decode(payload, len(keys), 500, 1, directed, model, sources) == keys).all()
        lanes = max(1, len(keys) // 500)
        alone = WordState()
        edgecodec.encode_keys(alone, keys, 500, 1, directed, model, sources)
        assert abs(len(payload) * 8 - bits) < 48 * (lanes + 1) and -50 < bits - alone.bits < 250 * lanes  # a state's begin, its length, and urns a step old
        took = edgelanes.steps(len(keys), lanes)
        assert sum(m for _, m in took) == len(keys) and (n < 6000 or len(took) < len(keys) / 4)


def test_draws_of_a_step_are_all_different():
    """F1, F2 of round 3: every state draws from all edges left, and the draws can be given back."""
    r = np.random.default_rng(12)
    for left in (1, 2, 7, 60, 5000):
        for m in {1, left // 2 or 1, left}:
            slot = np.array([r.integers(0, left - j) for j in range(m)])
            for s in (slot, np.zeros(m, np.int64), left - 1 - np.arange(m)):
                place = edgelanes.picked(s, left)
                assert len(set(place.tolist())) == m and place.min() >= 0 and place.max() < left
                assert (edgelanes.unpicked(place, left) == s).all()
            assert ((0 <= edgelanes.turned(m, left)) & (edgelanes.turned(m, left) < left - np.arange(m))).all()


@pytest.mark.parametrize("directed, shards", [(True, 1), (False, 1), (True, 3)])
def test_large_streams_are_coded_in_step(spark, monkeypatch, directed, shards):
    """F1, F2 of round 3: blobs of many edges, whole graphs and shards; parallel edges stay with one state."""
    monkeypatch.setattr(edgecodec, "LANED", 100)
    df, rows = _graph(spark)
    if not directed:
        df, rows = df.filter("src < dst"), {(a, b) for a, b in rows if a < b}
    blobs = edgecodec.encode(df, 500, directed=directed, shards=shards)
    assert all("_lanes:" in r.codec for r in blobs.select("codec").collect())
    assert sorted(map(tuple, edgecodec.decode(blobs).collect())) == sorted(rows)
    twice = edgecodec.encode(df.union(df), 500, directed=directed, shards=shards)
    assert not any("_lanes" in r.codec for r in twice.select("codec").collect())
    assert sorted(map(tuple, edgecodec.decode(twice).collect())) == sorted([*rows, *rows])


def _told_by_trial(nodes, window, min_run, choice, intervals):
    """The plain rule: every reference's symbols are written and counted."""
    told = (lambda n, x: reflist._by_intervals(n, x, min_run)) if intervals else (lambda n, x: [(reflist.RESIDUALS, len(x)), *reflist._residuals(n, x, min_run)])
    cost = lambda symbols: sum(v.bit_length() * (1 if c < reflist.GAP else 1.5) + 1 for c, v in symbols)
    out, chain = [], []
    for i, (node, own) in enumerate(nodes):
        same = {b: len(set(own) & set(nodes[i - b][1])) for b in range(1, min(window, i) + 1) if chain[i - b] < reflist.CHAIN}
        some = [b for b in same if same[b] > 1]
        if choice == "overlap" and some:
            some = [max(some, key=lambda b: (same[b], -b))]
        best, depth = [(reflist.REF, 0), *told(node, own)], 0
        for b in some:
            ref = nodes[i - b][1]
            blocks = reflist._blocks(ref, set(own))
            trial = [(reflist.REF, b), (reflist.BLOCKS, len(blocks)), *((reflist.BLOCK, n) for n in blocks), *told(node, [v for v in own if v not in ref])]
            if cost(trial) < cost(best):
                best, depth = trial, chain[i - b] + 1
        chain.append(depth)
        out += best
    return out


@pytest.mark.parametrize("intervals", [False, True])
@pytest.mark.parametrize("choice", ["greedy", "overlap"])
def test_references_are_compared_without_writing_each(monkeypatch, intervals, choice):
    """F1 of round 3: up to 32 references a list were written out to be compared; the symbols stay the same."""
    r, nodes = np.random.default_rng(13), []
    for i in range(120):
        x = set(r.integers(0, 150, int(r.integers(1, 15))).tolist())
        x |= set(range(i, i + int(r.integers(0, 9)))) | ({v for v in nodes[-1][1] if r.random() < 0.8} if i % 3 else set())
        nodes.append((2 * i, sorted(x)))
    for cells in (1 << 19, 50):
        monkeypatch.setattr(reflist, "COMPARED", cells)
        for window, min_run in ((1, 1), (7, 3), (32, 2)):
            assert reflist.describe(nodes, window, min_run, choice, intervals) == _told_by_trial(nodes, window, min_run, choice, intervals)
    name, calls = "_by_intervals" if intervals else "_residuals", []
    real = getattr(reflist, name)
    monkeypatch.setattr(reflist, name, lambda *a: calls.append(1) or real(*a))
    reflist.describe(nodes, 32, 3, choice, intervals)
    assert len(calls) <= 2 * len(nodes)
