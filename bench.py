"""Headline timings: one JSON line with seconds per query, ids coded per second and bits per id.

BENCH_SF_DIR names the tables, BENCH_CPUS the cores, BENCH_RUNS how often each query runs (the median counts).
"""

from __future__ import annotations

import json
import os
import statistics
import sys
import time

HERE = os.path.dirname(os.path.abspath(__file__))
sys.path.insert(0, HERE)

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", str(os.cpu_count() or 4)))
RUNS = int(os.environ.get("BENCH_RUNS", "3"))


def drain(df) -> None:
    df.write.format("noop").mode("overwrite").save()


def main() -> None:
    from orderless import session
    from orderless.functions import measures
    from orderless.operators import edgecodec, frames, graph, ivf, quantizers, reflist, search
    from orderless.plans import searches
    from orderless.sources import tables

    spark = session.local(CPUS)
    seconds: dict[str, float] = {}
    facts: dict[str, float] = {}

    def timed(name: str, f) -> None:
        f()
        took = []
        for _ in range(RUNS):
            began = time.perf_counter()
            f()
            took.append(time.perf_counter() - began)
        seconds[name] = round(statistics.median(took), 3)

    # encoding and decoding lists of 600,000 ids
    for name in ("part_order", "supplier_order", "user_event"):
        df = tables.id_lists(spark, SF_DIR, name).cache()
        n, u = df.count(), tables.universe(df)
        for codec in ("packed", "ef", "roc"):
            enc = frames.encode_lists(df, "k", "id", codec, u)
            timed(f"encode_{codec}_{name}", lambda enc=enc: drain(enc))
            enc = enc.cache()
            facts[f"bits_per_id_{codec}_{name}"] = enc.selectExpr("sum(bits) / sum(n)").first()[0]
            timed(f"decode_{codec}_{name}", lambda enc=enc: drain(frames.decode_lists(enc)))
            facts[f"decoded_ids_per_second_{codec}_{name}"] = n / seconds[f"decode_{codec}_{name}"]
            enc.unpersist()
        timed(f"rates_{name}", lambda df=df, u=u: measures.rates(measures.list_sizes(df, "k", "id"), u).collect())
        df.unpersist()

    # search with every id store, all vectors as queries
    db = searches.vectors(spark, SF_DIR).cache()
    q = db.selectExpr("id AS qid", "vec AS qvec")
    rows = db.count()
    clusters = max(8, round(rows**0.5))
    c = quantizers.kmeans(db, clusters, 4)
    timed("exact_knn", lambda: drain(search.exact(q, db, 10)))
    truth = search.exact(q, db, 10).cache()
    for codec in ("raw", "packed", "ef", "roc", "wt", "wt1"):
        ix = ivf.build(db, c, codec)
        ix.codes = ix.codes.cache()
        ix.lists = ix.lists.cache() if ix.lists is not None else None
        ix.tree = ix.tree.cache() if ix.tree is not None else None
        facts[f"ivf{clusters}_bits_per_id_{codec}"] = ivf.id_bits(ix).first().bits_per_id
        timed(f"ivf_search_{codec}", lambda ix=ix: drain(ivf.find(q, ix, 10, 16)))
        if codec == "roc":
            facts["ivf_recall_at_10"] = search.recall(ivf.find(q, ix, 10, 16), truth).first().recall
    for codec in ("packed", "ef", "roc", "wt", "wt1"):
        facts[f"ivf_slowdown_{codec}"] = seconds[f"ivf_search_{codec}"] / seconds["ivf_search_raw"]
    # product codes by look-up tables, with every id store: how much slower than raw ids each one is
    for m, bits in ((4, 8), (16, 8), (32, 8), (8, 10)):
        if rows < 1 << bits:
            continue
        pq = quantizers.ProductQuantizer.train(db, m, bits, iters=2)
        for codec in ("raw", "packed", "ef", "roc", "wt", "wt1"):
            ix = ivf.build(db, c, codec, pq)
            ix.codes = ix.codes.cache()
            ix.lists = ix.lists.cache() if ix.lists is not None else None
            ix.tree = ix.tree.cache() if ix.tree is not None else None
            timed(f"pq{m}x{bits}_search_{codec}", lambda ix=ix: drain(ivf.find(q, ix, 10, 16)))
            if codec != "raw":
                facts[f"pq{m}x{bits}_slowdown_{codec}"] = seconds[f"pq{m}x{bits}_search_{codec}"] / seconds[f"pq{m}x{bits}_search_raw"]
            ix.codes.unpersist()
    ix = ivf.build(db, c, "roc")
    timed("ivf_search_join", lambda: drain(ivf.find_by_join(q, ix, 10, 16)))

    # graphs
    timed("graph_build_16", lambda: drain(graph.build(db, 16)))
    edges = graph.build(db, 16).cache()
    u = tables.universe(db)
    for codec in ("packed", "ef", "roc"):
        lists = graph.friends(edges, codec, u).cache()
        facts[f"graph_bits_per_edge_{codec}"] = frames.bits_per_id(lists).first().bits_per_id
        timed(f"graph_search_{codec}", lambda lists=lists: drain(graph.find(q, db, lists, 10, 16)))
    e, n = tables.graph(spark, SF_DIR, "part_supplier")
    e = e.cache()
    facts["edge_coding_closed_form"] = measures.rec_bits(e, n).first().bits_per_edge
    for name, f in (("edge_coding", edgecodec.encode), ("reference_lists", reflist.encode)):
        timed(f"{name}_part_supplier", lambda f=f: drain(f(e, n, shards=CPUS)))
        blobs = f(e, n, shards=CPUS)
        facts[f"{name}_bits_per_edge"] = blobs.selectExpr("sum(bits) / sum(n_edges)").first()[0]

    out = {"metric": "sum of median query seconds", "value": round(sum(seconds.values()), 3), "unit": "sec", "queries": seconds, "sf": os.path.basename(SF_DIR.rstrip("/")).removeprefix("sf"), "runs": RUNS, "facts": {k: round(v, 4) for k, v in facts.items()}}
    print(json.dumps(out), flush=True)
    spark.stop()


if __name__ == "__main__":
    main()
