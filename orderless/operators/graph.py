"""Graph indexes: pruned neighbour graphs per shard, friend lists compressed per node, beam search.

A shard is a bounded set of vectors (`SHARD_ROWS`); its graph is built and searched by one task, and shards' answers are merged. So neither
vectors nor edges of the whole corpus meet in one place.
"""

from __future__ import annotations

import heapq

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions import listcodecs
from . import arrow, frames, search

SHARD_ROWS = 20_000


def squared(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum((a * a).sum(1)[:, None] + (b * b).sum(1) - 2 * (a @ b.T), 0)


def neighbours(x: np.ndarray, k: int) -> np.ndarray:
    """The k nearest other rows of each row, ties by number."""
    n, k = len(x), min(k, len(x) - 1)
    out = np.zeros((n, max(k, 0)), np.int64)
    for lo in range(0, n, 512):
        d = squared(x[lo : lo + 512], x)
        d[np.arange(len(d)), np.arange(lo, lo + len(d))] = np.inf
        row, col = search.best(d, np.arange(n), k) if k > 0 else (None, None)
        if k > 0:
            out[lo : lo + len(d)] = col.reshape(len(d), k)
    return out


def occlude(x: np.ndarray, i: int, candidates: np.ndarray, most: int) -> list[int]:
    """Nearest first; one is taken unless a taken one is closer to it than i is."""
    d = squared(x[i : i + 1], x[candidates])[0]
    order = np.lexsort((candidates, d))
    cand, d = candidates[order], d[order]
    rows, free = x[cand], np.ones(len(cand), bool)
    length, taken, j = (rows * rows).sum(1), [], 0
    while len(taken) < most:  # distances from the taken ones alone, never between all candidates
        left = np.flatnonzero(free[j:])
        if not len(left):
            break
        if 2 * len(left) < len(cand) - j:  # most are out: go on with the others alone
            left += j
            cand, d, rows, length, free, j = cand[left], d[left], rows[left], length[left], free[left], 0
        else:
            j += int(left[0])
        taken.append(int(cand[j]))
        free[j + 1 :] &= np.maximum(length[j] + length[j + 1 :] - 2 * (rows[j + 1 :] @ rows[j]), 0) >= d[j + 1 :]
        j += 1
    return taken


def monotone(x: np.ndarray, most: int, knn: int) -> list[list[int]]:
    """Out-neighbours after occlusion among neighbours and theirs, every row reachable from the medoid."""
    n = len(x)
    near = neighbours(x, knn)
    out = []
    for i in range(n):
        cand = np.unique(np.concatenate([near[i], near[near[i]].ravel()])) if near.shape[1] else np.zeros(0, np.int64)
        out.append(occlude(x, i, cand[cand != i], most))
    if not n:
        return out
    start = medoid(x)
    seen, front = np.zeros(n, bool), [start]
    seen[start] = True
    while True:
        while front:
            front = [j for i in front for j in out[i] if not seen[j] and not seen.__setitem__(j, True)]
        lost = np.flatnonzero(~seen)
        if not len(lost):
            return out
        # attach the first lost row to its nearest reached row with room, else to the nearest
        v = int(lost[0])
        reached = np.flatnonzero(seen)
        order = reached[np.argsort(squared(x[v : v + 1], x[reached])[0], kind="stable")]
        at = next((int(i) for i in order if len(out[i]) < most), int(order[0]))
        out[at].append(v)
        seen[v] = True
        front = [v]


def layer(x: np.ndarray, m: int, most: int) -> list[list[int]]:
    """One level of a layered graph: occlusion to m, reverse links, cut to `most` by the same rule."""
    near = neighbours(x, 4 * m)
    out = [occlude(x, i, near[i], m) for i in range(len(x))]
    back: list[set[int]] = [set(o) for o in out]
    for i, o in enumerate(out):
        for j in o:
            back[j].add(i)
    return [sorted(b) if len(b) <= most else occlude(x, i, np.array(sorted(b)), most) for i, b in enumerate(back)]


def layered(x: np.ndarray, level: np.ndarray, m: int) -> list[tuple[int, int, list[int]]]:
    """(level, row, out-neighbours) of a layered graph: level l links the rows whose top level is l or more, 2m links at the base, m above."""
    out = []
    for at in range(int(level.max(initial=-1)) + 1):
        rows = np.flatnonzero(level >= at)
        out += [(at, int(rows[i]), rows[o].tolist()) for i, o in enumerate(layer(x[rows], m, 2 * m if at == 0 else m))]
    return out


def levels(ids: DataFrame, m: int, seed: int = 0) -> DataFrame:
    """Adds each id's top level: floor(-ln u / ln m) with u from a seeded hash."""
    u = (F.pmod(F.xxhash64("id", F.lit(seed)), F.lit(1 << 30)) + 1) / float(1 << 30)
    return ids.withColumn("level", F.floor(-F.log(u) / float(np.log(m))).cast("int"))


def medoid(x: np.ndarray) -> int:
    return int(squared(x.mean(0)[None], x)[0].argmin())


def build(db: DataFrame, most: int, kind: str = "monotone", knn: int | None = None, shards: int | None = None, seed: int = 0) -> DataFrame:
    """Edges (shard, level, src, dst) of db (id, vec); kind monotone (at most `most` out-edges plus repairs, one level) or layered.

    Top levels of the layered kind follow from a hash of the ids and the seed. Without a number of shards, as many as bound each.
    """
    if kind not in ("monotone", "layered"):
        raise ValueError(f"no graph of kind {kind!r}")
    arrow.importable(db.sparkSession)
    shards = shards or shards_for(db.count())

    def run(key: tuple, t: pa.Table) -> pa.Table:
        t = t.sort_by("id").combine_chunks()
        ids, x = t["id"].to_numpy(), arrow.vectors(t["vec"].chunk(0)).astype(np.float64)
        if kind == "monotone":
            out = [(0, i, o) for i, o in enumerate(monotone(x, most, knn or max(most, 16)))]
        else:
            out = layered(x, t["level"].to_numpy(), most)
        size = [len(o) for *_, o in out]
        src = np.repeat(ids[np.array([i for _, i, _ in out], np.int64)], size)
        dst = ids[np.array([j for *_, o in out for j in o], np.int64)]
        at = np.repeat(np.array([a for a, *_ in out], np.int32), size)
        return pa.table({"shard": pa.array(np.full(len(src), key[0].as_py(), np.int32)), "level": at, "src": src, "dst": dst})

    rows = levels(_shards(db, shards), max(2, most), seed)
    return rows.groupBy("shard").applyInArrow(run, "shard int, level int, src long, dst long")


def base(edges: DataFrame) -> DataFrame:
    """src, dst of the base level, which is what gets compressed."""
    return edges.filter("level = 0").select("src", "dst")


def _shards(db: DataFrame, shards: int) -> DataFrame:
    return db.select(F.pmod(F.xxhash64("id"), F.lit(shards)).cast("int").alias("shard"), F.col("id").cast("long").alias("id"), "vec")


def shards_for(rows: int) -> int:
    return max(1, -(-rows // SHARD_ROWS))


def friends(edges: DataFrame, codec: str, universe: int) -> DataFrame:
    """Friend lists, one compressed row per source; of a layered graph those of the base."""
    return frames.encode_lists(base(edges) if "level" in edges.columns else edges, "src", "dst", codec, universe)


def walk(x: np.ndarray, read, q: np.ndarray, k: int, explore: int, start: int) -> list[tuple[float, int]]:
    """Best-first search with a beam of `explore`; read(i) gives the out-neighbours of row i."""
    d0 = float(((x[start] - q) ** 2).sum())
    front, best, seen = [(d0, start)], [(-d0, -start)], {start}
    while front:
        d, i = heapq.heappop(front)
        if len(best) >= explore and d > -best[0][0]:
            break
        new = [j for j in read(i) if j not in seen]
        if not new:
            continue
        seen.update(new)
        dist = ((x[new] - q) ** 2).sum(1)
        for dj, j in zip(dist.tolist(), new, strict=True):
            if len(best) < explore or dj < -best[0][0]:
                heapq.heappush(front, (dj, j))
                heapq.heappush(best, (-dj, -j))
                if len(best) > explore:
                    heapq.heappop(best)
    return sorted((-d, -i) for d, i in best)[:k]


def descend(x: np.ndarray, upper: dict[tuple[int, int], list[int]], q: np.ndarray, start: int, top: int) -> int:
    """Where a search of the base begins: from the top level down, to the nearest row that greedy steps reach."""
    at = start
    for level in range(top, 0, -1):
        while True:
            near = [at, *upper.get((level, at), ())]
            best = near[int(((x[near] - q) ** 2).sum(1).argmin())]
            if best == at:
                break
            at = best
    return at


def find(q: DataFrame, db: DataFrame, lists: DataFrame, k: int, explore: int = 16, shards: int | None = None, upper: DataFrame | None = None) -> DataFrame:
    """qid, rank, id, dist by beam search in each shard over compressed friend lists, decoded once per batch of queries.

    upper holds a layered graph's edges, whose levels over the base lead each query to where it begins; else it begins at the medoid.
    """
    spark, out = db.sparkSession, None
    arrow.importable(spark)
    nodes = _shards(db, shards or shards_for(db.count())).join(lists.filter("seg = 0").select(F.col("k").alias("id"), "n", "codec", "universe", "payload"), "id", "left")
    if upper is None:
        nodes = nodes.withColumn("up", F.array().cast("array<struct<level: int, dst: bigint>>"))
    else:  # a row's links over the base are some levels' m each
        up = upper.filter("level > 0").groupBy(F.col("src").alias("id")).agg(F.collect_list(F.struct("level", "dst")).alias("up"))
        nodes = nodes.join(up, "id", "left")
    for qid, qmat in search.query_blocks(q):
        got = nodes.groupBy("shard").applyInArrow(_searcher(spark.sparkContext.broadcast((qid, qmat)), k, explore), "qid long, id long, dist double")
        out = got if out is None else out.union(got)
    return search.ranked(out, k, ["id"]).select("qid", "rank", "id", "dist") if out is not None else search.empty(spark)


def find_by_join(q: DataFrame, db: DataFrame, lists: DataFrame, entry: DataFrame, k: int, explore: int = 16) -> DataFrame:
    """qid, rank, id, dist by beam search over one graph of any size: a round is a join of all queries' frontiers with lists and vectors.

    entry (id) are the rows where each query begins. A round opens what of a query's best `explore` rows isn't opened yet, decodes only
    the lists of these rows, and ends where no query has such a row left. Rows met are written between rounds.
    """
    rows, ask = db.select(F.col("id").cast("long").alias("id"), "vec"), q.select(F.col("qid").cast("long").alias("qid"), "qvec")
    d = F.aggregate(F.zip_with("qvec", "vec", lambda a, b: (a.cast("double") - b.cast("double")) * (a.cast("double") - b.cast("double"))), F.lit(0.0), lambda s, x: s + x)
    far = lambda pairs: pairs.join(ask, "qid").join(rows, "id").select("qid", "id", d.alias("dist"))
    first = far(ask.select("qid").crossJoin(F.broadcast(entry.select("id"))))  # a few rows
    seen = arrow.stage(first.withColumn("opened", F.lit(False)), "beam")
    best = Window.partitionBy("qid").orderBy("dist", "id")
    while True:
        beam = seen.withColumn("rank", F.row_number().over(best)).filter(F.col("rank") <= max(explore, k))
        front = arrow.stage(beam.filter(~F.col("opened")).select("qid", "id"), "frontier")
        if front.isEmpty():
            out = beam.filter(F.col("rank") <= k).select("qid", "rank", "id", "dist")
            return out
        opened = frames.decode_lists(lists.join(front.select(F.col("id").alias("k")).distinct(), "k", "left_semi"))
        met = front.join(opened.select(F.col("k").alias("id"), F.col("id").alias("to")), "id").select("qid", F.col("to").alias("id")).distinct()
        new = far(met.join(seen.select("qid", "id"), ["qid", "id"], "left_anti")).withColumn("opened", F.lit(False))
        done = seen.join(front.withColumn("now", F.lit(True)), ["qid", "id"], "left").select("qid", "id", "dist", (F.col("opened") | F.coalesce("now", F.lit(False))).alias("opened"))
        seen = arrow.stage(done.union(new), "beam")


def _opened(t: pa.Table, ids: np.ndarray) -> list[list[int]]:
    """Out-neighbours of a shard's rows, all lists decoded in lockstep."""
    n, payload, codec, universe = (t[c].to_pylist() for c in ("n", "payload", "codec", "universe"))
    out: list[list[int]] = [[] for _ in ids]
    have = [j for j in range(len(ids)) if n[j]]
    for kind in sorted({(codec[j], universe[j]) for j in have}):
        mine = [j for j in have if (codec[j], universe[j]) == kind]
        size = np.array([n[j] for j in mine])
        got = listcodecs.codec(*kind).decode([payload[j] for j in mine], size)
        at = np.searchsorted(ids, got)
        fits = (at < len(ids)) & (ids[np.minimum(at, len(ids) - 1)] == got)
        for j, x, f in zip(mine, np.split(at, np.cumsum(size)[:-1]), np.split(fits, np.cumsum(size)[:-1]), strict=True):
            out[j] = x[f].tolist()
    return out


def _searcher(held, k: int, explore: int):
    def run(batch: pa.Table) -> pa.Table:
        t = batch.sort_by("id").combine_chunks()
        ids, x = t["id"].to_numpy(), arrow.vectors(t["vec"].chunk(0)).astype(np.float64)
        place = {int(i): j for j, i in enumerate(ids.tolist())}
        links: dict[tuple[int, int], list[int]] = {}
        for j, up in enumerate(t["up"].to_pylist()):
            for e in up or ():
                if e["dst"] in place:
                    links.setdefault((e["level"], j), []).append(place[e["dst"]])
        opened = _opened(t, ids)
        top, start = max(((level, -j) for level, j in links), default=(0, 0))
        middle = medoid(x)
        rows = []
        for i, v in zip(*held.value, strict=True):
            begin = descend(x, links, v, -start, top) if links else middle
            rows += [(int(i), int(ids[j]), d) for d, j in walk(x, opened.__getitem__, v, k, max(explore, k), begin)]
        return pa.table({"qid": [r[0] for r in rows], "id": [r[1] for r in rows], "dist": [r[2] for r in rows]}, schema=pa.schema([("qid", pa.int64()), ("id", pa.int64()), ("dist", pa.float64())]))

    return run
