"""Whole graphs as one stream per shard: random-edge coding, and its hypergraph form.

The order of edges is latent: an edge is drawn by the state, taken out, and its vertices are coded under an urn in which a vertex weighs its
degree so far plus a bias. The encoder runs the urn backwards from the full degrees, so the decoder can run it forwards from
nothing. Shards are ranges of source vertices with about as many edges each; each is coded by one task. A shard's sources are
drawn from its range alone, which gives back what the shards' separate orders of edges cost.
"""

from __future__ import annotations

import bisect
import math
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.ans import PRECISION, ExactState, WordState
from ..functions.models import Urn
from ..functions.order_stats import Fenwick, SortedRanks
from . import arrow, edgelanes


def _put(state, start: int, freq: int, total: int) -> None:
    if isinstance(state, ExactState):
        state.push(start, freq, total)
        return
    a = (start << PRECISION) // total
    b = ((start + freq) << PRECISION) // total
    if b - a < 1 << PRECISION:
        state.push(a, b - a, PRECISION)


def _slot(state, total: int) -> int:
    return state.slot(total) if isinstance(state, ExactState) else ((state.slot(PRECISION) + 1) * total - 1) >> PRECISION


def _drop(state, start: int, freq: int, total: int) -> None:
    if isinstance(state, ExactState):
        state.pop(start, freq, total)
        return
    a = (start << PRECISION) // total
    b = ((start + freq) << PRECISION) // total
    if b - a < 1 << PRECISION:
        state.pop(a, b - a, PRECISION)


def _take(state, model) -> int:
    total = model.total
    symbol, start, freq = model.find(_slot(state, total))
    _drop(state, start, freq, total)
    return symbol


class _Left:
    """Sorted items still to be coded; equal ones (parallel edges) are drawn as one value with their number as weight."""

    def __init__(self, items: list):
        self.items, self.tree = items, Fenwick(len(items), ones=True)
        self.first = list(range(len(items)))
        for i in range(1, len(items)):
            if items[i] == items[i - 1]:
                self.first[i] = self.first[i - 1]
        self.last = list(range(1, len(items) + 1))
        for i in range(len(items) - 2, -1, -1):
            if items[i] == items[i + 1]:
                self.last[i] = self.last[i + 1]

    def draw(self, state, left: int):
        at = self.tree.find(_slot(state, left))
        start = self.tree.below(self.first[at])
        _drop(state, start, self.tree.below(self.last[at]) - start, left)
        self.tree.add(at, -1)
        return self.items[at]


def _keep(state, got: SortedRanks, item, above) -> None:
    """The decoder's counterpart: adds an item and gives its draw back; above is the least item over it."""
    got.insert(item)
    start = got.rank(item)
    _put(state, start, got.rank(above) - start, got.size)


#: Numbers above which a list is held as machine words instead of Python's own.
PLAIN = 1 << 22


def _cells(a: np.ndarray):
    """Numbers to be read and changed one at a time: a list is faster, a view of the array smaller."""
    return a.tolist() if len(a) <= PLAIN else memoryview(a)


def _ones(n: int):
    """A Fenwick tree of n places that hold one each."""
    i = np.arange(n + 1, dtype=np.int32 if n < 1 << 31 else np.int64)
    return _cells(i & -i)


def _tree(count: np.ndarray):
    """A Fenwick tree of counts."""
    n = len(count)
    total, i = np.r_[0, np.cumsum(count)], np.arange(n + 1)
    return _cells(total - total[i - (i & -i)])


def _keys(edges, vertices: int, directed: bool) -> np.ndarray:
    """Edges as sorted numbers, the source's place times the vertices plus the other end."""
    a = np.asarray(edges, np.int64).reshape(-1, 2)
    src, dst = (a[:, 0], a[:, 1]) if directed else (a.min(1), a.max(1))
    return np.sort(src * vertices + dst)


def encode_edges(state, edges: list[tuple[int, int]], vertices: int, bias: int = 1, directed: bool = True, model: str = "urn", sources: tuple[int, int] | None = None) -> None:
    """sources, a range that holds every source, is known to the decoder (directed edges only)."""
    encode_keys(state, _keys(edges, vertices, directed), vertices, bias, directed, model, sources)


def encode_keys(state, keys: np.ndarray, vertices: int, bias: int = 1, directed: bool = True, model: str = "urn", sources: tuple[int, int] | None = None) -> None:
    """`encode_edges` of sorted numbers src * vertices + dst; every step walks a tree once."""
    lo, hi = sources or (0, vertices)
    n, learns = len(keys), model == "urn"
    src, dst = keys // vertices, keys % vertices
    count = np.zeros(vertices, np.int64)
    if learns:
        count += np.bincount(src, minlength=vertices) + np.bincount(dst, minlength=vertices)
    total, low, inside = vertices * bias + int(count.sum()), lo * bias + int(count[:lo].sum()), (hi - lo) * bias + int(count[lo:hi].sum())
    urn, count = _tree(count), _cells(count)
    repeats = bool((keys[1:] == keys[:-1]).any())
    first, last = (_cells(np.searchsorted(keys, keys, side)) for side in ("left", "right")) if repeats else (None, None)
    del src, dst
    keys, rest, top = _cells(keys), _ones(n), 1 << max(0, n.bit_length() - 1)

    def below(tree, at: int) -> int:
        out = 0
        while at:
            out += tree[at]
            at &= at - 1
        return out

    for left in range(n, 0, -1):
        slot = left_slot = _slot(state, left)
        if repeats:  # equal edges are drawn as one value with their number as weight
            at, step = 0, top
            while step:
                to = at + step
                if to <= n and rest[to] <= slot:
                    slot -= rest[to]
                    at = to
                step >>= 1
            start = below(rest, first[at])
            _drop(state, start, below(rest, last[at]) - start, left)
            to = at + 1
            while to <= n:
                rest[to] -= 1
                to += to & -to
        else:  # found and taken out on one way down
            at, step = 0, top
            while step:
                to = at + step
                if to <= n:
                    share = rest[to]
                    if share <= slot:
                        slot -= share
                        at = to
                    else:
                        rest[to] = share - 1
                step >>= 1
            _drop(state, left_slot, 1, left)
        x, y = divmod(keys[at], vertices)
        if not directed and x != y and state.pop_uniform(2):
            x, y = y, x
        for v, is_source in ((y, False), (x, True)):  # the decoder reads the source first
            if learns:
                count[v] -= 1
                total -= 1
                if v < lo:
                    low -= 1
                elif v < hi:
                    inside -= 1
                to = v + 1
                while to <= vertices:
                    urn[to] -= 1
                    to += to & -to
                start, to = v * bias, v
                while to:
                    start += urn[to]
                    to &= to - 1
            else:
                start = v * bias
            if is_source:
                _put(state, start - low, count[v] + bias, inside)
            else:
                _put(state, start, count[v] + bias, total)


def decode_edges(state, count: int, vertices: int, bias: int = 1, directed: bool = True, model: str = "urn", sources: tuple[int, int] | None = None) -> list[tuple[int, int]]:
    return [(int(a), int(b)) for part in decode_parts(state, count, vertices, bias, directed, model, sources) for a, b in zip(*part, strict=True)]


#: Edges told at a time, about.
TOLD = 1 << 17


def decode_parts(state, count: int, vertices: int, bias: int = 1, directed: bool = True, model: str = "urn", sources: tuple[int, int] | None = None) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Sorted edges as arrays of sources and other ends, some at a time; a source's ends stand in an array of their own."""
    lo, hi = sources or (0, vertices)
    learns = model == "urn"
    total, low, inside = vertices * bias, lo * bias, (hi - lo) * bias
    urn, seen, top = _cells(np.zeros(vertices + 1, np.int64)), _cells(np.zeros(vertices, np.int64)), 1 << max(0, vertices.bit_length() - 1)
    ends: dict[int, array] = {}
    width, got = hi - lo, _cells(np.zeros(hi - lo + 1, np.int64))
    for size in range(1, count + 1):
        edge = []
        for is_source in (True, False):
            of, start = (inside, low) if is_source else (total, 0)
            slot = whole = _slot(state, of) + start
            v, step = 0, top
            while step:
                to = v + step
                if to <= vertices:
                    share = urn[to]
                    weight = share + step * bias
                    if weight <= slot:
                        slot -= weight
                        v = to
                    elif learns:  # the places whose share holds the vertex gain it on the way down
                        urn[to] = share + 1
                step >>= 1
            _drop(state, whole - slot - start, seen[v] + bias, of)
            if learns:
                seen[v] += 1
                total += 1
                if v < lo:
                    low += 1
                elif v < hi:
                    inside += 1
            edge.append(v)
        x, y = edge
        if not directed and x != y:
            state.push_uniform(int(x > y), 2)
            if x > y:
                x, y = y, x
        mine = ends.get(x)
        if mine is None:
            mine = ends[x] = array("q")
        at = bisect.bisect_left(mine, y)
        same = bisect.bisect_right(mine, y, at) - at + 1
        mine.insert(at, y)
        start, to = at, x - lo
        while to:
            start += got[to]
            to &= to - 1
        to = x - lo + 1
        while to <= width:
            got[to] += 1
            to += to & -to
        _put(state, start, same, size)  # gives the draw back
    some: list[int] = []
    held = 0
    for x in sorted(ends):
        some.append(x)
        held += len(ends[x])
        if held >= TOLD:
            yield _told(some, ends)
            some, held = [], 0
    if some:
        yield _told(some, ends)


def _told(some: list[int], ends: dict[int, array]) -> tuple[np.ndarray, np.ndarray]:
    return np.repeat(np.array(some, np.int64), [len(ends[x]) for x in some]), np.concatenate([np.frombuffer(ends[x], np.int64) for x in some])


def encode_hyper(state, edges: list[tuple[int, ...]], vertices: int, most: int, bias: int = 1) -> None:
    """Hyperedges as sorted tuples of distinct vertices, an unordered collection of unordered edges; arity under a uniform model."""
    left, urn = sorted(tuple(sorted(e)) for e in edges), Urn(vertices, bias)
    for e in left:
        for v in e:
            urn.add(v)
    some = _Left(left)
    for n in range(len(left), 0, -1):
        drawn = some.draw(state, n)
        rest = list(drawn)
        for i in range(len(rest), 0, -1):  # members in random order
            v = rest.pop(state.pop_uniform(i))
            urn.add(v, -1)
            _put(state, *urn.span(v), urn.total)
        state.push_uniform(len(drawn), most + 1)


def decode_hyper(state, count: int, vertices: int, most: int, bias: int = 1) -> list[tuple[int, ...]]:
    urn, got = Urn(vertices, bias), SortedRanks()
    for _ in range(count):
        edge = SortedRanks()
        for i in range(1, state.pop_uniform(most + 1) + 1):
            v = _take(state, urn)
            urn.add(v)
            rank = edge.rank(v)
            edge.insert(v)
            state.push_uniform(rank, i)
        e = tuple(edge)
        _keep(state, got, e, (*e, -1))  # the least tuple over e
    return list(got)


BLOB = "shard int, n_vertices long, n_edges long, codec string, payload binary, bits long"


#: Edges of a shard, about: what one task codes one after the other.
SHARD_EDGES = 1 << 17

#: Edges from which a stream's states step together, many at a time; parallel edges are always coded by one state.
LANED = 1 << 20


def bounds(edges: DataFrame, vertices: int, shards: int | None) -> list[int]:
    """First source of each shard, and the number of vertices.

    One shard if one is asked. Else as many as keep each near `SHARD_EDGES`, and no fewer than asked: what a task holds and codes one after
    the other stays the same as a graph grows.
    """
    if shards != 1:
        shards = max(shards or 1, -(-edges.count() // SHARD_EDGES))
    if shards == 1:
        return [0, vertices]
    cut = edges.select(F.col("src").cast("double").alias("src")).approxQuantile("src", [k / shards for k in range(1, shards)], 1 / (20 * shards))
    return [0, *sorted({int(c) for c in cut} - {0}), vertices]


def _sharded(edges: DataFrame, first: list[int]) -> DataFrame:
    """shard, src, dst, dealt by shard: its range of sources, found among every so many bounds and then between two of these."""
    cuts, src = first[1:-1], F.col("src").cast("long")
    number = F.lit(0)
    if cuts:
        step = math.isqrt(len(cuts)) + 1
        under = lambda a: F.size(F.filter(a, lambda x: x <= src))
        longs = lambda some: F.array(*(F.lit(c).cast("long") for c in some))
        at = F.greatest(under(longs(cuts[::step])) - 1, F.lit(0)) * step
        number = at + under(F.slice(longs(cuts), at + 1, F.lit(step)))
    rows = edges.select(number.cast("int").alias("shard"), src.alias("src"), F.col("dst").cast("long").alias("dst"))
    return rows.repartition(len(cuts) + 1, "shard")


def encode(edges: DataFrame, n_vertices: int, bias: int = 1, directed: bool = True, shards: int | None = None, model: str = "urn") -> DataFrame:
    """One blob per shard of sources; edges (src, dst), each once (twice is coded twice). Undirected edges go into one shard unless asked otherwise."""
    arrow.importable(edges.sparkSession)
    first = bounds(edges, n_vertices, shards if directed else shards or 1)
    one = len(first) == 2
    ordered = directed and not one

    def blob(k: int, parts: list[np.ndarray]) -> pa.RecordBatch:
        keys = np.concatenate(parts)
        parts.clear()
        if not ordered:
            keys.sort()
        lo, hi = (first[k], first[k + 1]) if directed else (0, n_vertices)
        name, how = "rec" if directed else "rec_undirected", (n_vertices, bias, directed, model, (lo, hi) if directed else None)
        if len(keys) >= LANED and not (keys[1:] == keys[:-1]).any():
            name += "_lanes"
            payload, bits = edgelanes.encode(keys, *how)
        else:
            state = WordState()
            encode_keys(state, keys, *how)
            payload, bits = state.to_bytes(), state.bits
        return pa.RecordBatch.from_pylist([{"shard": k, "n_vertices": n_vertices, "n_edges": len(keys), "codec": f"{name}:{model}:{bias}:{lo}:{hi}", "payload": payload, "bits": bits}], schema=_BLOB)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        """Rows arrive batch by batch, sorted by shard; of a shard, one number an edge is held."""
        now, parts = -1, []
        for b in batches:
            src, dst = b.column(1).to_numpy(), b.column(2).to_numpy()
            key = src * n_vertices + dst if directed else np.minimum(src, dst) * n_vertices + np.maximum(src, dst)
            at = arrow.edges([b.column(0)])
            for x, y in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
                k = b.column(0)[x].as_py()
                if k != now and parts:
                    yield blob(now, parts)
                    parts = []
                now = k
                parts.append(key[x:y].copy())
        if parts:
            yield blob(now, parts)

    rows = _sharded(edges, first)
    return (rows if one else rows.sortWithinPartitions("shard", "src", "dst")).mapInArrow(run, BLOB)  # one shard's numbers alone are sorted


_BLOB = pa.schema([("shard", pa.int32()), ("n_vertices", pa.int64()), ("n_edges", pa.int64()), ("codec", pa.string()), ("payload", pa.binary()), ("bits", pa.int64())])


def decode(blobs: DataFrame) -> DataFrame:
    """(src, dst) of blobs; undirected edges with the smaller vertex first."""
    arrow.importable(blobs.sparkSession)

    def run(batches):
        for b in batches:
            for r in b.to_pylist():
                name, model, bias, lo, hi = r["codec"].split(":")
                directed = not name.startswith("rec_undirected")
                how = (r["n_edges"], r["n_vertices"], int(bias), directed, model, (int(lo), int(hi)) if directed else None)
                if name.endswith("_lanes"):
                    parts = edgelanes.told(edgelanes.decode(r["payload"], *how), r["n_vertices"], TOLD)
                else:
                    parts = decode_parts(WordState.from_bytes(r["payload"]), *how)
                for src, dst in parts:
                    yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst)], ["src", "dst"])

    return blobs.mapInArrow(run, "src long, dst long")


def encode_hypergraph(df: DataFrame, edge: str, node: str, n_vertices: int, shards: int = 1) -> DataFrame:
    """Blobs of hyperedges, the node sets of each edge key; the keys themselves aren't kept."""
    arrow.importable(df.sparkSession)
    sets = df.groupBy(F.col(edge).alias("e")).agg(F.array_sort(F.collect_set(F.col(node).cast("long"))).alias("nodes"))
    rows = sets.select(F.pmod(F.xxhash64("e"), F.lit(shards)).cast("int").alias("shard"), "nodes")

    def run(key: tuple, t: pa.Table) -> pa.Table:
        state, sets = WordState(), [tuple(x) for x in t["nodes"].to_pylist()]
        most = max(map(len, sets), default=0)
        encode_hyper(state, sets, n_vertices, most)
        return pa.Table.from_pylist([{"shard": key[0].as_py(), "n_vertices": n_vertices, "n_edges": len(sets), "codec": f"hyper:{most}", "payload": state.to_bytes(), "bits": state.bits}], schema=_BLOB)

    return rows.groupBy("shard").applyInArrow(run, BLOB)


def decode_hypergraph(blobs: DataFrame) -> DataFrame:
    arrow.importable(blobs.sparkSession)

    def run(batches):
        for b in batches:
            for r in b.to_pylist():
                got = decode_hyper(WordState.from_bytes(r["payload"]), r["n_edges"], r["n_vertices"], int(r["codec"].split(":")[1]))
                yield pa.RecordBatch.from_arrays([pa.array([list(e) for e in got], pa.list_(pa.int64()))], ["nodes"])

    return blobs.mapInArrow(run, "nodes array<long>")
