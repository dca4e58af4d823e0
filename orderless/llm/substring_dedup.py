"""Removal of repeated passages: every byte covered by a string of `WINDOW` bytes that a document with a smaller id has too.

Each window of 50 bytes is found by its anchor, the least-hashed string of `ANCHOR` bytes in it; equal windows have equal anchors at equal
places, so only what shares an anchor is compared. No removal rests on a hash alone: every one is checked on the bytes.

1. Each document's anchors, with a hash of all bytes their windows span, are dealt by anchor. Spans that agree stand side by side in the
   order of (anchor, span, document); the task that has both texts compares their bytes at once, and sends only the smallest
   document of a span on.
2. Where spans of documents of different tasks agree, each document's predecessor in that order is asked for its bytes, ranges that touch
   as one. The bytes go to the document, which compares them with its own when it is cut. Predecessors form a chain to the smallest
   document, so no document, however often copied, is asked by many. If any bytes differed, a hash has collided: all is then done
   again under another hash.
3. Where an anchor is shared but spans differ, that is at the edges of repeated passages, the spans' bytes are fetched and
   their suffixes from the anchor on are sorted: a merge sort whose comparisons find the common extension of two
   suffixes by binary search over prefix polynomial hashes. Runs of the sorted suffixes that share enough to the right are
   parted by what stands to the left. Neighbours in the order and every match are checked on the bytes;
   were a hash to collide, the batch would be sorted by its bytes instead.
4. An anchor with more than `HOT` different spans is not sorted in one task: its windows become rows, sorted by their bytes and document
   over ranges that may part even one window's rows, with a running least document handed on from range to range.
5. Ranges are gathered per document and cut out.

Defined results: a null text is empty. Rows with equal ids remove nothing from each other; a null id counts as the largest.
Texts shorter than a window keep everything. Documents of any length are handled whole.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

WINDOW, ANCHOR = 50, 20
SPAN = WINDOW - ANCHOR + 1
#: Anchors a task gathers before it sends them.
FLUSH = 400_000
#: Different spans of one anchor that are sorted in one task.
HOT = 1024
#: Bytes of text per bucket of anchors.
BUCKET_BYTES = 64 << 20
#: Bytes of a text whose windows are hashed at a time.
PART = 1 << 22
#: Bits kept of a span's hash, beside the 64 of its anchor's.
SPAN_BITS = 48
_MOST = np.uint64(0xFFFFFFFFFFFFFFFF)


def base_of(seed: int) -> int:
    """The odd base of the polynomial hash at a trial."""
    return (common.BASE + 2 * seed * 0x2545F4914F6CDD1D) & 0xFFFFFFFFFFFFFFFF


def anchors(data: np.ndarray, off: np.ndarray, seed: int = 0, bits: int = SPAN_BITS) -> dict[str, np.ndarray]:
    """Anchors of concatenated texts: row, place in the text, first and last window start (as distances back), anchor and span hashes."""
    n, none = len(data), np.zeros(0, np.int64)
    starts = np.arange(n)
    end = np.repeat(off[1:], np.diff(off))
    valid = starts[starts + WINDOW <= end]
    if not len(valid):
        return {k: none for k in ("row", "at", "back", "ahead")} | {"h": none.astype(np.uint64), "x": none.astype(np.uint64)}
    base = base_of(seed)
    p = common.prefix_hash(data, base)
    whole = np.flatnonzero(starts + ANCHOR <= end)
    g = np.full(n, _MOST)
    g[whole] = common.mix((p[whole + ANCHOR] - p[whole]) * common.powers(n + 1, common.inverse(base))[whole])
    # the least of the next SPAN hashes and its place, the leftmost of equals, by doubling
    least, where = g.copy(), np.arange(n, dtype=np.int32 if n < 1 << 31 else np.int64)
    width = 1
    while width < SPAN:
        step = min(width, SPAN - width)
        later = least[step:] < least[:-step]
        where[:-step] = np.where(later, where[step:], where[:-step])
        least[:-step] = np.where(later, least[step:], least[:-step])
        width += step
    place = where[valid].astype(np.int64)
    new = np.flatnonzero(np.r_[True, (place[1:] != place[:-1]) | (valid[1:] != valid[:-1] + 1)])
    lo, hi, at = valid[new], valid[np.r_[new[1:], len(valid)] - 1], place[new]
    row = np.searchsorted(off, at, side="right") - 1
    # the least of many hashes is a small number: h is scrambled anew, so that its top bits deal evenly
    x = common.span_hash(p, lo, hi + WINDOW, base) ^ common.mix((at - lo).astype(np.uint64))
    return {"row": row, "at": at - off[row], "back": at - lo, "ahead": at - hi, "h": common.mix(g[at] + np.uint64(common.BASE)), "x": x & np.uint64((1 << bits) - 1)}


def anchors_in_parts(data: np.ndarray, off: np.ndarray, seed: int = 0, bits: int = SPAN_BITS, part: int = PART) -> dict[str, np.ndarray]:
    """`anchors`, of a text longer than a part by the parts that its windows begin in, so that memory doesn't grow with a text.

    An anchor whose windows begin in two parts gives two spans; these differ from an undivided one, so they are looked at closely.
    """
    if len(data) <= part:
        return anchors(data, off, seed, bits)
    some = []
    for row, (a, b) in enumerate(zip(off[:-1].tolist(), off[1:].tolist(), strict=True)):
        for lo in range(a, max(a + 1, b - WINDOW + 1), part):
            piece = data[lo : min(b, lo + part + WINDOW - 1)]
            got = anchors(piece, np.array([0, len(piece)]), seed, bits)
            some.append(got | {"row": got["row"] + row, "at": got["at"] + lo - a})
    return {k: np.concatenate([x[k] for x in some]) for k in some[0]}


def same_bytes(data: np.ndarray, a: np.ndarray, b: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Whether the `size` bytes (at most a span's) at a and at b agree."""
    out = np.zeros(len(a), bool)
    step, top = np.arange(WINDOW + SPAN - 1), len(data) - 1
    for lo in range(0, len(a), 1 << 15):
        x, y, n = (v[lo : lo + (1 << 15), None] for v in (a, b, size))
        differ = (data[np.minimum(x + step, top)] != data[np.minimum(y + step, top)]) & (step < n)
        out[lo : lo + (1 << 15)] = ~differ.any(1)
    return out


_FIELDS = (("h", "<u8"), ("x4", "<u4"), ("x2", "<u2"), ("doc", "<u4"), ("at", "<u4"), ("back", "u1"), ("ahead", "u1"))
_CODEC = pa.Codec("zstd", compression_level=1)


def _planes(a: np.ndarray) -> bytes:
    """Bytes of one significance together, which compress better."""
    return np.ascontiguousarray(a).view(np.uint8).reshape(len(a), -1).T.tobytes()


def _pack(rows: dict[str, np.ndarray], table: np.ndarray) -> bytes:
    """Rows with numbered documents, and the table (uid, ord) of those met, as one compressed string."""
    met, doc = np.unique(rows["doc"], return_inverse=True)
    rows = rows | {"doc": doc, "x4": rows["x"] & np.uint64(0xFFFFFFFF), "x2": rows["x"] >> np.uint64(32)}
    body = b"".join(_planes(rows[k].astype(t)) for k, t in _FIELDS) + table[met].astype("<i8").tobytes()
    return np.array([len(doc), len(met), len(body)], "<i8").tobytes() + _CODEC.compress(body, asbytes=True)


def _unpack(blob: bytes) -> dict[str, np.ndarray]:
    n, docs, size = np.frombuffer(blob, "<i8", 3).tolist()
    body, at, out = _CODEC.decompress(blob[24:], size, asbytes=True), 0, {}
    for k, t in _FIELDS:
        w = np.dtype(t).itemsize
        out[k] = np.ascontiguousarray(np.frombuffer(body, np.uint8, n * w, at).reshape(w, n).T).view(t).ravel()
        at += n * w
    table = np.frombuffer(body, "<i8", docs * 2, at).reshape(docs, 2)
    x = out.pop("x4").astype(np.uint64) | (out.pop("x2").astype(np.uint64) << np.uint64(32))
    doc = out.pop("doc")
    return out | {"x": x, "uid": table[doc, 0], "ord": table[doc, 1]}


def _edges(*keys: np.ndarray) -> np.ndarray:
    """True where sorted rows begin a new group."""
    new = np.ones(len(keys[0]), bool)
    new[1:] = False
    for k in keys:
        new[1:] |= k[1:] != k[:-1]
    return new


def _by_doc(uid: np.ndarray, *values: np.ndarray) -> Iterator[tuple[int, bytes]]:
    """Each document's values, 32-bit, side by side."""
    if not len(uid):
        return
    order = np.argsort(uid, kind="stable")
    flat = np.stack([v[order] for v in values], 1).astype("<i4")
    cut = np.flatnonzero(_edges(uid[order]))
    for a, b in zip(cut.tolist(), np.r_[cut[1:], len(uid)].tolist(), strict=True):
        yield int(uid[order[a]]), flat[a:b].tobytes()


def merged(start: np.ndarray, end: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Union of ranges as maximal runs."""
    if not len(start):
        return start, end
    order = np.argsort(start, kind="stable")
    start, end = start[order], np.maximum.accumulate(end[order])
    new = np.r_[True, start[1:] > end[:-1]]
    return start[new], end[np.r_[np.flatnonzero(new)[1:] - 1, len(end) - 1]]


def _batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], f.type) for i, f in enumerate(schema)], schema=schema)


_DEALT = pa.schema([("bucket", pa.int32()), ("kind", pa.int32()), ("uid", pa.int64()), ("blob", pa.binary())])
_TOLD = pa.schema([("kind", pa.int32()), ("uid", pa.int64()), ("blob", pa.binary())])
#: kinds of rows: anchors to compare, ranges to cut, spans to look at closely, ranges whose bytes another document asks for, a collision
SENT, CUT, LOOK, ASK, COLLIDED = 0, 1, 2, 3, 4
#: kinds of fetched rows: a span of a shared anchor, a window of a hot one, bytes that a document has asked for
NEAR, WINDOWED, PROOF = 0, 1, 2


def deal(buckets: int, seed: int = 0, bits: int = SPAN_BITS):
    """A task function: texts to anchors by bucket; spans that a smaller document of the same task has, byte by byte, become ranges at once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[dict] = []
        tables: list[np.ndarray] = []
        texts: list[np.ndarray] = []
        count = docs = size = 0

        def flush() -> pa.RecordBatch:
            rows = {k: np.concatenate([a[k] for a in held]) for k in held[0]}
            table, data = np.concatenate(tables), np.concatenate(texts)
            order = np.lexsort((table[rows["doc"], 1], rows["x"], rows["h"]))
            rows = {k: v[order] for k, v in rows.items()}
            first = rows.pop("base") + rows["at"] - rows["back"]  # where each span begins in data
            group = _edges(rows["h"], rows["x"])
            head = np.flatnonzero(group)[np.cumsum(group) - 1]
            over = table[rows["doc"], 1] > table[rows["doc"][head], 1]
            out = []
            if not same_bytes(data, first[over], first[head[over]], (rows["back"] - rows["ahead"])[over] + WINDOW).all():
                out.append((0, COLLIDED, 0, b""))
            for uid, blob in _by_doc(table[rows["doc"][over], 0], (rows["at"] - rows["back"])[over], (rows["at"] - rows["ahead"] + WINDOW)[over]):
                out.append((uid % buckets, CUT, uid, blob))
            rows = {k: v[~over] for k, v in rows.items()}
            to = (((rows["h"] >> np.uint64(40)) * np.uint64(buckets)) >> np.uint64(24)).astype(np.int64)
            cut = np.searchsorted(to, np.arange(buckets + 1))
            for b in np.flatnonzero(np.diff(cut)).tolist():
                out.append((b, SENT, 0, _pack({k: v[cut[b] : cut[b + 1]] for k, v in rows.items()}, table)))
            return _batch(out, _DEALT)

        for whole in batches:
            for b in common.slices(whole, 2):
                data, off = common.raw(b.column(2))
                a = anchors_in_parts(data, off, seed, bits)
                a["base"] = off[a["row"]] + size
                a["doc"] = a.pop("row") + docs
                held.append(a)
                texts.append(data)
                tables.append(np.stack([b.column(0).to_numpy(), b.column(1).to_numpy()], 1))
                docs += b.num_rows
                size += len(data)
                count += len(a["doc"])
                if count >= FLUSH or size >= FLUSH * SPAN:
                    yield flush()
                    held, tables, texts, count, docs, size = [], [], [], 0, 0, 0
        if held:
            yield flush()

    return run


def _halves(v: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """64-bit words as two 32-bit ones."""
    v = np.ascontiguousarray(v).view(np.uint64)
    return (v & np.uint64(0xFFFFFFFF)).astype(np.uint32).view(np.int32), (v >> np.uint64(32)).astype(np.uint32).view(np.int32)


def compare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Buckets of anchors to ranges to ask for (the next smaller document has the same span) and spans to look at (it has the anchor only)."""
    bucket, held = None, []

    def settle() -> Iterator[pa.RecordBatch]:
        if not held:
            return
        rows = {k: np.concatenate([a[k] for a in held]) for k in held[0]}
        held.clear()
        order = np.lexsort((rows["ord"], rows["x"], rows["h"]))
        rows = {k: v[order] for k, v in rows.items()}
        by_h, by_x = _edges(rows["h"]), _edges(rows["h"], rows["x"])
        least = rows["ord"][np.flatnonzero(by_x)][np.cumsum(by_x) - 1]
        over = rows["ord"] > least
        out = []
        at, back, ahead = (rows[k].astype(np.int64) for k in ("at", "back", "ahead"))
        after = np.flatnonzero(over)  # each one's predecessor stands before it, with the same span
        after = after[np.lexsort((at[after], rows["uid"][after]))]
        before = after - 1
        for uid, blob in _by_doc(rows["uid"][before], (at - back)[before], (back - ahead)[before] + WINDOW, *_halves(rows["uid"][after]), (at - back)[after]):
            out.append((ASK, uid, blob))
        number = np.cumsum(by_h) - 1
        first = np.flatnonzero(by_h)
        low, high = np.minimum.reduceat(rows["ord"], first), np.maximum.reduceat(rows["ord"], first)
        different = np.bincount(number, by_x)
        pick = ((different > 1) & (high > low))[number] & ~over
        hot = np.bincount(number[pick], minlength=len(first)) > HOT
        for uid, blob in _by_doc(rows["uid"][pick], *_halves(rows["h"][pick]), at[pick], back[pick], ahead[pick], hot[number[pick]]):
            out.append((LOOK, uid, blob))
        yield _batch(out, _TOLD)

    for b in batches:
        passed = []
        for k, kind, uid, blob in zip(*(b.column(c).to_pylist() for c in range(4)), strict=True):
            if kind != SENT:
                passed.append((kind, uid, blob))
                continue
            if k != bucket:
                yield from settle()
                bucket = k
            held.append(_unpack(blob))
        if passed:
            yield _batch(passed, _TOLD)
    yield from settle()


def fetch(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """What is asked of each document (uid, ord, text, looks, asks): spans of shared anchors, windows of hot ones, and bytes for other documents."""
    names = ["kind", "h", "ord", "uid", "at", "back", "ahead", "span"]
    for whole in batches:
        for b in common.slices(whole, 2):
            own, order = b.column(0).to_numpy(), b.column(1).to_numpy()
            out: list[list] = [[] for _ in names]

            def put(n: int, *values, out: list[list] = out) -> None:
                for o, v in zip(out[:-1], values[:-1], strict=True):
                    o.append(np.broadcast_to(v, (n,)))
                out[-1].extend(values[-1])

            for r in range(b.num_rows):
                data = b.column(2)[r].as_py().encode()
                q = np.frombuffer(b"".join(b.column(3)[r].as_py()), "<i4").reshape(-1, 6)
                hot = q[:, 5] > 0
                for at, back, ahead in q[hot, 2:5].tolist():
                    first = np.arange(at - back, at - ahead + 1)
                    put(len(first), WINDOWED, 0, order[r], own[r], first, 0, 0, [data[x : x + WINDOW] for x in first.tolist()])
                q = q[~hot]
                lo, hi = q[:, 2] - q[:, 3], q[:, 2] - q[:, 4] + WINDOW
                h = np.ascontiguousarray(q[:, :2]).view("<i8").ravel()
                put(len(q), NEAR, h, order[r], own[r], q[:, 2], q[:, 3], q[:, 4], [data[x:y] for x, y in zip(lo.tolist(), hi.tolist(), strict=True)])
                a = np.frombuffer(b"".join(b.column(4)[r].as_py()), "<i4").reshape(-1, 5)
                if len(a):  # ranges that one document asks for at one distance, joined where they touch
                    who, far = np.ascontiguousarray(a[:, 2:4]).view("<i8").ravel(), a[:, 4].astype(np.int64) - a[:, 0]
                    by = np.lexsort((a[:, 0], far, who))
                    who, far, lo, hi = who[by], far[by], a[by, 0].astype(np.int64), (a[by, 0] + a[by, 1]).astype(np.int64)
                    group = np.cumsum(_edges(who, far))
                    width = np.int64(len(data) + 1)  # groups are kept apart by shifting their ranges
                    start, end = merged(lo + group * width, hi + group * width)
                    pick = np.searchsorted(group * width + lo, start)
                    x, y = start - group[pick] * width, end - group[pick] * width
                    put(len(x), PROOF, 0, 0, who[pick], x + far[pick], 0, 0, [data[u:v] for u, v in zip(x.tolist(), y.tolist(), strict=True)])
            kinds = [np.int32, np.int64, np.int64, np.int64, np.int32, np.int32, np.int32]
            yield pa.RecordBatch.from_arrays([*[pa.array(np.concatenate(o).astype(k)) for o, k in zip(out[:-1], kinds, strict=True)], pa.array(out[-1], pa.binary())], names)


class Suffixes:
    """Suffixes of concatenated byte strings, compared through prefix hashes."""

    def __init__(self, data: np.ndarray, start: np.ndarray, end: np.ndarray):
        self.data, self.start, self.end = data, start, end
        self.prefix = common.prefix_hash(data)
        self.unshift = common.powers(len(data) + 1, common.INV)

    def hash(self, at: np.ndarray, size: np.ndarray) -> np.ndarray:
        return (self.prefix[at + size] - self.prefix[at]) * self.unshift[at]

    def extension(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Length of what suffixes i and j begin with in common, by binary search."""
        a, b = self.start[i], self.start[j]
        low, high = np.zeros(len(i), np.int64), np.minimum(self.end[i] - a, self.end[j] - b)
        while (low < high).any():
            mid = (low + high + 1) // 2
            same = self.hash(a, mid) == self.hash(b, mid)
            low, high = np.where(same, mid, low), np.where(same, high, mid - 1)
        return low

    def less(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        """Suffix i sorts before suffix j; -1 stands for one after all others."""
        out = i >= 0
        both = np.flatnonzero((i >= 0) & (j >= 0))
        x, y = i[both], j[both]
        same = self.extension(x, y)
        a, b = self.start[x] + same, self.start[y] + same
        ended, other = a >= self.end[x], b >= self.end[y]
        top = len(self.data) - 1
        byte = self.data[np.minimum(a, top)] < self.data[np.minimum(b, top)]
        out[both] = np.where(ended | other, ended & ~other, byte)
        out[j < 0] &= True
        return out

    def merge_sort(self, groups: np.ndarray) -> np.ndarray:
        """Sorts each row of a matrix of suffix numbers (a power of two wide, padded by -1), all rows in step."""
        width = 1
        rows, total = groups.shape
        while width < total:
            pair = groups.reshape(-1, 2, width)
            left, right = pair[:, 0], pair[:, 1]
            out = np.empty((len(pair), 2 * width), groups.dtype)
            line = np.arange(len(pair))[:, None]
            for own, other, strict in ((left, right, True), (right, left, False)):
                # how many of the other run come before each element: binary search in the run
                low, high = np.zeros(own.shape, np.int64), np.full(own.shape, width, np.int64)
                while (low < high).any():
                    mid = (low + high) // 2
                    probe = other[line, np.minimum(mid, width - 1)]
                    if strict:  # left element: those of the right run that are less
                        before = self.less(probe.ravel(), own.ravel()).reshape(own.shape)
                    else:  # right element: those of the left run that aren't greater
                        before = ~self.less(own.ravel(), probe.ravel()).reshape(own.shape)
                    active = low < high
                    low = np.where(active & before, mid + 1, low)
                    high = np.where(active & ~before, mid, high)
                out[line, low + np.arange(width)] = own
            groups = out.reshape(rows, total)
            width *= 2
        return groups


def sorted_suffixes(s: Suffixes, group: np.ndarray) -> np.ndarray:
    """Suffix numbers in order of (group, bytes); groups are contiguous. Groups of like size are sorted together."""
    n = len(group)
    first = np.flatnonzero(np.r_[True, group[1:] != group[:-1]])
    size = np.diff(np.r_[first, n])
    out = np.arange(n)
    width = 2
    while (size > width // 2).any():
        some = np.flatnonzero((size > width // 2) & (size <= width)) if width > 2 else np.flatnonzero(size == 2)
        if len(some):
            m = first[some][:, None] + np.arange(width)
            m = np.where(np.arange(width) < size[some][:, None], m, -1)
            done = s.merge_sort(m)
            place = first[some][:, None] + np.arange(width)
            real = np.arange(width) < size[some][:, None]
            out[place[real]] = done[real]
        width *= 2
    return out


def _bytes_at(data: np.ndarray, at: np.ndarray, size: int) -> np.ndarray:
    return data[np.minimum(at[:, None] + np.arange(size), len(data) - 1)]


def close_matches(h: np.ndarray, order: np.ndarray, back: np.ndarray, ahead: np.ndarray, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Among spans that share an anchor (h sorted): which spans have windows that a smaller ord has; their first and last distance back."""
    anchor = off[:-1] + back
    s = Suffixes(data, anchor, off[1:])
    rank = sorted_suffixes(s, h)
    n = len(h)
    same_h = h[rank[1:]] == h[rank[:-1]]
    lcp = np.zeros(n, np.int64)
    lcp[1:][same_h] = s.extension(rank[:-1][same_h], rank[1:][same_h])
    # collision check: neighbours agree on exactly lcp bytes and stand in order
    i, j = rank[:-1][same_h], rank[1:][same_h]
    if len(i):
        a, b = _bytes_at(data, anchor[i], WINDOW), _bytes_at(data, anchor[j], WINDOW)
        reach = np.minimum(off[i + 1] - anchor[i], off[j + 1] - anchor[j])
        inside = np.arange(WINDOW) < np.minimum(reach, WINDOW)[:, None]
        differ = (a != b) & inside
        true = np.where(differ.any(1), differ.argmax(1), np.minimum(reach, WINDOW))
        if (true != np.minimum(lcp[1:][same_h], WINDOW)).any():
            raw = data.tobytes()
            rank = np.array(sorted(range(n), key=lambda k: (int(h[k]), raw[anchor[k] : off[k + 1]])))
            lcp[:] = 0
            for k in range(1, n):
                if h[rank[k]] == h[rank[k - 1]]:
                    x, y = raw[anchor[rank[k]] : off[rank[k] + 1]], raw[anchor[rank[k - 1]] : off[rank[k - 1] + 1]]
                    lcp[k] = next((q for q in range(min(len(x), len(y))) if x[q] != y[q]), min(len(x), len(y)))
    hit = np.zeros((n, SPAN), bool)
    group = np.r_[True, h[rank[1:]] != h[rank[:-1]]]
    for left in range(SPAN):
        run = np.cumsum(group | (lcp < WINDOW - left)) - 1  # suffixes in a run share the right part of the window
        own = (ahead[rank] <= left) & (left <= back[rank])
        k, r = rank[own], run[own]
        if len(k) < 2:
            continue
        size = np.full(len(k), left)
        key = s.hash(anchor[k] - left, size)
        by = np.lexsort((order[k], key, r))
        k, r, key = k[by], r[by], key[by]
        new = _edges(r, key)
        head = k[np.flatnonzero(new)][np.cumsum(new) - 1]
        more = order[k] > order[head]
        k, head = k[more], head[more]
        if len(k):
            right = (_bytes_at(data, anchor[k] - left, WINDOW) == _bytes_at(data, anchor[head] - left, WINDOW)).all(1)
            if not right.all():  # a collision: compare those windows by their bytes
                raw = data.tobytes()
                least: dict[tuple[int, bytes], int] = {}
                for q in np.flatnonzero((ahead <= left) & (left <= back)).tolist():
                    w = (int(h[q]), raw[anchor[q] - left : anchor[q] - left + WINDOW])
                    least[w] = min(least.get(w, int(order[q])), int(order[q]))
                k = np.array([q for q in np.flatnonzero((ahead <= left) & (left <= back)).tolist() if order[q] > least[(int(h[q]), raw[anchor[q] - left : anchor[q] - left + WINDOW])]], np.int64)
            hit[k, left] = True
    flat = np.zeros((n, SPAN + 2), bool)
    flat[:, 1:-1] = hit
    who, first = np.nonzero(flat[:, 1:] & ~flat[:, :-1])
    _, last = np.nonzero(flat[:, :-1] & ~flat[:, 1:])
    return who, first, last - 1


def look(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Spans of shared anchors, sorted by anchor, to ranges."""
    for b in common.whole_groups(batches, 1):
        h, order, uid, at, back, ahead = (b.column(k).to_numpy() for k in range(6))
        back, ahead = back.astype(np.int64), ahead.astype(np.int64)
        data, off = common.raw(b.column(6))
        who, near, far = close_matches(h, order, back, ahead, data, off)
        out = [(CUT, u, blob) for u, blob in _by_doc(uid[who], at[who] - far, at[who] - near + WINDOW)]
        yield _batch(out, _TOLD)


#: kinds of what a range of sorted windows tells: a window to cut, one that an earlier range decides, the last window and its least document
DONE, OPEN, TAIL = 0, 1, 2


def scan_windows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Windows (w, ord, uid, at) in order of (w, ord) to those a smaller document has; only a range's first window may hang on another range."""
    names = ["kind", "w", "ord", "uid", "at"]
    first = last = None
    least = 0

    def told(kind: int, b: pa.RecordBatch) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([pa.array(np.full(b.num_rows, kind, np.int32)), *(b.column(c) for c in range(4))], names)

    for b in batches:
        if not b.num_rows:
            continue
        data, off = common.raw(b.column(0))
        w, order = data.reshape(len(off) - 1, WINDOW), b.column(1).to_numpy()
        new = np.ones(len(w), bool)
        new[1:] = (w[1:] != w[:-1]).any(1)
        head = w[0].tobytes()
        if first is None:
            first = head
        new[0] = head != last
        run = np.cumsum(new)
        lowest = np.r_[least, order[new]][run]  # the first row of a window has its least document
        over = order > lowest
        at_first = (w == np.frombuffer(first, np.uint8)).all(1)
        yield told(DONE, b.filter(pa.array(over)))
        yield told(OPEN, b.filter(pa.array(~over & at_first)))
        last, least = w[-1].tobytes(), int(lowest[-1])
    if last is not None:
        yield pa.RecordBatch.from_arrays([pa.array([TAIL], pa.int32()), pa.array([last], pa.binary()), pa.array([least]), pa.array([0]), pa.array([0], pa.int32())], names)


def hot_ranges(windows: DataFrame) -> DataFrame:
    """uid and start of each of the windows (w, ord, uid, at) that a smaller document has, in ranges that no window can overfill."""
    parts = common.parts(windows.sparkSession)
    ranges_ = windows.repartitionByRange(parts, "w", "ord").sortWithinPartitions("w", "ord")
    told = common.stage(ranges_.mapInArrow(scan_windows, "kind int, w binary, ord long, uid long, at int"), "passages-windows")
    tails = told.filter(F.col("kind") == TAIL).groupBy(F.col("w").alias("w2")).agg(F.min("ord").alias("least"))  # one row a range at most
    late = told.filter(F.col("kind") == OPEN).join(F.broadcast(tails), (F.col("w") == F.col("w2")) & (F.col("ord") > F.col("least")), "left_semi")
    return told.filter(F.col("kind") == DONE).select("uid", "at").union(late.select("uid", "at"))


def bucket_count(docs: DataFrame) -> int:
    """Buckets of anchors: as many as keep each one's share of the text bounded."""
    size = docs.agg(F.sum(F.octet_length("text").cast("long"))).first()[0] or 0
    return max(2 * common.parts(docs.sparkSession), -(-size // BUCKET_BYTES))


def ranges(docs: DataFrame, seed: int = 0, bits: int = SPAN_BITS) -> tuple[DataFrame, bool]:
    """What to cut of documents (uid, ord, text), and whether hashes collided within a task.

    Rows are uid with packed ranges (blob), a window's start (at), or a range's start and the bytes it should have (at, proof).
    """
    spark = docs.sparkSession
    common.importable(spark)
    buckets = bucket_count(docs)
    dealt = docs.select("uid", "ord", "text").mapInArrow(deal(buckets, seed, bits), "bucket int, kind int, uid long, blob binary")
    told = dealt.repartition(buckets, "bucket").sortWithinPartitions("bucket", "kind").mapInArrow(compare, "kind int, uid long, blob binary")
    told = common.stage(told, "passages-told")
    common.sweep(spark)
    collided = not told.filter(F.col("kind") == COLLIDED).isEmpty()
    asked = told.filter(F.col("kind").isin(LOOK, ASK))
    of = lambda kind: F.filter(F.collect_list(F.when(F.col("kind") == kind, F.col("blob"))), lambda x: x.isNotNull())
    wanted = asked.groupBy("uid").agg(of(LOOK).alias("looks"), of(ASK).alias("asks"))  # no more than a document's own anchors
    texts = common.sifted(docs.select("uid", "ord", "text"), "uid", common.sieve(asked, "uid"))
    fetched = texts.join(wanted.hint("merge"), "uid").select("uid", "ord", "text", "looks", "asks")
    fetched = common.stage(fetched.mapInArrow(fetch, "kind int, h long, ord long, uid long, at int, back int, ahead int, span binary"), "passages-fetched")
    common.sweep(spark)
    spans = fetched.filter(F.col("kind") == NEAR).select("h", "ord", "uid", "at", "back", "ahead", "span")
    close = spans.repartition("h").sortWithinPartitions("h").mapInArrow(look, "kind int, uid long, blob binary")
    close = common.stage(close, "passages-close")
    common.sweep(spark)
    windows = fetched.filter(F.col("kind") == WINDOWED).select(F.col("span").alias("w"), "ord", "uid", "at")
    none = F.lit(None).cast("binary")
    cuts = told.filter(F.col("kind") == CUT).select("uid", "blob").union(close.select("uid", "blob")).select("uid", "blob", F.lit(0).alias("at"), none.alias("proof"))
    proofs = fetched.filter(F.col("kind") == PROOF).select("uid", none.alias("blob"), "at", F.col("span").alias("proof"))
    if not windows.isEmpty():
        hot = hot_ranges(windows)
        cuts = cuts.union(hot.select("uid", none.alias("blob"), "at", none.alias("proof")))
    return cuts.union(proofs), collided


def cut_out(data: bytes, blobs: list[bytes], windows: list[int], proofs: list[tuple[int, bytes]]) -> tuple[list[bytes], int, int, bool]:
    """What stays of a document, bytes and runs removed, and whether it lacks bytes that it should have."""
    pairs = np.frombuffer(b"".join(blobs), "<i4").reshape(-1, 2).astype(np.int64)
    start, end = [pairs[:, 0], np.array(windows, np.int64)], [pairs[:, 1], np.array(windows, np.int64) + WINDOW]
    start.append(np.array([a for a, _ in proofs], np.int64))
    end.append(np.array([a + len(p) for a, p in proofs], np.int64))
    collided = any(data[a : a + len(p)] != p for a, p in proofs)
    first, last = merged(np.concatenate(start), np.concatenate(end))
    rest = [data[x:y] for x, y in zip([0, *last.tolist()], [*first.tolist(), len(data)], strict=True)]
    return rest, len(data) - sum(map(len, rest)), len(first), collided


def dedup(docs: DataFrame, text: str = "text", key: str = "doc_id", with_text: bool = False, bits: int = SPAN_BITS) -> DataFrame:
    """Per row: doc_id, n_bytes, n_removed, n_spans, kept_sha256 (and what is left, with invalid sequences replaced).

    bits of a span's hash are kept at the first trial; too few cost further trials, never a wrong result.
    """
    flat = docs.select(common.col(key).cast("long").alias("doc_id"), common.clean_text(common.col(text)).alias("text"))
    rows = common.identified(flat, "doc_id", ["doc_id", "text"])
    seed = 0
    while (out := attempt(rows, with_text, seed, SPAN_BITS if seed else bits)) is None:
        seed += 1  # a collision: other hashes
    return out


def attempt(rows: DataFrame, with_text: bool, seed: int, bits: int) -> DataFrame | None:
    """`dedup` of rows (uid, ord, doc_id, text) under one hash; nothing where bytes told that hashes had collided."""
    cuts, collided = ranges(rows, seed, bits)
    if collided:
        return None
    touched_bits = common.sieve(cuts, "uid")
    names = ["doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256", "collided", *(["text"] if with_text else [])]

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in common.slices(whole, 1):
                out: list[list] = [[] for _ in names[1:]]
                for t, got in zip(b.column(1), b.column(2), strict=True):
                    data = t.as_py().encode()
                    some = got.as_py() or []
                    proofs = [(g["at"], g["proof"]) for g in some if g["proof"] is not None]
                    rest, removed, runs, bad = cut_out(data, [g["blob"] for g in some if g["blob"] is not None], [g["at"] for g in some if g["blob"] is None and g["proof"] is None], proofs)
                    kept = b"".join(rest)
                    for o, v in zip(out, (len(data), removed, runs, hashlib.sha256(kept).hexdigest(), bad, *([kept.decode("utf-8", "replace")] if with_text else [])), strict=True):
                        o.append(v)
                kinds = [pa.int64(), pa.int64(), pa.int64(), pa.string(), pa.bool_(), pa.string()]
                yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array(o, k) for o, k in zip(out, kinds, strict=False)]], names)

    kinds = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string, collided boolean" + ", text string" * with_text
    per = cuts.groupBy("uid").agg(F.collect_list(F.struct("blob", "at", "proof")).alias("cuts"))  # no more than the document's own spans
    touched = common.sifted(rows, "uid", touched_bits).join(per.hint("merge"), "uid", "left").select("doc_id", "text", "cuts").mapInArrow(cut, kinds)
    touched = common.stage(touched, "passages-cut")
    common.sweep(rows.sparkSession)
    if not touched.filter("collided").isEmpty():
        return None
    zero = F.lit(0).cast("long")
    whole = common.sifted(rows, "uid", touched_bits, "left_anti").select(
        "doc_id", F.octet_length("text").cast("long").alias("n_bytes"), zero.alias("n_removed"), zero.alias("n_spans"), F.sha2(F.col("text").cast("binary"), 256).alias("kept_sha256"), *(["text"] if with_text else [])
    )
    return touched.drop("collided").union(whole)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return dedup(spark.read.parquet(f"{sf_dir}/documents.parquet"))
