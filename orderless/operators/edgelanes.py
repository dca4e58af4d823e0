"""Whole graphs of many edges as one stream whose word states step together.

Random-edge coding with one order of edges, one set of edges left and one urn, as in `edgecodec`; a step draws an edge for every state, without
replacement over all edges left, and codes them under the urn without these. So nothing is coded alone by its state but the
numbers themselves, and the rate is that of one state but for what a state holds when it begins, a length for each, and urns a step old.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np

from ..functions.ans import PRECISION, WordStateBatch

#: Edges a state codes, about.
LANE_EDGES = 1 << 12
#: A step draws at most one in so many of the edges left: urns learn in time, and few draws meet.
SHARE = 16
#: Keys that are looked at together where a whole array of them isn't needed.
SOME = 1 << 20
TREE = 13
U, P = np.uint64, np.uint64(PRECISION)


class Counts:
    """Counts of places under binary trees over 8,192 of them; many places are read, found and changed at a time."""

    def __init__(self, count: np.ndarray):
        leaf = np.zeros((len(count) >> TREE) + 1 << TREE, count.dtype)
        leaf[: len(count)] = count
        self.levels = [leaf]
        for _ in range(TREE):
            self.levels.append(self.levels[-1][::2] + self.levels[-1][1::2])
        self.leaf, self.top = leaf, self.levels.pop().astype(np.int64)
        self.sums = np.cumsum(self.top)

    def add(self, at: np.ndarray, d: int) -> None:
        for level in (*self.levels, self.top):
            (np.add if d > 0 else np.subtract).at(level, at, level.dtype.type(abs(d)))
            at = at >> 1
        self.sums = np.cumsum(self.top)

    def below(self, at: np.ndarray) -> np.ndarray:
        """The sum over all places before each."""
        out = np.zeros(len(at), np.int64)
        for level in self.levels:
            out += level[at ^ 1] * (at & 1)
            at = at >> 1
        return out + (self.sums[at] - self.top[at])

    def find(self, slot: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The place that holds each slot, and the sum before it."""
        at = np.searchsorted(self.sums, slot, side="right")
        rest = slot - (self.sums[at] - self.top[at])
        for level in reversed(self.levels):
            at += at
            left = level[at]
            right = rest >= left
            rest -= left * right
            at += right
        return at, slot - rest


class Ranks:
    """A growing set of numbers as a few sorted runs, each several times the next."""

    def __init__(self):
        self.runs: list[np.ndarray] = []

    def rank(self, x: np.ndarray) -> np.ndarray:
        return sum((np.searchsorted(r, x) for r in self.runs), np.zeros(len(x), np.int64))

    def add(self, x: np.ndarray, apart: int = 8) -> None:
        """Sorted numbers; apart 0 leaves one run."""
        self.runs.append(x)
        while len(self.runs) > 1 and (not apart or len(self.runs[-2]) < apart * len(self.runs[-1])):
            both = np.concatenate(self.runs[-2:])
            del self.runs[-2:]
            both.sort(kind="stable")  # merges the two
            self.runs.append(both)


def picked(slot: np.ndarray, left: int) -> np.ndarray:
    """Different places below `left` from slots, the j-th below left - j: the place drawn is filled with the last one."""
    out = slot.copy()
    order = np.sort(slot)
    again = order[1:][order[1:] == order[:-1]]
    met = slot >= left - len(slot)
    if len(again):
        met |= np.isin(slot, again)
    moved: dict[int, int] = {}
    for j in np.flatnonzero(met).tolist():  # the few that meet a moved place
        s, last = int(slot[j]), left - 1 - j
        out[j] = moved.get(s, s)
        moved[s] = moved.get(last, last)
    return out


def unpicked(place: np.ndarray, left: int) -> np.ndarray:
    """The slots that `picked` drew these places from."""
    out = place.copy()
    for k in np.flatnonzero(place >= left - len(place)).tolist():
        at = int(place[k])
        while left - 1 - at < k:  # moved by an earlier draw
            at = int(out[left - 1 - at])
        out[k] = at
    return out


def turned(m: int, left: int) -> np.ndarray:
    """How far each draw's slot is turned. A slot tells much of what its state coded last, so unturned ones meet at few places, whose counts
    would be those before the step for all of them."""
    h = (np.arange(m, dtype=U) + U(left * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)) * U(0xD1342543DE82EF95)
    h = (h ^ h >> U(32)) * U(0xBF58476D1CE4E5B9)
    return ((h >> U(32)) * (U(left) - np.arange(m, dtype=U)) >> U(32)).astype(np.int64)


def steps(n: int, lanes: int) -> list[tuple[int, int]]:
    """(edges left, edges drawn) of every step, in the encoder's order."""
    out = []
    while n:
        m = max(1, min(lanes, n // SHARE))
        out.append((n, m))
        n -= m
    return out


def _spans(start: np.ndarray, weight: np.ndarray, total: int) -> tuple[np.ndarray, np.ndarray]:
    a = (start.astype(U) << P) // U(total)
    return a, ((start + weight).astype(U) << P) // U(total) - a


def _slots(state: WordStateBatch, m: int, total: int) -> np.ndarray:
    return ((((state.head[:m] & U((1 << PRECISION) - 1)) + U(1)) * U(total) - U(1)) >> P).astype(np.int64)


def _weights(vertices: int, bias: int, most: int) -> np.ndarray:
    return np.full(vertices, bias, np.int32 if most < 1 << 31 else np.int64)


def encode(keys: np.ndarray, vertices: int, bias: int = 1, directed: bool = True, model: str = "urn", sources: tuple[int, int] | None = None) -> tuple[bytes, int]:
    """Payload and bits of sorted numbers src * vertices + dst, each once."""
    lo, hi = sources or (0, vertices)
    n, learns = len(keys), model == "urn"
    lanes = max(1, n // LANE_EDGES)
    weight = _weights(vertices, bias, vertices * bias + 2 * n)
    if learns:
        for k in range(0, n, SOME):
            for v in divmod(keys[k : k + SOME], vertices):
                weight += np.bincount(v, minlength=vertices).astype(weight.dtype)
    urn, left, state = Counts(weight), Counts(np.ones(n, np.int16)), WordStateBatch(lanes, 64)
    del weight
    for size, m in steps(n, lanes):
        of = size - np.arange(m)
        at, _ = left.find(picked((state.pop_uniform(m, of) + turned(m, size)) % of, size))
        left.add(at, -1)
        x, y = divmod(keys[at], vertices)
        if not directed:
            turn = state.pop_uniform(m, np.where(x != y, 2, 1)) > 0
            x, y = np.where(turn, y, x), np.where(turn, x, y)
        both = np.concatenate([y, x])
        if learns:
            urn.add(both, -1)
        start, own = urn.below(both), urn.leaf[both].astype(np.int64)
        low, high = urn.below(np.array([lo, hi])).tolist()
        total = vertices * bias + (2 * (size - m) if learns else 0)
        state.push(m, *_spans(start[:m], own[:m], total))
        state.push(m, *_spans(start[m:] - low, own[m:], high - low))  # the decoder reads the source first
    bodies = state.to_bytes()
    sizes = np.array([lanes, *map(len, bodies)], "<u4")
    return sizes.tobytes() + b"".join(bodies), int(state.bits().sum()) + 32 * lanes


def decode(payload: bytes, n: int, vertices: int, bias: int = 1, directed: bool = True, model: str = "urn", sources: tuple[int, int] | None = None) -> np.ndarray:
    """Sorted numbers src * vertices + dst."""
    lo, hi = sources or (0, vertices)
    learns = model == "urn"
    lanes = int(np.frombuffer(payload, "<u4", 1)[0])
    ends = 4 * (lanes + 1) + np.r_[0, np.cumsum(np.frombuffer(payload, "<u4", lanes, 4).astype(np.int64))]
    state = WordStateBatch.from_bytes([payload[a:b] for a, b in zip(ends[:-1].tolist(), ends[1:].tolist(), strict=True)])
    urn, got = Counts(_weights(vertices, bias, vertices * bias + 2 * n)), Ranks()
    for size, m in reversed(steps(n, lanes)):
        low, high = urn.below(np.array([lo, hi])).tolist()
        total = vertices * bias + (2 * (size - m) if learns else 0)
        edge = []
        for of, before in ((high - low, low), (total, 0)):
            v, start = urn.find(_slots(state, m, of) + before)
            state.pop(m, *_spans(start - before, urn.leaf[v].astype(np.int64), of))
            edge.append(v)
        x, y = edge
        if learns:
            urn.add(np.concatenate(edge), 1)
        if not directed:
            state.push_uniform(m, x > y, np.where(x != y, 2, 1))
            x, y = np.minimum(x, y), np.maximum(x, y)
        key = x * vertices + y
        order = np.argsort(key)
        new, place = key[order], np.empty(m, np.int64)
        place[order] = got.rank(new) + np.arange(m)
        of = size - np.arange(m)
        state.push_uniform(m, (unpicked(place, size) - turned(m, size)) % of, of)  # gives the draws back
        got.add(new)
    got.add(np.zeros(0, np.int64), 0)
    return got.runs[0]


def told(keys: np.ndarray, vertices: int, some: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Sources and other ends, some at a time."""
    for k in range(0, len(keys), some):
        yield divmod(keys[k : k + some], vertices)
