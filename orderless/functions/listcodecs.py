"""Codecs of sorted id lists behind one interface: raw words, fixed width, Elias-Fano, random order, random order in segments.

encode(flat, at) takes many lists (sorted ids of all, and m+1 positions) and gives payloads and their bits;
decode(payload, size) gives all ids back. Every codec knows the universe the ids come from.
"""

from __future__ import annotations

import numpy as np

from . import setcodec
from .models import Falling
from .bitvec import Flat, pack_bits, read_bits, unpack_bits


def width_of(universe: int) -> int:
    """Bits of an id in fixed width."""
    return max(0, (max(universe, 1) - 1).bit_length())


class Raw:
    name = "raw"

    def __init__(self, universe: int, word: int = 64):
        self.universe, self.word = universe, word

    def encode(self, flat: np.ndarray, at: np.ndarray) -> tuple[list[bytes], np.ndarray]:
        data = flat.astype(f"<i{self.word // 8}").tobytes()
        cut = (at * (self.word // 8)).tolist()
        return [data[a:b] for a, b in zip(cut[:-1], cut[1:], strict=True)], np.diff(at) * self.word

    def decode(self, payload: list[bytes], size: np.ndarray) -> np.ndarray:
        return np.frombuffer(b"".join(payload), f"<i{self.word // 8}").astype(np.int64)

    def get_many(self, payload: bytes, n: int, i: np.ndarray) -> np.ndarray:
        return np.frombuffer(payload, f"<i{self.word // 8}")[i].astype(np.int64)


class Packed:
    """Every id in the bits the universe needs; any one can be read alone."""

    name = "packed"

    def __init__(self, universe: int):
        self.universe, self.width = universe, width_of(universe)

    def encode(self, flat: np.ndarray, at: np.ndarray) -> tuple[list[bytes], np.ndarray]:
        return [pack_bits(flat[a:b], self.width) for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)], np.diff(at) * self.width

    def decode(self, payload: list[bytes], size: np.ndarray) -> np.ndarray:
        out = [unpack_bits(p, np.full(int(n), self.width)) for p, n in zip(payload, size, strict=True)]
        return np.concatenate(out) if out else np.zeros(0, np.int64)

    def get_many(self, payload: bytes, n: int, i: np.ndarray) -> np.ndarray:
        return read_bits(np.frombuffer(payload + bytes(16), np.uint8), np.asarray(i, np.int64) * self.width, self.width)


class EliasFano:
    """Low bits of the sorted ids side by side, high parts in unary: some two bits an id over the ratio's logarithm."""

    name = "ef"

    def __init__(self, universe: int, low_bits: str = "floor", account: str = "streams", directory: bool = False):
        self.universe, self.low_bits, self.account, self.directory = universe, low_bits, account, directory

    def low(self, n: int | np.ndarray) -> np.ndarray:
        n = np.maximum(np.asarray(n, np.int64), 1)
        ratio = np.maximum(self.universe // n, 1)
        out = np.floor(np.log2(ratio)).astype(np.int64)
        if self.low_bits == "ceil":
            out = np.where((self.universe > n) & ((n << out) < self.universe), out + 1, out)
        return out

    def size_bits(self, n: np.ndarray) -> np.ndarray:
        n = np.asarray(n, np.int64)
        low = self.low(n)
        high = n + (self.universe >> low) + 1
        streams = np.where(n > 0, n * low + high, 0)
        if self.directory:
            streams = streams + np.where(n > 0, 32 * (-(-high // Flat.EVERY) + 1), 0)
        return streams + (128 if self.account == "full" else 0)

    def encode(self, flat: np.ndarray, at: np.ndarray) -> tuple[list[bytes], np.ndarray]:
        size = np.diff(at)
        out = []
        for a, b, low in zip(at[:-1].tolist(), at[1:].tolist(), self.low(size).tolist(), strict=True):
            ids, n = flat[a:b], b - a
            if not n:
                out.append(b"")
                continue
            high = np.zeros(n + (self.universe >> low) + 1, np.uint8)
            high[(ids >> low) + np.arange(n)] = 1
            counts = Flat.of(high).counts.astype("<u4").tobytes() if self.directory else b""
            out.append(counts + pack_bits(ids & ((1 << low) - 1), low).ljust((n * low + 7) // 8, b"\0") + np.packbits(high, bitorder="little").tobytes())
        return out, self.size_bits(size)

    def open(self, payload: bytes, n: int) -> EliasFanoView:
        """The list ready for reads: nothing is decoded, and with a stored directory nothing but what a read asks for is looked at."""
        low = int(self.low(n))
        size = n + (self.universe >> low) + 1
        m = -(-size // Flat.EVERY) + 1 if self.directory else 0
        cut = 4 * m + (n * low + 7) // 8
        counts = np.frombuffer(payload, "<u4", m) if self.directory else None
        return EliasFanoView(n, low, np.frombuffer(payload[4 * m : cut] + bytes(16), np.uint8), Flat(np.frombuffer(payload, np.uint8, offset=cut), size, counts))

    def decode(self, payload: list[bytes], size: np.ndarray) -> np.ndarray:
        out = [np.zeros(0, np.int64)]
        for p, n in zip(payload, np.asarray(size).tolist(), strict=True):
            if n:
                v = self.open(p, n)
                ones = np.flatnonzero(np.unpackbits(v.high.packed, bitorder="little")[: v.high.n])
                out.append(((ones - np.arange(n)) << v.low) | unpack_bits(v.lows[:-16].tobytes(), np.full(n, v.low)))
        return np.concatenate(out)

    def get_many(self, payload: bytes, n: int, i: np.ndarray) -> np.ndarray:
        return self.open(payload, n).get(np.asarray(i, np.int64))

    def next_geq(self, payload: bytes, n: int, value: int) -> int | None:
        """The least id that isn't under value."""
        got = int(self.open(payload, n).next_geq(np.array([value]))[0]) if n else -1
        return got if got >= 0 else None

    def intersect(self, a: bytes, n: int, b: bytes, m: int) -> np.ndarray:
        """Common ids of two lists: those of the shorter one that a jump into the longer one finds."""
        (p, k), (q, other) = sorted(((a, n), (b, m)), key=lambda x: x[1])
        ids = self.decode([p], np.array([k]))
        return ids[self.open(q, other).next_geq(ids) == ids] if k and other else ids[:0]


class EliasFanoView:
    """Reads of one list: by place, and by value; each in logarithmic time."""

    def __init__(self, n: int, low: int, lows: np.ndarray, high: Flat):
        self.n, self.low, self.lows, self.high = n, low, lows, high

    def _low(self, i: np.ndarray) -> np.ndarray:
        return read_bits(self.lows, i * self.low, self.low)

    def get(self, i: np.ndarray) -> np.ndarray:
        return ((self.high.select(i) - i) << self.low) | self._low(i)

    def next_geq(self, value: np.ndarray) -> np.ndarray:
        """The least id not under each value; -1 where there is none."""
        value = np.maximum(np.asarray(value, np.int64), 0)
        zeros, bucket = self.high.n - self.n, value >> self.low
        inside = bucket < zeros
        b = np.where(inside, bucket, 0)
        # ids of a bucket stand between its zero and the one before
        first = np.where(b > 0, self.high.select(np.maximum(b - 1, 0), 0) + 1 - b, 0)
        last = self.high.select(b, 0) - b
        low, rest = first.copy(), last.copy()
        while (low < rest).any():
            mid = (low + rest) // 2
            less = self._low(np.minimum(mid, self.n - 1)) < (value & ((1 << self.low) - 1))
            active = low < rest
            low, rest = np.where(active & less, mid + 1, low), np.where(active & ~less, mid, rest)
        found = inside & (low < self.n)
        return np.where(found, self.get(np.where(found, low, 0)), -1)


class RandomOrder:
    """Random-order coding, one word state a list, all lists of a batch in lockstep."""

    name = "roc"

    def __init__(self, universe: int, seeded: int | None = None):
        self.universe, self.seeded = universe, seeded

    def encode(self, flat: np.ndarray, at: np.ndarray) -> tuple[list[bytes], np.ndarray]:
        if self.seeded is not None or not (np.diff(at) > STEP_IDS).any():
            return setcodec.encode_sets(flat, at, self.universe, self.seeded)
        size = np.diff(at)
        short = np.flatnonzero(size <= STEP_IDS)
        some, bits = setcodec.encode_sets(flat[np.repeat(size <= STEP_IDS, size)], np.r_[0, np.cumsum(size[short])], self.universe)
        out, total = [b""] * len(size), np.zeros(len(size), np.int64)
        for i, p in zip(short.tolist(), some, strict=True):
            out[i] = p
        total[short] = bits
        for i in np.flatnonzero(size > STEP_IDS).tolist():
            state = setcodec.WordState()
            setcodec.encode_set(state, flat[at[i] : at[i + 1]].tolist(), self.universe)
            out[i], total[i] = state.to_bytes(), state.bits
        return out, total

    def decode(self, payload: list[bytes], size: np.ndarray) -> np.ndarray:
        size = np.asarray(size)
        if self.seeded is not None or not (size > STEP_IDS).any():
            return setcodec.decode_sets(payload, size, self.universe)
        short = np.flatnonzero(size <= STEP_IDS)
        parts = dict(zip(short.tolist(), np.split(setcodec.decode_sets([payload[i] for i in short], size[short], self.universe), np.cumsum(size[short])[:-1]), strict=False))
        for i in np.flatnonzero(size > STEP_IDS).tolist():
            parts[i] = np.array(setcodec.decode_set(setcodec.WordState.from_bytes(payload[i]), int(size[i]), self.universe), np.int64)
        return np.concatenate([parts[i] for i in range(len(size))])


#: Ids of a list up to which lists are coded in step: that moves a row of a matrix at each id, so longer ones go alone by a tree, with the same bits.
STEP_IDS = 1 << 12
#: Ids of a list that an exact state takes: its work grows with the square of the length. Longer lists go in segments.
EXACT_IDS = 1 << 17
#: Codecs on exact states.
EXACT = ("roc_exact", "roc_distinct", "roc_buckets", "roc_falling")


def _within(sizes: np.ndarray) -> None:
    if len(sizes) and int(sizes.max()) > EXACT_IDS:
        raise ValueError(f"a list of {int(sizes.max())} ids is too long for an exact state; cut it by segment_bits, or take roc")


class ExactRandomOrder:
    """Random-order coding on exact states: no word to fill, so short lists lose nothing. Scalar; lists of up to `EXACT_IDS` ids."""

    name = "roc_exact"

    def __init__(self, universe: int, distinct: bool = False, model=None):
        self.universe, self.distinct, self.model = universe, distinct, model

    def encode(self, flat: np.ndarray, at: np.ndarray) -> tuple[list[bytes], np.ndarray]:
        _within(np.diff(at))
        out, bits = [], []
        for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
            state = setcodec.ExactState(0)
            setcodec.encode_set(state, flat[a:b].tolist(), self.universe, self.distinct, self.model)
            out.append(state.to_bytes())
            bits.append(state.bits)
        return out, np.array(bits, np.int64)

    def decode(self, payload: list[bytes], size: np.ndarray) -> np.ndarray:
        out: list[int] = []
        for p, n in zip(payload, np.asarray(size).tolist(), strict=True):
            out += setcodec.decode_set(setcodec.ExactState.from_bytes(p), n, self.universe, self.distinct, self.model)
        return np.array(out, np.int64)


class BucketedRandomOrder:
    """Random-order coding with counts of some 64 id ranges in place of exact ranks, on exact states. Scalar."""

    name = "roc_buckets"

    def __init__(self, universe: int, buckets: int = 64):
        self.universe, self.shift = universe, max(0, width_of(universe) - (buckets - 1).bit_length())

    def encode(self, flat: np.ndarray, at: np.ndarray) -> tuple[list[bytes], np.ndarray]:
        _within(np.diff(at))
        out, bits = [], []
        for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True):
            state = setcodec.ExactState(0)
            setcodec.encode_bucketed(state, flat[a:b].tolist(), self.universe, self.shift)
            out.append(state.to_bytes())
            bits.append(state.bits)
        return out, np.array(bits, np.int64)

    def decode(self, payload: list[bytes], size: np.ndarray) -> np.ndarray:
        out: list[int] = []
        for p, n in zip(payload, np.asarray(size).tolist(), strict=True):
            out += setcodec.decode_bucketed(setcodec.ExactState.from_bytes(p), n, self.universe, self.shift)
        return np.array(out, np.int64)


CODECS = {c.name: c for c in (Raw, Packed, EliasFano, RandomOrder, ExactRandomOrder, BucketedRandomOrder)}
CODECS["raw32"] = lambda universe: Raw(universe, 32)
CODECS["ef_dir"] = lambda universe: EliasFano(universe, directory=True)
CODECS["ef_ceil"] = lambda universe: EliasFano(universe, "ceil")
CODECS["roc_seeded"] = lambda universe: RandomOrder(universe, 7)
CODECS["roc_falling"] = lambda universe: ExactRandomOrder(universe, model=Falling(universe))
CODECS["roc_distinct"] = lambda universe: ExactRandomOrder(universe, True)


def get_many(c, payload: bytes, n: int, i: np.ndarray) -> np.ndarray:
    """Ids at places of one list: read alone where the codec can, else from the decoded list."""
    return c.get_many(payload, n, i) if hasattr(c, "get_many") else c.decode([payload], np.array([n]))[i]


def codec(name: str, universe: int):
    if name not in CODECS:
        raise ValueError(f"no codec {name!r}; there are {sorted(CODECS)}")
    return CODECS[name](universe)
