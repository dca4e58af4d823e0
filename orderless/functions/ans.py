"""Asymmetric numeral systems: an exact state of any size, a word state, and word states in lockstep.

A state is a natural number. Pushing a symbol that owns `freq` of `total` slots from `start` on makes it larger by about
log2(total / freq) bits; popping undoes the last push. Popping under any distribution also draws a sample that can be
pushed back, which is what codes with latent order rest on.
"""

from __future__ import annotations

from array import array

import numpy as np

#: Slots of the word coders, as a power of two; totals are mapped to it.
PRECISION = 31
#: Largest alphabet coded in one step; larger ones go in two digits.
DIGIT = 20
U = np.uint64


class ExactState:
    """One arbitrarily large integer; no redundancy but rounding."""

    def __init__(self, value: int = 0):
        self.value = value

    @classmethod
    def seeded(cls, bits: int, seed: int = 0) -> ExactState:
        import random

        return cls((1 << bits) | random.Random(seed).getrandbits(bits))

    def push(self, start: int, freq: int, total: int) -> None:
        whole, part = divmod(self.value, freq)
        self.value = whole * total + start + part

    def slot(self, total: int) -> int:
        return self.value % total

    def pop(self, start: int, freq: int, total: int) -> None:
        """Takes out the symbol that holds the current slot."""
        whole, slot = divmod(self.value, total)
        self.value = freq * whole + slot - start

    def push_uniform(self, symbol: int, total: int) -> None:
        self.value = self.value * total + symbol

    def pop_uniform(self, total: int) -> int:
        self.value, symbol = divmod(self.value, total)
        return symbol

    def sample(self, model) -> int:
        symbol, start, freq = model.find(self.slot(model.total))
        self.pop(start, freq, model.total)
        return symbol

    def encode(self, model, symbol: int) -> None:
        start, freq = model.span(symbol)
        self.push(start, freq, model.total)

    decode = sample

    @property
    def bits(self) -> int:
        return self.value.bit_length()

    def to_bytes(self) -> bytes:
        return self.value.to_bytes((self.bits + 7) // 8, "little")

    @classmethod
    def from_bytes(cls, data: bytes) -> ExactState:
        return cls(int.from_bytes(data, "little"))


class WordState:
    """A head under 2**64 over a stack of 32-bit words; amortised constant time per symbol.

    Starts empty by default: refills stop when the stack is empty, and stop likewise when a decoder runs the same steps back.
    """

    def __init__(self, head: int = 0, stack: array | list[int] | None = None):
        self.head, self.stack = head, stack if stack is not None else array("I")  # four bytes a word

    @classmethod
    def seeded(cls, seed: int = 0) -> WordState:
        import random

        return cls((1 << 63) | random.Random(seed).getrandbits(63))

    def push(self, start: int, freq: int, precision: int) -> None:
        if self.head >= freq << (64 - precision):
            self.stack.append(self.head & 0xFFFFFFFF)
            self.head >>= 32
        self.head = (self.head // freq << precision) + self.head % freq + start

    def slot(self, precision: int) -> int:
        return self.head & ((1 << precision) - 1)

    def pop(self, start: int, freq: int, precision: int) -> None:
        self.head = freq * (self.head >> precision) + self.slot(precision) - start
        if self.head < 1 << 32 and self.stack:
            self.head = self.head << 32 | self.stack.pop()

    def push_uniform(self, symbol: int, total: int) -> None:
        for s, t in reversed(digits(symbol, total)):
            if t > 1:
                start = (s << PRECISION) // t
                self.push(start, ((s + 1 << PRECISION) // t) - start, PRECISION)

    def pop_uniform(self, total: int) -> int:
        out = 0
        for shift, t in digit_totals(total):
            if t > 1:
                s = ((self.slot(PRECISION) + 1) * t - 1) >> PRECISION
                start = (s << PRECISION) // t
                self.pop(start, ((s + 1 << PRECISION) // t) - start, PRECISION)
                out |= s << shift
        return out

    @property
    def bits(self) -> int:
        return self.head.bit_length() + 32 * len(self.stack)

    def to_bytes(self) -> bytes:
        head = self.head.to_bytes((self.head.bit_length() + 7) // 8, "little")
        return bytes([len(head)]) + head + np.array(self.stack, "<u4").tobytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> WordState:
        n = data[0]
        return cls(int.from_bytes(data[1 : 1 + n], "little"), array("I", np.frombuffer(data, "<u4", offset=1 + n).tobytes()))


def digit_totals(total: int) -> list[tuple[int, int]]:
    """(shift, alphabet) of the digits a uniform symbol is coded in, the high one first."""
    if total <= 1 << 26:
        return [(0, total)]
    return [(DIGIT, (total + (1 << DIGIT) - 1) >> DIGIT), (0, 1 << DIGIT)]


def digits(symbol: int, total: int) -> list[tuple[int, int]]:
    if total <= 1 << 26:
        return [(symbol, total)]
    return [(symbol >> DIGIT, digit_totals(total)[0][1]), (symbol & ((1 << DIGIT) - 1), 1 << DIGIT)]


class WordStateBatch:
    """Many word states advanced by the same step at once; numpy only. Same bits as WordState."""

    def __init__(self, count: int, words: int, seeded: int | None = None):
        self.head = np.zeros(count, U)
        if seeded is not None:
            self.head[:] = np.random.default_rng(seeded).integers(1 << 62, 1 << 63, count, dtype=np.uint64) << U(1)
        self.stack = np.zeros((count, max(1, words)), np.uint32)
        self.depth = np.zeros(count, np.int64)

    def _room(self) -> None:
        if int(self.depth.max(initial=0)) >= self.stack.shape[1]:
            self.stack = np.concatenate([self.stack, np.zeros_like(self.stack)], 1)

    def push(self, n: int, start: np.ndarray, freq: np.ndarray) -> None:
        """Pushes onto the first n states."""
        head = self.head[:n]
        full = np.flatnonzero(head >= freq << U(64 - PRECISION))
        if len(full):
            self._room()
            self.stack[full, self.depth[full]] = (head[full] & U(0xFFFFFFFF)).astype(np.uint32)
            self.depth[full] += 1
            head[full] >>= U(32)
        whole = head // freq
        self.head[:n] = (whole << U(PRECISION)) + (head - whole * freq) + start

    def pop(self, n: int, start: np.ndarray, freq: np.ndarray) -> None:
        head = self.head[:n]
        head = freq * (head >> U(PRECISION)) + (head & U((1 << PRECISION) - 1)) - start
        low = np.flatnonzero((head < U(1 << 32)) & (self.depth[:n] > 0))
        if len(low):
            self.depth[low] -= 1
            head[low] = (head[low] << U(32)) | self.stack[low, self.depth[low]].astype(U)
        self.head[:n] = head

    def push_uniform(self, n: int, symbol: np.ndarray, total: np.ndarray) -> None:
        """Symbols under per-state totals up to 2**26; a total of 1 costs nothing."""
        symbol, total = symbol.astype(U), np.broadcast_to(np.asarray(total, U), (n,))
        one = total <= U(1)
        if one.all():
            return
        p = U(PRECISION)
        start = (symbol << p) // total
        freq = ((symbol + U(1)) << p) // total - start
        if one.any():  # only the last members of lists: code around them
            keep, depth = self.head[:n][one].copy(), self.depth[:n][one].copy()
            self.push(n, np.where(one, U(0), start), np.where(one, U(1), freq))
            self.head[:n][one] = keep
            self.depth[:n][one] = depth
        else:
            self.push(n, start, freq)

    def pop_uniform(self, n: int, total: np.ndarray) -> np.ndarray:
        total = np.broadcast_to(np.asarray(total, U), (n,))
        one = total <= U(1)
        if one.all():
            return np.zeros(n, np.int64)
        p = U(PRECISION)
        slot = self.head[:n] & U((1 << PRECISION) - 1)
        symbol = ((slot + U(1)) * total - U(1)) >> p
        start = (symbol << p) // total
        freq = ((symbol + U(1)) << p) // total - start
        if one.any():
            keep, depth = self.head[:n][one].copy(), self.depth[:n][one].copy()
            symbol, start, freq = (np.where(one, U(v), x) for v, x in ((0, symbol), (0, start), (1, freq)))
            self.pop(n, start, freq)
            self.head[:n][one] = keep
            self.depth[:n][one] = depth
        else:
            self.pop(n, start, freq)
        return symbol.astype(np.int64)

    def bits(self) -> np.ndarray:
        length = np.zeros(len(self.head), np.int64)
        head = self.head.copy()
        for shift in (32, 16, 8, 4, 2, 1):
            more = head >= U(1 << shift)
            length[more] += shift
            head[more] >>= U(shift)
        return length + (head > 0) + 32 * self.depth

    def to_bytes(self) -> list[bytes]:
        out = []
        for h, d, s in zip(self.head.tolist(), self.depth.tolist(), self.stack, strict=True):
            head = h.to_bytes((h.bit_length() + 7) // 8, "little")
            out.append(bytes([len(head)]) + head + s[:d].astype("<u4").tobytes())
        return out

    @classmethod
    def from_bytes(cls, data: list[bytes]) -> WordStateBatch:
        words = [np.frombuffer(b, "<u4", offset=1 + b[0]) for b in data]
        out = cls(len(data), max(map(len, words), default=0) + 4)
        for i, (b, w) in enumerate(zip(data, words, strict=True)):
            out.head[i] = int.from_bytes(b[1 : 1 + b[0]], "little")
            out.stack[i, : len(w)] = w
            out.depth[i] = len(w)
        return out
