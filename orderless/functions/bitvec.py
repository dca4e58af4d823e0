"""Bit vectors with rank and select: flat words with a count directory, and block-compressed ones."""

from __future__ import annotations

import functools
import math

import numpy as np


def _ones_before(bits: np.ndarray, row: np.ndarray, at: np.ndarray) -> np.ndarray:
    """How many ones stand before place `at` of a row."""
    before = np.zeros((len(bits), bits.shape[1] + 1), np.int64)
    np.cumsum(bits, 1, out=before[:, 1:])
    return before[row, at]


def _place_of(bits: np.ndarray, row: np.ndarray, i: np.ndarray, bit: int) -> np.ndarray:
    """The place in a row of its i-th bit that equals bit; the row's length if it has fewer."""
    hit = bits == bit
    first = np.r_[0, np.cumsum(np.count_nonzero(hit, 1))]
    at = first[row] + i
    found = at < first[row + 1]
    out = np.full(len(row), bits.shape[1], np.int64)
    out[found] = np.flatnonzero(hit)[at[found]] - row[found] * bits.shape[1]
    return out


class Flat:
    """Bits in bytes, an absolute count of ones every 512 bits (a 16th of the bits more)."""

    EVERY = 512

    def __init__(self, packed: np.ndarray, n: int, counts: np.ndarray | None = None):
        self.packed, self.n = packed, n
        if counts is None:
            padded = np.zeros(-(-n // self.EVERY) * self.EVERY // 8, np.uint8)
            padded[: len(packed)] = packed
            counts = np.r_[0, np.cumsum(np.bitwise_count(padded).reshape(-1, self.EVERY // 8).sum(1))].astype(np.uint32)
        self.counts = counts

    @classmethod
    def of(cls, bits: np.ndarray) -> Flat:
        return cls(np.packbits(bits.astype(np.uint8), bitorder="little"), len(bits))

    def access(self, at: np.ndarray) -> np.ndarray:
        return (self.packed[at >> 3] >> (at & 7).astype(np.uint8)) & 1

    def _block(self, k: np.ndarray) -> np.ndarray:
        width = self.EVERY // 8
        rows = k[:, None] * width + np.arange(width)
        data = np.where(rows < len(self.packed), self.packed[np.minimum(rows, len(self.packed) - 1)], 0)
        return np.unpackbits(data.astype(np.uint8), axis=1, bitorder="little")

    def rank(self, at: np.ndarray, bit: int = 1) -> np.ndarray:
        """How many of the first `at` bits equal bit."""
        at = np.asarray(at, np.int64)
        if not self.n:
            return np.zeros(len(at), np.int64)
        k = np.minimum(at // self.EVERY, max(0, len(self.counts) - 2))
        opened, row = np.unique(k, return_inverse=True)  # a block is opened once for all its questions
        ones = self.counts[k].astype(np.int64) + _ones_before(self._block(opened), row, at - k * self.EVERY)
        return ones if bit else at - ones

    def select(self, i: np.ndarray, bit: int = 1) -> np.ndarray:
        """The place of the i-th (from 0) bit that equals bit."""
        i = np.asarray(i, np.int64)
        blocks = np.arange(len(self.counts))
        ones = self.counts.astype(np.int64)
        have = ones if bit else np.minimum(blocks * self.EVERY, self.n) - ones
        k = np.searchsorted(have, i, side="right") - 1
        opened, row = np.unique(k, return_inverse=True)
        return k * self.EVERY + _place_of(self._block(opened), row, i - have[k], bit)

    def bits(self, directory: bool = True) -> int:
        return self.n + (32 * len(self.counts) if directory else 0)

    def to_bytes(self) -> bytes:
        """Length, counts, bits: opening it again costs nothing, and no read looks at more than one count and 64 bytes."""
        return np.array([self.n], "<i8").tobytes() + self.counts.astype("<u4").tobytes() + self.packed.tobytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> Flat:
        n = int(np.frombuffer(data, "<i8", 1)[0])
        m = -(-n // cls.EVERY) + 1
        return cls(np.frombuffer(data, np.uint8, offset=8 + 4 * m), n, np.frombuffer(data, "<u4", m, 8))


@functools.cache
def _choose(block: int) -> np.ndarray:
    return np.array([[math.comb(n, k) for k in range(block + 1)] for n in range(block + 1)], np.int64)


class RRR:
    """Blocks of bits stored as their number of ones and a place among the blocks with as many.

    Numbers of ones have a fixed width, places the width that their number of ones needs; every `SUPER` blocks a count of the ones
    before and the bit where the places go on. That is what is stored and counted, and a read opens one such stretch.
    """

    SUPER = 64

    def __init__(self, n: int, block: int, marks: np.ndarray, classes: np.ndarray, places: np.ndarray):
        self.n, self.block, self.marks = n, block, marks  # marks: ones before, first bit of the places
        self.classes, self.places = (np.r_[x, np.zeros(16, np.uint8)] for x in (classes, places))  # room for reads of whole words
        self.blocks = -(-n // block)

    @classmethod
    def of(cls, bits: np.ndarray, block: int = 63) -> RRR:
        choose, n = _choose(block), len(bits)
        m = np.zeros((-(-n // block), block), np.int64)
        m.ravel()[:n] = bits
        left = m.sum(1)
        classes, place = left.copy(), np.zeros(len(m), np.int64)
        for j in range(block):  # place in the enumeration: every block with 0 here comes before
            one = m[:, j] == 1
            place[one] += choose[block - 1 - j, left[one]]
            left = left - m[:, j]
        widths = _offset_widths(block)[classes]
        before = np.stack([np.r_[0, np.cumsum(classes)], np.r_[0, np.cumsum(widths)]], 1)[: len(m) : cls.SUPER]
        packed = [np.frombuffer(pack_bits(v, w), np.uint8) for v, w in ((classes, block.bit_length()), (place, widths))]
        return cls(n, block, before.astype("<u4"), *packed)

    def _stretch(self, s: np.ndarray) -> np.ndarray:
        """Numbers of ones of the blocks of each asked stretch, 0 beyond the last."""
        k = s[:, None] * self.SUPER + np.arange(self.SUPER)
        width = self.block.bit_length()
        got = read_bits(self.classes, np.minimum(k, max(0, self.blocks - 1)).ravel() * width, width).reshape(k.shape)
        return np.where(k < self.blocks, got, 0)

    def _opened(self, k: np.ndarray, s: np.ndarray, classes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Bits of the blocks asked, each once, and which row is whose; classes are the numbers of ones of stretches s, which ascend."""
        opened, row = np.unique(k, return_inverse=True)
        return self._blocks(opened, classes[np.searchsorted(s, opened // self.SUPER)]), row

    def _blocks(self, k: np.ndarray, classes: np.ndarray) -> np.ndarray:
        """Bits of blocks k; classes are the numbers of ones of their stretches."""
        choose, widths = _choose(self.block), _offset_widths(self.block)
        inner = k % self.SUPER
        ahead = np.where(np.arange(self.SUPER) < inner[:, None], widths[classes], 0).sum(1)
        left = classes[np.arange(len(k)), inner]
        place = read_bits(self.places, self.marks[k // self.SUPER, 1].astype(np.int64) + ahead, widths[left])
        out = np.zeros((len(k), self.block), np.int8)
        for j in range(self.block):
            zero_first = choose[self.block - 1 - j, left]
            one = (place >= zero_first) & (left > 0)
            out[:, j] = one
            place = place - np.where(one, zero_first, 0)
            left = left - one
        return out

    def rank(self, at: np.ndarray, bit: int = 1) -> np.ndarray:
        at = np.asarray(at, np.int64)
        if not self.n:
            return np.zeros(len(at), np.int64)
        k = np.minimum(at // self.block, self.blocks - 1)
        s, of = np.unique(k // self.SUPER, return_inverse=True)  # a stretch and a block are opened once for all their questions
        classes = self._stretch(s)
        ones = self.marks[k // self.SUPER, 0].astype(np.int64) + _ones_before(classes, of, k % self.SUPER)
        bits, row = self._opened(k, s, classes)
        ones += _ones_before(bits, row, at - k * self.block)
        return ones if bit else at - ones

    def select(self, i: np.ndarray, bit: int = 1) -> np.ndarray:
        i = np.asarray(i, np.int64)
        ones = self.marks[:, 0].astype(np.int64)
        have = ones if bit else np.arange(len(ones)) * self.SUPER * self.block - ones
        stretch = np.searchsorted(have, i, side="right") - 1
        s, of = np.unique(stretch, return_inverse=True)
        classes = self._stretch(s)
        run = np.cumsum(classes if bit else self.block - classes, 1)
        left = i - have[stretch]
        inner = np.minimum((run[of] <= left[:, None]).sum(1), self.SUPER - 1)
        left = left - np.where(inner > 0, run[of, inner - 1], 0)
        k = stretch * self.SUPER + inner
        bits, row = self._opened(k, s, classes)
        return k * self.block + _place_of(bits, row, left, bit)

    def access(self, at: np.ndarray) -> np.ndarray:
        at = np.asarray(at, np.int64)
        k = at // self.block
        s = np.unique(k // self.SUPER)
        bits, row = self._opened(k, s, self._stretch(s))
        return bits[row, at % self.block].astype(np.int64)

    def bits(self, directory: bool = True) -> int:
        """Bits of numbers of ones and places; the directory has a count and a pointer, 32 bits each, per stretch."""
        body = 8 * (len(self.classes) + len(self.places) - 32)
        return body + (64 * len(self.marks) if directory else 0)

    def to_bytes(self) -> bytes:
        cut = (self.blocks * self.block.bit_length() + 7) // 8
        return np.array([self.n, self.block], "<i8").tobytes() + self.marks.tobytes() + self.classes[:cut].tobytes() + self.places[:-16].tobytes()

    @classmethod
    def from_bytes(cls, data: bytes) -> RRR:
        n, block = np.frombuffer(data, "<i8", 2).tolist()
        m = -(-n // block)
        s = -(-m // cls.SUPER)
        cut = 16 + 8 * s
        end = cut + (m * block.bit_length() + 7) // 8
        raw = np.frombuffer(data, np.uint8)
        return cls(n, block, np.frombuffer(data, "<u4", 2 * s, 16).reshape(s, 2), raw[cut:end], raw[end:])


def read_bits(data: np.ndarray, first: np.ndarray, widths: np.ndarray | int) -> np.ndarray:
    """Numbers of up to 63 bits that begin at bits `first`; data has 16 bytes to spare at its end."""
    first = np.asarray(first, np.int64)
    rows = data[(first >> 3)[:, None] + np.arange(16)].view("<u8").reshape(-1, 2)
    shift = (first & 7).astype(np.uint64)
    high = np.where(shift > 0, rows[:, 1] << ((np.uint64(64) - shift) & np.uint64(63)), np.uint64(0))
    mask = (np.uint64(1) << np.asarray(widths, np.uint64)) - np.uint64(1)
    return (((rows[:, 0] >> shift) | high) & mask).astype(np.int64)


@functools.cache
def _offset_widths(block: int) -> np.ndarray:
    return np.array([(math.comb(block, k) - 1).bit_length() for k in range(block + 1)], np.int64)


def pack_bits(values: np.ndarray, widths: np.ndarray | int) -> bytes:
    """Values one after the other, each in its own number of bits, low bits first."""
    values = np.asarray(values, np.uint64)
    if not len(values):
        return b""
    widths = np.broadcast_to(np.asarray(widths, np.int64), values.shape)
    end = np.cumsum(widths)
    which = np.repeat(np.arange(len(values)), widths)
    shift = (np.arange(int(end[-1])) - np.repeat(end - widths, widths)).astype(np.uint64)
    return np.packbits(((values[which] >> shift) & np.uint64(1)).astype(np.uint8), bitorder="little").tobytes()


def unpack_bits(data: bytes, widths: np.ndarray) -> np.ndarray:
    widths = np.asarray(widths, np.int64)
    total = int(widths.sum())
    if not total:
        return np.zeros(len(widths), np.int64)
    bit = np.unpackbits(np.frombuffer(data, np.uint8), bitorder="little")[:total].astype(np.int64)
    end = np.cumsum(widths)
    shift = np.arange(total) - np.repeat(end - widths, widths)
    sums = np.r_[0, np.cumsum(bit << shift)]
    return sums[end] - sums[end - widths]
