"""Probability models as integer slots: span(symbol) -> (start, freq), find(slot) -> (symbol, start, freq)."""

from __future__ import annotations

import bisect
from itertools import accumulate

from .order_stats import Fenwick


class Uniform:
    def __init__(self, total: int):
        self.total = total

    def span(self, symbol: int) -> tuple[int, int]:
        return symbol, 1

    def find(self, slot: int) -> tuple[int, int, int]:
        return slot, slot, 1


class Table:
    """Fixed integer weights."""

    def __init__(self, weights: list[int]):
        self.weights, self.starts = list(weights), [0, *accumulate(weights)]
        self.total = self.starts[-1]

    def span(self, symbol: int) -> tuple[int, int]:
        return self.starts[symbol], self.weights[symbol]

    def find(self, slot: int) -> tuple[int, int, int]:
        symbol = bisect.bisect_right(self.starts, slot) - 1
        return symbol, self.starts[symbol], self.weights[symbol]


class Falling:
    """Symbol s weighs total - s: low ids are likelier, as where ids go by popularity. Spans in closed form, so any universe fits."""

    def __init__(self, size: int):
        self.size, self.total = size, size * (size + 1) // 2

    def _start(self, symbol: int) -> int:
        return symbol * self.size - symbol * (symbol - 1) // 2

    def span(self, symbol: int) -> tuple[int, int]:
        return self._start(symbol), self.size - symbol

    def find(self, slot: int) -> tuple[int, int, int]:
        low, high = 0, self.size - 1
        while low < high:
            mid = (low + high + 1) // 2
            low, high = (mid, high) if self._start(mid) <= slot else (low, mid - 1)
        return low, *self.span(low)


class Bernoulli(Table):
    def __init__(self, ones: int, total: int):
        super().__init__([total - ones, ones])


class Counts:
    """Weights that change, over 0..size-1: a bias for each symbol plus its count so far."""

    def __init__(self, size: int, bias: int = 1):
        self.bias, self.tree, self.total = bias, Fenwick(size), size * bias

    def add(self, symbol: int, by: int = 1) -> None:
        self.tree.add(symbol, by)
        self.total += by

    def span(self, symbol: int) -> tuple[int, int]:
        below = self.tree.below(symbol)
        return below + symbol * self.bias, self.tree.below(symbol + 1) - below + self.bias

    def find(self, slot: int) -> tuple[int, int, int]:
        symbol = self.tree.find(slot, self.bias)
        start, freq = self.span(symbol)
        return symbol, start, freq


class AdaptiveBytes(Counts):
    """Every symbol starts with weight 1 and gains 1 each time it is seen."""

    def __init__(self, alphabet: int = 256):
        super().__init__(alphabet, 1)


class Urn(Counts):
    """Vertices drawn in proportion to their degree so far plus a bias."""
