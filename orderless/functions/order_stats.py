"""Order statistics under insertion and removal."""

from __future__ import annotations

import bisect


class Fenwick:
    """Counts over 0..size-1 with prefix sums and their inverse in logarithmic time."""

    def __init__(self, size: int, ones: bool = False):
        self.size, self.tree = size, [0] * (size + 1)
        if ones:
            for i in range(1, size + 1):
                self.tree[i] = i & -i
        self.top = 1 << max(0, size.bit_length() - 1)

    def add(self, at: int, by: int = 1) -> None:
        at += 1
        while at <= self.size:
            self.tree[at] += by
            at += at & -at

    def below(self, at: int) -> int:
        out = 0
        while at:
            out += self.tree[at]
            at &= at - 1
        return out

    def find(self, slot: int, bias: int = 0) -> int:
        """The place whose share, its count plus the bias, holds the slot."""
        at, step = 0, self.top
        while step:
            to = at + step
            if to <= self.size and (share := self.tree[to] + step * bias) <= slot:
                slot -= share
                at = to
            step >>= 1
        return at


class SortedRanks:
    """A sorted multiset in blocks: insert and rank in about the square root of its size."""

    def __init__(self, block: int = 512):
        self.block, self.parts, self.size = block, [[]], 0

    def rank(self, value) -> int:
        """How many members are smaller."""
        out = 0
        for part in self.parts:
            if part and part[-1] < value:
                out += len(part)
            else:
                return out + bisect.bisect_left(part, value)
        return out

    def insert(self, value) -> None:
        self.size += 1
        for i, part in enumerate(self.parts):
            if not part or value <= part[-1] or i == len(self.parts) - 1:
                bisect.insort(part, value)
                if len(part) > 2 * self.block:
                    self.parts[i : i + 1] = [part[: self.block], part[self.block :]]
                return

    def __iter__(self):
        for part in self.parts:
            yield from part
