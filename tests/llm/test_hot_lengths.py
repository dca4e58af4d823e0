"""Best fit on few distinct, often repeated lengths: the plan equals piece-by-piece packing."""

import random
from collections import Counter, defaultdict

import pytest

from orderless.llm import packing


def one_by_one(lengths, capacity):
    rooms = []
    for n in sorted(lengths, reverse=True):
        fits = [b for b in rooms if b >= n]
        if fits:
            rooms.remove(min(fits))
        rooms.append((min(fits) if fits else capacity) - n)
    return sorted(rooms)


def rooms_of(lengths, capacity):
    used = defaultdict(int)
    ranks = defaultdict(list)
    for length, rank, count, first, offset in sorted(packing.best_fit_plan(Counter(lengths), capacity).tolist(), key=lambda p: p[4]):
        ranks[length] += range(rank, rank + count)
        for k in range(count):
            assert used[first + k] == offset
            used[first + k] += length
    assert all(sorted(r) == list(range(Counter(lengths)[n])) for n, r in ranks.items())
    return sorted(capacity - u for u in used.values())


@pytest.mark.parametrize("seed", range(60))
def test_few_lengths(seed):
    r = random.Random(seed)
    capacity = r.choice([20, 64, 200])
    some = [r.randrange(1, capacity + 1) for _ in range(r.randrange(1, 6))]
    lengths = [n for n in some for _ in range(r.randrange(1, 80))]
    assert rooms_of(lengths, capacity) == one_by_one(lengths, capacity)


def test_known_counts():
    assert len(rooms_of([12, 12, 4, 4, 3, 3, 2], 20)) == len(one_by_one([12, 12, 4, 4, 3, 3, 2], 20)) == 2
    assert len(rooms_of([2100] * 1000 + [660] * 1000 + [499] * 2668, 4096)) == 1001
