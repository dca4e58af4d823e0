"""Random-order coding of sets and multisets of ids.

The order in which ids are coded is a latent variable drawn from the state itself: the encoder pops the rank of the next id among
those left and pushes the id; the decoder pops the id and pushes its rank among those it has. About log2(n!) bits are
saved, and after decoding the state is what it was before encoding.
"""

from __future__ import annotations

import numpy as np

from .ans import DIGIT, ExactState, WordState, WordStateBatch
from .order_stats import Fenwick, SortedRanks

State = ExactState | WordState


def encode_set(state: State, ids: list[int], universe: int, distinct: bool = False, model=None) -> None:
    """distinct codes each id among the ids not used yet (exactly log2 of the number of sets); else among all.

    A model of the elements (span, find, total; exact states only) takes the place of the uniform one.
    """
    left = sorted(ids)
    if distinct:  # the decoder's last id comes first here; ids coded later by the decoder are those still left here
        tree = Fenwick(len(left), ones=True)
        for i in range(len(left), 0, -1):
            at = tree.find(state.pop_uniform(i))
            tree.add(at, -1)
            # the decoder will have decoded exactly the ids that remain; the id's rank among unused ones skips those below it
            state.push_uniform(left[at] - tree.below(at), universe - (i - 1))
        return
    tree = Fenwick(len(left), ones=True)
    for i in range(len(left), 0, -1):
        at = tree.find(state.pop_uniform(i))
        tree.add(at, -1)
        state.push_uniform(left[at], universe) if model is None else state.encode(model, left[at])


def decode_set(state: State, n: int, universe: int, distinct: bool = False, model=None) -> list[int]:
    got = SortedRanks()
    for i in range(1, n + 1):
        if distinct:
            gap = state.pop_uniform(universe - (i - 1))
            # the gap-th id not decoded yet
            value = gap
            while True:
                at = got.rank(value + 1)
                if gap + at == value:
                    break
                value = gap + at
            rank = at
        else:
            value = state.pop_uniform(universe) if model is None else state.decode(model)
            rank = got.rank(value)
        got.insert(value)
        state.push_uniform(rank, i)
    return list(got)


def encode_multiset(state: ExactState, values: list[int], universe: int) -> None:
    left = sorted(values)
    distinct = sorted(set(left))
    tree = Fenwick(len(distinct))
    place = {v: i for i, v in enumerate(distinct)}
    for v in left:
        tree.add(place[v])
    for i in range(len(left), 0, -1):
        at = tree.find(state.slot(i))
        start = tree.below(at)
        state.pop(start, tree.below(at + 1) - start, i)
        tree.add(at, -1)
        state.push_uniform(distinct[at], universe)


def decode_multiset(state: ExactState, n: int, universe: int) -> list[int]:
    got = SortedRanks()
    for i in range(1, n + 1):
        value = state.pop_uniform(universe)
        got.insert(value)
        start = got.rank(value)
        state.push(start, got.rank(value + 1) - start, i)
    return list(got)


def encode_bucketed(state: ExactState, ids: list[int], universe: int, shift: int) -> None:
    """A set whose latent is only the order of id ranges of 2**shift: counts over few ranges stand in for exact ranks.

    Within a range the order is fixed, so its log2(count!) bits aren't saved; ranks cost less to keep.
    """
    stacks: dict[int, list[int]] = {}
    for v in sorted(ids):
        stacks.setdefault(v >> shift, []).append(v)
    tree = Fenwick(((universe - 1) >> shift) + 1)
    for b, s in stacks.items():
        tree.add(b, len(s))
    for i in range(len(ids), 0, -1):
        b = tree.find(state.slot(i))
        state.pop(tree.below(b), len(stacks[b]), i)
        tree.add(b, -1)
        state.push_uniform(stacks[b].pop(), universe)


def decode_bucketed(state: ExactState, n: int, universe: int, shift: int) -> list[int]:
    tree, got = Fenwick(((universe - 1) >> shift) + 1), []
    for i in range(1, n + 1):
        value = state.pop_uniform(universe)
        b = value >> shift
        tree.add(b)
        start = tree.below(b)
        state.push(start, tree.below(b + 1) - start, i)
        got.append(value)
    return sorted(got)


def _pop_id(state: WordStateBatch, n: int, universe: int) -> np.ndarray:
    if universe <= 1 << 26:
        return state.pop_uniform(n, universe)
    high = state.pop_uniform(n, (universe + (1 << DIGIT) - 1) >> DIGIT)
    return (high << DIGIT) | state.pop_uniform(n, 1 << DIGIT)


def _push_id(state: WordStateBatch, n: int, value: np.ndarray, universe: int) -> None:
    if universe <= 1 << 26:
        state.push_uniform(n, value, universe)
        return
    state.push_uniform(n, value & ((1 << DIGIT) - 1), 1 << DIGIT)
    state.push_uniform(n, value >> DIGIT, (universe + (1 << DIGIT) - 1) >> DIGIT)


def encode_sets(flat: np.ndarray, at: np.ndarray, universe: int, seeded: int | None = None) -> tuple[list[bytes], np.ndarray]:
    """Many sets in lockstep, ids sorted within each; at holds their m+1 positions. Payloads and bits, in the order given."""
    size = np.diff(at)
    order = np.argsort(-size, kind="stable")
    size, m = size[order], len(order)
    longest = int(size[0]) if m else 0
    left = np.zeros((m, longest), np.int64)
    inside = np.arange(longest) < size[:, None]
    left[inside] = flat[np.repeat(at[:-1][order], size) + np.arange(int(size.sum())) - np.repeat(np.cumsum(size) - size, size)]
    state = WordStateBatch(m, longest * (max(universe, 2) - 1).bit_length() // 32 + 4, seeded)
    todo = size.copy()
    for step in range(longest):
        n = int(np.searchsorted(-size, -step, side="left"))  # sets with more than `step` ids
        i = todo[:n]
        rank = state.pop_uniform(n, i)
        value = left[np.arange(n), rank]
        width = int(i.max())
        move = np.arange(width - 1) >= rank[:, None]
        left[:n, : width - 1] = np.where(move, left[:n, 1:width], left[:n, : width - 1])
        _push_id(state, n, value, universe)
        todo[:n] -= 1
    back = np.empty(m, np.int64)
    back[order] = np.arange(m)
    payload = state.to_bytes()
    return [payload[k] for k in back.tolist()], state.bits()[back]


def decode_sets(payload: list[bytes], size: np.ndarray, universe: int) -> np.ndarray:
    """Ids of all sets, sorted within each, one set after the other."""
    order = np.argsort(-size, kind="stable")
    by, m = size[order], len(order)
    longest = int(by[0]) if m else 0
    state = WordStateBatch.from_bytes([payload[k] for k in order.tolist()])
    got = np.full((m, longest), np.iinfo(np.int64).max)
    # the encoder's steps backwards: its last id is the first here, coded when one was left
    for step in range(longest):
        n = int(np.searchsorted(-by, -step, side="left"))
        value = _pop_id(state, n, universe)
        have = got[:n, : step + 1]
        rank = (have[:, :step] < value[:, None]).sum(1)
        after = np.arange(step + 1) > rank[:, None]
        shifted = np.concatenate([have[:, :1], have[:, :-1]], 1)
        have = np.where(after, shifted, have)
        have[np.arange(n), rank] = value
        got[:n, : step + 1] = have
        state.push_uniform(n, rank, step + 1)
    inside = np.arange(longest) < by[:, None]
    flat = got[inside]
    start = np.cumsum(by) - by
    back = np.empty(m, np.int64)
    back[order] = np.arange(m)
    n = size.astype(np.int64)
    return flat[np.repeat(start[back], n) + np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)] if m else flat
