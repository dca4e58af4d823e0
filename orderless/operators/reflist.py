"""Reference-list graph coding, the offline baseline: a node's list copies blocks of an earlier list and adds residuals.

Per node: how far back the reference stands (0 for none), which blocks of it are copied and skipped in turn, and the other neighbours as
gaps with runs of consecutive ids. All integers become a token and raw low bits; tokens are entropy-coded under the shard's
histogram of their context, whose size is counted. The older form tells residuals as intervals of consecutive ids and the rest as
gaps, and writes the integers in plain variable length: as many zeros as the number plus one has digits after its first, then these.
"""

from __future__ import annotations

import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from ..functions.ans import PRECISION, WordState
from ..functions.bitvec import pack_bits
from . import arrow
from .edgecodec import _BLOB, BLOB, _sharded, bounds

REF, BLOCKS, BLOCK, RESIDUALS, FIRST, GAP, RUN, INTERVALS, LENGTH = range(9)
CONTEXTS, TOKENS, CHAIN = 9, 160, 3


def _token(v: int) -> tuple[int, int, int]:
    """(token, raw bits, how many): small values are their own token, larger ones exponent and leading mantissa bit."""
    if v < 16:
        return v, 0, 0
    e = v.bit_length() - 1
    return 16 + (e - 4) * 2 + (v >> (e - 1) & 1), v & ((1 << (e - 1)) - 1), e - 1


def _value(token: int, raw) -> int:
    if token < 16:
        return token
    e, lead = divmod(token - 16, 2)
    e += 4
    return (2 + lead) << (e - 1) | raw(e - 1)


def _zigzag(v: int) -> int:
    return v * 2 if v >= 0 else -v * 2 - 1


def _blocks(ref: list[int], own: set[int]) -> list[int]:
    """Lengths of copied and skipped blocks in turn, copied first; the last is implied."""
    runs = [(k, len(list(g))) for k, g in itertools.groupby(ref, lambda v: v in own)]
    out = ([0] if runs and not runs[0][0] else []) + [n for _, n in runs]
    return out[:-1]


def _copied(ref: list[int], blocks: list[int]) -> list[int]:
    out, at, copy = [], 0, True
    for n in blocks:
        out += ref[at : at + n] if copy else []
        at += n
        copy = not copy
    return out + (ref[at:] if copy else [])


def _residuals(node: int, rest: list[int], min_run: int) -> list[tuple[int, int]]:
    out, i = [], 0
    while i < len(rest):
        if i == 0:
            out.append((FIRST, _zigzag(rest[0] - node)))
            i = 1
            continue
        gap = rest[i] - rest[i - 1] - 1
        out.append((GAP, gap))
        i += 1
        if gap == 0:  # how many more ids follow without a gap, once min_run have
            run = 1
            while i < len(rest) and run < min_run and rest[i] == rest[i - 1] + 1:
                out.append((GAP, 0))
                run += 1
                i += 1
            if run == min_run:
                more = 0
                while i < len(rest) and rest[i] == rest[i - 1] + 1:
                    more += 1
                    i += 1
                out.append((RUN, more))
    return out


def _by_intervals(node: int, rest: list[int], min_run: int) -> list[tuple[int, int]]:
    """Intervals of min_run or more consecutive ids by start and length, then the other ids by gaps."""
    runs, i = [], 0
    while i < len(rest):
        j = i + 1
        while j < len(rest) and rest[j] == rest[j - 1] + 1:
            j += 1
        runs.append((rest[i], j - i))
        i = j
    long = [r for r in runs if r[1] >= max(2, min_run)]
    alone = [v for a, n in runs if n < max(2, min_run) for v in range(a, a + n)]
    out, last = [(INTERVALS, len(long))], None
    for a, n in long:
        out += [(FIRST, _zigzag(a - node)) if last is None else (GAP, a - last - 1), (LENGTH, n - max(2, min_run))]
        last = a + n - 1
    out.append((RESIDUALS, len(alone)))
    return out + [(FIRST, _zigzag(v - node)) if k == 0 else (GAP, v - alone[k - 1] - 1) for k, v in enumerate(alone)]


def _digits(v: np.ndarray) -> np.ndarray:
    """Binary digits of numbers, none for zero."""
    if v.max(initial=0) < 1 << 53:
        return np.frexp(v.astype(np.float64))[1].astype(np.int64)
    return np.array([x.bit_length() for x in v.tolist()], np.int64)


#: Numbers of lists that are compared with their references together.
COMPARED = 1 << 19


def _near(flat: np.ndarray, owner: np.ndarray, window: int) -> tuple[np.ndarray, np.ndarray]:
    """Places of equal numbers of two lists at most `window` apart: in the later list and in the earlier one."""
    order = np.argsort(flat, kind="stable")
    v, o, late, early = flat[order], owner[order], [], []
    for s in range(1, min(window, len(v) - 1) + 1):  # a number's lists ascend
        hit = (v[s:] == v[:-s]) & (o[s:] - o[:-s] <= window)
        if not hit.any():
            break
        late.append(order[s:][hit])
        early.append(order[:-s][hit])
    none = np.zeros(0, np.int64)
    return np.concatenate([none, *late]), np.concatenate([none, *early])


def _options(nodes: list[tuple[int, list[int]]], window: int, min_run: int, intervals: bool) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(list, how far back, numbers in common, twice the cost) of every list with every reference that has two of its numbers or more."""
    size = np.array([len(x) for _, x in nodes], np.int64)
    at, name = np.r_[0, np.cumsum(size)], np.array([n for n, _ in nodes], np.int64)
    flat = np.fromiter(itertools.chain.from_iterable(x for _, x in nodes), np.int64, int(at[-1]))
    owner = np.repeat(np.arange(len(nodes)), size)
    late, early = _near(flat, owner, window)
    pair = owner[late] * (window + 1) + owner[late] - owner[early]
    order = np.argsort(pair, kind="stable")
    late, early = late[order], early[order]
    pairs, common = np.unique(pair[order], return_counts=True)
    wanted = (common > 1) & (pairs % (window + 1) > 0)
    mine = np.repeat(wanted, common)
    late, early, pairs, common = late[mine], early[mine], pairs[wanted], common[wanted]
    one, back = pairs // (window + 1), pairs % (window + 1)
    met = np.r_[0, np.cumsum(common)]
    held = np.cumsum(size[one] + size[one - back]) // COMPARED
    cuts = [0, *(np.flatnonzero(np.diff(held)) + 1).tolist(), len(pairs)]
    cost = np.zeros(len(pairs), np.int64)
    for x, y in zip(cuts[:-1], cuts[1:], strict=True):
        if y > x:
            cost[x:y] = _costs(flat, at, size, name, one[x:y], back[x:y], common[x:y], late[met[x] : met[y]], early[met[x] : met[y]], min_run, intervals)
    return one, back, common, cost


def _costs(flat, at, size, name, one, back, common, late, early, min_run: int, intervals: bool) -> np.ndarray:
    """Twice what `describe` counts for each list under its reference; late and early are the places of the numbers in common."""
    n, ref, of = len(one), one - back, np.repeat(np.arange(len(one)), common)
    total = lambda i, c: np.bincount(i, c, n).astype(np.int64)
    low, high = lambda v: 2 * _digits(v) + 2, lambda v: 3 * _digits(v) + 2  # contexts before GAP, and the others
    zigzag = lambda v: np.where(v >= 0, 2 * v, -2 * v - 1)
    # blocks of the reference
    begin = np.r_[0, np.cumsum(size[ref])]
    i, copied = np.repeat(np.arange(n), size[ref]), np.zeros(begin[-1], bool)
    copied[begin[of] + early - at[ref][of]] = True
    new = np.r_[True, (copied[1:] != copied[:-1]) | (i[1:] != i[:-1])]
    start = np.flatnonzero(new)
    length, whose = np.diff(np.r_[start, len(copied)]), i[start]
    told = np.r_[whose[1:] == whose[:-1], False]  # a list's last block is implied
    skips = ~copied[begin[:-1]]
    out = low(back) + low(np.bincount(whose, minlength=n) - 1 + skips) + 2 * skips + total(whose[told], low(length[told]))
    # what the reference doesn't have
    begin = np.r_[0, np.cumsum(size[one])]
    i, keep = np.repeat(np.arange(n), size[one]), np.ones(begin[-1], bool)
    keep[begin[of] + late - at[one][of]] = False
    v, i = flat[np.arange(begin[-1]) + (at[one] - begin[:-1])[i]][keep], i[keep]
    if not intervals:
        first = np.r_[True, i[1:] != i[:-1]][: len(i)]
        gap = np.r_[0, v[1:] - v[:-1] - 1][: len(i)]
        zero = ~first & (gap == 0)
        far = ~first & ~zero
        out += low(size[one] - common) + total(i[first], low(zigzag(v[first] - name[one][i[first]]))) + total(i[far], high(gap[far]))
        start, stop = np.flatnonzero(zero & ~np.r_[False, zero[:-1]][: len(i)]), np.flatnonzero(zero & ~np.r_[zero[1:], False][: len(i)])
        run = stop - start + 1
        return out + total(i[start], 2 * np.minimum(run, min_run) + np.where(run >= min_run, high(np.maximum(run - min_run, 0)), 0))
    least = max(2, min_run)

    def numbers(i, v, gap):
        """A list's first number by its distance from the node, the others by their gaps."""
        first = np.r_[True, i[1:] != i[:-1]][: len(i)]
        return total(i, np.where(first, low(zigzag(v - name[one][i])), high(np.where(first, 0, gap))))

    start = np.flatnonzero(np.r_[True, (i[1:] != i[:-1]) | (v[1:] != v[:-1] + 1)][: len(i)])
    length = np.diff(np.r_[start, len(i)])
    long = length >= least
    a, k, w = v[start[long]], length[long], i[start[long]]
    out += high(np.bincount(w, minlength=n)) + numbers(w, a, np.r_[0, a[1:] - (a + k)[:-1]][: len(a)]) + total(w, high(k - least))
    alone = np.repeat(~long, length)
    v, i = v[alone], i[alone]
    return out + low(np.bincount(i, minlength=n)) + numbers(i, v, np.r_[0, v[1:] - v[:-1] - 1][: len(v)])


def describe(nodes: list[tuple[int, list[int]]], window: int = 32, min_run: int = 3, ref_choice: str = "greedy", intervals: bool = False) -> list[tuple[int, int]]:
    """(context, value) of all lists; nodes ascend. What every reference would cost is computed for many lists at a time."""
    told = (lambda node, rest: _by_intervals(node, rest, min_run)) if intervals else (lambda node, rest: [(RESIDUALS, len(rest)), *_residuals(node, rest, min_run)])
    out: list[tuple[int, int]] = []
    chain: list[int] = []
    cost = lambda symbols: sum(v.bit_length() * (2 if c < GAP else 3) + 2 for c, v in symbols)  # twice, a whole number
    options = _options(nodes, window, min_run, intervals)
    cuts = np.searchsorted(options[0], np.arange(len(nodes) + 1)).tolist()
    _, back, common, costs = (x.tolist() for x in options)
    for i, (node, nbrs) in enumerate(nodes):
        plain = [(REF, 0), *told(node, nbrs)]
        some = [k for k in range(cuts[i], cuts[i + 1]) if chain[i - back[k]] < CHAIN]
        if ref_choice == "overlap" and some:
            some = [max(some, key=lambda k: (common[k], -back[k]))]
        best = min(some, key=costs.__getitem__, default=None)  # the nearest of the cheapest
        if best is None or costs[best] >= cost(plain):
            chain.append(0)
            out += plain
            continue
        b, ref = back[best], nodes[i - back[best]][1]
        blocks, have = _blocks(ref, set(nbrs)), set(ref)
        chain.append(chain[i - b] + 1)
        out += [(REF, b), (BLOCKS, len(blocks)), *((BLOCK, n) for n in blocks), *told(node, [v for v in nbrs if v not in have])]
    return out


def _write_plain(values: list[int]) -> tuple[bytes, int]:
    """Integers in variable length, and their bits."""
    v = np.array(values, np.int64) + 1
    digits = np.array([x.bit_length() for x in v.tolist()], np.int64)
    # low bits first: zeros, a one, then the digits after the first
    body = np.stack([np.zeros(len(v), np.int64), np.ones(len(v), np.int64), v & ((1 << (digits - 1)) - 1)], 1)
    width = np.stack([digits - 1, np.ones(len(v), np.int64), digits - 1], 1)
    return pack_bits(body.ravel(), width.ravel()), int(width.sum())


def _read_plain(data: bytes):
    """A function that gives the next integer."""
    bits = np.unpackbits(np.frombuffer(data, np.uint8), bitorder="little")
    ones, at = np.flatnonzero(bits), 0

    def read(_: int) -> int:
        nonlocal at
        zeros = int(ones[np.searchsorted(ones, at)]) - at
        first = at + zeros + 1
        at = first + zeros
        return (1 << zeros | sum(int(b) << k for k, b in enumerate(bits[first:at]))) - 1

    return read


def encode_lists(nodes: list[tuple[int, list[int]]], window: int = 32, min_run: int = 3, entropy: str = "ans", ref_choice: str = "greedy", intervals: bool = False) -> tuple[bytes, int]:
    symbols = describe(nodes, window, min_run, ref_choice, intervals)
    if entropy == "none":
        return _write_plain([v for _, v in symbols])
    context, value = np.array(symbols, np.int64).reshape(-1, 2).T
    large = value >= 16
    e = np.where(large, _digits(value) - 1, 1)  # of small values nothing but the token is told
    token, low = np.where(large, 16 + (e - 4) * 2 + (value >> (e - 1) & 1), value), np.where(large, e - 1, 0)
    hist = np.bincount(context * TOKENS + token, minlength=CONTEXTS * TOKENS).reshape(CONTEXTS, TOKENS)
    start = np.concatenate([np.zeros((CONTEXTS, 1), np.int64), np.cumsum(hist, 1)], 1)
    total, state = hist.sum(1)[context], WordState()
    a, b = ((start[context, token + k] << PRECISION) // total for k in (0, 1))
    for x, freq in zip(a[::-1].tolist(), (b - a)[::-1].tolist(), strict=True):
        if freq < 1 << PRECISION:
            state.push(x, freq, PRECISION)
    raw = pack_bits((value & ((1 << low) - 1)).astype(np.uint64), low)
    used = np.argwhere(hist > 0)
    table = np.array([[c * TOKENS + t, hist[c, t]] for c, t in used], "<u4").reshape(-1, 2)
    body = state.to_bytes()
    bits = state.bits + int(low.sum()) + sum(8 + 7 * max(1, -(-int(h).bit_length() // 7)) for h in table[:, 1])
    return np.array([len(table), len(body)], "<u4").tobytes() + table.tobytes() + body + raw, bits


def _read_coded(payload: bytes):
    """A function that gives the next integer of a context."""
    n, size = np.frombuffer(payload, "<u4", 2).tolist()
    table = np.frombuffer(payload, "<u4", 2 * n, 8).reshape(n, 2).astype(np.int64)
    hist = np.zeros((CONTEXTS, TOKENS), np.int64)
    hist.ravel()[table[:, 0]] = table[:, 1]
    start = np.concatenate([np.zeros((CONTEXTS, 1), np.int64), np.cumsum(hist, 1)], 1)
    totals, state = hist.sum(1).tolist(), WordState.from_bytes(payload[8 + 8 * n : 8 + 8 * n + size])
    rest, at = payload[8 + 8 * n + size :], 0

    def raw(k: int) -> int:
        nonlocal at
        out = int.from_bytes(rest[at >> 3 : (at + k + 7) >> 3], "little") >> (at & 7) & ((1 << k) - 1) if k < 64 else 0
        at += k
        return out

    def read(c: int) -> int:
        slot = ((state.slot(PRECISION) + 1) * totals[c] - 1) >> PRECISION
        t = int(np.searchsorted(start[c], slot, side="right")) - 1
        a, b = (int(start[c, t + k] << PRECISION) // totals[c] for k in (0, 1))
        if b - a < 1 << PRECISION:
            state.pop(a, b - a, PRECISION)
        return _value(t, raw)

    return read


def _signed(v: int) -> int:
    return v // 2 if v % 2 == 0 else -(v + 1) // 2


def decode_lists(payload: bytes, node_ids: list[int], min_run: int = 3, entropy: str = "ans", intervals: bool = False) -> list[tuple[int, list[int]]]:
    if not node_ids:
        return []
    read = _read_coded(payload) if entropy == "ans" else _read_plain(payload)
    done: list[list[int]] = []
    for i, node in enumerate(node_ids):
        back = read(REF)
        rest: list[int] = []
        have = _copied(done[i - back], [read(BLOCK) for _ in range(read(BLOCKS))]) if back else []
        if intervals:
            last = None
            for _ in range(read(INTERVALS)):
                a = node + _signed(read(FIRST)) if last is None else last + 1 + read(GAP)
                last = a + read(LENGTH) + max(2, min_run) - 1
                have += range(a, last + 1)
        left = read(RESIDUALS)
        run = 0
        while len(rest) < left:
            if not rest:
                rest.append(node + _signed(read(FIRST)))
                continue
            gap = read(GAP)
            rest.append(rest[-1] + 1 + gap)
            run = run + 1 if gap == 0 else 0
            if run == min_run and not intervals:
                for _ in range(read(RUN)):
                    rest.append(rest[-1] + 1)
                run = 0
        done.append(sorted(have + rest))
    return list(zip(node_ids, done, strict=True))


def encode(edges: DataFrame, n_vertices: int, window: int = 32, min_run: int = 3, entropy: str = "ans", ref_choice: str = "greedy", shards: int | None = None, intervals: bool = False) -> DataFrame:
    """One blob per shard of sources; the nodes' ids go along as gaps, counted. entropy "none" with intervals is the older form."""
    arrow.importable(edges.sparkSession)
    first = bounds(edges, n_vertices, shards)

    def run(key: tuple, t: pa.Table) -> pa.Table:
        t = t.sort_by([("src", "ascending"), ("dst", "ascending")])
        src, dst = t["src"].to_numpy(), t["dst"].to_pylist()
        cut = np.flatnonzero(np.r_[True, src[1:] != src[:-1], True]).tolist()
        nodes = [(int(src[a]), dst[a:b]) for a, b in zip(cut[:-1], cut[1:], strict=True)]
        body, bits = encode_lists(nodes, window, min_run, entropy, ref_choice, intervals)
        ids, more = _write_plain((np.diff(np.array([-1, *(n for n, _ in nodes)])) - 1).tolist())
        head = np.array([len(nodes), len(ids), min_run], "<u4").tobytes() + ids
        name = f"reflist:{entropy}:{'intervals' if intervals else 'runs'}"
        return pa.Table.from_pylist([{"shard": key[0].as_py(), "n_vertices": n_vertices, "n_edges": len(dst), "codec": name, "payload": head + body, "bits": bits + more}], schema=_BLOB)

    return _sharded(edges, first).groupBy("shard").applyInArrow(run, BLOB)


def decode(blobs: DataFrame) -> DataFrame:
    """(src, dst) of blobs of any form; a blob of another coder is an error."""
    arrow.importable(blobs.sparkSession)

    def run(batches):
        for b in batches:
            for r in b.to_pylist():
                name, *form = r["codec"].split(":")
                if name != "reflist":
                    raise ValueError(f"no reference-list blob: {r['codec']!r}")
                n, size, min_run = np.frombuffer(r["payload"], "<u4", 3).tolist()
                read = _read_plain(r["payload"][12 : 12 + size])
                ids = np.cumsum([read(0) + 1 for _ in range(n)]) - 1
                got = decode_lists(r["payload"][12 + size :], ids.tolist(), min_run, form[0], form[1] == "intervals")
                yield pa.RecordBatch.from_arrays([pa.array([i for i, x in got for _ in x], pa.int64()), pa.array([v for _, x in got for v in x], pa.int64())], ["src", "dst"])

    return blobs.mapInArrow(run, "src long, dst long")
