"""Coders, set codecs and bit structures: worked values, invertibility, bounds."""

import copy
import math
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from orderless.functions import bitsback, measures, models, setcodec
from orderless.functions.ans import ExactState, WordState
from orderless.functions.bitvec import RRR, Flat, pack_bits, unpack_bits
from orderless.functions.listcodecs import CODECS, EliasFano, codec
from orderless.functions.order_stats import Fenwick, SortedRanks
from orderless.operators import codecodec, edgecodec, reflist
from orderless.operators.wavelet import Tree


def test_push_trace():
    s, t, seen = ExactState(1), models.Table([1, 2, 5]), []
    for x in (2, 0, 1, 2):
        s.encode(t, x)
        seen.append(s.value)
    assert seen == [4, 32, 129, 207]
    assert [s.decode(t) for _ in range(4)] == [2, 1, 0, 2]
    assert s.value == 1


@pytest.mark.parametrize(("start", "distinct", "end"), [(24, False, 66620), (0, False, 1084), (24, True, 44579)])
def test_set_values(start, distinct, end):
    s = ExactState(start)
    setcodec.encode_set(s, [1, 3, 8, 12], 16, distinct)
    assert s.value == end
    assert setcodec.decode_set(s, 4, 16, distinct) == [1, 3, 8, 12]
    assert s.value == start


def test_multiset_value():
    s = ExactState(100)
    setcodec.encode_multiset(s, [2, 2, 5], 8)
    assert s.value == 17237
    assert setcodec.decode_multiset(s, 3, 8) == [2, 2, 5]
    assert s.value == 100


@settings(max_examples=60, deadline=None)
@given(st.sets(st.integers(0, 10**12 - 1), max_size=60), st.booleans(), st.booleans())
def test_set_states_return(ids, exact, seeded):
    make = (ExactState.seeded if seeded else lambda *_: ExactState(0)) if exact else (WordState.seeded if seeded else lambda *_: WordState())
    s = make(80) if exact and seeded else make()
    before = copy.deepcopy(s)
    setcodec.encode_set(s, sorted(ids), 10**12)
    assert setcodec.decode_set(s, len(ids), 10**12) == sorted(ids)
    assert s.__dict__ == before.__dict__


@settings(max_examples=40, deadline=None)
@given(st.lists(st.sets(st.integers(0, 999), max_size=40), max_size=20), st.sampled_from(sorted(CODECS)))
def test_codecs_return_ids(lists, name):
    at = np.r_[0, np.cumsum([len(x) for x in lists])].astype(np.int64)
    flat = np.array([i for x in lists for i in sorted(x)], np.int64)
    c = codec(name, 1000)
    payload, bits = c.encode(flat, at)
    assert (c.decode(payload, np.diff(at)) == flat).all()
    assert len(bits) == len(lists)


@pytest.mark.parametrize("universe", [1, 2, 7, 1 << 26, (1 << 26) + 1, 1 << 40])
@pytest.mark.parametrize("name", ["packed", "roc", "roc_exact", "ef"])
def test_codecs_at_the_edges(universe, name):
    if name == "ef" and universe > 1 << 26:
        pytest.skip("a list of two ids needs no such universe")
    lists = [[], [0], [universe - 1], sorted({0, universe - 1}), list(range(min(universe, 50)))]
    at = np.r_[0, np.cumsum([len(x) for x in lists])].astype(np.int64)
    flat = np.array(sum(lists, []), np.int64)
    c = codec(name, universe)
    payload, _ = c.encode(flat, at)
    assert (c.decode(payload, np.diff(at)) == flat).all()


def test_exact_states_say_what_is_too_long():
    ids = np.arange((1 << 17) + 1)
    for name in ("roc_exact", "roc_buckets"):
        with pytest.raises(ValueError, match="segment_bits"):
            codec(name, 1 << 20).encode(ids, np.array([0, len(ids)]))


def test_lockstep_equals_scalar():
    r = random.Random(0)
    for universe in (10**6, 10**9):
        lists = [sorted(r.sample(range(universe), r.choice([0, 1, 2, 7, 50, 200]))) for _ in range(60)]
        payload, bits = setcodec.encode_sets(np.array(sum(lists, [])), np.r_[0, np.cumsum([len(x) for x in lists])], universe)
        for x, p, b in zip(lists, payload, bits, strict=True):
            s = WordState()
            setcodec.encode_set(s, x, universe)
            assert s.to_bytes() == p and s.bits == b


def test_rates_meet_bounds():
    r = random.Random(3)
    ids = sorted(r.sample(range(10**6), 3906))
    bound = (3906 * math.log2(10**6) - measures.log2_factorial(3906)) / 3906
    s = ExactState(0)
    setcodec.encode_set(s, ids, 10**6)
    assert abs(s.bits / 3906 - bound) < 0.01
    w = WordState()
    setcodec.encode_set(w, ids, 10**6)
    assert bound - 0.01 < w.bits / 3906 < bound + 0.03
    assert measures.project(10**9, 1 << 20)["roc"] == pytest.approx(21.436, abs=1e-3)
    assert measures.project(10**9, 1 << 20)["ef"] == pytest.approx(22.0, abs=1e-2)


def test_word_state_redundancy():
    s, r = WordState.seeded(), random.Random(1)
    before = s.bits
    for _ in range(20000):
        s.push_uniform(r.randrange(1000), 1000)
    assert (s.bits - before) / 20000 - math.log2(1000) < 3e-3  # 32-bit words round the state


def test_permuted_input_gives_equal_bytes():
    a = np.array([5, 9, 1, 700])
    c = codec("roc", 1000)
    assert c.encode(np.sort(a), np.array([0, 4]))[0] == c.encode(np.sort(a[::-1]), np.array([0, 4]))[0]


def test_elias_fano_value():
    e = EliasFano(44)
    payload, bits = e.encode(np.array([3, 4, 7, 13, 14, 15, 21, 43]), np.array([0, 8]))
    assert bits.tolist() == [36]
    high = np.unpackbits(np.frombuffer(payload[0][2:], np.uint8), bitorder="little")[:20]
    assert "".join(map(str, high)) == "10110011100100000100"
    assert [e.next_geq(payload[0], 8, v) for v in (0, 4, 5, 16, 22, 43, 44)] == [3, 4, 7, 21, 43, 43, None]


def test_elias_fano_gap():
    n, u = 4096, 1 << 24
    gap = (EliasFano(u).size_bits(np.array([n]))[0] - (n * math.log2(u) - measures.log2_factorial(n))) / n
    assert 0.45 < gap < 0.6


@settings(max_examples=40, deadline=None)
@given(st.lists(st.booleans(), min_size=1, max_size=700), st.sampled_from([15, 31, 63]))
def test_bit_vectors(bits, block):
    bits = np.array(bits, np.int64)
    for v in (Flat.of(bits), RRR.of(bits, block)):
        v = type(v).from_bytes(v.to_bytes())
        assert (v.access(np.arange(len(bits))) == bits).all()
        assert (v.rank(np.arange(len(bits) + 1)) == np.r_[0, np.cumsum(bits)]).all()
        for b in (0, 1):
            at = np.flatnonzero(bits == b)
            if len(at):
                assert (v.select(np.arange(len(at)), b) == at).all()


def test_block_compressed_bits_are_what_is_stored():
    """Numbers of ones in their width, places in theirs, a count and a pointer per stretch: the payload but for its head; smaller than flat bits."""
    r = np.random.default_rng(3)
    for p in (0.5, 0.1):
        bits = (r.random(1 << 18) < p).astype(np.int64)
        v, flat = RRR.of(bits), Flat.of(bits)
        assert len(v.to_bytes()) * 8 - 128 == v.bits() and len(flat.to_bytes()) * 8 - 64 == flat.bits()
        assert v.bits() < flat.bits() * (1.0 if p == 0.5 else 0.6)


def test_wavelet_sizes_as_published():
    """Block-compressed trees take less than flat ones, on uniform labels too; on skewed ones much less."""
    r = np.random.default_rng(1)
    for labels, most in ((r.integers(0, 256, 1 << 17), 1.0), ((r.random(1 << 17) ** 4 * 256).astype(np.int64), 0.85)):
        flat, small = (Tree.of(labels, 8, kind).size_bits() for kind in ("flat", "rrr"))
        assert small < flat * most


@settings(max_examples=60, deadline=None)
@given(st.sets(st.integers(0, 4999), min_size=1, max_size=700), st.booleans())
def test_elias_fano_reads(ids, directory):
    ids = np.array(sorted(ids))
    e = EliasFano(5000, directory=directory)
    payload, bits = e.encode(ids, np.array([0, len(ids)]))
    assert (e.get_many(payload[0], len(ids), np.arange(len(ids))) == ids).all()
    asked = np.r_[-3, np.arange(0, 5200, 37), ids, ids + 1]
    at = np.searchsorted(ids, asked)
    want = np.where(at < len(ids), ids[np.minimum(at, len(ids) - 1)], -1)
    assert (e.open(payload[0], len(ids)).next_geq(asked) == want).all()
    other, _ = e.encode(np.arange(0, 5000, 3), np.array([0, 1667]))
    assert e.intersect(payload[0], len(ids), other[0], 1667).tolist() == [i for i in ids.tolist() if i % 3 == 0]


def test_reads_with_a_directory_open_no_list():
    """A stored directory is used as it is, and a jump looks at a bounded part of the list."""
    ids = np.arange(0, 1 << 22, 4)
    e = EliasFano(1 << 22, directory=True)
    payload, bits = e.encode(ids, np.array([0, len(ids)]))
    v = e.open(payload[0], len(ids))
    assert v.high.counts.base is not None and bits[0] < EliasFano(1 << 22).size_bits(np.array([len(ids)]))[0] * 1.06
    assert v.get(np.array([1000])).tolist() == [4000] and v.next_geq(np.array([4001])).tolist() == [4004]


def test_packed_bits():
    values, widths = np.array([5, 0, 1, 1023]), np.array([3, 0, 1, 10])
    assert (unpack_bits(pack_bits(values, widths), widths) == values).all()


def test_wavelet_value():
    t = Tree.of(np.array([2, 0, 3, 1, 0, 2, 2, 1]), 2)
    assert "".join(map(str, t.bits[0].access(np.arange(8)))) == "10100110"
    assert "".join(map(str, t.bits[1].access(np.arange(8)))) == "01010100"
    assert t.select(np.array([2]), np.array([1])).tolist() == [5]


@pytest.mark.parametrize("kind", ["flat", "rrr"])
@pytest.mark.parametrize("k", [1, 2, 5, 300])
def test_wavelet_trees(kind, k):
    s = np.random.default_rng(k).integers(0, k, 1500)
    t = Tree.of(s, max(1, (k - 1).bit_length()), kind)
    off, seen = [], {}
    for x in s.tolist():
        off.append(seen.get(x, 0))
        seen[x] = off[-1] + 1
    assert (t.access(np.arange(1500)) == s).all()
    assert (t.select(s, np.array(off)) == np.arange(1500)).all()
    assert (t.rank(s, np.arange(1500)) == off).all()


def test_edge_values():
    s = ExactState(1060921)
    edgecodec.encode_edges(s, [(0, 1), (0, 2), (1, 2), (3, 0)], 4)
    assert s.value == 12253678603
    assert edgecodec.decode_edges(s, 4, 4) == [(0, 1), (0, 2), (1, 2), (3, 0)]
    assert s.value == 1060921
    s = ExactState(1060921)
    edgecodec.encode_edges(s, [(0, 1), (0, 2), (1, 2), (0, 3)], 4, directed=False)
    assert s.value == 765850823


@settings(max_examples=25, deadline=None)
@given(st.lists(st.tuples(st.integers(0, 19), st.integers(0, 19)), max_size=60), st.booleans(), st.sampled_from(["urn", "uniform"]))
def test_edges_return(edges, directed, model):
    s = WordState()
    edgecodec.encode_edges(s, edges, 20, 1, directed, model)
    got = edgecodec.decode_edges(WordState.from_bytes(s.to_bytes()), len(edges), 20, 1, directed, model)
    assert got == sorted(edges if directed else [tuple(sorted(e)) for e in edges])


def test_hyperedges_return():
    r, s = random.Random(5), WordState()
    sets = [tuple(r.sample(range(50), r.randint(0, 6))) for _ in range(80)]
    edgecodec.encode_hyper(s, sets, 50, 6)
    assert edgecodec.decode_hyper(s, 80, 50, 6) == sorted(tuple(sorted(e)) for e in sets)
    assert s.bits == 0


def test_edge_rate_equals_closed_form():
    r = random.Random(9)
    edges = sorted({(r.randrange(200), r.randrange(200)) for _ in range(1500)})
    s = ExactState.seeded(4000)
    before = s.bits
    edgecodec.encode_edges(s, edges, 200)
    deg = np.bincount(np.array(edges).ravel(), minlength=200)
    e = len(edges)
    form = measures.log2_factorial(2 * e + 199) - measures.log2_factorial(199) - sum(measures.log2_factorial(d) for d in deg) - measures.log2_factorial(e)
    assert s.bits - before == pytest.approx(form, abs=3)


@settings(max_examples=25, deadline=None)
@given(st.lists(st.sets(st.integers(0, 99), max_size=25), max_size=40), st.sampled_from([1, 3]), st.sampled_from(["greedy", "overlap"]), st.sampled_from(["ans", "none"]), st.booleans())
def test_reference_lists_return(lists, min_run, choice, entropy, intervals):
    nodes = [(2 * i, sorted(x)) for i, x in enumerate(lists)]
    payload, bits = reflist.encode_lists(nodes, 8, min_run, entropy, choice, intervals)
    assert reflist.decode_lists(payload, [n for n, _ in nodes], min_run, entropy, intervals) == nodes
    assert entropy == "ans" or len(payload) == -(-bits // 8)


def test_sources_of_a_shard_cost_less():
    """Two shards that know their ranges take about what one stream does: the order lost is given back by the smaller choice of sources."""
    r = random.Random(2)
    edges = sorted({(r.randrange(400), r.randrange(400)) for _ in range(6000)})
    whole, parts, blind = ExactState(0), 0, 0
    edgecodec.encode_edges(whole, edges, 400)
    for lo, hi in ((0, 200), (200, 400)):
        some = [e for e in edges if lo <= e[0] < hi]
        for known in (True, False):
            state = ExactState(0)
            edgecodec.encode_edges(state, some, 400, sources=(lo, hi) if known else None)
            assert edgecodec.decode_edges(ExactState(state.value), len(some), 400, sources=(lo, hi) if known else None) == some
            parts, blind = (parts + state.bits, blind) if known else (parts, blind + state.bits)
    assert parts < whole.bits * 1.03 and blind > whole.bits * 1.05


def test_reference_lists_gain_from_overlap():
    base = random.Random(4).sample(range(4000), 60)
    nodes = [(i, sorted({*base[i % 3 :], 4001 + i})) for i in range(120)]
    with_refs, without = (reflist.encode_lists(nodes, w)[1] for w in (32, 0))
    assert with_refs < without / 2


def test_adaptive_columns():
    cols = [np.random.default_rng(i).integers(0, 256, n) for i, n in enumerate((0, 1, 5, 300, 77))]
    payload, bits = codecodec.encode_columns(cols, 256)
    assert all((a == b).all() for a, b in zip(codecodec.decode_columns(payload, [len(c) for c in cols], 256), cols, strict=True))
    form = measures.log2_factorial(255 + 300) - measures.log2_factorial(255) - sum(measures.log2_factorial(c) for c in np.bincount(cols[3]))
    assert abs(bits[3] - form) < 40
    exact = measures.log2_factorial(259) - measures.log2_factorial(255) - measures.log2_factorial(3) - measures.log2_factorial(1)
    assert exact == pytest.approx(29.448698, abs=1e-5)


def test_bits_back_costs_the_marginal():
    prior, lik = [0.5, 0.25, 0.25], [[0.5, 0.5], [0.25, 0.75], [1.0, 0.0]]
    for v in (0, 1):
        post = bitsback.exact_posterior(v, prior, lik)
        assert bitsback.negative_elbo(v, prior, lik, post) == pytest.approx(-math.log2(bitsback.marginal(v, prior, lik)))
        off = [0.4, 0.4, 0.2] if v == 0 else [0.5, 0.5, 0.0]
        assert bitsback.negative_elbo(v, prior, lik, off) - bitsback.kl(off, post) == pytest.approx(-math.log2(bitsback.marginal(v, prior, lik)))
    s = ExactState.seeded(200)
    before = s.value
    p, table, q = models.Table([2, 1, 1]), [models.Table([2, 2]), models.Table([1, 3]), models.Table([4, 0])], {0: models.Table([4, 1, 4]), 1: models.Table([4, 3, 0])}
    for v in (0, 1, 1, 0):
        bitsback.encode(s, v, p, table.__getitem__, q.__getitem__)
    assert [bitsback.decode(s, p, table.__getitem__, q.__getitem__) for _ in range(4)] == [0, 1, 1, 0]
    assert s.value == before


def test_order_statistics():
    f = Fenwick(10, ones=True)
    f.add(3, -1)
    assert [f.find(i) for i in range(9)] == [0, 1, 2, 4, 5, 6, 7, 8, 9]
    s, r = SortedRanks(4), random.Random(2)
    values = [r.randrange(100) for _ in range(200)]
    for v in values:
        s.insert(v)
    assert list(s) == sorted(values)
    assert all(s.rank(v) == sum(x < v for x in values) for v in range(0, 101, 7))
