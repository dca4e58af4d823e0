"""The text operators against brute force, and on nulls, empties, ties, repeats, empty tables and clashing columns."""

import hashlib
import random
import re
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F
from pyspark.sql import types as T

from orderless.llm import byte_bpe, catalog, common, exact_dedup, fingerprints, license_texts, licenses, near_dedup, packing, pii, quality, secrets, substring_dedup

tokenizers = pytest.importorskip("public_tokenizers")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORDS = "alpha beta gamma delta epsilon zeta eta theta iota kappa lambda mu nu xi omicron pi rho sigma tau upsilon".split()


def prose(seed, n):
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) + str(r.randrange(40)) for _ in range(n))


def odd_documents(spark):
    """Nulls in every column, empty and long texts, copies, near copies, a repeated row."""
    long = prose(1, 9000)
    near = prose(2, 200)
    rows = [
        (1, near, "en", "a", 5), (2, near.replace("alpha", "omega", 1), "en", None, None), (3, None, None, None, None), (4, "", "en", "b", 0), (5, "  \t\n ", "en", "b", 5),
        (6, long, "en", "a", 1), (7, long, "de", "c", 1), (8, "one  two\tthree", "en", "c", 1), (9, "one two three", "en", "c", 1), (10, "é ß \U0001f600 a<|endoftext|>b", "fr", "c", 1),
        (11, prose(3, 40) + "\nReleased under the MIT License.\nmail bob.x@ex-1.example.com +1 (555) 123-4567 10.0.0.1, 4111 1111 1111 1111\ntoken = \"abcdef0123456789abcdef0123456789\"", "en", "c", 1),
        (12, prose(2, 60), "en", "a", 5), (12, prose(2, 60), "en", "a", 5), (None, prose(5, 30), "en", "a", 5),
    ]
    return spark.createDataFrame(rows, SCHEMA)


def clashing(df):
    """Extra columns named as the operators' own."""
    extra = ["keep_id", "kept", "group_size", "head", "rid", "n", "best", "uid", "ord", "bucket", "k1", "node", "score", "path", "part", "length", "rank", "spans", "p0", "text_sha256", "a.b", "near_copy", "copy", "k", "t", "doc", "class_id", "comp", "kept_as"]
    return df.withColumns({c: F.lit("x") for c in extra})


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def texts_of(spark, sf):
    return [(r.doc_id, r.text or "") for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text").orderBy("doc_id").collect()]


# exact dedup


def by_text(rows):
    groups = defaultdict(list)
    for d, t in rows:
        groups[re.sub(r"[\x20\x09-\x0D]+", " ", t or "")].append(d)
    return groups


def test_exact_dedup_brute(spark, sf):
    got = {r.doc_id: r for r in exact_dedup.query(spark, sf).collect()}
    for text, ids in by_text(texts_of(spark, sf)).items():
        for d in ids:
            assert (got[d].keep_id, got[d].group_size, got[d].kept) == (min(ids), len(ids), d == min(ids))
            assert got[d].text_sha256 == hashlib.sha256(text.encode()).hexdigest()


def test_exact_dedup_of_blank_runs(spark):
    """Runs of white space longer than what a round normalises, before, between and after words; texts that differ late."""
    r = random.Random(9)
    run = lambda: "".join(r.choice(" \t\n\r\x0b\x0c") for _ in range(r.choice((0, 1, 2, 40))))
    rows = [(i, "".join(run() + r.choice(("ab", "é", "c")) for _ in range(r.randrange(6))) + run()) for i in range(500)]
    got = exact_dedup.exact_groups(spark.createDataFrame(rows, "doc_id long, text string"), first=3, widen=2).collect()
    want = {d: (min(ids), len(ids)) for ids in by_text(rows).values() for d in ids}
    assert {x.p0: (x.keep_key, x.group_size) for x in got} == want and len(want) > len(set(want.values())) > 20


def test_exact_dedup_odd(spark):
    df = clashing(odd_documents(spark))
    got = exact_dedup.exact_groups(df, first=4, widen=4).collect()
    assert len(got) == 14
    key = f"p{df.columns.index('doc_id')}"
    assert sum(r.kept for r in got) == 14 - len([1 for d in (4, 7, 9)]) - 1
    assert {r[key]: r.keep_key for r in got if r[key] in (4, 5, 7, 9)} == {4: 3, 5: 5, 7: 6, 9: 8}
    assert [r.group_size for r in got if r[key] == 12] == [2, 2] and sum(r.kept for r in got if r[key] == 12) == 1
    kept = exact_dedup.kept_documents(df)
    assert kept.columns == df.columns and kept.count() == 10
    assert exact_dedup.exact_groups(empty(spark)).count() == 0


# near duplicates


def shingles(t):
    w = t.split()
    return {tuple(w)} if 0 < len(w) < 5 else {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def near_brute(rows):
    sets = [(d, shingles(t), tuple(t.split())) for d, t in rows]
    links, root = Counter(), {d: d for d, *_ in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i, (a, s, v) in enumerate(sets):
        for b, u, w in sets[:i]:
            if v == w or (s and u and len(s & u) * 5 >= len(s | u) * 4):
                links[a] += 1
                links[b] += 1
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {d: (find(d), links[d]) for d, *_ in sets}


def test_near_links_brute(spark):
    base = [prose(100 + i, 120) for i in range(6)]
    r, rows = random.Random(3), []
    for i in range(150):
        w = base[i % 6].split()
        for _ in range(r.randrange(0, 6)):
            w[r.randrange(len(w))] = "edit" + str(r.randrange(1000))
        rows.append((i, " ".join(w)))
    rows += [(200 + i, prose(500 + i, 50)) for i in range(40)] + [(300, ""), (301, " "), (302, "a b"), (303, "a  b"), (304, "a c")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {x.doc_id: (x.class_id, x.n_links) for x in near_dedup.near_links(df).collect()}
    assert got == near_brute(rows)


def test_near_links_in_blocks(spark, monkeypatch):
    """A group larger than a block is compared in tiles, none of its pairs lost."""
    monkeypatch.setattr(near_dedup, "TILE", 16)
    w = prose(7, 150).split()
    rows = [(i, " ".join([*w[:i], f"new{i}", *w[i + 1 :]])) for i in range(70)]
    got = {x.doc_id: (x.class_id, x.n_links) for x in near_dedup.near_links(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == near_brute(rows)


def test_near_odd(spark):
    df = clashing(odd_documents(spark))
    got = Counter((x.doc_id, x.class_id, x.n_links) for x in near_dedup.near_links(df).collect())
    assert sum(got.values()) == 14
    assert got[(2, 1, 1)] == 1 and got[(12, 12, 1)] == 2 and got[(7, 6, 1)] == 1 and got[(4, 3, 2)] == 1
    assert near_dedup.kept_documents(df).columns == df.columns
    assert near_dedup.near_links(empty(spark)).count() == 0


def test_pruning_keeps_what_counts():
    least = near_dedup.least_matches(0.8)
    assert least[32] < 0.8 * 32 and least[64] < 0.8 * 64 and least[96] < 0.8 * 96
    assert all(least[n] / n > 0.4 for n in least)


# repeated passages


def passages_brute(rows):
    seen, out = {}, {}
    order = sorted(rows, key=lambda r: r[0])
    for d, t in order:
        b = t.encode()
        for i in range(len(b) - 49):
            seen.setdefault(b[i : i + 50], d)
    for d, t in order:
        b = t.encode()
        cover = bytearray(len(b))
        for i in range(len(b) - 49):
            if seen[b[i : i + 50]] < d:
                cover[i : i + 50] = b"\1" * 50
        kept = bytes(x for x, c in zip(b, cover, strict=True) if not c)
        out[d] = (len(b), sum(cover), len(re.findall(b"\1+", bytes(cover))), hashlib.sha256(kept).hexdigest())
    return out


def test_passages_brute(spark, sf):
    got = {r.doc_id: tuple(r)[1:] for r in substring_dedup.query(spark, sf).collect()}
    assert got == passages_brute(texts_of(spark, sf))


def test_passages_patchwork(spark):
    """Pieces of a few texts in every arrangement: edges of matches on all sides, periodic texts, flushes within a task."""
    rows = patchwork(8, 120)
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(5)
    assert {x.doc_id: tuple(x)[1:] for x in substring_dedup.dedup(df).collect()} == passages_brute(rows)


def test_passages_survive_collisions():
    """With a hash that can't tell anything apart the byte path gives the same matches."""
    r = np.random.default_rng(2)
    spans = [bytes(r.integers(97, 99, 80, dtype=np.uint8)) for _ in range(5)]
    rows = [(s[:30], o) for o, s in enumerate(spans) for _ in (0,)]
    data = np.frombuffer(b"".join(spans[i % 5] for i in range(10)), np.uint8)
    off = np.arange(11) * 80
    h, order = np.full(10, 7), np.arange(10)
    back, ahead = np.full(10, 30), np.zeros(10, np.int64)
    want = substring_dedup.close_matches(h, order, back, ahead, data, off)
    real = substring_dedup.Suffixes.hash
    substring_dedup.Suffixes.hash = lambda self, at, size: np.zeros(len(at), np.uint64)
    try:
        got = substring_dedup.close_matches(h, order, back, ahead, data, off)
    finally:
        substring_dedup.Suffixes.hash = real
    assert len(rows) == 5 and all((a == b).all() for a, b in zip(want, got, strict=True))
    assert want[0].tolist() == [5, 6, 7, 8, 9]


def test_anchors_of_long_texts_in_parts():
    """Every window has the anchor it has in the undivided text, whatever the parts."""
    r = np.random.default_rng(7)
    texts = [bytes(r.integers(97, 100, n, dtype=np.uint8)) for n in (0, 49, 50, 51, 700, 333)]
    off = np.r_[0, np.cumsum([len(t) for t in texts])]
    data = np.frombuffer(b"".join(texts), np.uint8)

    def windows(a):
        return sorted((row, at - d, at, h) for row, at, back, ahead, h in zip(*(a[k].tolist() for k in ("row", "at", "back", "ahead", "h")), strict=True) for d in range(ahead, back + 1))

    want = windows(substring_dedup.anchors(data, off))
    assert len(want) == sum(max(0, len(t) - 49) for t in texts)
    for part in (1, 31, 64, 500):
        assert windows(substring_dedup.anchors_in_parts(data, off, part=part)) == want


def test_merge_sort_of_suffixes():
    r = np.random.default_rng(5)
    for n in (1, 2, 3, 7, 33, 100):
        texts = [bytes(r.integers(97, 99, r.integers(0, 30), dtype=np.uint8)) for _ in range(n)]
        off = np.r_[0, np.cumsum([len(t) for t in texts])]
        data = np.frombuffer(b"".join(texts) + b"\0", np.uint8)
        s = substring_dedup.Suffixes(data, off[:-1], off[1:])
        got = substring_dedup.sorted_suffixes(s, np.zeros(n))
        assert [texts[i] for i in got] == sorted(texts)


def patchwork(seed, n):
    r = random.Random(seed)
    source = [prose(i, 60) for i in range(4)] + ["ab" * 200, "x" * 300, "é" * 120]
    rows = []
    for i in range(n):
        parts = []
        for _ in range(r.randrange(1, 5)):
            s = r.choice(source)
            a = r.randrange(len(s))
            parts.append(s[a : a + r.randrange(1, 140)])
        rows.append((i, r.choice(["", " ", "|"]).join(parts)))
    return rows


@pytest.mark.parametrize("parts", [1, 60])
def test_passages_collide_and_start_anew(spark, monkeypatch, parts):
    """Span hashes of no bits make all spans of an anchor equal: within a task and between tasks the bytes tell, and the next trial is right."""
    rows, trials, real = patchwork(3, 60), [], substring_dedup.attempt
    monkeypatch.setattr(substring_dedup, "attempt", lambda *a: trials.append(real(*a)) or trials[-1])
    df = spark.sparkContext.parallelize(rows, parts).toDF("doc_id long, text string")
    assert {x.doc_id: tuple(x)[1:] for x in substring_dedup.dedup(df, bits=0).collect()} == passages_brute(rows)
    assert trials[0] is None and trials[1] is not None


def test_passages_of_hot_anchors(spark):
    """A line that many documents share, each going on in its own way: more spans of one anchor than a task sorts."""
    r, line = random.Random(4), "this line of more than fifty bytes stands in every document of the table, "
    own = lambda: "".join(r.choice("abcdef ") for _ in range(r.randrange(3, 60)))
    rows = [(i, own() + line + own() + (line if i % 7 == 0 else "")) for i in range(2600)]
    df = spark.createDataFrame(rows, "doc_id long, text string").repartition(6)
    assert {x.doc_id: tuple(x)[1:] for x in substring_dedup.dedup(df).collect()} == passages_brute(rows)


def test_windows_over_ranges():
    """A window's rows over several ranges: the running least document decides, equal documents remove nothing."""
    r = np.random.default_rng(4)
    rows = sorted((bytes([97 + int(k)]) * 50, int(o), int(o), i) for i, (k, o) in enumerate(r.integers(0, [3, 12], (60, 2))))
    want = sorted(i for w, o, _, i in rows if o > min(q[1] for q in rows if q[0] == w))
    schema = pa.schema([("w", pa.binary()), ("ord", pa.int64()), ("uid", pa.int64()), ("at", pa.int32())])
    for cut in ([0, 60], [0, 7, 8, 30, 60], [0, 1, 2, 3, 20, 21, 59, 60]):
        done, opened, tails = [], [], {}
        for a, b in zip(cut[:-1], cut[1:], strict=True):
            batches = [pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(zip(*rows[k : min(k + 5, b)], strict=True), schema, strict=True)], schema=schema) for k in range(a, b, 5)]
            for out in substring_dedup.scan_windows(iter(batches)):
                for kind, w, o, _, i in zip(*(c.to_pylist() for c in out.columns), strict=True):
                    if kind == substring_dedup.DONE:
                        done.append(i)
                    elif kind == substring_dedup.OPEN:
                        opened.append((w, o, i))
                    else:
                        tails[w] = min(o, tails.get(w, o))
        assert sorted(done + [i for w, o, i in opened if tails.get(w, o) < o]) == want


def test_passages_odd(spark):
    got = Counter((x.doc_id, x.n_removed > 0) for x in substring_dedup.dedup(clashing(odd_documents(spark))).collect())
    assert sum(got.values()) == 14 and got[(7, True)] == 1 and got[(6, False)] == 1 and got[(12, True)] == 2
    assert substring_dedup.dedup(empty(spark)).count() == 0


# tokenising and packing


def library(name):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(tokenizers.path(name))
    t.no_truncation()
    t.no_padding()
    return t


ODD_TEXT = ["", " ", "a<|endoftext|>b  c", "  x\n\n y'll 12 ½ é́ \U0001f600 Á", "aaaa aaaaa aaaaaaaaa", "\x1c z<|endoftext|>x\x1dy\x85q w　e İ ΑΣ ΑΣ.", "<|x it's!!?'s ×÷ ÀÉß ǅ ﬁ", prose(4, 300), "漢字かな交じり文" * 9]


@pytest.mark.parametrize("kind", ["word", "byte"])
def test_ids_are_the_library_s(kind):
    r = random.Random(3)
    parts = ["a", "B", "é", "É", "ß", "×", "'", "s", "ll", "9", ".", "!!", " ", "\n", "\x1c", "\x85", "中", "ς", "İ", "́", "<|", "|>", "<|endoftext|>", "𝒳", "\x00", "the", "ing"]
    texts = ODD_TEXT + ["".join(r.choice(parts) for _ in range(r.randrange(30))) for _ in range(600)]
    if kind == "word":
        lib, mine = library(packing.VOCABULARY), packing.WordBpe(tokenizers.path(packing.VOCABULARY))
    else:
        lib, mine = library(byte_bpe.VOCABULARY), byte_bpe.ByteBpe(tokenizers.path(byte_bpe.VOCABULARY), tokenizers.PATTERN)
    for _ in range(2):  # the second time from the cache
        for t, code in zip(texts, mine.encode(texts), strict=True):
            assert np.frombuffer(code, "<u4").tolist() == lib.encode(t, add_special_tokens=False).ids, t


def test_byte_bpe_query(spark, sf):
    lib = library(byte_bpe.VOCABULARY)
    got = {r.doc_id: r for r in byte_bpe.query(spark, sf).collect()}
    for d, t in texts_of(spark, sf):
        ids = lib.encode(t, add_special_tokens=False).ids
        assert got[d].n_tokens == len(ids) and got[d].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert got[d].decoded_sha256 == hashlib.sha256(lib.decode(ids, skip_special_tokens=False).encode()).hexdigest() == hashlib.sha256(t.encode()).hexdigest()
    args = tokenizers.path(byte_bpe.VOCABULARY), tokenizers.PATTERN
    assert byte_bpe.encode_documents(clashing(odd_documents(spark)), *args).count() == 14
    assert byte_bpe.encode_documents(empty(spark), *args).count() == 0


def test_cache_of_words_is_bounded():
    lib, mine = library(byte_bpe.VOCABULARY), byte_bpe.ByteBpe(tokenizers.path(byte_bpe.VOCABULARY), tokenizers.PATTERN)
    texts = ["x" * 5000 + " a", "y z " + "qz" * 40, "x" * 5000 + " a", ""]
    for t, code in zip(texts, mine.encode(texts), strict=True):
        assert np.frombuffer(code, "<u4").tolist() == lib.encode(t, add_special_tokens=False).ids
    assert max(map(len, mine.known)) <= byte_bpe.CACHE_LENGTH


def best_fit_brute(lengths, capacity):
    bins = []
    for n in sorted(lengths, reverse=True):
        fits = [b for b in bins if b >= n]
        if fits:
            bins.remove(min(fits))
            bins.append(min(fits) - n)
        else:
            bins.append(capacity - n)
    return sorted(bins)


@pytest.mark.parametrize("seed", range(6))
def test_plan_is_best_fit_decreasing(seed):
    r = random.Random(seed)
    lengths = [r.randrange(1, 65) for _ in range(r.randrange(1, 300))]
    plan = packing.best_fit_plan(Counter(lengths), 64)
    used = defaultdict(int)
    for length, _, count, first, offset in sorted(plan.tolist(), key=lambda p: p[4]):
        for k in range(count):
            assert used[first + k] == offset
            used[first + k] += length
    assert sorted(64 - u for u in used.values()) == best_fit_brute(lengths, 64)
    assert packing.best_fit_plan({}, 64).shape == (0, 5)


def packed(df, capacity):
    return packing.pack_documents(df, tokenizers.path(packing.VOCABULARY), capacity).collect()


def test_packing(spark, sf):
    import zlib

    lib, docs = library(packing.VOCABULARY), texts_of(spark, sf)
    got = packed(spark.read.parquet(f"{sf}/documents.parquet"), 256)
    by_doc, by_seq = defaultdict(list), defaultdict(list)
    for r in got:
        by_doc[r.doc_id].append(r)
        by_seq[r.sequence_id].append((r.offset, r.length))
    for d, t in docs:
        ids = [*lib.encode(t, add_special_tokens=False).ids, 1]
        some = sorted(by_doc[d], key=lambda r: r.piece)
        assert [r.length for r in some] == [min(256, len(ids) - k) for k in range(0, len(ids), 256)]
        assert all(r.ids_crc32 == zlib.crc32(np.array(ids[r.start : r.start + r.length], "<u4").tobytes()) for r in some)
    for places in by_seq.values():
        end = 0
        for o, n in sorted(places):
            assert o == end
            end += n
        assert end <= 256
    assert len(by_seq) == len(best_fit_brute([r.length for r in got], 256))


def test_packing_odd(spark):
    got = packed(clashing(odd_documents(spark)), 4096)
    assert Counter(r.doc_id for r in got if r.piece == 0) == Counter({d: 1 for d in (1, 2, 3, 4, 5, 6, 7, 8, 9, 10, 11, None)} | {12: 2})
    assert {r.length for r in got if r.doc_id in (3, 4, 5)} == {1}
    assert packed(empty(spark), 4096) == []


# spans

PII = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def pii_brute(t):
    out = {}
    for kind, p in PII.items():
        out[kind] = []
        for m in re.finditer(p, t):
            d = re.sub("[^0-9]", "", m[0])
            if kind == "email" or (kind == "ip" and all(int(x.lstrip("0")[:4] or 0) <= 255 for x in m[0].split("."))) or (kind == "card" and 13 <= len(d) <= 19 and pii.luhn(d)) or (kind == "phone" and 9 <= len(d) <= 15):
                out[kind].append(m.span())
    return out


def test_pii_base_spans():
    r = random.Random(1)
    for _ in range(8000):
        t = "".join(r.choice("a1.@+- (0)2%é4") for _ in range(r.randrange(60))) + "".join(r.choice("0123456789 -") for _ in range(r.choice((0, 30))))
        assert pii.base_spans(t) == pii_brute(t), t


def test_pii_model_is_right_on_new_findings():
    model = pii.Chooser()
    rows, y = pii.findings(800, 99)
    got = np.array([bool(model.choose(f[0], [f[1:]])) for f in rows])
    assert got[y > 0].mean() > 0.95 and got[y == 0].mean() < 0.02


def test_pii_query(spark, sf):
    got = {r.doc_id: r for r in pii.query(spark, sf).collect()}
    for d, t in texts_of(spark, sf):
        base = pii_brute(t)
        named = ",".join(f"{k}:{a}:{b}" for k in pii.KINDS for a, b in base[k])
        assert [got[d][f"n_{k}"] for k in pii.KINDS] == [len(base[k]) for k in pii.KINDS]
        assert got[d].base_sha256 == hashlib.sha256(named.encode()).hexdigest()
        assert set(filter(None, named.split(","))) <= set(got[d].spans.split(","))
    odd = {r.doc_id: [s.kind for s in r.spans] for r in pii.find_personal_data(clashing(odd_documents(spark))).collect()}
    assert odd[11] == ["email", "ip", "card", "phone"] and odd[3] == odd[4] == []
    assert pii.find_personal_data(empty(spark)).count() == 0


def secrets_brute(t):
    out = [("assign", *m.span()) for m in re.finditer(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", t, re.I | re.A) if len(m[2]) >= 8]
    out += [("access", *m.span()) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 16]
    return out + [("hex", *m.span()) for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 32]


def test_secret_base_spans():
    r = random.Random(2)
    parts = ["token", "PassWd", "api_key", "apikey", "AKIA", "AKIAABCDEFGH12345", "=", ": ", "'", '"', "abcdef0123456789", "a", "9f", "Zz-", "é", " "]
    for _ in range(4000):
        t = "".join(r.choice(parts) for _ in range(r.randrange(14)))
        assert secrets.base_spans(t) == secrets_brute(t)
        if secrets.base_spans(t) or secrets.candidates(t):
            data = np.frombuffer(t.encode(), np.uint8)
            assert 0 in secrets.suspects(data, np.array([0, len(data)]))


def test_secret_network():
    judge = secrets.Judge()
    rows, y = secrets.findings(600, 77)
    p = np.array([judge.chances(t, [("other", a, b)])[0] for t, a, b in rows])
    assert (p[y > 0] >= judge.least).mean() >= 0.98 and (p[y == 0] >= judge.least).mean() < 0.05


def test_secret_query(spark, sf):
    got = {r.doc_id: r for r in secrets.query(spark, sf).collect()}
    for d, t in texts_of(spark, sf):
        base = secrets.ordered(secrets_brute(t))
        named = ",".join(f"{k}:{a}:{b}" for k, a, b in base)
        assert [got[d][f"n_{k}"] for k in secrets.KINDS] == [sum(x[0] == k for x in base) for k in secrets.KINDS]
        assert got[d].base_sha256 == hashlib.sha256(named.encode()).hexdigest()
    odd = odd_documents(spark)
    assert secrets.find_secrets(clashing(odd)).count() == 14 and secrets.find_secrets(empty(spark)).count() == 0
    redact = secrets.redactor(spark)
    out = {r.doc_id: r.t for r in odd.select("doc_id", redact(F.col("text")).alias("t")).collect()}
    assert "abcdef0123456789" not in out[11] and "[secret]" in out[11] and out[1] is None


# fingerprints


def sha(t):
    return hashlib.sha256(t.encode()).hexdigest()


def print_brute(t):
    """The fingerprint string, by hand."""
    tree = [[sha(p) for p in re.findall(r"[^.!?]{1,32}[.!?]*|[.!?]+", s)] for s in t.split("\n")]
    node = [sha(",".join(x)) for x in tree]
    return sha(",".join(node)) + "|" + ";".join(n[:16] + ":" + ",".join(x[:8] for x in leaves) for n, leaves in zip(node, tree, strict=True))


def likeness_brute(p, q):
    a, b = (x.split("|")[1].split(";") for x in (p, q))
    if a == b:
        return 1.0
    leaves = lambda some: [x for s in some for x in s.split(":")[1].split(",") if x]
    both = len(leaves(set(a) & set(b)))
    x, y = (set(leaves(set(m) - set(n))) for m, n in ((a, b), (b, a)))
    total = 2 * both + len(x) + len(y)
    return 2 * (both + len(x & y)) / total if total else 0.0


def test_fingerprints_brute(spark, sf):
    docs = texts_of(spark, sf)[::-1]
    got = {r.doc_id: r for r in fingerprints.query(spark, sf).collect()}
    for i, (d, t) in enumerate(docs):
        after, cut = docs[(i + 1) % len(docs)], len(t) // 3
        edited = t[: len(t) - cut] + after[1][:cut]
        r, own, other = got[d], print_brute(t), print_brute(edited)
        assert (r.n_chars, r.edited_sha256, r.fingerprint, r.edited_fingerprint) == (len(t), sha(edited), own, other)
        assert r.near_edited == pytest.approx(likeness_brute(own, other)) and r.near_next == pytest.approx(likeness_brute(own, print_brute(after[1])))
        a, b = (x.split("|")[1].split(";") for x in (own, other))
        assert r.changed_sections == [k for k in range(max(len(a), len(b))) if a[k : k + 1] != b[k : k + 1]]
    prints = defaultdict(set)
    for d, t in docs:
        prints[t].add(got[d].fingerprint)
    assert all(len(p) == 1 for p in prints.values()) and len(set().union(*prints.values())) == len(prints)
    long = [got[d] for d, t in docs if len(t) > 600]
    assert 0.5 < np.mean([r.near_edited for r in long]) < 0.8


def test_successors_of_any_ids(spark):
    """Sparse, negative, repeated and null ids: every row follows the one before it, whatever the ranges."""
    r = random.Random(6)
    ids = [r.randrange(-(1 << 62), 1 << 62) for _ in range(300)] + [7, 7, 8, None, None]
    rows = common.identified(spark.createDataFrame([(i,) for i in ids], "doc_id long").repartition(3), "doc_id", ["doc_id"])
    order = sorted(((x.ord, x.uid) for x in rows.collect()), reverse=True)
    got = {x.uid: x.next_uid for x in fingerprints.successors(rows.select("uid", "ord")).collect()}
    assert got == {a[1]: b[1] for a, b in zip(order, order[1:] + order[:1], strict=True)}


def test_fingerprints_odd(spark):
    got = fingerprints.compare_with_edits(clashing(odd_documents(spark))).collect()
    assert len(got) == 14 and all(r.near_edited is not None and r.near_next is not None for r in got)
    one = fingerprints.compare_with_edits(spark.createDataFrame([(5, "abc def.")], "doc_id long, text string")).first()
    assert one.near_next == 1.0
    assert fingerprints.compare_with_edits(empty(spark)).count() == 0


def test_changed_sections(spark):
    df = spark.createDataFrame([("a b.\nc d.\ne f.", "a b.\nc x.\ne f.\ng")], "s string, t string")
    p = lambda c: fingerprints.sections(fingerprints.fingerprint(fingerprints.tree(F.col(c))))
    r = df.select(p("s").alias("s"), p("t").alias("t")).select(fingerprints.changed_sections(F.col("s"), F.col("t")).alias("c"), F.size(fingerprints.leaves_of(F.col("s"))).alias("n"), fingerprints.likeness(F.col("s"), F.col("t")).alias("l")).first()
    assert r.c == [1, 3] and r.n == 3 and r.l == pytest.approx(4 / 7)


def test_native_plans_hold_no_python(spark, sf):
    for q in (fingerprints.query, licenses.query, license_texts.query):
        plan = q(spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert not re.search("Python|Pandas|Arrow", plan)


# licences


def test_licences_inherit(spark):
    rows = [(1, "a/b/LICENSE", "Released under the MIT License."), (2, "a/b/c/x", "some words here"), (3, "a/y", "other words"), (4, "a/b/c/z", "long text " * 20 + "\nLicensed under the Apache License, Version 2.0."), (5, None, None), (6, "a/b/w", ""), (6, "a/b/w", "")]
    got = licenses.license_scan(clashing(spark.createDataFrame(rows, "doc_id long, where string, text string")), F.col("where")).collect()
    told = {r.doc_id: (r.license, r.origin) for r in got}
    assert len(got) == 7
    assert told == {1: ("MIT", "notice"), 2: ("MIT", "inherited"), 3: (None, "none"), 4: ("Apache-2.0", "notice"), 5: (None, "none"), 6: ("MIT", "inherited")}
    assert licenses.license_scan(spark.createDataFrame([], "doc_id long, text string"), F.lit("a/b")).count() == 0


@pytest.mark.parametrize("query", [licenses, exact_dedup])
def test_oracle(spark, sf, query):
    import duckdb

    c = duckdb.connect()
    c.execute(f"CREATE VIEW documents AS SELECT * FROM '{sf}/documents.parquet'")
    df = query.query(spark, sf)
    r = c.sql(query.SQL)
    at = [r.columns.index(x) for x in df.columns]
    assert sorted(map(repr, map(tuple, df.collect()))) == sorted(repr(tuple(x[i] for i in at)) for x in r.fetchall())


def test_one_query_an_operator():
    names = [n for n in catalog.queries() if n.startswith("op")]
    assert sorted(int(n[2:].split("_")[0]) for n in names) == list(range(1, 11)) and "pipeline" in catalog.queries()


# quality


def test_quality(spark):
    sf = "/root/testdata/sf0.01"
    got = quality.query(spark, sf)
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    rows = got.join(labels, "doc_id").collect()
    held = [r for r in rows if r.held_out]
    good, bad = ([r.score for r in held if r.quality == q] for q in (1, 0))
    auc = np.mean([[a > b for a in good] for b in bad])
    assert auc > 0.97 and np.mean([r.predicted == r.quality for r in held]) > 0.95
    assert all((r.predicted == 1) == (r.score >= 0.3) for r in rows)


def test_quality_odd(spark):
    docs = odd_documents(spark)
    labels = spark.createDataFrame([(1, 1), (6, 0), (6, 1), (None, 1), (8, None)], "doc_id long, quality int")
    score = quality.scorer(spark, quality.train(clashing(docs), labels))
    got = clashing(docs).select("doc_id", score(F.col("text")).alias("s")).collect()
    assert len(got) == 14 and all(0 <= r.s <= 1 for r in got)
    assert not quality.train(docs, labels.filter("false")).any() and not quality.train(empty(spark), labels).any()
    assert empty(spark).select(score(F.col("text")).alias("s")).count() == 0


def score_brute(weights, t):
    """A score from weights, by plain arithmetic: runs of letters and digits and runs of marks, alone and in pairs."""
    mask = (1 << 64) - 1

    def mixed(x):
        for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            x = ((x ^ (x >> shift)) * factor) & mask
        return x ^ (x >> 31)

    tokens = re.findall(rb"[a-zA-Z0-9\x80-\xff]+|[!-/:-@\[-`{-~]+", t.encode())
    one = [mixed((sum((c + 1) * pow(common.BASE, k, 1 << 64) for k, c in enumerate(w)) + len(w)) & mask) for w in tokens]
    features = [x >> (64 - quality.BITS) for x in one]
    features += [mixed((x * 31 + y) & mask) >> (64 - quality.BITS) for x, y in zip(one, one[1:], strict=False)]
    features += [quality.REPEAT for x, y in zip(one, one[1:], strict=False) if x == y]
    total = sum(weights[f] for f in features)
    return 1 / (1 + np.exp(-(quality.SCALE * total / max(1, len(features)) + weights[-1])))


def test_quality_scores_brute(spark, sf):
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    weights = quality.train(docs, labels).astype(np.float32).astype(float)
    assert np.count_nonzero(weights) > 100
    got = {r.doc_id: r.score for r in quality.query(spark, sf).collect()}
    for d, t in texts_of(spark, sf):
        if len(t) < 20_000:
            assert got[d] == pytest.approx(score_brute(weights, t), abs=1e-9)


def test_quality_learns_alike_in_any_order(spark):
    """Repeated ids and any partitioning: the same weights."""
    rows = [(i % 40, prose(i, 30)) for i in range(120)]
    labels = spark.createDataFrame([(i, i % 2) for i in range(40)], "doc_id long, quality int")
    w = [quality.train(spark.createDataFrame(r, "doc_id long, text string").repartition(n), labels) for r, n in ((rows, 2), (rows[::-1], 7))]
    assert (w[0] == w[1]).all() and w[0].any()


def test_leader_learns_and_stays_sparse():
    r = np.random.default_rng(0)
    rows = [(np.array([i % 2, 2 + r.integers(0, 50), 60]), np.array([1.0, 1.0, 1.0])) for i in range(400)]
    w = quality.follow_the_leader(rows, np.array([i % 2 for i in range(400)], float), 61)
    assert w[1] > 1 > -1 > w[0]


# what they share


def test_groups_are_kept_whole():
    r = random.Random(4)
    keys = sorted(r.randrange(30) for _ in range(500))
    t = pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(range(500))], ["k", "v"])
    for size in (1, 7, 64, 500):
        out = list(common.whole_groups((t.slice(i, size) for i in range(0, 500, size)), 1))
        assert [v for b in out for v in b.column(1).to_pylist()] == list(range(500))
        seen = [set(b.column(0).to_pylist()) for b in out]
        assert all(not a & b for i, a in enumerate(seen) for b in seen[:i])


def test_components(spark):
    edges = [(i, i + 1) for i in range(1, 40)] + [(100, 101), (103, 102), (101, 102), (7, 7)]
    got = {r.node: r.comp for r in common.components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {i: 1 for i in range(1, 41)} | {i: 100 for i in range(100, 104)}
    assert common.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_pipeline_stages_on_odd_rows(spark, sf):
    """Nulls, empties, ties, repeats and clashing columns through every stage; and an empty table."""
    import corpus_pipeline

    for docs in (clashing(odd_documents(spark)), clashing(empty(spark))):
        n, first = docs.count(), docs
        for name, f in corpus_pipeline.STAGES:
            new = common.stage(f(spark, docs, sf), "test")
            if name != "best-fit packing":
                assert new.columns == first.columns and new.count() <= n, name
                docs, n = new, new.count()
        assert n == new.filter("piece = 0").count()


def test_pipeline(spark, sf):
    import corpus_pipeline

    docs = spark.read.parquet(f"{sf}/documents.parquet")
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality classifier", "exact dedup", "n-gram Jaccard join", "secret scans", "best-fit packing"]
    left = docs
    for name, f in corpus_pipeline.STAGES[:-1]:
        new = common.stage(f(spark, left, sf), "test")
        assert new.columns == docs.columns and 0 < new.count() <= left.count(), name
        left = new
    groups = by_text([(r.doc_id, r.text) for r in left.select("doc_id", "text").collect()])
    assert all(len(ids) == 1 for ids in groups.values())
    assert not any(secrets_brute(r.text) for r in left.select("text").collect())
    out = corpus_pipeline.run(spark, sf)
    assert {r.doc_id for r in out.select("doc_id").collect()} == {r.doc_id for r in left.select("doc_id").collect()}
    assert isinstance(out.schema, T.StructType)
