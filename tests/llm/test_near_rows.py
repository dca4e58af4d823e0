"""Near-copy removal by row: repeated and null ids lose no clean row and keep no copy."""

import random
from collections import Counter, defaultdict

from orderless.llm import near_dedup


def words(seed, n=120):
    r = random.Random(seed)
    return [f"w{r.randrange(4000)}" for _ in range(n)]


def near(text, k):
    return " ".join([*text[:-1], f"other{k}"])


def test_repeated_and_null_ids(spark):
    a, b, c, d = (words(i) for i in range(4))
    rows = [
        (1, " ".join(a)),
        (7, near(a, 1)),  # a near copy of row 1
        (7, " ".join(b)),  # the same id, a clean text
        (3, " ".join(c)),
        (3, near(c, 2)),  # near copies with the same least id
        (None, near(a, 3)),  # a near copy without id
        (None, " ".join(d)),
        (None, near(d, 4)),
    ]
    left = near_dedup.kept_documents(spark.createDataFrame(rows, "doc_id long, text string"))
    assert left.columns == ["doc_id", "text"]
    got = [(r.doc_id, r.text.split()[0]) for r in left.collect()]
    assert sorted(got, key=repr) == sorted([(1, a[0]), (7, b[0]), (3, c[0]), (None, d[0])], key=repr)


def test_rows_without_id_have_links(spark):
    w = words(9)
    rows = [(1, " ".join(w)), (None, near(w, 1)), (None, " ".join(words(10))), (None, near(words(10), 2)), (4, " ".join(words(11)))]
    got = [(r.doc_id, r.class_id, r.n_links) for r in near_dedup.near_links(spark.createDataFrame(rows, "doc_id long, text string")).collect()]
    assert sorted(got, key=repr) == sorted([(1, 1, 1), (None, 1, 1), (None, None, 1), (None, None, 1), (4, 4, 0)], key=repr)


def test_links_of_documents_are_exact(spark):
    """All rows against all, by an index of whole shingles: classes and numbers of links are equal, so recall is 1."""
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text")
    texts = {r.doc_id: tuple((r.text or "").split()) for r in docs.collect()}
    sets = {d: {w} if 0 < len(w) < 5 else {w[i : i + 5] for i in range(len(w) - 4)} for d, w in texts.items()}
    holders = defaultdict(list)
    for d, s in sets.items():
        for g in s:
            holders[g].append(d)
    same = defaultdict(Counter)
    for ids in holders.values():
        for a in ids:
            same[a].update(ids)
    blank = [d for d, w in texts.items() if not w]
    links = {d: {e for e, n in c.items() if e != d and n * 5 >= (len(sets[d]) + len(sets[e]) - n) * 4} for d, c in same.items()}
    links |= {d: set(blank) - {d} for d in blank}
    root = {}
    for d in sorted(texts):
        todo = [] if d in root else [d]
        while todo:
            if (x := todo.pop()) not in root:
                root[x] = d
                todo += links[x]
    got = {r.doc_id: (r.class_id, r.n_links) for r in near_dedup.query(spark, sf).collect()}
    assert got == {d: (root[d], len(links[d])) for d in texts}
    assert sum(len(x) for x in links.values()) > 50
