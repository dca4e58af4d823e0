"""Near-duplicate join on word n-grams: MinHash candidates, Bayesian pruning, exact Jaccard verification.

1. Every text becomes a MinHash signature of its five-word shingles (narrow). Texts with the same words are one node from
   here on, with a count of copies.
2. Nodes meet in buckets, one per signature band. A bucket of more than `TILE` nodes is cut into blocks, and pairs of
   blocks are compared apart, so no task holds an unbounded bucket. Pairs are compared some MinHash values
   at a time and dropped when the posterior probability of reaching the threshold falls under the
   tolerance. Survivors are only used to connect nodes; no pair is a row.
3. Connected nodes get their shingle sets and are compared again by blocks of their component: pruned the
   same way, then verified exactly. Verified links are counted per node and connect the final classes.

Defined results: a null or empty text has no shingles; such texts are copies of each other and link to nothing else. A text of
one to four words has one shingle, all its words. Words are what stands between ASCII white space. Repeated rows are copies.
Rows with a null or repeated id are rows like any other: where ids aren't unique, rows are numbered and written first. A class is named
by its least id, nulls aside; it is null only where no row of the class has an id. Similarity is over sets.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common

WORDS, ROWS, BANDS, STEP = 5, 4, 24, 32
HASHES = ROWS * BANDS
#: A pair is dropped when the chance that it reaches the threshold is less than this, given the values compared so far.
TOLERANCE = 1e-6
#: Nodes of a bucket or component compared in one block.
TILE = 1024
_SEED = np.random.default_rng(20)
_XOR = _SEED.integers(0, 1 << 63, HASHES, dtype=np.uint64)
_ODD = _SEED.integers(0, 1 << 63, HASHES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_BASE2 = 0xD1B54A32D192ED03


def _rows_hash(values: np.ndarray, first: np.ndarray, base: int) -> np.ndarray:
    """A hash of each row's run of values; first has n+1 positions."""
    p = np.zeros(len(values) + 1, np.uint64)
    np.cumsum(values * common.powers(len(values), base), out=p[1:])
    inv = pow(base, -1, 1 << 64)
    return common.mix((p[first[1:]] - p[first[:-1]]) * common.powers(len(values) + 1, inv)[first[:-1]] + np.diff(first).astype(np.uint64))


def shingles(data: np.ndarray, off: np.ndarray, words: int = WORDS) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Shingle hashes (rows in order), their n+1 row positions, and two hashes of each text's whole word sequence."""
    n = len(off) - 1
    start, end, row = common.word_spans(data, off)
    word = common.span_hash(common.prefix_hash(data), start, end)
    first = np.searchsorted(row, np.arange(n + 1))
    k1, k2 = _rows_hash(word, first, common.BASE), _rows_hash(word, first, _BASE2)
    count = np.diff(first)
    h = np.zeros(max(0, len(word) - words + 1), np.uint64)
    for i in range(words):
        h = h * np.uint64(0x2545F4914F6CDD1D) + word[i : i + len(h)]
    inside = row[: len(h)] == row[words - 1 :] if len(h) else np.zeros(0, bool)
    h, r = common.mix(h[inside]), row[: len(inside)][inside]
    short = np.flatnonzero((count > 0) & (count < words))
    if len(short):
        h, r = np.concatenate([h, k1[short]]), np.concatenate([r, short])
        order = np.argsort(r, kind="stable")
        h, r = h[order], r[order]
    return h, np.searchsorted(r, np.arange(n + 1)), k1, k2


def signatures(h: np.ndarray, first: np.ndarray) -> np.ndarray:
    """MinHash values, a row of HASHES 32-bit words per text; all ones where a text has no shingle."""
    n = len(first) - 1
    out = np.full((n, HASHES), 0xFFFFFFFF, np.uint32)
    some = np.flatnonzero(np.diff(first) > 0)
    if len(some):
        at = first[some]
        for i in range(HASHES):
            out[some, i] = np.minimum.reduceat((((h ^ _XOR[i]) * _ODD[i]) >> np.uint64(32)).astype(np.uint32), at)
    return out


def band_keys(sig: np.ndarray) -> np.ndarray:
    part = sig.reshape(len(sig), BANDS, ROWS).astype(np.uint64)
    key = np.broadcast_to(np.arange(1, BANDS + 1, dtype=np.uint64) * np.uint64(common.BASE), part.shape[:2]).copy()
    for i in range(ROWS):
        key = common.mix(key + part[:, :, i])
    return key.view(np.int64)


def least_matches(threshold: float, tolerance: float = TOLERANCE) -> dict[int, int]:
    """After n equal-or-not comparisons, the fewest matches a pair may have and stay.

    With a uniform prior the posterior of the similarity is a beta distribution; its mass over the threshold is a binomial
    sum.
    """
    out = {}
    for n in range(STEP, HASHES + 1, STEP):
        total, m = 0.0, -1
        while total < tolerance:
            m += 1
            total += math.comb(n + 1, m) * threshold**m * (1 - threshold) ** (n + 1 - m)
        out[n] = m
    return out


def survivors(sig: np.ndarray, p: np.ndarray, q: np.ndarray, least: dict[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """The pairs that incremental comparison doesn't rule out."""
    matched = np.zeros(len(p), np.int32)
    for lo in range(0, HASHES, STEP):
        matched += (sig[p, lo : lo + STEP] == sig[q, lo : lo + STEP]).sum(1, dtype=np.int32)
        stay = matched >= least[lo + STEP]
        p, q, matched = p[stay], q[stay], matched[stay]
    return p, q


def pairs(group: np.ndarray, block: np.ndarray, cross: np.ndarray, most: int = 1 << 17) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """All pairs within groups (contiguous); in a group that crosses two blocks only pairs between them."""
    n, p_out, q_out, held = len(group), [], [], 0
    size = int(np.diff(np.flatnonzero(np.r_[True, group[1:] != group[:-1], True])).max()) if n else 0
    for d in range(1, size):
        p = np.flatnonzero((group[:-d] == group[d:]) & (~cross[:-d] | (block[:-d] != block[d:])))
        if not len(p):
            continue
        p_out.append(p)
        q_out.append(p + d)
        held += len(p)
        if held >= most:
            yield np.concatenate(p_out), np.concatenate(q_out)
            p_out, q_out, held = [], [], 0
    if held:
        yield np.concatenate(p_out), np.concatenate(q_out)


def tiles(members: DataFrame, group: str, size: str, node: str) -> DataFrame:
    """Adds i, j (a pair of blocks) and block; a member of a large group stands in one tile per block of the group."""
    blocks = F.ceil(F.col(size) / F.lit(TILE)).cast("int")
    out = members.withColumn("blocks", blocks).withColumn("block", F.pmod(F.xxhash64(node), F.col("blocks")).cast("int"))
    out = out.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    return out.withColumn("i", F.least("block", "other")).withColumn("j", F.greatest("block", "other")).drop("other", "blocks", size)


def _matrix(arr: pa.Array, width: int) -> np.ndarray:
    data, _ = common.raw(arr)
    return data.view(np.uint32).reshape(-1, width)


def sketch(rows: DataFrame) -> DataFrame:
    """uid, ord, doc_id, word-sequence hashes, band keys and signature of rows (uid, ord, doc_id, text)."""
    common.importable(rows.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in common.slices(whole, 3):
                h, first, k1, k2 = shingles(*common.raw(b.column(3)))
                sig = signatures(h, first)
                keys = np.where((np.diff(first) > 0)[:, None], band_keys(sig), 0)
                n = b.num_rows
                empty = np.diff(first) == 0
                lists = pa.ListArray.from_arrays(pa.array(np.r_[0, np.cumsum(np.where(empty, 0, BANDS))].astype(np.int32)), pa.array(keys[~empty].ravel(), pa.int64()))
                packed = pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer((np.arange(n + 1) * HASHES * 4).astype(np.int32)), pa.py_buffer(sig.tobytes())])
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in range(3)), pa.array(k1.view(np.int64)), pa.array(k2.view(np.int64)), lists, packed], ["uid", "ord", "doc_id", "k1", "k2", "bands", "sig"])

    return rows.select("uid", "ord", "doc_id", "text").mapInArrow(run, "uid long, ord long, doc_id long, k1 long, k2 long, bands array<long>, sig binary")


def near_links(docs: DataFrame, text: str = "text", key: str = "doc_id", threshold: float = 0.8) -> DataFrame:
    """One row per input row: doc_id, class_id (least id of its class), n_links (other rows at or over the threshold)."""
    flat = docs.select(common.col(key).cast("long").alias("doc_id"), common.clean_text(common.col(text)).alias("text"))
    return linked(common.identified(flat, "doc_id", ["doc_id", "text"]), threshold).select("doc_id", "class_id", "n_links")


def linked(rows: DataFrame, threshold: float = 0.8) -> DataFrame:
    """uid, doc_id, class_id, class_uid (the row of a class that is first by id, nulls last, then uid), n_links of rows (uid, ord, doc_id, text)."""
    spark, least = rows.sparkSession, least_matches(threshold)
    seen = common.stage(sketch(rows), "near-sketch")
    nodes = seen.groupBy("k1", "k2").agg(
        F.min(F.struct("ord", "uid")).alias("head"), F.min("doc_id").alias("rep"), F.count(F.lit(1)).alias("copies"), F.first("bands").alias("bands"), F.first("sig").alias("sig")
    )
    nodes = common.stage(nodes.withColumn("node", F.monotonically_increasing_id()), "near-nodes")

    # step 2: crowded buckets, then tiles of their members
    placed = nodes.select("node", F.explode("bands").alias("bucket"))
    crowded = common.stage(placed.groupBy("bucket").agg(F.count(F.lit(1)).alias("size")).filter("size > 1"), "near-buckets")
    met = placed.join(crowded.hint("merge"), "bucket").groupBy("node").agg(F.collect_list(F.struct("bucket", "size")).alias("met"))  # at most BANDS a node
    met = common.stage(met, "near-met")
    members = common.sifted(nodes.select("node", "sig"), "node", common.sieve(met, "node")).join(met.hint("merge"), "node").select("node", "sig", F.explode("met").alias("m")).select("m.bucket", "m.size", "node", "sig")
    placed2 = tiles(members, "bucket", "size", "node").select("bucket", "i", "j", "block", "node", "sig")

    def connect(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in common.whole_groups(batches, 3):
            bucket, i, j, block, node = (b.column(k).to_numpy() for k in range(5))
            sig = _matrix(b.column(5), HASHES)
            new = np.r_[True, (bucket[1:] != bucket[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1])]
            got = [survivors(sig, p, q, least) for p, q in pairs(np.cumsum(new), block, i != j)]
            if got:
                root = common.star_edges(np.concatenate([g[0] for g in got]), np.concatenate([g[1] for g in got]), len(node))
                at = np.flatnonzero(root != np.arange(len(node)))
                yield pa.RecordBatch.from_arrays([pa.array(node[at]), pa.array(node[root[at]])], ["a", "b"])

    linked = placed2.repartition("bucket", "i", "j").sortWithinPartitions("bucket", "i", "j").mapInArrow(connect, "a long, b long")
    first = common.components(linked.distinct())
    common.unstage(crowded)
    common.unstage(met)

    # step 3: exact verification within components
    sizes = common.stage(first.groupBy("comp").agg(F.count(F.lit(1)).alias("size")), "near-sizes")
    near = first.join(sizes, "comp").join(nodes.select("node", F.col("head.uid").alias("uid"), "copies"), "node")
    near = common.stage(near, "near-members")

    def prepare(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for whole in batches:
            for b in common.slices(whole, 0):
                h, at, _, _ = shingles(*common.raw(b.column(0)))
                sig = signatures(h, at)
                sets = [np.unique(h[at[r] : at[r + 1]]).tobytes() for r in range(b.num_rows)]
                yield pa.RecordBatch.from_arrays([*(b.column(c) for c in range(1, 5)), pa.array([x.tobytes() for x in sig], pa.binary()), pa.array(sets, pa.binary())], ["comp", "size", "node", "copies", "sig", "grams"])

    full = common.sifted(rows.select("uid", "text"), "uid", common.sieve(near, "uid")).join(near.hint("merge"), "uid").select("text", "comp", "size", "node", "copies")
    full = common.stage(full.mapInArrow(prepare, "comp long, size long, node long, copies long, sig binary, grams binary"), "near-sets")
    common.unstage(near)
    common.unstage(sizes)
    blocks = tiles(full, "comp", "size", "node").select("comp", "i", "j", "block", "node", "copies", "sig", "grams")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in common.whole_groups(batches, 3):
            comp, i, j, block, node, copies = (b.column(k).to_numpy() for k in range(6))
            sig = _matrix(b.column(6), HASHES)
            data, off = common.raw(b.column(7))
            edge = np.flatnonzero(np.r_[True, (comp[1:] != comp[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1]), True])
            out_p, out_q = [], []
            for lo, hi in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True):
                p, q = verified(data[off[lo] : off[hi]].view(np.uint64), (off[lo : hi + 1] - off[lo]) // 8, sig[lo:hi], block[lo:hi], i[lo] != j[lo], least, threshold)
                out_p.append(p + lo)
                out_q.append(q + lo)
            p, q = np.concatenate(out_p), np.concatenate(out_q)
            root = common.star_edges(p, q, len(node))
            links = np.bincount(p, copies[q], len(node)) + np.bincount(q, copies[p], len(node))
            at = np.flatnonzero(links > 0)
            yield pa.RecordBatch.from_arrays([pa.array(node[at]), pa.array(node[root[at]]), pa.array(links[at].astype(np.int64))], ["a", "b", "links"])

    exact = blocks.repartition("comp", "i", "j").sortWithinPartitions("comp", "i", "j").mapInArrow(verify, "a long, b long, links long")
    exact = common.stage(exact, "near-links")
    common.unstage(full)
    final = common.components(exact.filter("a <> b").select("a", "b"))
    links = exact.groupBy(F.col("a").alias("node")).agg(F.sum("links").alias("links"))
    told = nodes.select("node", "k1", "k2", "head", "rep", "copies").join(final, "node", "left").join(links, "node", "left")
    told = common.stage(told.withColumn("comp", F.coalesce("comp", "node")), "near-told")
    first_row = common.stage(told.groupBy("comp").agg(F.min("head").alias("head"), F.min("rep").alias("class_id")), "near-classes")
    named = told.select("comp", "k1", "k2", "copies", "links").join(first_row, "comp")
    named = named.select("k1", "k2", "class_id", F.col("head.uid").alias("class_uid"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).cast("long").alias("n_links"))
    named = common.stage(named, "near-named")
    for old in (exact, told, first_row, nodes):
        common.unstage(old)
    common.sweep(spark)
    return seen.select("uid", "doc_id", "k1", "k2").join(named.hint("merge"), ["k1", "k2"]).select("uid", "doc_id", "class_id", "class_uid", "n_links")


def verified(h: np.ndarray, first: np.ndarray, sig: np.ndarray, block: np.ndarray, cross: bool, least: dict[int, int], threshold: float) -> tuple[np.ndarray, np.ndarray]:
    """The pairs of one tile whose exact Jaccard similarity reaches the threshold."""
    n = len(first) - 1
    none = np.zeros(0, np.int64)
    if n < 2:
        return none, none
    got = [survivors(sig, p, q, least) for p, q in pairs(np.zeros(n, np.int64), block, np.full(n, cross))]
    if not got:
        return none, none
    p, q = np.concatenate([g[0] for g in got]), np.concatenate([g[1] for g in got])
    if not len(p):
        return none, none
    size = np.diff(first)
    row = np.repeat(np.arange(n), size)
    order = np.argsort(h, kind="stable")
    hs, rs = h[order], row[order]
    new = np.r_[True, hs[1:] != hs[:-1]]
    gram = np.cumsum(new) - 1
    common_gram = np.bincount(gram) > 1
    keep = common_gram[gram]
    gram, rs = (np.cumsum(common_gram) - 1)[gram[keep]], rs[keep]
    both = np.zeros(len(p))
    width = 2048
    cut = np.searchsorted(gram, np.arange(0, (int(gram[-1]) if len(gram) else -1) + 1 + width, width))
    whole = len(p) * 4 > n  # many pairs: products of incidence matrices, some grams at a time
    for k in range(len(cut) - 1):
        g, r = gram[cut[k] : cut[k + 1]] - k * width, rs[cut[k] : cut[k + 1]]
        if not len(g):
            continue
        m = np.zeros((n, width), np.float32)
        m[r, g] = 1
        both += (m @ m.T)[p, q] if whole else np.einsum("pk,pk->p", m[p], m[q])
    either = size[p] + size[q] - both
    good = both >= threshold * either - 1e-9 * either
    return p[good], q[good]


def kept_documents(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """One row of each near-duplicate class, the one with the least id; columns of docs. Of equal ids one row, null ids last."""
    kept_as = {c: f"p{i}" for i, c in enumerate(docs.columns)}
    flat = docs.select(common.col(key).cast("long").alias("k"), common.clean_text(common.col(text)).alias("t"), *[common.col(c).alias(p) for c, p in kept_as.items()])
    rows = common.identified(flat, "k", ["k", "t", *kept_as.values()])
    links = linked(rows.select("uid", "ord", F.col("k").alias("doc_id"), F.col("t").alias("text")))
    drop = common.stage(links.filter("uid <> class_uid").select(F.col("uid").alias("copy")), "near-drop")
    return rows.join(drop, F.col("uid") == F.col("copy"), "left_anti").select(*[F.col(p).alias(c) for c, p in kept_as.items()])


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_links(spark.read.parquet(f"{sf_dir}/documents.parquet"))
