"""Inverted-file index: clusters of vectors, ids compressed per cluster or as a wavelet tree, search with early or late ids.

Rows of a cluster stand in ascending order of id: set codecs forget any other order, so an id's rank is its offset.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.dataset as ds
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import listcodecs
from ..sources import store
from . import arrow, frames, graph, quantizers, search, wavelet


@dataclass
class Ivf:
    centroids: np.ndarray
    codes: DataFrame  # k, off, vec or code
    lists: DataFrame | None  # compressed ids per cluster
    tree: DataFrame | None  # wavelet index over cluster labels
    universe: int
    codec: str
    scorer: object
    shard_bits: int = 20
    links: CentroidGraph | None = None  # made once, on the first search that asks for it


@dataclass
class CentroidGraph:
    """Neighbours among centroids, in parts of bounded size: numbers of a part's centroids, where each one's links start, links, entry."""

    parts: list[tuple[np.ndarray, np.ndarray, np.ndarray, int]]

    @classmethod
    def of(cls, spark: SparkSession, centroids: np.ndarray, most: int = 16) -> CentroidGraph:
        """Built part by part on the executors."""
        vec = pa.ListArray.from_arrays(pa.array(np.arange(len(centroids) + 1, dtype=np.int32) * centroids.shape[1]), pa.array(centroids.ravel()))
        db = spark.createDataFrame(pa.table({"id": pa.array(np.arange(len(centroids))), "vec": vec}))
        shards = graph.shards_for(len(centroids))
        edges = graph.build(db, most, "monotone", 2 * most, shards).toArrow().combine_chunks()  # some links a centroid
        shard, src, dst = (edges[c].to_numpy() for c in ("shard", "src", "dst"))
        own = graph._shards(db, shards).select("shard", "id").toArrow().combine_chunks()
        number, of = own["id"].to_numpy(), own["shard"].to_numpy()
        parts = []
        for k in np.unique(of).tolist():
            ids = np.sort(number[of == k])
            a, b = np.searchsorted(ids, src[shard == k]), np.searchsorted(ids, dst[shard == k])
            order = np.argsort(a, kind="stable")
            parts.append((ids, np.searchsorted(a[order], np.arange(len(ids) + 1)), b[order], graph.medoid(centroids[ids])))
        return cls(parts)

    def probe(self, q: np.ndarray, centroids: np.ndarray, nprobe: int, explore: int) -> np.ndarray:
        """Numbers of about the nprobe closest clusters of each query, by beam search in every part; missing ones are filled up in order."""
        n = min(nprobe, len(centroids))
        out = np.zeros((len(q), n), np.int64)
        views = [(ids, centroids[ids], start, links, entry) for ids, start, links, entry in self.parts]
        for row, v in enumerate(q):
            found = sorted((d, int(ids[j])) for ids, x, start, links, entry in views for d, j in graph.walk(x, lambda i, start=start, links=links: links[start[i] : start[i + 1]].tolist(), v, n, max(explore, n), entry))
            some = [j for _, j in found[:n]]
            if len(some) < n:
                have = set(some)
                some += [j for j in range(len(centroids)) if j not in have][: n - len(some)]
            out[row] = some
        return out


def canonical(assigned: DataFrame) -> DataFrame:
    """Adds off, the place of a row in its cluster by ascending id."""
    return assigned.withColumn("off", (F.row_number().over(Window.partitionBy("k").orderBy("id")) - 1).cast("long"))


def placed(db: DataFrame, centroids: np.ndarray) -> DataFrame:
    """id, vec, k, off: every row with its cluster and its place there."""
    return canonical(quantizers.assign(db.select(F.col("id").cast("long").alias("id"), "vec"), centroids))


def stored_ids(rows: DataFrame, codec: str, universe: int, clusters: int, shard_bits: int = 20) -> tuple[DataFrame | None, DataFrame | None]:
    """Ids of placed rows as lists per cluster, or as a wavelet tree. Lists too long for exact states are cut into ranges that can't be."""
    if codec in ("wt", "wt1"):
        return None, wavelet.build(rows, "id", "k", clusters, "flat" if codec == "wt" else "rrr", shard_bits)
    segment = None
    if codec in listcodecs.EXACT and (rows.groupBy("k").count().agg(F.max("count")).first()[0] or 0) > listcodecs.EXACT_IDS:
        segment = listcodecs.EXACT_IDS.bit_length() - 1
    return frames.encode_lists(rows.select("k", "id"), "k", "id", codec, universe, segment), None


def build(db: DataFrame, centroids: np.ndarray, codec: str = "roc", quantizer=None, metric: str = "l2", shard_bits: int = 20) -> Ivf:
    """codec: any list codec, or wt / wt1 for flat or block-compressed wavelet trees. db (id, vec), ids dense for wavelet trees."""
    rows = placed(db, centroids)
    universe = int(db.agg(F.coalesce(F.max("id"), F.lit(-1))).first()[0]) + 1
    codes = rows if quantizer is None else quantizers.encode(rows, quantizer)
    scorer = search.Flat(metric) if quantizer is None else quantizer
    lists, tree = stored_ids(rows, codec, universe, len(centroids), shard_bits)
    return Ivf(centroids, codes.select("k", "off", scorer.column), lists, tree, universe, codec, scorer, shard_bits)


def probe(q: np.ndarray, centroids: np.ndarray, nprobe: int) -> np.ndarray:
    """Numbers of the nprobe closest clusters of each query."""
    n, out = min(nprobe, len(centroids)), []
    length, step = (centroids * centroids).sum(1), max(1, quantizers.CELLS // max(1, len(centroids)))
    for lo in range(0, len(q), step):
        out.append(np.argsort(length - 2 * (q[lo : lo + step] @ centroids.T), 1, kind="stable")[:, :n])
    return np.concatenate(out) if out else np.zeros((0, n), np.int64)


def _links(ix: Ivf) -> CentroidGraph:
    if ix.links is None:
        ix.links = CentroidGraph.of(ix.codes.sparkSession, ix.centroids)
    return ix.links


def resolve(ix: Ivf, found: DataFrame) -> DataFrame:
    """Ids of found (k, off, ...) rows, only these: by select on the tree, or by reading the lists of the clusters that won."""
    if ix.tree is not None:
        return wavelet.select(ix.tree, found, ix.shard_bits)
    won = ix.lists.join(found.select("k").distinct(), "k", "left_semi")
    ids = canonical(frames.decode_lists(won))
    return found.join(ids, ["k", "off"])


def find(q: DataFrame, ix: Ivf, k: int, nprobe: int = 16, ids: str = "deferred", centroid_explore: int = 0) -> DataFrame:
    """qid, rank, id, dist. deferred carries (cluster, offset) and resolves the winners; eager decodes all probed lists first.

    With centroid_explore, clusters are chosen by a beam search of that width on a graph over the centroids.
    """
    out, links = None, _links(ix) if centroid_explore else None
    for qid, qmat in search.query_blocks(q):
        probes = links.probe(qmat, ix.centroids, nprobe, centroid_explore) if links else probe(qmat, ix.centroids, nprobe)
        if ids == "eager":
            if ix.lists is None:
                raise wavelet.UnsupportedError("a wavelet tree has no lists to decode; ask for deferred ids")
            probed = sorted({int(c) for c in probes.ravel()})
            decoded = canonical(frames.decode_lists(ix.lists.filter(F.col("k").isin(probed))))
            rows = ix.codes.filter(F.col("k").isin(probed)).join(decoded, ["k", "off"]).select("k", "id", ix.scorer.column)
            got = search.ranked(search.scan(rows, (qid, qmat), probes, k, ix.scorer, "id"), k, ["id"])
        else:
            got = search.ranked(search.scan(ix.codes, (qid, qmat), probes, k, ix.scorer), k, ["k", "off"])
            got = resolve(ix, got.select("k", "off", "qid", "rank", "dist"))
        got = got.select("qid", "rank", "id", "dist")
        out = got if out is None else out.union(got)
    return out if out is not None else search.empty(ix.codes.sparkSession)


#: Rows of a cluster that are scanned in one group.
PART_ROWS = 1 << 15


def probes(q: DataFrame, ix: Ivf, nprobe: int, centroid_explore: int = 0) -> DataFrame:
    """(qid, k): the clusters each query probes, chosen by the tasks that hold the queries."""
    spark = q.sparkSession
    arrow.importable(spark)
    held = spark.sparkContext.broadcast((ix.centroids, _links(ix) if centroid_explore else None))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        centroids, links = held.value
        for b in batches:
            if b.num_rows:
                x = arrow.vectors(b.column(1)).astype(np.float64)
                near = links.probe(x, centroids, nprobe, centroid_explore) if links else probe(x, centroids, nprobe)
                yield pa.RecordBatch.from_arrays([b.column(0).take(pa.array(np.repeat(np.arange(len(x)), near.shape[1]))), pa.array(near.ravel())], ["qid", "k"])

    return q.select(F.col("qid").cast("long").alias("qid"), "qvec").mapInArrow(run, "qid long, k long")


def find_by_join(q: DataFrame, ix: Ivf, k: int, nprobe: int = 16, centroid_explore: int = 0) -> DataFrame:
    """The same answers as `find` for batches and numbers of clusters of any size: queries meet the clusters they probe in a join.

    A large cluster is scanned in parts; nothing of the batch passes the driver.
    """
    arrow.importable(q.sparkSession)
    scorer = ix.scorer
    parts = ix.codes.groupBy("k").agg(F.floor(F.max("off") / PART_ROWS).cast("int").alias("last"))
    asked = probes(q, ix, nprobe, centroid_explore).join(parts, "k").withColumn("part", F.explode(F.sequence(F.lit(0), F.col("last"))))
    asked = asked.join(q.select(F.col("qid").cast("long").alias("qid"), "qvec"), "qid").select("k", "part", "qid", "qvec")
    codes = ix.codes.select(F.col("k").cast("long").alias("k"), F.floor(F.col("off") / PART_ROWS).cast("int").alias("part"), F.col("off").cast("long").alias("off"), scorer.column)

    def run(key: tuple, a: pa.Table, b: pa.Table) -> pa.Table:
        schema = pa.schema([("qid", pa.int64()), ("k", pa.int64()), ("off", pa.int64()), ("dist", pa.float64())])
        if not a.num_rows or not b.num_rows:
            return schema.empty_table()
        a, b = a.combine_chunks(), b.combine_chunks()
        ids, x = a["qid"].to_numpy(), arrow.vectors(a["qvec"].chunk(0)).astype(np.float64)
        off, rows = b["off"].to_numpy(), scorer.rows(b[scorer.column].chunk(0))
        out, step = [], max(1, quantizers.CELLS // len(off))
        for lo in range(0, len(ids), step):
            dist = scorer.distances(x[lo : lo + step], rows)
            row, col = search.best(dist, off, k)
            out.append((ids[lo + row], off[col], dist[row, col]))
        qid, at, dist = (np.concatenate(v) for v in zip(*out, strict=True))
        return pa.table({"qid": qid, "k": np.full(len(qid), key[0].as_py()), "off": at, "dist": dist}, schema=schema)

    near = asked.groupBy("k", "part").cogroup(codes.groupBy("k", "part")).applyInArrow(run, "qid long, k long, off long, dist double")
    got = search.ranked(near, k, ["k", "off"])
    return resolve(ix, got.select("k", "off", "qid", "rank", "dist")).select("qid", "rank", "id", "dist")


def rerank(found: DataFrame, q: DataFrame, db: DataFrame, k: int) -> DataFrame:
    """The k best of a short list (qid, id) by exact distance."""
    d = F.aggregate(F.zip_with("qvec", "vec", lambda a, b: (a.cast("double") - b.cast("double")) * (a.cast("double") - b.cast("double"))), F.lit(0.0), lambda s, x: s + x)
    short = found.select("qid", "id").join(q.select("qid", "qvec"), "qid").join(db.select("id", "vec"), "id").select("qid", "id", d.alias("dist"))
    return search.ranked(short, k, ["id"]).select("qid", "rank", "id", "dist")


def id_bits(ix: Ivf) -> DataFrame:
    """codec, ids, bits_per_id of an index, without reading payloads."""
    rows = ix.tree if ix.tree is not None else ix.lists
    return rows.agg(F.lit(ix.codec).alias("codec"), F.sum("n").cast("long").alias("ids"), F.round(F.sum("bits") / F.sum("n"), 4).alias("bits_per_id"))


def permute(db: DataFrame, factor: int, n: int) -> DataFrame:
    """The same vectors under renumbered ids, id -> id * factor mod n (factor coprime to n): a check that order doesn't matter."""
    return db.withColumn("id", F.pmod(F.col("id") * factor, F.lit(n)))


def size(ix: Ivf) -> DataFrame:
    """One row: bytes of ids, codes (as stored symbols of 2**bits, or 32-bit floats) and centroids, and their sum."""
    rows = ix.tree if ix.tree is not None else ix.lists
    ids = rows.agg((F.sum("bits") / 8).alias("id_bytes"), F.sum("n").alias("n"))
    books = getattr(ix.scorer, "books", None)
    per = ix.centroids.shape[1] * 4 if books is None else books.shape[0] * (books.shape[1] - 1).bit_length() / 8
    fixed = ix.centroids.size * 4 + (0 if books is None else books.size * 4)
    out = ids.select(F.lit(ix.codec).alias("codec"), F.round("id_bytes", 1).alias("id_bytes"), F.round(F.col("n") * float(per), 1).alias("code_bytes"), F.lit(float(fixed)).alias("model_bytes"))
    return out.withColumn("bytes", F.round(F.col("id_bytes") + F.col("code_bytes") + F.col("model_bytes"), 1))


def save(ix: Ivf, path: str, buckets: int = 16) -> None:
    """A new folder with the index: one row of settings and models, codes by cluster bucket in canonical order, ids in their coded form."""
    spark, books = ix.codes.sparkSession, getattr(ix.scorer, "books", None)
    kind = f"flat:{ix.scorer.metric}" if books is None else type(ix.scorer).__name__
    meta = (ix.codec, ix.universe, ix.shard_bits, buckets, kind, list(ix.centroids.shape), ix.centroids.ravel().tolist(), [] if books is None else list(books.shape), [] if books is None else books.ravel().tolist())
    spark.createDataFrame([meta], META).coalesce(1).write.parquet(f"{path}/meta")
    rows = ix.codes.withColumn("bucket", F.pmod(F.xxhash64("k"), F.lit(buckets)).cast("int"))
    rows.repartition("bucket").sortWithinPartitions("bucket", "k", "off").write.partitionBy("bucket").parquet(f"{path}/codes")
    if ix.lists is not None:
        store.save_index(ix.lists, f"{path}/lists", buckets)
    else:
        ix.tree.write.parquet(f"{path}/tree")


META = "codec string, universe long, shard_bits int, buckets int, scorer string, shape array<int>, centroids array<double>, book_shape array<int>, books array<double>"


def _scorer(kind: str, shape: list[int], books: list[float]):
    if kind.startswith("flat:"):
        return search.Flat(kind[5:])
    return {c.__name__: c for c in (quantizers.ProductQuantizer, quantizers.ResidualQuantizer)}[kind](np.array(books).reshape(shape))


def load(spark: SparkSession, path: str) -> Ivf:
    """The index that save wrote; codes and ids are read when a search asks for them."""
    m = spark.read.schema(META).parquet(f"{path}/meta").first()
    scorer = _scorer(m.scorer, m.book_shape, m.books)
    coded = m.codec in ("wt", "wt1")
    lists = None if coded else store.open_index(spark, f"{path}/lists", buckets=m.buckets)
    tree = spark.read.parquet(f"{path}/tree") if coded else None
    return Ivf(np.array(m.centroids).reshape(m.shape), spark.read.parquet(f"{path}/codes").drop("bucket"), lists, tree, m.universe, m.codec, scorer, m.shard_bits)


class OpenIvf:
    """A saved index as one task opens it, from a folder that every executor can open: models at once, clusters and id lists as they are asked for."""

    #: Clusters that are kept once they are read.
    KEPT = 64

    def __init__(self, path: str):
        self.path = path.removeprefix("file://")
        m = pq.read_table(f"{self.path}/meta").to_pylist()[0]
        if m["codec"] in ("wt", "wt1"):
            raise wavelet.UnsupportedError("a task opens lists, not trees; search trees by ivf.find")
        self.centroids, self.scorer = np.array(m["centroids"]).reshape(m["shape"]), _scorer(m["scorer"], m["book_shape"], m["books"])
        self.kept: dict[int, tuple] = {}

    def _read(self, folder: str, k: int, columns: list[str]) -> pa.Table:
        return ds.dataset(f"{self.path}/{folder}", format="parquet", partitioning="hive").to_table(columns=columns, filter=ds.field("k") == k).combine_chunks()

    def cluster(self, k: int) -> tuple:
        """Rows of a cluster in order of their places, and its id lists."""
        if k not in self.kept:
            if len(self.kept) >= self.KEPT:
                self.kept.pop(next(iter(self.kept)))
            t = self._read("codes", k, ["off", self.scorer.column]).sort_by("off").combine_chunks()
            lists = self._read("lists", k, ["seg", "n", "lo", "universe", "codec", "payload"]).sort_by("seg").to_pylist()
            self.kept[k] = (self.scorer.rows(t[self.scorer.column].chunk(0)) if t.num_rows else None, lists)
        return self.kept[k]

    def _ids(self, lists: list[dict], off: np.ndarray) -> np.ndarray:
        out, first = np.zeros(len(off), np.int64), 0
        for x in lists:
            mine = np.flatnonzero((off >= first) & (off < first + x["n"]))
            if len(mine):
                out[mine] = listcodecs.get_many(listcodecs.codec(x["codec"], x["universe"]), x["payload"], x["n"], off[mine] - first) + x["lo"]
            first += x["n"]
        return out

    def search(self, q: np.ndarray, k: int, nprobe: int) -> list[tuple[int, int, float]]:
        """rank, id, dist of one query."""
        found = []
        for c in probe(q[None], self.centroids, nprobe)[0].tolist():
            rows, lists = self.cluster(c)
            if rows is not None:
                dist = self.scorer.distances(q[None], rows)
                _, off = search.best(dist, np.arange(len(rows)), k)
                found += [(float(dist[0, o]), c, int(o), lists) for o in off.tolist()]
        found = sorted(found, key=lambda f: f[:3])[:k]
        return [(rank, int(self._ids(lists, np.array([o]))[0]), d) for rank, (d, _, o, lists) in enumerate(found, 1)]
