"""Reading and writing tables and indexes: plain formats, versioned index folders, vector files, a compressed-list data source."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, In, InputPartition

from ..operators import arrow

FORMATS = ("parquet", "orc", "json", "csv", "text", "binaryFile")


def read(spark: SparkSession, fmt: str, path: str, schema=None) -> DataFrame:
    if fmt not in FORMATS:
        raise ValueError(f"no format {fmt!r}")
    r = spark.read.format(fmt)
    if schema is not None:
        r = r.schema(schema)
    return r.option("header", "true").load(path) if fmt == "csv" else r.load(path)


def write(df: DataFrame, fmt: str, path: str, mode: str = "errorifexists", partition_by: list[str] | None = None) -> None:
    w = df.write.format(fmt).mode(mode)
    if partition_by:
        w = w.partitionBy(*partition_by)
    (w.option("header", "true") if fmt == "csv" else w).save(path)


def save_index(encoded: DataFrame, path: str, buckets: int = 16) -> None:
    """A new version of compressed lists: folders by key bucket, rows sorted by key, so that a point read opens one folder."""
    rows = encoded.withColumn("bucket", F.pmod(F.xxhash64("k"), F.lit(buckets)).cast("int"))
    rows.repartition("bucket").sortWithinPartitions("bucket", "k", "seg").write.partitionBy("bucket").parquet(path)


def open_index(spark: SparkSession, path: str, keys: list | None = None, buckets: int = 16) -> DataFrame:
    """Compressed lists; with keys, only these lists: bucket folders are pruned and the key filter reaches the scan."""
    df = spark.read.parquet(path)
    if keys is not None:
        kind = dict(df.dtypes)["k"]
        wanted = spark.range(1).select(F.explode(F.array(*[F.lit(k).cast(kind) for k in keys])).alias("k")).select(F.pmod(F.xxhash64("k"), F.lit(buckets)).cast("int").alias("b")).distinct()
        df = df.filter(F.col("bucket").isin([r.b for r in wanted.collect()]) & F.col("k").isin(keys))
    return df.drop("bucket")


def vector_files(spark: SparkSession, path: str, kind: str = "fvecs") -> DataFrame:
    """(file, pos, vec) of files that hold, per vector, a 32-bit dimension and its components (float32, or bytes for bvecs)."""
    arrow.importable(spark)
    item = np.dtype({"fvecs": "<f4", "ivecs": "<i4", "bvecs": "u1"}[kind])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for name, content in zip(b.column(0).to_pylist(), b.column(1), strict=True):
                data = content.as_py()
                if not data:
                    continue
                dim = int(np.frombuffer(data, "<i4", 1)[0])
                step = 4 + dim * item.itemsize
                x = np.ascontiguousarray(np.frombuffer(data, np.uint8).reshape(-1, step)[:, 4:]).view(item).astype(np.float32)
                vec = pa.ListArray.from_arrays(pa.array(np.arange(len(x) + 1, dtype=np.int32) * dim), pa.array(x.ravel()))
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(x)), pa.array(np.arange(len(x))), vec], ["file", "pos", "vec"])

    return spark.read.format("binaryFile").load(path).select("path", "content").mapInArrow(run, "file string, pos long, vec array<float>")


class IdLists(DataSource):
    """format("idlists"): (k, id) decoded while scanning. Options: path, a folder of compressed lists that every executor can open.

    A filter on k (equal or in) is taken by the reader, which opens only row groups whose statistics admit the key.
    """

    @classmethod
    def name(cls) -> str:
        return "idlists"

    def schema(self) -> str:
        return "k long, id long"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


class _Part(InputPartition):
    def __init__(self, file: str):
        super().__init__(file)
        self.file = file


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.keys = options["path"].removeprefix("file://"), None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("k",):
                self.keys = {f.value} if self.keys is None else self.keys & {f.value}
            elif isinstance(f, In) and f.attribute == ("k",):
                self.keys = set(f.value) if self.keys is None else self.keys & set(f.value)
            else:
                yield f

    def partitions(self):
        import glob

        return [_Part(f) for f in sorted(glob.glob(f"{self.path}/**/*.parquet", recursive=True))]

    def read(self, partition):
        import pyarrow.dataset as ds

        from ..functions import listcodecs

        where = None if self.keys is None else ds.field("k").isin(sorted(self.keys))
        t = ds.dataset(partition.file).to_table(filter=where, columns=["k", "n", "lo", "codec", "universe", "payload"])
        for b in t.to_batches(max_chunksize=256):
            for r in b.to_pylist():
                ids = listcodecs.codec(r["codec"], r["universe"]).decode([r["payload"]], np.array([r["n"]])) + r["lo"]
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(ids), r["k"])), pa.array(ids)], ["k", "id"])


def register(spark: SparkSession) -> None:
    """Makes format("idlists") known, and lets Spark hand it filters."""
    arrow.importable(spark)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(IdLists)
