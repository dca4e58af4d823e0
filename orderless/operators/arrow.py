"""Helpers for Arrow task functions: whole groups of sorted rows, importing the package in workers, staged tables."""

from __future__ import annotations

import atexit
import os
import re
import tempfile
import uuid
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession

_ROOT = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
_OWN: list[str] = []


def importable(spark: SparkSession) -> None:
    """Lets Python workers import this package from where the driver found it."""
    env = spark.sparkContext.environment
    if _ROOT not in env.get("PYTHONPATH", "").split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(filter(None, [_ROOT, env.get("PYTHONPATH", "")]))


def edges(columns: list[pa.Array]) -> np.ndarray:
    """Positions where sorted rows begin a new group, and their number at the end."""
    n = len(columns[0])
    new = np.zeros(n, bool)
    new[:1] = True
    for c in columns:
        if n > 1:
            new[1:] |= pc.fill_null(pc.not_equal(c[1:], c[:-1]), True).to_numpy(zero_copy_only=False)
    return np.r_[np.flatnonzero(new), n]


def whole_groups(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.RecordBatch]:
    """Rows sorted by their first `keys` columns, rebatched so that no batch ends within a group."""
    held: list[pa.RecordBatch] = []
    for b in batches:
        if not b.num_rows:
            continue
        if held:
            a = held[-1]
            if any(a.column(k)[-1] != b.column(k)[0] for k in range(keys)):
                yield _joined(held)
                held = []
        cut = int(edges([b.column(k) for k in range(keys)])[-2])
        if cut:
            yield _joined([*held, b.slice(0, cut)])
            held = []
        held.append(b.slice(cut))
    if held:
        yield _joined(held)


def _joined(some: list[pa.RecordBatch]) -> pa.RecordBatch:
    return some[0] if len(some) == 1 else pa.Table.from_batches(some).combine_chunks().to_batches()[0]


def vectors(column: pa.Array) -> np.ndarray:
    """A list column of equal lengths as a matrix, without a Python object per number."""
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share; a temporary one only where a local session names none."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not re.match(r"local(\[|$)", spark.sparkContext.master):
        raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _OWN:
        _OWN.append(tempfile.mkdtemp(prefix="orderless-"))
    return "file://" + _OWN[0]


def fresh(spark: SparkSession, tag: str) -> str:
    """A path in the shared folder that nothing else uses; it goes when the driver process ends."""
    path = f"{shared_dir(spark)}/orderless/{spark.sparkContext.applicationId}/{tag}-{uuid.uuid4().hex}"
    atexit.register(_delete, spark, path)
    return path


def stage(df: DataFrame, tag: str) -> DataFrame:
    """Cuts lineage: writes df to the shared folder as Parquet, which survives lost executors, and reads it back."""
    spark = df.sparkSession
    path = fresh(spark, tag)
    df.write.option("compression", "zstd").parquet(path)
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_path = path  # type: ignore[attr-defined]
    return out


def _delete(spark: SparkSession, path: str) -> None:
    try:
        p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # the session has ended
        pass
