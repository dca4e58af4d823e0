"""SQL surface: functions that encode, decode and read id lists, registered on a session."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Row, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import udtf

from ..functions import listcodecs
from ..operators import arrow, ivf


def _encode(ids: list[int], universe: int, codec: str) -> bytes:
    flat = np.unique(np.array(ids, np.int64))
    payload, _ = listcodecs.codec(codec, universe).encode(flat, np.array([0, len(flat)]))
    head = np.array([len(flat), universe], "<i8").tobytes() + bytes([len(codec)]) + codec.encode()
    return head + payload[0]


def _decode(data: bytes) -> np.ndarray:
    n, universe = np.frombuffer(data, "<i8", 2).tolist()
    cut = 17 + data[16]
    return listcodecs.codec(data[17:cut].decode(), universe).decode([data[cut:]], np.array([n]))


@F.arrow_udf(T.BinaryType())
def ids_encode(ids: pa.Array, universe: pa.Array, codec: pa.Array) -> pa.Array:
    return pa.array([_encode(i, u, c) if i is not None else None for i, u, c in zip(ids.to_pylist(), universe.to_pylist(), codec.to_pylist(), strict=True)], pa.binary())


@F.arrow_udf(T.ArrayType(T.LongType()))
def ids_decode(data: pa.Array) -> pa.Array:
    return pa.array([_decode(d).tolist() if d is not None else None for d in data.to_pylist()], pa.list_(pa.int64()))


@F.arrow_udf(T.LongType())
def ids_count(data: pa.Array) -> pa.Array:
    return pa.array([int(np.frombuffer(d, "<i8", 1)[0]) if d is not None else None for d in data.to_pylist()], pa.int64())


@F.arrow_udf(T.LongType())
def ids_get(data: pa.Array, off: pa.Array) -> pa.Array:
    out = []
    for d, o in zip(data.to_pylist(), off.to_pylist(), strict=True):
        if d is None or o is None:
            out.append(None)
            continue
        n, universe = np.frombuffer(d, "<i8", 2).tolist()
        cut = 17 + d[16]
        out.append(int(listcodecs.get_many(listcodecs.codec(d[17:cut].decode(), universe), d[cut:], n, np.array([o]))[0]) if 0 <= o < n else None)
    return pa.array(out, pa.int64())


@F.arrow_udf(T.BooleanType())
def ids_contains(data: pa.Array, id: pa.Array) -> pa.Array:
    return pa.array([None if d is None or i is None else bool(np.isin(i, _decode(d))) for d, i in zip(data.to_pylist(), id.to_pylist(), strict=True)], pa.bool_())


@F.pandas_udf(T.BinaryType())
def ids_encode_agg(ids: pd.Series, universe: pd.Series) -> bytes:
    return _encode(ids.tolist(), int(universe.iloc[0]), "roc")


@udtf(returnType=T.StructType([T.StructField("id", T.LongType())]))
class IdsUnnest:
    def eval(self, data: bytes):
        for i in _decode(bytes(data)).tolist():
            yield (i,)


@udtf(returnType="qid bigint, rank int, id bigint, dist double")
class IvfSearch:
    """ivf_search(TABLE(queries), path, k, nprobe): queries have qid and qvec, path leads to a saved index; each task opens what its queries probe."""

    def __init__(self):
        self.index = None

    def eval(self, row: Row, path: str, k: int, nprobe: int):
        if self.index is None:
            self.index = ivf.OpenIvf(path)
        for rank, id, dist in self.index.search(np.array(row["qvec"], np.float64), k, nprobe):
            yield row["qid"], rank, id, dist


def register(spark: SparkSession) -> None:
    """ids_encode(ids, universe, codec), ids_decode, ids_count, ids_get, ids_contains; aggregate ids_encode_agg(id, universe); table functions ids_unnest, ivf_search."""
    arrow.importable(spark)
    for name, f in (("ids_encode", ids_encode), ("ids_decode", ids_decode), ("ids_count", ids_count), ("ids_get", ids_get), ("ids_contains", ids_contains), ("ids_encode_agg", ids_encode_agg)):
        spark.udf.register(name, f)
    spark.udtf.register("ids_unnest", IdsUnnest)
    spark.udtf.register("ivf_search", IvfSearch)
