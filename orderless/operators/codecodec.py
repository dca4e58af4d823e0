"""Quantizer codes coded per cluster and column under running counts: a symbol weighs 1 plus the times it was seen.

The coder is last in, first out, so the encoder walks a column backwards, taking counts away; the decoder walks forwards from none.
Codes of a cluster stand in ascending order of id, which is also the order its decoded ids come in.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import setcodec
from ..functions.ans import ExactState, WordStateBatch
from . import arrow


#: Cells of the matrices that columns coded in step share.
CELLS = 1 << 21


def portions(sizes: np.ndarray, alphabet: int) -> Iterator[list[int]]:
    """Numbers of columns of like length that are coded together, so that neither codes nor counts of them exceed a bound."""
    order, lo = np.argsort(-sizes, kind="stable"), 0
    while lo < len(order):
        n = max(1, CELLS // max(1, int(sizes[order[lo]]), alphabet))
        yield order[lo : lo + n].tolist()
        lo += n


def encode_columns(columns: list[np.ndarray], alphabet: int) -> tuple[list[bytes], np.ndarray]:
    """Many columns in lockstep, longest first; payloads and bits in the order given."""
    order = sorted(range(len(columns)), key=lambda i: -len(columns[i]))
    size = np.array([len(columns[i]) for i in order], np.int64)
    longest = int(size[0]) if len(size) else 0
    code = np.zeros((len(order), longest), np.int64)
    counts = np.ones((len(order), alphabet), np.int64)
    for row, i in enumerate(order):
        code[row, : size[row]] = columns[i]
        counts[row] += np.bincount(columns[i], minlength=alphabet)
    state = WordStateBatch(len(order), longest * alphabet.bit_length() // 32 + 4)
    for i in range(longest - 1, -1, -1):
        n = int(np.searchsorted(-size, -i, side="left"))  # columns with more than i codes
        x, rows = code[:n, i], np.arange(n)
        counts[rows, x] -= 1
        start = np.where(np.arange(alphabet) < x[:, None], counts[:n], 0).sum(1)
        _push(state, n, start, counts[rows, x], alphabet + i)
    back = np.empty(len(order), np.int64)
    back[order] = np.arange(len(order))
    payload = state.to_bytes()
    return [payload[k] for k in back.tolist()], state.bits()[back]


def decode_columns(payload: list[bytes], sizes: list[int], alphabet: int) -> list[np.ndarray]:
    order = sorted(range(len(payload)), key=lambda i: -sizes[i])
    size = np.array([sizes[i] for i in order], np.int64)
    longest = int(size[0]) if len(size) else 0
    state = WordStateBatch.from_bytes([payload[i] for i in order])
    counts, out = np.ones((len(order), alphabet), np.int64), np.zeros((len(order), longest), np.int64)
    for i in range(longest):
        n = int(np.searchsorted(-size, -i, side="left"))
        total = alphabet + i
        slot = (((state.head[:n] & np.uint64((1 << 31) - 1)) + np.uint64(1)) * np.uint64(total) - np.uint64(1)) >> np.uint64(31)
        sums = np.cumsum(counts[:n], 1)
        x = (sums <= slot.astype(np.int64)[:, None]).sum(1)
        rows = np.arange(n)
        start = sums[rows, x] - counts[rows, x]
        a, f = _slots(start, counts[rows, x], total)
        state.pop(n, a, f)
        counts[rows, x] += 1
        out[:n, i] = x
    back = np.empty(len(order), np.int64)
    back[order] = np.arange(len(order))
    return [out[k, : size[k]] for k in back.tolist()]


def _slots(start: np.ndarray, freq: np.ndarray, total: int) -> tuple[np.ndarray, np.ndarray]:
    a = (start.astype(np.uint64) << np.uint64(31)) // np.uint64(total)
    return a, ((start + freq).astype(np.uint64) << np.uint64(31)) // np.uint64(total) - a


def _push(state: WordStateBatch, n: int, start: np.ndarray, freq: np.ndarray, total: int) -> None:
    a, f = _slots(start, freq, total)
    state.push(n, a, f)


def encode(codes: DataFrame, cluster: str = "k", sub: str = "sub", order: str = "id", code: str = "code", alphabet: int = 256) -> DataFrame:
    """codes (cluster, sub, order, code) to (k, sub, n, alphabet, payload, bits); cluster=lit(0) upstream gives the unconditioned control."""
    arrow.importable(codes.sparkSession)
    rows = codes.select(F.col(cluster).cast("long").alias("k"), F.col(sub).cast("int").alias("sub"), F.col(order).cast("long").alias("o"), F.col(code).cast("int").alias("code"))
    rows = rows.repartition("k", "sub").sortWithinPartitions("k", "sub", "o")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in arrow.whole_groups(batches, 2):
            at, code = arrow.edges([b.column(0), b.column(1)]), b.column(3).to_numpy().astype(np.int64)
            payload, bits = [b""] * (len(at) - 1), np.zeros(len(at) - 1, np.int64)
            for some in portions(np.diff(at), alphabet):
                got, bits[some] = encode_columns([code[at[i] : at[i + 1]] for i in some], alphabet)
                for i, p in zip(some, got, strict=True):
                    payload[i] = p
            pick = pa.array(at[:-1])
            yield pa.RecordBatch.from_arrays([b.column(0).take(pick), b.column(1).take(pick), pa.array(np.diff(at)), pa.array(np.full(len(payload), alphabet, np.int32)), pa.array(payload, pa.binary()), pa.array(bits.astype(np.int64))], ["k", "sub", "n", "alphabet", "payload", "bits"])

    return rows.mapInArrow(run, "k long, sub int, n long, alphabet int, payload binary, bits long")


def decode(encoded: DataFrame) -> DataFrame:
    """(k, sub, off, code) with off the place within the cluster."""
    arrow.importable(encoded.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for lo in range(0, b.num_rows, 64):
                part = b.slice(lo, 64)
                n = part.column(2).to_pylist()
                for alphabet in sorted(set(part.column(3).to_pylist())):
                    mine = [i for i, a in enumerate(part.column(3).to_pylist()) if a == alphabet]
                    got = decode_columns([part.column(4)[i].as_py() for i in mine], [n[i] for i in mine], alphabet)
                    pick = pa.array(np.repeat(mine, [n[i] for i in mine]))
                    off = np.concatenate([np.arange(n[i]) for i in mine])
                    yield pa.RecordBatch.from_arrays([part.column(0).take(pick), part.column(1).take(pick), pa.array(off), pa.array(np.concatenate(got).astype(np.int32))], ["k", "sub", "off", "code"])

    return encoded.select("k", "sub", "n", "alphabet", "payload").mapInArrow(run, "k long, sub int, off long, code int")


def encode_sets(rows: DataFrame, alphabet: int = 256) -> DataFrame:
    """Rows (k, code) with code an array of symbols, to (k, n, width, alphabet, payload, bits): each cluster's codes as one multiset.

    Where ids are implied by nothing but the codes' order, that order goes too, and log2(n!) bits with it. Scalar, exact states;
    a cluster is one group, so clusters should be bounded.
    """
    arrow.importable(rows.sparkSession)

    def run(key: tuple, t: pa.Table) -> pa.Table:
        codes = t["code"].to_pylist()
        width = len(codes[0])
        values = [sum(int(c) * alphabet**j for j, c in enumerate(row)) for row in codes]
        state = ExactState(0)
        setcodec.encode_multiset(state, values, alphabet**width)
        return pa.table({"k": [key[0].as_py()], "n": [len(values)], "width": pa.array([width], pa.int32()), "alphabet": pa.array([alphabet], pa.int32()), "payload": pa.array([state.to_bytes()], pa.binary()), "bits": [state.bits]})

    return rows.select(F.col("k").cast("long").alias("k"), "code").groupBy("k").applyInArrow(run, "k long, n long, width int, alphabet int, payload binary, bits long")


def decode_sets(encoded: DataFrame) -> DataFrame:
    """(k, code) of coded multisets, in ascending order of the codes."""
    arrow.importable(encoded.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in b.to_pylist():
                values = setcodec.decode_multiset(ExactState.from_bytes(r["payload"]), r["n"], r["alphabet"] ** r["width"])
                codes = [[v // r["alphabet"] ** j % r["alphabet"] for j in range(r["width"])] for v in values]
                yield pa.RecordBatch.from_arrays([pa.array([r["k"]] * len(codes), pa.int64()), pa.array(codes, pa.list_(pa.int32()))], ["k", "code"])

    return encoded.mapInArrow(run, "k long, code array<int>")
