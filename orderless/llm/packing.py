"""Best-fit-decreasing packing of tokenised documents into sequences of a fixed size.

Three steps. (1) Each document is tokenised and cut where it is longer than a sequence; narrow. (2) Pieces are
counted by length: a table of at most `capacity` rows, whatever the corpus, over which best-fit decreasing runs on the
driver. A segment tree over remaining capacities finds the tightest open sequence in logarithmic time; all pieces of
one length that meet sequences of one remaining capacity are placed in one step, so the plan is the one that
placing document by document would give, yet its size depends on the lengths alone. (3) Each piece gets its rank among
the pieces of its length (a count per task and length, offsets by a window over those counts) and looks its place up.

Defined results: a null or empty text is one token, the end id. Repeated rows are packed each. An empty table gives no rows.
A hot length needs no shuffle of rows: ranks come from counts.
"""

from __future__ import annotations

import json
import os
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import common
from .byte_bpe import MergeTable, byte_letters

VOCABULARY = "word_bpe_49k.json"
CAPACITY = 4096
END_ID = 1
#: Slots of a worker's table of known units (27 bytes each), and ids a unit may have to be kept there.
SLOTS, INLINE = 1 << 21, 8

# classes of bytes: 0 white space, 1 letter, 2 digit, 3 mark; a word with an odd byte goes to the library whole
_CLASS = np.full(256, 3, np.uint8)
_CLASS[[9, 10, 11, 12, 13, 32]] = 0
_CLASS[list(b"abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ")] = 1
_CLASS[list(b"0123456789")] = 2
_CLASS[128:] = 1
_ODD = np.zeros(256, bool)
_ODD[:32] = True
_ODD[[9, 10, 11, 12, 13]] = False
_ODD[[39, 127]] = True  # the apostrophe joins contractions
_ODD[128:] = True
_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32


class WordBpe:
    """Encodes as the tokenizers library does with a vocabulary that lowers case, drops white space and marks ends of words.

    Units (runs of letters, runs of marks, single digits) are told apart and hashed in numpy; new ones are merged together in
    batched rounds and kept in a table where a new unit takes the place of another of its slot, so its size is fixed.
    Words with bytes beyond ASCII and the Latin-1 letters, or with apostrophes, go to the library whole.
    """

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")
        from tokenizers import Tokenizer

        self.lib = Tokenizer.from_file(path)
        self.lib.no_truncation()
        self.lib.no_padding()
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        vocab, letters = spec["model"]["vocab"], byte_letters()
        self.table = MergeTable(vocab, spec["model"]["merges"], len(vocab) + len(spec["added_tokens"]))
        inner, last = ([vocab[letters[b] + tail] for b in range(256)] for tail in ("", spec["model"]["end_of_word_suffix"]))
        self.inner, self.last = np.array(inner), np.array(last)
        self.key, self.count, self.ids = np.zeros(SLOTS, np.uint64), np.zeros(SLOTS, np.uint8), np.zeros((SLOTS, INLINE), np.uint16)

    def _units(self, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        """Bytes with letters lowered, starts and ends of units, and which are odd words."""
        n = len(data)
        kind, odd = _CLASS[data], _ODD[data]
        lead = np.flatnonzero(data[:-1] == 0xC3)
        tail = data[lead + 1]
        fine = lead[(tail >= 0x80) & (tail <= 0xBF) & (tail != 0x97) & (tail != 0xB7)]  # the letters of Latin-1, not the two signs among them
        odd[fine] = odd[fine + 1] = False
        odd[:-1] |= (data[:-1] == 60) & (data[1:] == 124)  # what may begin a special token
        solid = kind > 0
        first = solid.copy()
        first[1:] &= ~solid[:-1]
        edge = off[(off > 0) & (off < n)]
        first[edge] = solid[edge]
        start = np.flatnonzero(first)
        strange = np.logical_or.reduceat(odd, start) if len(start) else np.zeros(0, bool)
        mine = np.zeros(n, bool)  # bytes of odd words
        if strange.any():
            word = np.cumsum(first) - 1
            mine = strange[np.maximum(word, 0)] & solid
        low = _LOWER[data]
        low[fine + 1] += np.where(data[fine + 1] <= 0x9E, 32, 0).astype(np.uint8)
        low = np.where(mine, data, low)
        new = first.copy()
        new[1:] |= solid[1:] & ~mine[1:] & ((kind[1:] != kind[:-1]) | (kind[1:] == 2))
        begin = np.flatnonzero(new)
        stop = ~solid
        stop |= new
        stop = np.flatnonzero(np.r_[stop, True])
        end = stop[np.searchsorted(stop, begin, side="right")]
        return low, begin, end, mine[begin]

    def encode_bytes(self, data: np.ndarray, off: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of concatenated texts and the n+1 positions of the texts among them."""
        if not len(data):
            return np.zeros(0, "<u4"), np.zeros(len(off), np.int64)
        low, begin, end, strange = self._units(data, off)
        h = common.span_hash(common.prefix_hash(low), begin, end)
        h[strange] ^= np.uint64(0x5851F42D4C957F2D)
        h |= np.uint64(1)  # 0 is an empty slot
        slot = (h >> np.uint64(64 - SLOTS.bit_length() + 1)).astype(np.int64)
        hit = self.key[slot] == h
        count = self.count[slot].astype(np.int64)
        miss = np.flatnonzero(~hit)
        if len(miss):
            unit, one, which = np.unique(h[miss], return_index=True, return_inverse=True)
            one = miss[one]
            flat, size = self._encode_units(low, begin[one], end[one], strange[one])
            at = np.r_[0, np.cumsum(size)]
            count[miss] = size[which]
        place = np.r_[0, np.cumsum(count)]
        out = np.zeros(place[-1], "<u4")

        def spread(units: np.ndarray, source: np.ndarray, values: np.ndarray) -> None:
            n = count[units]
            ahead = np.cumsum(n) - n
            step = np.arange(int(n.sum()))
            out[np.repeat(place[units] - ahead, n) + step] = values[np.repeat(source - ahead, n) + step]

        known = np.flatnonzero(hit)
        spread(known, slot[known] * INLINE, self.ids.ravel())
        if len(miss):
            spread(miss, at[which], flat)
            keep = np.flatnonzero(size <= INLINE)
            to = (unit[keep] >> np.uint64(64 - SLOTS.bit_length() + 1)).astype(np.int64)
            to, only = np.unique(to, return_index=True)
            keep = keep[only]
            self.key[to], self.count[to] = unit[keep], size[keep]
            for j in range(INLINE):
                some = size[keep] > j
                self.ids[to[some], j] = flat[at[keep[some]] + j]
        return out, place[np.searchsorted(begin, off)]

    def _encode_units(self, low: np.ndarray, begin: np.ndarray, end: np.ndarray, strange: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        size = np.zeros(len(begin), np.int64)
        plain = np.flatnonzero(~strange)
        lens = (end - begin)[plain]
        ahead = np.cumsum(lens) - lens
        data = low[np.repeat(begin[plain] - ahead, lens) + np.arange(int(lens.sum()))]
        sym = self.inner[data]
        sym[ahead + lens - 1] = self.last[data[ahead + lens - 1]]
        flat, size[plain] = self.table.run(sym, lens)
        odd = np.flatnonzero(strange)
        if not len(odd):
            return flat, size
        words = [low[a:b].tobytes().decode() for a, b in zip(begin[odd].tolist(), end[odd].tolist(), strict=True)]
        codes = [e.ids for e in self.lib.encode_batch_fast(words, add_special_tokens=False)]
        size[odd] = [len(c) for c in codes]
        at = np.r_[0, np.cumsum(size)]
        out = np.zeros(at[-1], np.int64)
        fits = np.repeat(~strange, size)
        out[fits] = flat
        for k, c in zip(odd.tolist(), codes, strict=True):
            out[at[k] : at[k + 1]] = c
        return out, size

    def encode(self, texts: list[str]) -> list[bytes]:
        ids, at = self.encode_bytes(*common.raw(pa.array(texts, pa.string())))
        return [ids[a:b].tobytes() for a, b in zip(at[:-1].tolist(), at[1:].tolist(), strict=True)]


_LOADED: dict[str, WordBpe] = {}


def tokenised(docs: DataFrame, path: str, capacity: int = CAPACITY, end: int = END_ID, text: str = "text", key: str = "doc_id", ids: bool = False) -> DataFrame:
    """Pieces: doc_id, piece, start, length, ids_crc32, part and local (rank among this task's pieces of that length).

    With ids=True the piece's ids travel along as an array.
    """
    common.importable(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        part = TaskContext.get().partitionId()
        if path not in _LOADED:
            _LOADED[path] = WordBpe(path)
        bpe, last = _LOADED[path], np.array([end], "<u4").tobytes()
        seen = np.zeros(capacity + 1, np.int64)
        for whole in batches:
            for b in common.slices(whole, 1):
                at, piece, start, length, crc, local, held = [], [], [], [], [], [], []
                flat, place = bpe.encode_bytes(*common.raw(b.column(1)))
                for row in range(b.num_rows):
                    code = flat[place[row] : place[row + 1]].tobytes() + last
                    for k, lo in enumerate(range(0, len(code), capacity * 4)):
                        some = code[lo : lo + capacity * 4]
                        n = len(some) // 4
                        at.append(row)
                        piece.append(k)
                        start.append(lo // 4)
                        length.append(n)
                        crc.append(zlib.crc32(some))
                        local.append(int(seen[n]))
                        seen[n] += 1
                        if ids:
                            held.append(np.frombuffer(some, "<u4").astype(np.int32))
                cols = [b.column(0).take(pa.array(at, pa.int64())), pa.array(piece, pa.int32()), pa.array(start, pa.int64()), pa.array(length, pa.int64()), pa.array(crc, pa.int64()), pa.array([part] * len(at), pa.int32()), pa.array(local, pa.int64())]
                names = ["doc_id", "piece", "start", "length", "ids_crc32", "part", "local"]
                if ids:
                    cols, names = [*cols, pa.array(held, pa.list_(pa.int32()))], [*names, "ids"]
                yield pa.RecordBatch.from_arrays(cols, names)

    rows = docs.select(common.col(key).cast("long").alias("doc_id"), common.clean_text(common.col(text)).alias("text"))
    return rows.mapInArrow(run, "doc_id long, piece int, start long, length long, ids_crc32 long, part int, local long" + ", ids array<int>" * ids)


class TightestFit:
    """A segment tree over remaining capacities 0..most; finds the least one that is open and not under a need."""

    def __init__(self, most: int):
        self.leaves = 1 << most.bit_length()
        self.open = np.zeros(2 * self.leaves, np.int64)

    def add(self, room: int, count: int) -> None:
        at = room + self.leaves
        while at:
            self.open[at] += count
            at >>= 1

    def find(self, need: int) -> int:
        at = need + self.leaves
        if self.open[at]:
            return need
        while at > 1:  # climb until a right sibling holds an open sequence, then go down leftmost
            if not at & 1 and self.open[at + 1]:
                at += 1
                break
            at >>= 1
        else:
            return -1
        while at < self.leaves:
            at *= 2
            if not self.open[at]:
                at += 1
        return at - self.leaves


def best_fit_plan(counts: dict[int, int], capacity: int = CAPACITY) -> np.ndarray:
    """Rows (length, first_rank, count, first_sequence, offset): pieces of a length, by rank, to successive sequences.

    Lengths fall; each piece goes to the open sequence with the least room that still takes it, or to a new one.
    """
    tree, runs, plan, fresh = TightestFit(capacity), {}, [], 0
    for length in sorted((n for n in counts if n > 0), reverse=True):
        left, rank = counts[length], 0
        while left:
            room = tree.find(length)
            if room < 0:
                per = capacity // length
                bins, rest = divmod(left, per)
                # whole sequences of this length alone: the j-th slot of each is one run
                for j in range(per):
                    some = bins + (1 if j < rest else 0)
                    if some:
                        plan.append((length, rank, some, fresh, j * length))
                        rank += some
                for some, used, first in ((bins, per, fresh), (1 if rest else 0, rest, fresh + bins)):
                    if some:
                        runs.setdefault(capacity - used * length, []).append((first, some))
                        tree.add(capacity - used * length, some)
                fresh += bins + (1 if rest else 0)
                left = 0
                continue
            # a sequence that took a piece is the tightest as long as it takes more: it is filled before the next
            first, some = runs[room].pop()
            per = room // length
            full, rest = min(some, left // per), 0
            if full < some:
                rest = left - full * per
                used = full + (1 if rest else 0)
                if used < some:
                    runs[room].append((first + used, some - used))
            tree.add(room, -full - (1 if rest else 0))
            for j in range(per):
                count = full + (1 if j < rest else 0)
                if count:
                    plan.append((length, rank, count, first, capacity - room + j * length))
                    rank += count
                    left -= count
            for count, held, at in ((full, per, first), (1 if rest else 0, rest, first + full)):
                if count:
                    runs.setdefault(room - held * length, []).append((at, count))
                    tree.add(room - held * length, count)
    return np.array(plan, np.int64).reshape(-1, 5)


def pack(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """Adds sequence_id and offset to staged pieces as `tokenised` makes them."""
    spark = pieces.sparkSession
    per = common.stage(pieces.groupBy("part", "length").agg(F.count(F.lit(1)).alias("n")), "pack-counts")
    counts = {r.length: r.n for r in per.groupBy("length").agg(F.sum("n").alias("n")).collect()}  # at most `capacity` rows
    plan = best_fit_plan(counts, capacity)
    ahead = Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    before = per.select("part", "length", F.coalesce(F.sum("n").over(ahead), F.lit(0)).alias("before"))
    ranked = pieces.join(before.hint("merge"), ["part", "length"]).withColumn("rank", F.col("local") + F.col("before")).drop("part", "local", "before")
    order = np.lexsort((plan[:, 1], plan[:, 0]))
    plan = plan[order]
    held = spark.sparkContext.broadcast(plan)  # bounded by capacity, not by the corpus: a row per step of the packing
    names = [*ranked.columns, "sequence_id", "offset"]
    keep, had = [c for c in names if c != "rank"], ranked.columns

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        p = held.value
        at_length = np.searchsorted(p[:, 0], np.arange(capacity + 2))
        span = int(p[:, 1].max()) + 1 if len(p) else 1
        key = p[:, 0] * span + p[:, 1]
        for b in batches:
            rank, length = b.column("rank").to_numpy(), b.column("length").to_numpy()
            at = np.searchsorted(key, length * span + rank, side="right") - 1
            assert (at >= at_length[length]).all()
            cols = {c: b.column(c) for c in had} | {"sequence_id": pa.array(p[at, 3] + rank - p[at, 1]), "offset": pa.array(p[at, 4])}
            yield pa.RecordBatch.from_arrays([cols[c] for c in keep], keep)

    kinds = dict(ranked.dtypes) | {"sequence_id": "long", "offset": "long"}
    return ranked.mapInArrow(run, ", ".join(f"`{c}` {kinds[c]}" for c in keep))


def pack_documents(docs: DataFrame, path: str, capacity: int = CAPACITY, end: int = END_ID, text: str = "text", key: str = "doc_id", ids: bool = False) -> DataFrame:
    """Tokenises, cuts and packs: a row per piece with its sequence and its place there."""
    return pack(common.stage(tokenised(docs, path, capacity, end, text, key, ids), "pack-pieces"), capacity)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return pack_documents(docs, public_tokenizers.path(VOCABULARY))
