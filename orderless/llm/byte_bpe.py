"""Byte-level BPE encoding and decoding in batched numpy merge rounds.

Text is cut by the vocabulary's split pattern; words not met before are encoded together: their symbols lie in one
flat array, every adjacent pair is looked up by binary search in the sorted pair keys, and in each round every
word merges its lowest-ranked pair wherever it occurs. Known words come from a cache bounded in words and in their
length, so memory doesn't grow with the vocabulary of the corpus. Ids decode through a table of token bytes. All of it is narrow: no shuffle.

Defined results: null and empty texts have no ids and decode to an empty text. Special tokens written out in a text
become their single id, as the tokenizers library does. Extra columns are not read. Repeated rows are encoded each.
"""

from __future__ import annotations

import hashlib
import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession

from . import common

VOCABULARY = "byte_bpe_50k.json"
#: Words a worker remembers before it starts anew, and their length in bytes at most: some 200 MB. Longer words are merged where they stand.
CACHE_WORDS, CACHE_LENGTH = 600_000, 64


def byte_letters() -> dict[int, str]:
    """The printable letter that stands for each byte in byte-level vocabularies."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    letters = {b: chr(b) for b in plain}
    letters |= {b: chr(256 + i) for i, b in enumerate(b for b in range(256) if b not in letters)}
    return letters


class MergeTable:
    """The merges of a vocabulary as sorted pair keys, run over many words at once."""

    def __init__(self, vocab: dict[str, int], merges: list, size: int):
        pairs = [m.split(" ") if isinstance(m, str) else m for m in merges]
        self.size = size
        key = np.array([vocab[a] * size + vocab[b] for a, b in pairs], np.int64)
        order = np.argsort(key, kind="stable")
        self.keys, self.rank = np.r_[key[order], np.iinfo(np.int64).max], np.r_[order, 0].astype(np.int32)
        self.made = np.array([vocab[a + b] for a, b in pairs], np.int64)

    def _ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        key = left * self.size + right
        at = np.searchsorted(self.keys, key)
        return np.where(self.keys[at] == key, self.rank[at], len(self.made))

    def run(self, sym: np.ndarray, lens: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all words in a row and each word's n; sym holds the words' first symbols one after the other."""
        none, owner = np.int32(len(self.made)), np.repeat(np.arange(len(lens), dtype=np.int32), lens)
        sym = sym.astype(np.int64)
        rank = np.full(len(sym), none, np.int32)  # of the pair that begins at each symbol
        inner = np.flatnonzero(owner[:-1] == owner[1:])
        rank[inner] = self._ranks(sym[inner], sym[inner + 1])
        ids, owners = [], []
        while len(sym):
            starts = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
            best = np.minimum.reduceat(rank, starts)
            per = np.diff(np.r_[starts, len(sym)])
            over = best == none
            if over.any():  # words that can merge no further leave the array
                out = np.repeat(over, per)
                ids.append(sym[out])
                owners.append(owner[out])
                sym, owner, rank, best, per = sym[~out], owner[~out], rank[~out], best[~over], per[~over]
                if not len(sym):
                    break
            at = np.flatnonzero(rank == np.repeat(best, per))
            # of overlapping occurrences of one pair (x x x) every second counts, from the left
            near = np.diff(at) == 1
            if near.any():
                new = np.flatnonzero(np.r_[True, ~near | (owner[at[1:]] != owner[at[:-1]])])
                place = np.arange(len(at)) - np.repeat(new, np.diff(np.r_[new, len(at)]))
                at = at[place % 2 == 0]
            sym[at] = self.made[rank[at]]
            keep = np.ones(len(sym), bool)
            keep[at + 1] = False
            at -= np.arange(len(at))
            sym, owner, rank = sym[keep], owner[keep], rank[keep]
            # only pairs beside a merge have changed
            near = np.zeros(len(sym), bool)
            near[at] = True
            near[at[at > 0] - 1] = True
            touched = np.flatnonzero(near)
            rank[touched] = none
            touched = touched[touched + 1 < len(sym)]
            touched = touched[owner[touched] == owner[touched + 1]]
            rank[touched] = self._ranks(sym[touched], sym[touched + 1])
        who = np.concatenate(owners) if owners else np.zeros(0, np.int32)
        flat = np.concatenate(ids)[np.argsort(who, kind="stable")] if ids else np.zeros(0, np.int64)
        return flat, np.bincount(who, minlength=len(lens))


class ByteBpe:
    """A byte-level BPE vocabulary with batched encoding and table decoding."""

    def __init__(self, path: str, pattern: str):
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        back = {v: k for k, v in byte_letters().items()}
        vocab = spec["model"]["vocab"]
        special = {t["content"]: t["id"] for t in spec["added_tokens"]}
        size = max([*vocab.values(), *special.values()]) + 1
        self.token: list[bytes] = [b""] * size
        for word, i in vocab.items():
            self.token[i] = bytes(back[c] for c in word)
        for word, i in special.items():
            self.token[i] = word.encode()
        self.special = {w: np.uint32(i).tobytes() for w, i in special.items()}
        self.first = np.array([vocab[byte_letters()[b]] for b in range(256)], np.int64)
        self.table = MergeTable(vocab, spec["model"]["merges"], size)
        self.split = regex.compile(pattern)
        self.cut_special = regex.compile("(" + "|".join(map(regex.escape, special)) + ")") if special else None
        self.known: dict[str, bytes] = {}

    def merge(self, words: list[bytes]) -> list[bytes]:
        """Ids of each word as little-endian 32-bit integers."""
        flat, count = self.table.run(self.first[np.frombuffer(b"".join(words), np.uint8)], np.fromiter(map(len, words), np.int64, len(words)))
        code, ends = flat.astype("<u4").tobytes(), np.cumsum(count) * 4
        return [code[a:b] for a, b in zip(np.r_[0, ends[:-1]].tolist(), ends.tolist(), strict=True)]

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian 32-bit integers."""
        cut = []
        for t in texts:
            if self.cut_special is not None and "<|" in t and (piece := self.cut_special.split(t))[1:]:
                words: list[str] = []
                for p in piece:
                    words += [p] if p in self.special else self.split.findall(p)
                cut.append(words)
            else:
                cut.append(self.split.findall(t))
        if len(self.known) > CACHE_WORDS:
            self.known.clear()
        known = self.known
        new: set[str] = set()
        for words in cut:
            new.update(words)
        new = {w for w in new if w not in known}
        for s in self.special.keys() & new:
            known[s] = self.special[s]
            new.discard(s)
        long: dict[str, bytes] = {}
        if new:
            for w, code in zip(new, self.merge([w.encode() for w in new]), strict=True):
                (known if len(w) <= CACHE_LENGTH else long)[w] = code
        if not long:
            return [b"".join(map(known.__getitem__, words)) for words in cut]
        return [b"".join(known[w] if w in known else long[w] for w in words) for words in cut]

    def decode(self, ids: np.ndarray) -> str:
        return b"".join(map(self.token.__getitem__, ids.tolist())).decode("utf-8", errors="replace")


_LOADED: dict[str, ByteBpe] = {}


def loaded(path: str, pattern: str) -> ByteBpe:
    if path not in _LOADED:
        _LOADED[path] = ByteBpe(path, pattern)
    return _LOADED[path]


def encode_documents(docs: DataFrame, path: str, pattern: str, text: str = "text", key: str = "doc_id") -> DataFrame:
    """doc_id, ids (array of int), decoded text's SHA-256 and the ids' SHA-256, per row."""
    common.importable(docs.sparkSession)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = loaded(path, pattern)
        for whole in batches:
            for b in common.slices(whole, 1):
                coded = bpe.encode(b.column(1).to_pylist())
                n, a, d = [], [], []
                for c in coded:
                    n.append(len(c) // 4)
                    a.append(hashlib.sha256(c).hexdigest())
                    d.append(hashlib.sha256(bpe.decode(np.frombuffer(c, "<u4")).encode()).hexdigest())
                yield pa.RecordBatch.from_arrays([b.column(0), pa.array(n, pa.int64()), pa.array(a, pa.string()), pa.array(d, pa.string())], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    rows = docs.select(common.col(key).cast("long").alias("doc_id"), common.clean_text(common.col(text)).alias("text"))
    return rows.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return encode_documents(docs, public_tokenizers.path(VOCABULARY), public_tokenizers.PATTERN)
