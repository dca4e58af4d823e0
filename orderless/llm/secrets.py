"""Secret scans: every candidate and its surroundings judged by a character convolutional network in numpy.

Candidates are the valid matches of the base patterns, which always count, and long mixed tokens from a looser
generator (dots included, of any length). The network embeds the characters of a window, convolves, pools the maximum and
gives a logit; a candidate is as suspicious as its worst window, and its windows cover all its characters and the context on
both sides. It is trained on labelled findings, calibrated on held-out ones, and its threshold is the highest that still reaches
the wanted recall there. Findings are drawn by rule from a fixed seed (no table labels secrets), so the
model has a fixed size at every size of the corpus. Everything is narrow; only texts with a
candidate leave bytes.

Defined results: a candidate of the network that lies within a base span gives no span of its own. A null or empty text has no spans.
Offsets are in code points, ends exclusive. Repeated rows are each scanned. Texts of a batch don't see each other's ends.
"""

from __future__ import annotations

import random
import re
from bisect import bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .boosting import calibrate, sigmoid
from .pii import counted, listed

# fixed values: the base patterns, letters of keywords in either case
KINDS = ("assign", "access", "hex")
_ASSIGN = re.compile(r"""([Pp][Aa][Ss][Ss][Ww][Oo][Rr][Dd]|[Pp][Aa][Ss][Ss][Ww][Dd]|[Ss][Ee][Cc][Rr][Ee][Tt]|[Tt][Oo][Kk][Ee][Nn]|[Aa][Pp][Ii]_?[Kk][Ee][Yy])["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")
_ACCESS = re.compile(r"AKIA[A-Z0-9]+")
_HEX = re.compile(r"[0-9a-f]{32,}")
_KEYWORDS = (b"password", b"passwd", b"secret", b"token", b"apikey", b"api_key")
#: The looser generator: tokens of 20 characters or more with letters and digits, single dots inside allowed.
_RUN = re.compile(r"[A-Za-z0-9+/_=.-]{20,}")
_LONG = re.compile(r"[A-Za-z0-9+/_=-]+(?:\.[A-Za-z0-9+/_=-]+)*")
_DIGIT, _LETTER = re.compile(r"[0-9]"), re.compile(r"[A-Za-z]")

WINDOW, WIDTH, FILTERS, KERNEL = 96, 8, 24, 5
LEAD, STEP, BLOCK = 32, 48, 2048
RECALL = 0.995
#: Stands in place of a secret; it must not match a base pattern itself.
MARK = "[secret]"


def base_spans(t: str) -> list[tuple[str, int, int]]:
    out = [("assign", *m.span()) for m in _ASSIGN.finditer(t) if len(m[2]) >= 8]
    out += [("access", *m.span()) for m in _ACCESS.finditer(t) if len(m[0]) >= 16]
    return out + [("hex", *m.span()) for m in _HEX.finditer(t)]


def candidates(t: str) -> list[tuple[str, int, int]]:
    found = [m for run in _RUN.finditer(t) for m in _LONG.finditer(t, *run.span())]
    return [("other", *m.span()) for m in found if len(m[0]) >= 20 and _DIGIT.search(m[0]) and _LETTER.search(m[0])]


def ordered(rows: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
    kinds = (*KINDS, "other")
    return sorted(rows, key=lambda c: (c[1], kinds.index(c[0]), c[2]))


_CLASS = np.zeros(256, np.int64)  # characters as small numbers; all others are 1, padding is 0
_CLASS[:] = 1
for _i, _c in enumerate("abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ0123456789 \n\"'=:_-+/.()[]{}<>,;#"):
    _CLASS[ord(_c)] = _i + 2
SYMBOLS = 2 * (int(_CLASS.max()) + 1)  # once for context, once for the candidate itself


def windows(t: str, a: int, b: int) -> Iterator[np.ndarray]:
    """Character numbers of a candidate of any length with its context, in windows of one width; some windows at a time."""
    last = max(a - LEAD, b + LEAD - WINDOW)
    for lo in range(a - LEAD, last + STEP, STEP * BLOCK):
        first = np.unique(np.minimum(lo + STEP * np.arange(BLOCK), last))
        begin, end = max(0, int(first[0])), min(len(t), int(first[-1]) + WINDOW)
        codes = _CLASS[np.frombuffer(t[begin:end].encode("latin-1", "replace"), np.uint8)]
        at = first[:, None] + np.arange(WINDOW)
        real = (at >= 0) & (at < len(t))
        out = np.zeros(at.shape, np.int64)
        out[real] = codes[at[real] - begin] + (SYMBOLS // 2) * ((at[real] >= a) & (at[real] < b))
        yield out


class CharConv:
    """Embedding, one convolution with rectifier, maximum over positions, logistic output; trained by Adam."""

    def __init__(self, seed: int = 11):
        r = np.random.default_rng(seed)
        self.p = [r.normal(0, 0.3, (SYMBOLS, WIDTH)), r.normal(0, 1 / np.sqrt(KERNEL * WIDTH), (KERNEL * WIDTH, FILTERS)), np.zeros(FILTERS), r.normal(0, 0.3, FILTERS), np.zeros(1)]

    def _forward(self, x: np.ndarray):
        e = self.p[0][x]  # rows, WINDOW, WIDTH
        steps = WINDOW - KERNEL + 1
        cols = np.stack([e[:, k : k + steps] for k in range(KERNEL)], 2).reshape(len(x), steps, KERNEL * WIDTH)
        h = cols @ self.p[1] + self.p[2]
        top = h.argmax(1)
        pooled = np.maximum(np.take_along_axis(h, top[:, None], 1)[:, 0], 0)
        return cols, top, pooled, pooled @ self.p[3] + self.p[4]

    def logit(self, x: np.ndarray) -> np.ndarray:
        return np.concatenate([self._forward(x[i : i + 256])[3] for i in range(0, len(x), 256)]) if len(x) else np.zeros(0)

    def fit(self, x: np.ndarray, y: np.ndarray, epochs: int = 6, rate: float = 0.01, seed: int = 3) -> CharConv:
        r, m, v, step = np.random.default_rng(seed), [np.zeros_like(p) for p in self.p], [np.zeros_like(p) for p in self.p], 0
        for _ in range(epochs):
            order = r.permutation(len(y))
            for lo in range(0, len(y), 64):
                at = order[lo : lo + 64]
                cols, top, pooled, f = self._forward(x[at])
                d = (sigmoid(f) - y[at]) / len(at)
                back = (d[:, None] * self.p[3]) * (pooled > 0)  # rows, FILTERS
                picked = np.take_along_axis(cols, top[:, :, None], 1)  # rows, FILTERS, KERNEL*WIDTH
                g_kernel = np.einsum("rf,rfk->kf", back, picked)
                g_cols = back[:, :, None] * self.p[1].T[None]  # to the inputs of each filter's best place
                g_embed = np.zeros_like(self.p[0])
                for k in range(KERNEL):
                    np.add.at(g_embed, np.take_along_axis(x[at], top + k, 1), g_cols[:, :, k * WIDTH : (k + 1) * WIDTH])
                step += 1
                for i, g in enumerate([g_embed, g_kernel, back.sum(0), pooled.T @ d, d.sum(keepdims=True)]):
                    m[i] = 0.9 * m[i] + 0.1 * g
                    v[i] = 0.999 * v[i] + 0.001 * g * g
                    self.p[i] -= rate * (m[i] / (1 - 0.9**step)) / (np.sqrt(v[i] / (1 - 0.999**step)) + 1e-8)
        return self


def findings(n: int, seed: int) -> tuple[list[tuple[str, int, int]], np.ndarray]:
    """Labelled findings by rule: (text, start, end) and 1 for secrets."""
    r = random.Random(seed)
    some = lambda a, k: "".join(r.choice(a) for _ in range(k))
    low, up, dig = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
    w = lambda: "".join(r.choice(["the", "on", "er", "ti", "ha", "st", "re", "de", "la", "ou"]) for _ in range(r.randint(1, 4)))
    out, y = [], []
    for _ in range(n):
        good = r.random() < 0.5
        if good:
            s = r.choice([lambda: some(low + up + dig, r.randint(24, 48)), lambda: some(low + up + dig + "+/", r.randint(30, 60)) + "==", lambda: r.choice(["sk_live_", "ghp_", "xoxb-", "AIza"]) + some(low + up + dig, 32), lambda: some("0123456789abcdef", r.choice([32, 40, 64])), lambda: "AKIA" + some(up + dig, 16)])()
            if r.random() < 0.25:  # long ones: blobs, tokens of dotted parts
                s = r.choice([lambda: some(low + up + dig + "+/", r.randint(65, 700)) + r.choice(["", "=", "=="]), lambda: some(low + up + dig + "-_", r.randint(65, 400)), lambda: "eyJ" + some(low + up + dig, r.randint(17, 60)) + "." + some(low + up + dig + "-_", r.randint(40, 300)) + "." + some(low + up + dig + "-_", 43)])()
            cue = r.choice(["key = ", "Bearer ", "token: ", "secret=", "auth: \"", "", "credentials ", "Authorization: "])
        else:
            s = r.choice([lambda: w() + w() + w() + w() + some(dig, 1) + w(), lambda: "/".join(w() for _ in range(6)) + some(dig, 2), lambda: "-".join(w() for _ in range(6)) + "-" + some(dig, 4), lambda: "_".join([w(), w(), w(), w(), some(dig, 2)]), lambda: f"{r.randint(1990, 2040)}-{some(dig, 2)}-{some(dig, 2)}T{some(dig, 6)}Z-{w()}", lambda: w().upper() + "-" + some(dig, 10) + "-" + w().upper() + some(dig, 6)])()
            if r.random() < 0.25:  # long ones: paths, dotted and hyphened names
                s = r.choice(["/", ".", "-", "_", "/"]).join(w() for _ in range(r.randint(5, 80))) + r.choice(["", "-", "."]) + some(dig, r.randint(1, 4))
            cue = r.choice(["", "file ", "see ", "path: ", "version ", "page ", "name = "])
        s = s if len(s) >= 20 else s + w() + some(dig, 20 - len(s))
        head = " ".join(w() for _ in range(r.randint(0, 8))) + " " + cue
        out.append((head + s + r.choice(["", "\"", " "]) + " " + " ".join(w() for _ in range(r.randint(0, 6))), len(head), len(head) + len(s)))
        y.append(float(good))
    return out, np.array(y)


class Judge:
    """The trained network with its calibration and the threshold that keeps the wanted recall."""

    def __init__(self, recall: float = RECALL, seed: int = 5):
        rows, y = findings(2400, seed)
        fit = np.arange(len(y)) % 3 > 0
        x = [np.concatenate(list(windows(*f))) for f in rows]
        some = np.flatnonzero(fit)
        self.net = CharConv().fit(np.concatenate([x[i] for i in some]), np.repeat(y[fit], [len(x[i]) for i in some]))
        f = self.logits([rows[i] for i in np.flatnonzero(~fit)])
        self.slope, self.offset = calibrate(f, y[~fit])
        p = np.sort(sigmoid(self.slope * f + self.offset)[y[~fit] > 0])
        self.least = float(p[int((1 - recall) * len(p))])

    def logits(self, rows: list[tuple[str, int, int]]) -> np.ndarray:
        """The largest logit of each candidate's windows; rows: text, start, end."""
        out, held, who, count = np.full(len(rows), -np.inf), [], [], 0

        def flush() -> None:
            if held:
                np.maximum.at(out, np.concatenate(who), self.net.logit(np.concatenate(held)))

        for i, row in enumerate(rows):
            for x in windows(*row):
                held.append(x)
                who.append(np.full(len(x), i))
                count += len(x)
                if count >= BLOCK:
                    flush()
                    held, who, count = [], [], 0
        flush()
        return out

    def chances(self, t: str, proposed: list[tuple[str, int, int]]) -> np.ndarray:
        return sigmoid(self.slope * self.logits([(t, a, b) for _, a, b in proposed]) + self.offset)


def spans(t: str, model: Judge) -> tuple[list[tuple[str, int, int]], list[tuple[str, int, int]]]:
    """Base spans and all spans, both in order; every candidate is judged, base ones stay whatever the verdict."""
    base = ordered(base_spans(t))
    proposed = base + candidates(t)
    chance = model.chances(t, proposed)[len(base) :]
    taken = sorted((a, b) for _, a, b in base)
    start, reach = [a for a, _ in taken], np.maximum.accumulate(np.array([0, *[b for _, b in taken]]))
    extra = []
    for (k, a, b), p in zip(proposed[len(base) :], chance, strict=True):
        if p >= model.least and reach[bisect_right(start, a)] < b:
            extra.append((k, a, b))
    return base, ordered(base + extra)


_TOKEN = np.zeros(256, bool)
_TOKEN[list(b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/_=.-")] = True
_HEXA = np.zeros(256, bool)
_HEXA[list(b"0123456789abcdef")] = True


def suspects(data: np.ndarray, off: np.ndarray) -> list[int]:
    """Rows whose text may hold a candidate: a keyword, the access prefix, or a token of 20 bytes or more."""
    blob = data.tobytes()
    at: list[int] = []
    low = blob.lower()
    for word, where in [*((k, low) for k in _KEYWORDS), (b"AKIA", blob)]:
        k = where.find(word)
        while k >= 0:
            at.append(k)
            k = where.find(word, k + 1)
    for kind, least in ((_TOKEN, 20), (_HEXA, 32)):
        gap = np.flatnonzero(np.r_[True, ~kind[data], True])
        long = np.diff(gap) > least
        at += gap[:-1][long].tolist()
        begin = off[:-1]  # a run may go on over the end of a text
        at += begin[gap[np.searchsorted(gap, begin, side="right").clip(max=len(gap) - 1)] - begin > least].tolist()
    return np.unique(np.searchsorted(off, np.array(at, np.int64), side="right") - 1).tolist()


def _verdicts(texts: pa.Array, model: Judge) -> Iterator[tuple[int, str, list, list]]:
    """Row number, text, base and all spans of each text that has candidates."""
    batch, first = pa.RecordBatch.from_arrays([texts], ["t"]), 0
    for b in common.slices(batch, 0):
        for row in suspects(*common.raw(b.column(0))):
            if row < b.num_rows:
                t = b.column(0)[row].as_py()
                yield first + row, t, *spans(t, model)
        first += b.num_rows


def find_secrets(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Per row: doc_id, base (list of kind, start, end) and spans (the same, with what the network adds)."""
    spark = docs.sparkSession
    common.importable(spark)
    held = spark.sparkContext.broadcast(Judge())  # of fixed size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))
        for b in batches:
            base: list[list] = [[]] * b.num_rows
            every: list[list] = [[]] * b.num_rows
            for row, _, own, both in _verdicts(b.column(1), held.value):
                base[row], every[row] = own, both
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array([[dict(zip(("kind", "start", "end"), s, strict=True)) for s in r] for r in v], kind) for v in (base, every)]], ["doc_id", "base", "spans"])

    rows = docs.select(common.col(key).cast("long").alias("doc_id"), common.clean_text(common.col(text)).alias("text"))
    span = "array<struct<kind: string, start: int, end: int>>"
    return rows.mapInArrow(run, f"doc_id long, base {span}, spans {span}")


def replaced(t: str, found: list[tuple[str, int, int]], mark: str) -> str:
    """t with each span, in order of start, replaced by the mark; spans that overlap share one."""
    parts, free = [], 0
    for _, a, b in found:
        if b > free:
            parts += [t[free:a], mark] if a >= free else []
            free = b
    return "".join(parts) + t[free:]


def redacted(texts: pa.Array, model: Judge, mark: str = MARK) -> pa.Array:
    """Texts with their secrets replaced; null where nothing was found.

    What a replacement brings to light (a keyword that a longer token had swallowed) is replaced too, until no base secret is left.
    """
    out: list[str | None] = [None] * len(texts)
    for row, t, _, both in _verdicts(texts, model):
        while both:
            out[row] = t = replaced(t, both, mark)
            both = ordered(base_spans(t))
    return pa.array(out, pa.string())


def redactor(spark: SparkSession, mark: str = MARK):
    """A column function: the text with each secret replaced by a mark; null where nothing was found."""
    common.importable(spark)
    held = spark.sparkContext.broadcast(Judge())

    @F.arrow_udf("string")
    def redact(texts: pa.Array) -> pa.Array:
        return redacted(texts, held.value, mark)

    return lambda text: redact(common.clean_text(text))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = find_secrets(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return got.select("doc_id", *[counted("base", k) for k in KINDS], F.sha2(listed("base").cast("binary"), 256).alias("base_sha256"), listed("spans").alias("spans"))
