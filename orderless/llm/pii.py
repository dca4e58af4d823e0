"""Personal data: overlapping candidates from high-recall generators, chosen by boosted trees.

Generators propose spans: the four base patterns, whose valid matches always count, and looser ones of every kind (numbers
without a country sign, whole and local; spelled-out mail addresses; host addresses in brackets or of version 6; card digits
with other marks between). Proposals overlap. Trees trained on labelled findings use format and context features; a calibrated
threshold per kind says which may count, and of those that overlap the one with the highest chance is added.
The training findings are drawn by rule from a fixed seed (no table labels personal data), so the model is
the same everywhere and its size is fixed. Everything is narrow: texts that hold no '@', '+', bracket or digit never leave bytes.

Defined results: a null or empty text has no spans. Offsets are in code points, ends exclusive. Repeated rows are each
scanned. Base matches follow their patterns leftmost and without overlap within a kind; each is found in linear time, at any
length. A proposal that lies within one base span adds nothing; base spans of different kinds may overlap, added spans never do.
Equal chances go to the longer span, then to the earlier one.
"""

from __future__ import annotations

import random
import re
from bisect import bisect_left, bisect_right
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from . import common
from .boosting import BoostedTrees, calibrate, sigmoid

KINDS = ("email", "ip", "card", "phone")

# fixed values: the base patterns, in forms that read a text once
_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_NUMBERS = re.compile(r"[0-9]+(?:\.[0-9]+)*")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_DIGITS = re.compile(r"[^0-9]")
_DIGIT = re.compile(r"[0-9]")

# generators beyond the base patterns; names and domains may have any length, digit groups have those of their formats
_DOT = r"\x20?[\[({]\x20?(?:\.|dot|DOT)\x20?[\])}]\x20?"
_HEX4 = r"[0-9A-Fa-f]{1,4}(?::[0-9A-Fa-f]{1,4})*+"
_LOOSE = [
    ("phone", re.compile(r"(?<![0-9A-Za-z+])\(?[0-9]{2,4}\)?[\x20./-][0-9]{3,4}[\x20./-][0-9]{3,4}(?![0-9A-Za-z])")),
    ("phone", re.compile(r"(?<![0-9A-Za-z+])[0-9]{3}[\x20.-][0-9]{4}(?![0-9A-Za-z])")),
    ("card", re.compile(r"(?<![0-9.])[0-9]{4}(?:[._/][0-9]{4}){3}(?![0-9.])")),
    ("email", re.compile(rf"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++\x20?[\[({{]\x20?(?:at|AT)\x20?[\])}}]\x20?[A-Za-z0-9-]++(?:(?:{_DOT}|\.)[A-Za-z0-9-]++)++")),
    ("ip", re.compile(rf"(?<![0-9A-Za-z.])[0-9]{{1,3}}(?:{_DOT}[0-9]{{1,3}}){{3}}(?![0-9A-Za-z])")),
    ("ip", re.compile(rf"(?<![0-9A-Za-z:])(?:{_HEX4})?::(?:{_HEX4})?(?![0-9A-Za-z:])|(?<![0-9A-Za-z:])(?:[0-9A-Fa-f]{{1,4}}:){{7}}[0-9A-Fa-f]{{1,4}}(?![0-9A-Za-z:])")),
]
_CUES = ("mail", "contact", "phone", "tel", "call", "fax", "mobile", "card", "visa", "pay", "account", "ip", "host", "address", "order", "version", "ref", "isbn", "page", "no.", "id", "date", "total", "server", "from", "class", "mac", "ratio")


def luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        d = ord(c) - 48
        if i % 2:
            d = d * 2 - 9 * (d > 4)
        total += d
    return total % 10 == 0


def emails(t: str) -> list[tuple[int, int]]:
    out, free, at = [], 0, t.find("@")
    while at >= 0:
        start = at
        while start > free and t[start - 1] in _LOCAL:
            start -= 1
        if start < at and (m := _DOMAIN.match(t, at + 1)):
            out.append((start, m.end()))
            free = m.end()
        at = t.find("@", at + 1)
    return out


def addresses(t: str) -> list[tuple[int, int]]:
    out = []
    for m in _NUMBERS.finditer(t):
        part = m[0].split(".")
        at = m.start()
        for k in range(0, len(part) - 3, 4):
            four = part[k : k + 4]
            size = sum(map(len, four)) + 3
            if all(len(q := p.lstrip("0")) < 4 and int(q or 0) <= 255 for p in four):
                out.append((at, at + size))
            at += size + 1
    return out


def base_spans(t: str) -> dict[str, list[tuple[int, int]]]:
    """Valid matches of the base patterns by kind."""
    card, phone = [], []
    for m in _CARD.finditer(t):
        if m.end() - m.start() <= 37 and 13 <= len(d := _DIGITS.sub("", m[0])) <= 19 and luhn(d):
            card.append(m.span())
    for m in _PHONE.finditer(t):
        if 9 <= len(_DIGITS.sub("", m[0])) <= 15:
            phone.append(m.span())
    return {"email": emails(t), "ip": addresses(t), "card": card, "phone": phone}


def candidates(t: str) -> list[tuple[str, int, int]]:
    """Overlapping proposals of the looser generators; each holds a digit, but for mail addresses."""
    return [(k, *m.span()) for k, p in _LOOSE for m in p.finditer(t) if k != "ip" or _DIGIT.search(m[0])]


def features(t: str, kind: str, a: int, b: int) -> list[float]:
    s, left, right = t[a:b], t[max(0, a - 40) : a], t[b : b + 24]
    digits = _DIGITS.sub("", s)
    groups = re.findall("[0-9]+", s)
    low = left.lower()
    return [
        KINDS.index(kind), len(s), len(digits), len(groups), max(map(len, groups), default=0), min(map(len, groups), default=0),
        len(set(digits)), float(luhn(digits)) if digits else 0.0, s.count("."), s.count("-"), s.count(" "), s.count("/"), s.count("("), s.count(":"), s.count("::"), s.count("[") + s.count("{"),
        max(map(int, groups), default=0) if len(digits) < 40 else -1.0, sum(c in "abcdefABCDEF" for c in s) / len(s),
        float(digits[:1] == "0"), int(groups[0]) if groups and len(groups[0]) < 9 else -1.0, int(groups[-1]) if groups and len(groups[-1]) < 9 else -1.0,
        sum(c.isdigit() for c in left) / max(1, len(left)), sum(c.isdigit() for c in right) / max(1, len(right)),
        float(left[-1:].isspace() or not left), float(right[:1].isspace() or not right or right[:1] in ".,;"), float(left[-1:] in "#$€£=" and bool(left)),
        float(right[:1] in "%°" and bool(right)), *[float(c in low) for c in _CUES],
    ]


def findings(n: int, seed: int) -> tuple[list[tuple[str, str, int, int]], np.ndarray]:
    """Labelled findings by rule: (text, kind, start, end) and 1 for personal data."""
    r = random.Random(seed)
    d = lambda k: "".join(r.choice("0123456789") for _ in range(k))
    w = lambda: "".join(r.choice(["the", "on", "er", "ti", "ha", "st", "re", "de", "la", "ou"]) for _ in range(r.randint(1, 4)))

    def card() -> str:
        body = r.choice("456") + d(14)
        return body + next(c for c in "0123456789" if luhn(body + c))

    out, y = [], []
    for _ in range(n):
        kind, good = r.choice(KINDS), r.random() < 0.5
        sep = r.choice("- ./")
        if kind == "phone" and good:
            s, cue = r.choice([f"({d(3)}) {d(3)}-{d(4)}", f"{r.choice('23456789')}{d(2)}{sep}{d(3)}{sep}{d(4)}", f"0{d(2)}{sep}{d(4)}{sep}{d(4)}"]), r.choice(["", "phone ", "tel ", "call ", "mobile: "])
            if r.random() < 0.25:  # a local number counts where the words before it say what it is
                s, cue = f"{d(3)}{r.choice('- .')}{d(4)}", r.choice(["phone ", "tel ", "call ", "mobile: ", "fax "])
        elif kind == "phone":
            s, cue = r.choice([(f"{r.randint(1900, 2099)}-{d(3)}-{d(4)}", "ref "), (f"{d(3)}.{d(3)}.{d(3)}", "total "), (f"{d(4)} {d(4)} {d(4)}", "order "), (f"{d(2)}/{d(3)}/{d(4)}", "id "), (f"{d(3)}-{d(4)}-{d(4)}", "isbn "), (f"{d(3)} {d(3)} {d(3)}", "page "), (f"{d(3)}-{d(4)}", r.choice(["", "ref ", "order ", "page "])), (f"{d(3)}-{d(4)}", f"call {d(3)}-")])
        elif kind == "card" and good:
            c, sep = card(), r.choice("._/")
            s, cue = sep.join(c[i : i + 4] for i in range(0, 16, 4)), r.choice(["", "card ", "visa ", "pay "])
        elif kind == "card":
            c, sep = d(16), r.choice("._/")
            if luhn(c):
                c = c[:-1] + str((int(c[-1]) + 1) % 10)
            s, cue = sep.join(c[i : i + 4] for i in range(0, 16, 4)), r.choice(["", "order ", "version ", "ref "])
        elif kind == "ip" and good:
            o, h = r.choice(["[.]", "(.)", " [dot] ", "(dot)", "{.}"]), lambda: f"{r.randrange(1 << r.choice((4, 8, 16))):x}"
            six = [h() for _ in range(8)]
            at = r.randint(1, 5)
            s = r.choice([o.join(str(r.randrange(256)) for _ in range(4)), ":".join(six), f"2001:db8::{r.randrange(1, 999)}", ":".join(six[:at]) + "::" + ":".join(six[at + 1 : 7]), f"fe80::{d(1)}{h()}:{h()}"])
            cue = r.choice(["", "host ", "ip ", "from ", "address ", "server "])
        elif kind == "ip":
            h = lambda: r.choice(["ab", "add", "bad", "dead", "cafe", "de"])
            o = r.choice(["[.]", "(.)", " [dot] ", "{.}"])
            s, cue = r.choice([(o.join([d(1), d(1), str(r.randint(256, 999)), d(2)]), "version "), (f"{h()}{d(1)}::{h()}", "class "), (f"{h()}::{h()}{d(1)}", "class "), (":".join(f"{r.randrange(256):02x}" for _ in range(8)), "mac "), (f"{d(2)}::{d(2)}", "ratio "), (f"{d(1)}::", "page ")])
        elif good:
            a, o = r.choice([(" [at] ", " [dot] "), ("(at)", "."), (" (at) ", " (dot) "), (" {at} ", ".")])
            s, cue = w() + r.choice(["", ".", "_"]) + d(r.randint(0, 2)) + "x" + a + w() + o + r.choice(["com", "org", "net"]), r.choice(["", "mail ", "contact "])
        else:
            s, cue = f"{w()} (at) {w()}.{d(2)}{d(1)}", r.choice(["date ", "page ", "total "])
        head = " ".join(w() for _ in range(r.randint(0, 8))) + " " + cue
        text = head + s + " " + " ".join(w() for _ in range(r.randint(0, 5)))
        out.append((text, kind, len(head), len(head) + len(s)))
        y.append(float(good))
    return out, np.array(y)


class Chooser:
    """Boosted trees with a calibrated threshold per kind, picked for precision on held-out findings."""

    def __init__(self, precision: float = 0.99, seed: int = 7):
        rows, y = findings(6000, seed)
        x = np.array([features(*f) for f in rows])
        fit = np.arange(len(y)) % 3 > 0
        self.trees = BoostedTrees(rounds=60).fit(x[fit], y[fit])
        f = self.trees.raw(x[~fit])
        self.slope, self.offset = calibrate(f, y[~fit])
        p, kind, self.least = sigmoid(self.slope * f + self.offset), x[~fit][:, 0], {}
        for k, name in enumerate(KINDS):
            ps, ys = p[kind == k], y[~fit][kind == k]
            order = np.argsort(-ps, kind="stable")
            right = np.cumsum(ys[order]) / np.arange(1, len(order) + 1)
            fine = np.flatnonzero(right >= precision)
            self.least[name] = float(max(0.5, ps[order[fine[-1]]])) if len(fine) else 2.0

    def choose(self, t: str, proposed: list[tuple[str, int, int]]) -> list[tuple[str, int, int]]:
        """The proposals whose chance reaches their kind's threshold, the likeliest first."""
        if not proposed:
            return []
        p = sigmoid(self.slope * self.trees.raw(np.array([features(t, *c) for c in proposed])) + self.offset)
        good = [(-q, c[1] - c[2], c[1], c) for c, q in zip(proposed, p.tolist(), strict=True) if q >= self.least[c[0]]]
        return [c for *_, c in sorted(good)]


def spans(t: str, model: Chooser) -> tuple[dict[str, list[tuple[int, int]]], list[tuple[str, int, int]]]:
    """Base spans by kind, and all spans in order: base ones, and of the chosen proposals the likeliest that overlap no likelier one."""
    base = base_spans(t)
    taken = sorted(s for v in base.values() for s in v)
    start, reach = [a for a, _ in taken], np.maximum.accumulate(np.array([0, *[b for _, b in taken]]))
    extra: list[tuple[int, int, str]] = []  # in order of start, none overlapping
    for k, a, b in model.choose(t, candidates(t)):
        at = bisect_left(extra, (a,))
        if reach[bisect_right(start, a)] < b and (not at or extra[at - 1][1] <= a) and (at == len(extra) or extra[at][0] >= b):
            extra.insert(at, (a, b, k))
    every = [(k, a, b) for k, v in base.items() for a, b in v] + [(k, a, b) for a, b, k in extra]
    return base, sorted(every, key=lambda c: (KINDS.index(c[0]), c[1], c[2]))


_ASKED = np.zeros(256, bool)
_ASKED[list(b"@+0123456789[({")] = True


def found(texts: pa.Array, model: Chooser) -> tuple[list[list], list[list]]:
    """Base spans and all spans of each text of a batch."""
    batch, base, every = pa.RecordBatch.from_arrays([texts], ["t"]), [], []
    for b in common.slices(batch, 0):
        data, off = common.raw(b.column(0))
        own: list[list] = [[]] * b.num_rows
        both: list[list] = [[]] * b.num_rows
        for row in np.unique(np.searchsorted(off, np.flatnonzero(_ASKED[data]), side="right") - 1).tolist():
            some, both[row] = spans(b.column(0)[row].as_py(), model)
            own[row] = [(k, a, e) for k in KINDS for a, e in some[k]]
        base += own
        every += both
    return base, every


def find_personal_data(docs: DataFrame, text: str = "text", key: str = "doc_id") -> DataFrame:
    """Per row: doc_id, base (list of kind, start, end) and spans (the same, with what the model adds)."""
    spark = docs.sparkSession
    common.importable(spark)
    held = spark.sparkContext.broadcast(Chooser())  # of fixed size

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int32()), ("end", pa.int32())]))
        for b in batches:
            told = found(b.column(1), held.value)
            yield pa.RecordBatch.from_arrays([b.column(0), *[pa.array([[dict(zip(("kind", "start", "end"), s, strict=True)) for s in r] for r in v], kind) for v in told]], ["doc_id", "base", "spans"])

    rows = docs.select(common.col(key).cast("long").alias("doc_id"), common.clean_text(common.col(text)).alias("text"))
    span = "array<struct<kind: string, start: int, end: int>>"
    return rows.mapInArrow(run, f"doc_id long, base {span}, spans {span}")


def listed(column: str) -> Column:
    """kind:start:end of each span in order, comma-joined."""
    return F.array_join(F.transform(F.col(column), lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")


def counted(column: str, kind: str) -> Column:
    return F.size(F.filter(F.col(column), lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    got = find_personal_data(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    return got.select("doc_id", *[counted("base", k) for k in KINDS], F.sha2(listed("base").cast("binary"), 256).alias("base_sha256"), listed("spans").alias("spans"))
