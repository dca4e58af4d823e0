"""Spans of many texts in one batch equal those of each text alone, whatever stands at their edges; no input raises."""

import random

import pyarrow as pa
import pytest

from orderless.llm import pii, secrets

from test_operators import pii_brute, secrets_brute

EDGES = ["", "see the end", "0123456789abcdef" * 2, "0123456789abcdef" * 2 + " and more", "abc", "token", "=", "password: hunter2hunter2", "AKIA", "AKIAABCDEFGH12345", "Zx9" * 30, "Zx9" * 120, " ", "é", "\n", "sec", "ret: abcdefgh1"]
PARTS = ["a@b.co", "+1 555 123 4567", "10.0.0.1", "4111 1111 1111 1111", "0" * 5000 + ".0.0.0", "1.2.3", "@", "+", "(555) 123-4567", "call 555-1234", "2001:db8::7", "1[.]2[.]3[.]4", "x [at] y [dot] org", "a::b", "é", " ", "", "page"]


@pytest.fixture(scope="module")
def judge():
    return secrets.Judge()


@pytest.fixture(scope="module")
def chooser():
    return pii.Chooser()


def mixed(r, parts):
    return ["".join(r.choice(parts) for _ in range(r.randrange(4))) for _ in range(r.randrange(1, 12))]


def test_secrets_of_batches(judge):
    r = random.Random(5)
    for _ in range(250):
        texts = mixed(r, EDGES)
        got = {row: (t, base, both) for row, t, base, both in secrets._verdicts(pa.array(texts), judge)}
        for row, t in enumerate(texts):
            base, both = secrets.spans(t, judge)
            assert base == secrets.ordered(secrets_brute(t))
            assert got.get(row, (t, [], [])) == (t, base, both), texts


def test_a_text_that_starts_with_a_secret(judge):
    texts = ["see the end", "0123456789abcdef" * 2 + " and more", "plain"]
    assert [(row, base) for row, _, base, _ in secrets._verdicts(pa.array(texts), judge) if base] == [(1, [("hex", 0, 32)])]


def test_redaction_leaves_no_base_secret(judge):
    r = random.Random(6)
    for _ in range(250):
        for t in secrets.redacted(pa.array(mixed(r, [*EDGES, "secret: api_key", "= ABCDEFGHIJ", "x1" * 12])), judge).to_pylist():
            assert t is None or not secrets.base_spans(t), t


def test_personal_data_of_batches(chooser):
    r = random.Random(7)
    for _ in range(250):
        texts = mixed(r, PARTS)
        base, every = pii.found(pa.array(texts), chooser)
        for t, own, both in zip(texts, base, every, strict=True):
            want = pii_brute(t)
            assert own == [(k, a, b) for k in pii.KINDS for a, b in want[k]]
            assert set(own) <= set(both) and both == pii.spans(t, chooser)[1]
            extra = sorted((a, b) for k, a, b in both if (k, a, b) not in set(own))
            assert all(x[1] <= y[0] for x, y in zip(extra, extra[1:], strict=False))


def test_no_generator_has_a_length_bound(chooser):
    name = "n" * 3000
    t = f"mail {name} [at] {'d' * 900} [dot] {'e' * 900}.org today"
    assert ("email", 5, len(t) - 6) in pii.spans(t, chooser)[1]
    assert pii.spans("1" + "0" * 5000 + ".0.0.0 " + "0" * 5000 + "7.0.0.0", chooser)[0]["ip"] == [(5008, 10015)]


def test_host_addresses_beyond_the_base_pattern(chooser):
    t = "host 10[.]1[.]2[.]3 and server 2001:db8::17 but class add1::bad"
    assert [t[a:b] for k, a, b in pii.spans(t, chooser)[1] if k == "ip"] == ["10[.]1[.]2[.]3", "2001:db8::17"]


def test_of_overlapping_numbers_one_is_told(chooser):
    t = "call 212-555-1234 now"
    assert [t[a:b] for _, a, b in pii.spans(t, chooser)[1]] == ["212-555-1234"]
