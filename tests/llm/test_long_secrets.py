"""Secrets of any length: long and dotted tokens are candidates, judged over all their characters."""

import random
import string

import numpy as np
import pytest

from orderless.llm import secrets


def some(n, seed=1, letters=string.ascii_letters + string.digits):
    r = random.Random(seed)
    return "".join(r.choice(letters) for _ in range(n - 2)) + "a1"


@pytest.fixture(scope="module")
def judge():
    return secrets.Judge()


@pytest.mark.parametrize("n", [20, 64, 200, 201, 344, 700, 250_000])
def test_no_upper_bound(judge, n):
    t = "the key = " + some(n) + " and more words"
    assert ("other", 10, 10 + n) in secrets.candidates(t)
    if n > 24:
        assert ("other", 10, 10 + n) in secrets.spans(t, judge)[1]


def test_dotted_tokens_are_whole(judge):
    token = ".".join(["eyJ" + some(30), some(180, 2), some(43, 3)])
    t = f"Bearer {token}. Then words."
    assert ("other", 7, 7 + len(token)) in secrets.spans(t, judge)[1]


def test_windows_cover_candidate_and_both_contexts():
    t = "x" * 50 + some(333) + "y" * 50
    x = np.concatenate(list(secrets.windows(t, 50, 383)))
    inside = (x >= secrets.SYMBOLS // 2).sum()
    assert inside >= 333
    assert (x[0, : secrets.LEAD] == x[0, 0]).all() and (x[-1, -secrets.LEAD :] == x[-1, -1]).all()


def test_a_base_span_inside_leaves_no_rest(judge):
    token = some(60) + "0123456789abcdef" * 3 + some(60, 2)
    t = "token of " + token + " here"
    assert any(a <= 9 and b >= 9 + len(token) for _, a, b in secrets.spans(t, judge)[1])


def test_a_token_after_a_text_that_ends_in_one():
    a, b = "ends in abc", some(40)
    data = np.frombuffer((a + b).encode(), np.uint8)
    assert 1 in secrets.suspects(data, np.array([0, len(a), len(a + b)]))
