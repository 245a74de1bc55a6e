"""Recall of the entropy rule on random keys of each alphabet, and its silence on prose."""

import math
from collections import Counter

import numpy as np
import pytest

from ditherspark.llm import secret_scan

LOWER, UPPER, DIGIT = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
KEYS = [
    ("0123456789ABCDEF", 20, 0.95), ("0123456789ABCDEF", 32, 0.99), ("0123456789ABCDEF", 64, 0.99), ("0123456789abcdef", 20, 0.95),
    (UPPER + "234567", 32, 0.95), (LOWER + "234567", 32, 0.95), (LOWER + DIGIT, 24, 0.95), (UPPER + DIGIT, 24, 0.95),
    (LOWER + UPPER + DIGIT, 20, 0.9), (LOWER + UPPER + DIGIT, 32, 0.99), (LOWER + UPPER + DIGIT + "+/", 40, 0.99),
]


@pytest.mark.parametrize("alphabet,length,least", KEYS)
def test_random_keys_are_found(alphabet, length, least):
    g = np.random.default_rng(13)
    keys = ["".join(alphabet[i] for i in g.integers(0, len(alphabet), length)) for _ in range(1500)]
    assert np.mean([any(k == "entropy" for k, _, _ in secret_scan.find_spans(f"x {k} y")) for k in keys]) >= least


def test_words_and_paths_are_not():
    prose = (
        "internationalization2 windows10professional donaudampfschifffahrtsgesellschaft2024 ANNUALREPORTSUPPLEMENT1999 some-long-article-title-from-2024-05 "
        "docs/guide/getting-started/part2 getUserProfileResponseV2 1234567890123456789012345 2024-05-17/2024-06-18 chapter12introduction ISO_8859_1_CHARACTER_SET "
    )
    assert [s for s in secret_scan.find_spans(prose * 3) if s[0] == "entropy"] == []


def test_counts_follow_the_window():
    """Incremental counts and turns against each window counted anew."""
    g, rule = np.random.default_rng(14), secret_scan.EntropyRule()
    chars = LOWER + UPPER[:6] + DIGIT + "-"
    for n in range(200):
        s = "".join(chars[i] for i in g.integers(0, len(chars) if n % 2 else 26, 30)) + "A7" * 3 + "".join(UPPER[i] for i in g.integers(0, 6, 12)) + "9"
        want = set()
        for i in range(len(s) - 19):
            w = s[i : i + 20]
            h = -sum(c / 20 * math.log2(c / 20) for c in Counter(w).values())
            kinds = [sum(ch in k for ch in w) for k in (DIGIT, "abcdef", LOWER, UPPER, "ABCDEF", "0189")]
            if h >= rule.threshold(*kinds, sum((a in DIGIT) != (b in DIGIT) for a, b in zip(w, w[1:]))) - 1e-9:
                want |= set(range(i, i + 20))
        assert {i for a, b in secret_scan.hot_windows(s, rule) for i in range(a, b)} == want


def test_keys_without_a_digit():
    g = np.random.default_rng(16)
    for alphabet, length, least in ((LOWER + UPPER, 40, 0.95), (LOWER + UPPER, 24, 0.7), (LOWER, 64, 0.5)):
        keys = ["".join(alphabet[i] for i in g.integers(0, len(alphabet), length)) for _ in range(600)]
        assert np.mean([any(k == "entropy" for k, _, _ in secret_scan.find_spans(f"x {k} y")) for k in keys]) >= least


def test_suppression_covers_what_it_matches():
    key, other = "q7Zp2LmX9vRt4KsW8yBn3Hc6", "t5Gx1QwE8rTz6UiP0aSd4Fg9"
    assert secret_scan.find_spans(key) and not secret_scan.find_spans("q7Zp2LmEXAMPLE9vRt4KsW8")
    found = secret_scan.find_spans(key + "EXAMPLE" + other)  # windows that don't hold the word cover both keys
    assert {i for _, a, b in found for i in range(a, b)} >= {*range(24), *range(31, 55)}
    assert not secret_scan.find_spans("x" * 5 + "EXAMPLE" + key[:8])
    assert not secret_scan.find_spans("3f2504e0-4f89-11d3-9a0c-0305e82c3301")
    assert secret_scan.find_spans(key + "aaaaaa" + other)
