"""The multiset hash against a version of its own: paragraphs cut by a plain loop, vectors summed in Python numbers."""

import hashlib

import numpy as np
import pytest

from ditherspark.llm import multiset_hash as M

SPACE = b" \t\n\x0b\f\r"


def slow_paragraphs(t):
    n, begins = len(t), []
    for i in range(1, n):
        if t[i - 1] == 10 or (i >= 2 and t[i - 2] in b".!?" and t[i - 1] in SPACE):
            begins.append(i)
    edges = [0, *begins, n]

    def pick(i):
        m = sum(t[i - k] * c for k, c in zip((1, 2, 3, 4), (0x01000193, 0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D)) if i >= k) % 2**32
        return ((m ^ (m >> 15)) * 0x2C1B3C6D % 2**32 >> 24) & 63

    def run_length(i):
        a = b = i
        while a > 0 and t[a - 1] not in SPACE:
            a -= 1
        while b < n and t[b] not in SPACE:
            b += 1
        return b - a

    parts = []
    for a, b in zip(edges, edges[1:]):
        cuts = [a]
        if b - a > M.LONG:
            for i in range(a + 1, b):
                word = t[i - 1] in SPACE and t[i] not in SPACE and i >= 2 and pick(i - 1) < 8
                inner = run_length(i) >= M.RUN and t[i] not in SPACE and t[i - 1] not in SPACE and t[i] & 0xC0 != 0x80 and pick(i) < 2
                if word or inner:
                    cuts.append(i)
        cuts.append(b)
        parts += [t[x:y].strip(SPACE) for x, y in zip(cuts, cuts[1:])]
    return [p for p in parts if p]


def slow_fingerprint(t):
    uniform, signs, parts = [0] * 32, [0] * 160, slow_paragraphs(t)
    for p in parts:
        h = hashlib.blake2b(p).digest()
        for k in range(32):
            uniform[k] += h[2 * k] | h[2 * k + 1] << 8
        for k in range(160):
            signs[k] += 1 if h[k // 8] >> (7 - k % 8) & 1 else -1
    return f"{len(parts):08x}" + "".join(f"{x % 2**16:04x}" for x in uniform) + "".join(f"{x % 2**32:08x}" for x in signs)


def test_against_a_plain_loop(texts):
    odd = ["", ".", "a", "?!... abc", "abc", "a. b! c? d", "x" * 300, "ab cd " * 40, "é" * 200 + " end", " \n\n ", "One. Two.\nThree"]
    for t in [t for t in texts.values() if t and len(t) < 6000][:150] + odd:
        assert M.fingerprint(t).hex() == slow_fingerprint(t.encode()), t[:80]


def test_no_character_is_dropped():
    for t in ("?!...", "...abc", "a.b.c", "!x ?y .z", "word " * 60 + "!", "日本語" * 80):
        assert b"".join(M.paragraphs(t.encode())).replace(b" ", b"") == t.encode().replace(b" ", b"")
    assert M.fingerprint("...abc").hex() != M.fingerprint("abc").hex() and M.fingerprint("?!...").count == 1


def test_an_insertion_changes_what_it_touches():
    g = np.random.default_rng(3)
    for sep in (" ", ""):
        t = sep.join("".join(chr(97 + i) for i in g.integers(0, 26, 6)) for _ in range(600))
        assert M.fingerprint("z " + t).likeness(M.fingerprint(t)) > 0.9
        assert M.fingerprint(t[:1500] + "new" + t[1500:]).likeness(M.fingerprint(t)) > 0.8


def test_many_repeats_keep_their_sign():
    t = "short line\n" * 40_000
    new = M.edited(t, "other words\n" * 40_000)
    assert 0.8 < M.fingerprint(t).likeness(M.fingerprint(new)) < 0.95


def test_ids_must_be_numbers(spark):
    with pytest.raises(TypeError):
        M.digest(spark.createDataFrame([("a", "b")], "doc_id string, text string"))
