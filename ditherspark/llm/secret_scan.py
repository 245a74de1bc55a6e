"""Secret scans: pattern spans, and spans whose sliding-window entropy is too high for their character class.

A candidate is a run of at least ``window`` characters of ``[A-Za-z0-9+/_=-]``. Over it slides a window whose
character counts, and with them sum(c*log2 c), change by one character in and one out per step, so the entropy of
every window costs O(1). The threshold is that of the narrowest class that holds the window: hexadecimal of either
case, base32, letters of one case with digits, letters and digits, all candidate characters. Each class's threshold but
the last is what 98 % of windows of random characters of its alphabet reach. In the three middle classes digits must stand
apart, as in keys: words with a number at an end are held to the last class. Letters without a digit are held to what
few words reach. A window that holds a whole match of the allow-list is suppressed, and no other; the rest above their
threshold are united to spans. An identifier of hexadecimal groups is suppressed if it is the whole candidate. Pattern
spans are never suppressed.

Nulls count as empty texts. Empty texts have no span. Rows are independent of each other, so repeated rows, ties and
an empty table need no rule; columns other than the id and the text pass through untouched by ``redact`` and are not
read by ``scan``.
"""

from __future__ import annotations

import hashlib
import math
import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ditherspark.llm.common import buffers, mapped

# The patterns of the scan's contract.
ASSIGN = r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
ACCESS = r"AKIA[A-Z0-9]+"
HEX = r"[0-9a-f]+"
KINDS = ("assign", "access", "hex", "entropy")
MIN_ASSIGN, MIN_ACCESS, MIN_HEX = 6, 20, 24

_ASSIGN = re.compile(ASSIGN, re.I | re.A)
_ACCESS = re.compile(ACCESS)
_HEX = re.compile(HEX)
_CANDIDATE = re.compile(r"[A-Za-z0-9+/_=-]+")


def _lut(chars: str) -> np.ndarray:
    out = np.zeros(256, bool)
    out[list(chars.encode())] = True
    return out


_LOWER, _UPPER, _DIGIT = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "0123456789"
#: What a window's counts are of, in the order of ``EntropyRule.threshold``.
_CLASSES = (_DIGIT, "abcdef", _LOWER, _UPPER, "ABCDEF", "0189")
_HEX_LUT = _lut(_DIGIT + "abcdef")
_CAND_LUT = _lut(_LOWER + _UPPER + _DIGIT + "+/_=-")

#: Known harmless strings: documentation keys, placeholders, ids that are public by nature. Searched in the candidate.
ALLOW = (
    r"(?i)example|sample|placeholder|change_?me|dummy|redacted|your[_-]",
    r"^[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}$",
    r"(.)\1{5}",
    r"0123456789|(?i:abcdefghij|qwertyuiop)",
)


@dataclass(frozen=True)
class EntropyRule:
    """Window length, bits per character from which a window of each class counts, and the allow-list."""

    window: int = 20
    digits: float = 9.0  # numbers alone are never secrets
    hexadecimal: float = 2.94  # of either case
    base32: float = 3.4
    one_case_digits: float = 3.48
    alphanumeric: float = 3.68  # both cases and digits
    letters: float = 3.9  # without a digit: few words of this length have so many different ones
    words: float = 9.0  # letters with +/_=- and few digits: words joined by marks
    mixed: float = 3.9  # letters of either case with digits, beside +/_=-, or with digits that don't stand apart
    allow: tuple[str, ...] = ALLOW

    def threshold(self, n_digit: int, n_hexletter: int, n_lower: int, n_upper: int, n_hexupper: int = 0, n_not32: int = 0, turns: int = 0) -> float:
        """The threshold of the narrowest class that holds a window with these counts; ``n_not32`` are digits that base32
        lacks, ``turns`` changes between a digit and another character."""
        if not n_digit:
            return self.letters if n_lower + n_upper == self.window else self.words
        if n_digit == self.window:
            return self.digits
        if n_digit + n_hexletter + n_hexupper == self.window:
            return self.hexadecimal
        if n_digit >= 2 and turns >= 3 and n_digit + n_lower + n_upper == self.window:
            if n_lower and n_upper:
                return self.alphanumeric
            return self.one_case_digits if n_not32 else self.base32
        if n_lower and n_upper:
            return self.mixed
        return self.mixed if n_digit * 5 >= self.window else self.words


_CLOGC = [0.0] + [c * math.log2(c) for c in range(1, 4097)]


def hot_starts(s: str, rule: EntropyRule) -> list[int]:
    """Starts of the windows of ``s`` whose entropy reaches their class's threshold, by incremental counts."""
    w, out = rule.window, []
    if len(s) < w:
        return out
    counts: dict[str, int] = {}
    total, kinds = 0.0, [0] * 7
    for i, ch in enumerate(s):
        c = counts.get(ch, 0)
        total += _CLOGC[c + 1] - _CLOGC[c]
        counts[ch] = c + 1
        for k, chars in enumerate(_CLASSES):
            kinds[k] += ch in chars
        kinds[6] += i > 0 and (ch in _DIGIT) != (s[i - 1] in _DIGIT)
        if i >= w:
            old = s[i - w]
            c = counts[old]
            total += _CLOGC[c - 1] - _CLOGC[c]
            counts[old] = c - 1
            for k, chars in enumerate(_CLASSES):
                kinds[k] -= old in chars
            kinds[6] -= (old in _DIGIT) != (s[i - w + 1] in _DIGIT)
        if i >= w - 1 and math.log2(w) - total / w >= rule.threshold(*kinds) - 1e-9:
            out.append(i - w + 1)
    return out


def united(starts: list[int], window: int) -> list[tuple[int, int]]:
    """Windows that overlap or touch as one span."""
    out: list[tuple[int, int]] = []
    for a in starts:
        if out and out[-1][1] >= a:
            out[-1] = (out[-1][0], a + window)
        else:
            out.append((a, a + window))
    return out


def hot_windows(s: str, rule: EntropyRule) -> list[tuple[int, int]]:
    """The spans of ``s`` before suppression."""
    return united(hot_starts(s, rule), rule.window)


def unsuppressed(s: str, starts: list[int], window: int, allow: list[re.Pattern]) -> list[int]:
    """Those of ``starts`` whose windows hold no whole match of the allow-list."""
    for p in allow:
        if not starts:
            break
        found = [m.span() for m in p.finditer(s)]
        if any(b - a == len(s) for a, b in found):  # the candidate is such a string itself
            return []
        starts = [i for i in starts if not any(i <= a and b <= i + window for a, b in found)]
    return starts


def find_spans(text: str, rule: EntropyRule = EntropyRule(), kinds: tuple[bool, bool, bool, bool] = (True,) * 4) -> list[tuple[str, int, int]]:
    """(kind, start, end) of every secret of ``text`` in code points, by start, then kind as listed."""
    out = []
    if kinds[0]:
        out += [("assign", m.start(), m.end()) for m in _ASSIGN.finditer(text) if len(m[2]) >= MIN_ASSIGN]
    if kinds[1]:
        out += [("access", *m.span()) for m in _ACCESS.finditer(text) if len(m[0]) >= MIN_ACCESS]
    if kinds[2]:
        out += [("hex", *m.span()) for m in _HEX.finditer(text) if len(m[0]) >= MIN_HEX]
    if kinds[3]:
        allow = [re.compile(p) for p in rule.allow]
        for m in _CANDIDATE.finditer(text):
            if len(m[0]) >= rule.window:
                starts = unsuppressed(m[0], hot_starts(m[0], rule), rule.window, allow)
                out += [("entropy", m.start() + a, m.start() + b) for a, b in united(starts, rule.window)]
    return sorted(out, key=lambda s: (s[1], KINDS.index(s[0]), s[2]))


def _long_runs(inside: np.ndarray, offsets: np.ndarray, least: int) -> np.ndarray:
    """For each text, whether it has a run of ``least`` bytes that are ``inside``; text borders end runs."""
    edge = np.zeros(len(inside) + 2, np.int8)
    edge[1:-1] = inside
    step = np.diff(edge)
    start, end = np.flatnonzero(step == 1), np.flatnonzero(step == -1)
    long = end - start >= least
    out = np.zeros(len(offsets) - 1, bool)
    if long.any():  # a run over a border is looked at again by the exact patterns
        a = np.searchsorted(offsets, start[long], side="right") - 1
        b = np.searchsorted(offsets, end[long] - 1, side="right") - 1
        for i, j in zip(a, b, strict=True):
            out[i : j + 1] = True
    return out


def _spans_of(texts: pa.Array, rule: EntropyRule) -> dict[int, list[tuple[str, int, int]]]:
    """Spans by row, for rows that have any; whole-batch filters choose the rows that the patterns look at."""
    data, off = buffers(texts)
    if not len(data):
        return {}
    filled = pc.fill_null(texts, "")
    assign = pc.match_substring_regex(filled, r"""(password|passwd|secret|token|api_?key)["']? *[:=]""", ignore_case=True).to_numpy(zero_copy_only=False)
    access = pc.match_substring(filled, "AKIA").to_numpy(zero_copy_only=False)
    hexes = _long_runs(_HEX_LUT[data], off, MIN_HEX)
    dense = _long_runs(_CAND_LUT[data], off, rule.window)
    out = {}
    for i in np.flatnonzero(assign | access | hexes | dense):
        if spans := find_spans(filled[int(i)].as_py(), rule, (assign[i], access[i], hexes[i], dense[i])):
            out[int(i)] = spans
    return out


def _joined(spans) -> str:
    return ",".join(f"{k}:{a}:{b}" for k, a, b in spans)


def scan(docs: DataFrame, rule: EntropyRule = EntropyRule(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per row of ``docs``: the id and ``found``, an array of (kind, start, end)."""

    def kernel():
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))

        def step(batch):
            spans = _spans_of(batch["text"], rule)
            found = [[{"kind": k, "start": a, "end": b} for k, a, b in spans.get(i, ())] for i in range(batch.num_rows)]
            return pa.RecordBatch.from_arrays([batch["id"], pa.array(found, kind)], ["id", "found"])

        return step

    kind = dict(docs.dtypes)[id_col]
    src = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return mapped(src, kernel, f"id {kind}, found array<struct<kind:string,start:bigint,end:bigint>>").withColumnRenamed("id", id_col)


def redact(docs: DataFrame, rule: EntropyRule = EntropyRule(), text_col: str = "text", mark: str = "[SECRET]") -> DataFrame:
    """``docs``, all columns, with each secret of the text replaced by ``mark`` (overlapping spans by one mark)."""

    def clean(text: str, spans) -> str:
        out, at = [], 0
        for _, a, b in spans:
            if b <= at:
                continue
            out += [text[at:a], mark] if a >= at else []
            at = b
        return "".join(out) + text[at:]

    def kernel():
        def step(batch):
            texts = batch[text_col]
            spans = _spans_of(texts, rule)
            if not spans:
                return batch
            new = texts.to_pylist()
            for i, s in spans.items():
                new[i] = clean(new[i], s)
            at = batch.schema.get_field_index(text_col)
            return batch.set_column(at, batch.schema.field(at), pa.array(new, texts.type))

        return step

    return mapped(docs, kernel, docs.schema, text_col)


def digest(docs: DataFrame, rule: EntropyRule = EntropyRule()) -> DataFrame:
    """The contract's columns out of ``scan``."""
    listed = lambda a: F.array_join(F.transform(a, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")
    count = lambda k: F.size(F.filter("found", lambda s: s["kind"] == k)).cast("long").alias(f"n_{k}")
    base = F.filter("found", lambda s: s["kind"] != "entropy")
    return scan(docs, rule).select(
        "doc_id", count("assign"), count("access"), count("hex"),
        F.sha2(listed(base), 256).alias("base_sha256"), listed(F.col("found")).alias("spans"), count("entropy"),
    )


def digest_of(text: str | None, rule: EntropyRule = EntropyRule()) -> tuple[int, int, int, str, str]:
    """What ``digest`` returns for one text; the brute force of tests may differ in how it finds spans."""
    spans = find_spans(text or "", rule)
    base = [s for s in spans if s[0] != "entropy"]
    n = [sum(s[0] == k for s in spans) for k in KINDS]
    return n[0], n[1], n[2], hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(spans)
