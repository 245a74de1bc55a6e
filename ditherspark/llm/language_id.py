"""Language identification by language-bitmask n-gram filters.

For each language the n-grams that are typical of it go into a Bloom filter; the filters of all languages are stored
bit-sliced, one row of language bits per position, so the AND of an n-gram's rows names every language that contains it
in one lookup. A text's set bits are counted per language, each count is corrected for its filter's false positives,
and the language with the largest corrected count is the answer. Its score is its lead, 1 - second/best. Where only one
language was learned there is none to lead: its filter holds all its n-grams, and the score is the share of the text's
n-grams that it has.

The n-grams are those of the lower-cased text's bytes with everything but letters blanked, of the orders ``orders``. A
language contains an n-gram if its share there is at least ``least`` and no less than a ``ratio``-th of its largest
share in any language. Filters are fitted on labelled rows of the training folds, about ``most_docs`` a language (those
with the least hashes), which bounds the model; every text is then judged whole.

A null text or one without a letter is ``und`` with score 0, as is any if nothing could be learned. A text without any
hit gets the language with most training rows, with score 0. Ties go to the language with more training rows, then to the
lesser name. Rows are independent; an empty table gives an empty result. Columns other than those named are not read by
``digest``; ``kept_only`` passes all on untouched.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ditherspark.llm.common import NARROW_BYTES, buffers, doc_crc, free_name, mapped

_WORDLIKE = re.compile(r"[^\W\d_]")  # letters, and numbers such as fractions or circled digits
_BLANK = np.arange(256, dtype=np.uint8)
_BLANK[[b for b in range(128) if not chr(b).isalpha()]] = 32
_MULTIPLY = np.array([0x9E3779B97F4A7C15, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5], np.uint64)


@dataclass(frozen=True)
class FilterRule:
    """N-gram orders, filter shape, what a language contains, the training bound, and what a filtering stage asks for."""

    orders: tuple[int, ...] = (3, 5)
    probes: int = 3
    cells_per_entry: int = 12
    least: float = 2e-6
    ratio: float = 4.0
    most_docs: int = 3000
    min_score: float = 0.02
    short: int = 20


@dataclass(frozen=True)
class Filters:
    """Languages by falling number of training rows, one row of language bits per cell, and each filter's false positives."""

    languages: tuple[str, ...]
    cells: np.ndarray
    false_positive: np.ndarray
    rule: FilterRule


def _grams(data: np.ndarray, order: int) -> np.ndarray:
    """The n-gram at each byte as a number; those that run over the end are zero-filled."""
    out = np.zeros(len(data), np.uint64)
    for k in range(order):
        out[: max(0, len(data) - k)] |= data[k:].astype(np.uint64) << np.uint64(8 * k)
    return out | np.uint64(order << 56)


def _cells(grams: np.ndarray, probe: int, bits: int) -> np.ndarray:
    mixed = (grams ^ (grams >> np.uint64(29))) * _MULTIPLY[probe]
    return (mixed >> np.uint64(64 - bits)).astype(np.int64)


def _letters(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    data, off = buffers(pc.utf8_lower(pc.fill_null(texts, "")))
    return _BLANK[data], off


def gram_counts(docs: DataFrame, rule: FilterRule) -> DataFrame:
    """(lang, gram, n) over ``docs`` (lang, text), summed by slice before the shuffle."""

    def kernel():
        def step(batch):
            langs, texts = batch["lang"].to_pylist(), batch["text"]
            out = []
            for lang in sorted(set(langs)):
                data, off = _letters(texts.filter(pa.array([x == lang for x in langs])))
                for n in rule.orders:
                    ok = np.ones(len(data), bool)
                    for k in range(1, n):
                        ok[np.maximum(off[1:] - k, 0)[np.diff(off) >= k]] = False
                    g, c = np.unique(_grams(data, n)[ok], return_counts=True)
                    out.append(pa.RecordBatch.from_arrays([pa.array([lang] * len(g), pa.string()), pa.array(g.view(np.int64)), pa.array(c)], ["lang", "gram", "n"]))
            schema = pa.schema([("lang", pa.string()), ("gram", pa.int64()), ("n", pa.int64())])
            return pa.Table.from_batches(out, schema).combine_chunks().to_batches()[0] if out and sum(map(len, out)) else pa.RecordBatch.from_pylist([], schema)

        return step

    return mapped(docs.select("lang", "text"), kernel, "lang string, gram bigint, n bigint").groupBy("lang", "gram").agg(F.sum("n").alias("n"))


def fit(docs: DataFrame, rule: FilterRule = FilterRule()) -> Filters | None:
    """Filters from labelled ``docs`` (doc_id, text, lang), or None without any."""
    known = docs.where("lang IS NOT NULL AND text IS NOT NULL").select("doc_id", "text", "lang")
    sizes = {r.lang: r.n for r in known.groupBy("lang").agg(F.count("*").alias("n")).collect()}  # a row a language
    if not sizes:
        return None
    languages = tuple(sorted(sizes, key=lambda x: (-sizes[x], x)))
    share = F.create_map(*[F.lit(x) for k in languages for x in (k, min(1.0, rule.most_docs / sizes[k]))])
    sample = known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < share[F.col("lang")] * (1 << 20))
    counts = gram_counts(sample, rule)
    order = F.shiftrightunsigned("gram", 56)
    totals = counts.groupBy("lang", order.alias("o")).agg(F.sum("n").alias("total"))
    shares = counts.withColumn("o", order).join(F.broadcast(totals), ["lang", "o"]).select("lang", "gram", (F.col("n") / F.col("total")).alias("p"))
    most = shares.groupBy("gram").agg(F.max("p").alias("most"), F.collect_list(F.struct("lang", "p")).alias("of")).where(F.col("most") >= rule.least)
    has = F.filter("of", lambda x: (x["p"] >= rule.least) & (x["p"] * rule.ratio >= F.col("most")))
    table = most.select("gram", F.transform(has, lambda x: x["lang"]).alias("langs")).where(F.size("langs") < max(2, len(languages))).toArrow()
    grams = table["gram"].combine_chunks().to_numpy(zero_copy_only=False).view(np.uint64)
    held = table["langs"].combine_chunks()
    row = np.repeat(np.arange(len(grams)), pc.list_value_length(held).to_numpy(zero_copy_only=False))
    bit = np.array([languages.index(x) for x in held.flatten().to_pylist()], np.int64)
    return _filters(languages, grams[row], bit, len(grams), rule)


def _filters(languages: tuple[str, ...], grams: np.ndarray, bit: np.ndarray, entries: int, rule: FilterRule) -> Filters:
    bits = max(10, int(np.ceil(np.log2(max(1, entries) * rule.cells_per_entry))))
    width = -(-len(languages) // 8)
    cells = np.zeros((1 << bits, width), np.uint8)
    for probe in range(rule.probes):
        np.bitwise_or.at(cells, (_cells(grams, probe, bits), bit >> 3), (1 << (bit & 7)).astype(np.uint8))
    fill = np.array([((cells[:, k >> 3] >> (k & 7)) & 1).mean() for k in range(len(languages))])
    return Filters(languages, cells, fill**rule.probes, rule)


def counted(texts: pa.Array, model: Filters) -> tuple[np.ndarray, np.ndarray]:
    """Corrected counts (texts x languages), and the n-grams of each text."""
    data, off = _letters(texts)
    bits = int(np.log2(len(model.cells)))
    hits, total = np.zeros((len(off) - 1, len(model.languages))), np.zeros(len(off) - 1)
    for n in model.rule.orders:
        grams = _grams(data, n)
        mask = model.cells[_cells(grams, 0, bits)]
        for probe in range(1, model.rule.probes):
            mask = mask & model.cells[_cells(grams, probe, bits)]
        stop = np.maximum(off[:-1], off[1:] - n + 1)
        total += stop - off[:-1]
        for k in range(len(model.languages)):
            run = np.zeros(len(data) + 1, np.int64)
            np.cumsum((mask[:, k >> 3] >> (k & 7)) & 1, out=run[1:])
            hits[:, k] += run[stop] - run[off[:-1]]
    fp = model.false_positive
    return np.maximum(0, (hits - total[:, None] * fp) / (1 - fp)), total


def has_letter(text: str | None) -> bool:
    """Whether a character of ``text`` is a letter (any Unicode category L)."""
    return text is not None and any(m[0].isalpha() for m in _WORDLIKE.finditer(text))


def predict_batch(texts: pa.Array, model: Filters | None) -> tuple[list[str], np.ndarray]:
    """Language and score of each text."""
    letters = np.array([has_letter(t) for t in texts.to_pylist()], bool)
    if model is None or not len(letters):
        return ["und"] * len(letters), np.zeros(len(letters))
    count, grams = counted(texts, model)
    best = count.argmax(axis=1)
    top = count.max(axis=1)
    lead = 1 - np.partition(count, -2, axis=1)[:, -2] / np.where(top > 0, top, 1) if count.shape[1] > 1 else top / np.maximum(1, grams)
    score = np.where((top > 0) & letters, lead, 0.0)
    return [model.languages[b] if ok else "und" for b, ok in zip(best, letters, strict=True)], score


def predict(docs: DataFrame, model: Filters | None, names: tuple[str, str] = ("__lm_lang", "__lm_score")) -> DataFrame:
    """``docs``, all columns, with the language and its score under ``names``."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def kernel():
        model = held.value

        def step(batch):
            lang, score = predict_batch(batch["text"], model)
            return batch.append_column(names[0], pa.array(lang, pa.string())).append_column(names[1], pa.array(score, pa.float64()))

        return step

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)
    return mapped(docs, kernel, f"{fields}, {names[0]} string, {names[1]} double", budget=NARROW_BYTES)


def training(docs: DataFrame) -> DataFrame:
    """Rows of the folds that may be learned from."""
    return docs.where(doc_crc() % 3 != 1)


def digest(docs: DataFrame, rule: FilterRule = FilterRule()) -> DataFrame:
    """The contract's columns."""
    model = fit(training(docs), rule)
    out = predict(docs.select("doc_id", "text"), model)
    return out.select("doc_id", (doc_crc() % 3 == 1).alias("held_out"), F.col("__lm_lang").alias("lang_pred"), F.col("__lm_score").alias("score"))


def kept_only(docs: DataFrame, rule: FilterRule = FilterRule()) -> DataFrame:
    """``docs``, all columns, without those whose language is unknown, or leads by less than ``min_score`` in a text of
    ``short`` characters or more (shorter ones have too few n-grams to hold a small lead against them)."""
    lang, score = free_name(docs, "__lm_lang"), free_name(docs, "__lm_score")
    out = predict(docs, fit(training(docs), rule), (lang, score))
    clear = (F.col(score) >= rule.min_score) | (F.length("text") < rule.short)
    return out.where((F.col(lang) != "und") & clear).select(docs.columns)
