"""Quality rules by a hashed n-gram log-likelihood ratio, with DataFrame functions only.

Word unigrams and bigrams are hashed to ``buckets``. Two multinomials over the buckets are counted: one over trusted
target texts, one over the whole raw corpus. A document's score is the mean over its n-grams of the log ratio of the
two, and every document with a score of at least ``threshold`` is kept: a fixed rule, no draw.

Repeated 8-word windows are found within the row: hashes of all windows are sorted with their positions, and neighbours
with equal hashes mark positions, so a text costs n log n and nothing is shuffled. The only shuffle is of bucket counts,
summed in each task first; the weights, one array of ``buckets`` numbers, come back as a scalar subquery.

Null texts count as having no words, as do empty texts and white space; they fail the base rules. With no target text
every weight is zero and the base rules alone decide. Repeated rows are judged alike. An empty table gives an empty
result. Labels may repeat or name unknown documents. ``kept_only`` passes all other columns on untouched; helper columns
have names that the table lacks.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ditherspark.llm.common import free_name

# What separates words, and the symbols that are counted.
SPACE = r"[\x20\x09-\x0D]"
BLANKS = " \t\n\x0b\f\r"
SYMBOLS = "#*$%&|<>"
WINDOW, LEAST_WORDS, MOST_REPEATED = 8, 20, 30


@dataclass(frozen=True)
class RatioRule:
    """Hash buckets, smoothing count, score from which a document is kept, and the bound on trusted labels."""

    buckets: int = 1 << 16
    alpha: float = 5.0
    threshold: float = -0.1
    most_labels: int = 200_000


def bound(value: Column, use) -> Column:
    """``use(value)`` with ``value`` computed once a row."""
    return F.transform(F.array(value), use)[0]


def words(text: Column) -> Column:
    trimmed = F.btrim(F.coalesce(text, F.lit("")), F.lit(BLANKS))
    return F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACE + "+"))


def _ngrams(hashes: Column, buckets: int) -> Column:
    """Buckets of unigrams, then of bigrams, from the words' hashes."""
    n = F.size(hashes)
    pairs = F.zip_with(F.slice(hashes, 1, F.greatest(n - 1, F.lit(0))), F.slice(hashes, 2, F.greatest(n - 1, F.lit(0))), lambda a, b: F.pmod(F.xxhash64(a, b), F.lit(buckets)).cast("int"))
    return F.concat(F.transform(hashes, lambda h: F.pmod(h, F.lit(buckets)).cast("int")), F.when(n > 1, pairs).otherwise(F.array().cast("array<int>")))


def _repeated(hashes: Column) -> Column:
    """Words in ``WINDOW``-word windows that the text holds twice or more."""
    def covered(windows: Column) -> Column:
        at = F.sequence(F.lit(0), F.size(windows) - 1)
        pairs = F.array_sort(F.zip_with(windows, at, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

        def marked(s: Column) -> Column:
            same = lambda a, b: F.coalesce(s[a]["h"] == s[b]["h"], F.lit(False))
            twice = F.filter(at, lambda k: (F.when(k > 0, same(F.greatest(k - 1, F.lit(0)), k)).otherwise(False)) | F.when(k < F.size(s) - 1, same(F.least(k + 1, F.size(s) - 1), k)).otherwise(False))
            return F.array_sort(F.transform(twice, lambda k: s[k]["i"]))

        def length(p: Column) -> Column:
            steps = F.zip_with(F.slice(p, 1, F.size(p) - 1), F.slice(p, 2, F.size(p) - 1), lambda a, b: F.least(b - a, F.lit(WINDOW)))
            return F.aggregate(steps, F.lit(WINDOW).cast("long"), lambda acc, x: acc + x)

        return bound(bound(pairs, marked), length)

    n = F.size(hashes)
    windows = F.transform(F.sequence(F.lit(0), n - WINDOW), lambda i: F.xxhash64(*[F.get(hashes, i + j) for j in range(WINDOW)]))
    found = bound(windows, lambda w: F.when(F.size(F.array_distinct(w)) == F.size(w), F.lit(0).cast("long")).otherwise(covered(w)))
    return F.when(n >= WINDOW, found).otherwise(F.lit(0).cast("long"))


def base_counts(text: Column, hashes: Column) -> dict[str, Column]:
    """Columns of the base rules out of the text and its words' hashes."""
    full = F.coalesce(text, F.lit(""))
    lines = F.filter(F.split(full, "\n"), lambda x: F.btrim(x, F.lit(BLANKS)) != "")
    return {
        "word_chars": F.length(F.translate(full, BLANKS, "")).cast("long"),
        "n_symbols": (F.length(full) - F.length(F.translate(full, SYMBOLS, ""))).cast("long"),
        "n_dup_lines": bound(lines, lambda x: F.size(x) - F.size(F.array_distinct(x))).cast("long"),
        "n_repeat_words": _repeated(hashes),
    }


def _hashed(docs: DataFrame, text_col: str) -> DataFrame:
    return docs.withColumn("__lm_hashes", F.transform(words(F.col(text_col)), lambda w: F.xxhash64(w)))


def fit(docs: DataFrame, trusted: DataFrame, rule: RatioRule = RatioRule(), id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row, ``weights``: log ratios by bucket. ``trusted`` has the ids of target texts; at most ``most_labels`` of
    them count (those of least hash), so that they can be broadcast. The raw corpus counts whole."""
    ids = trusted.select(F.col(id_col).alias("__lm_id")).where("__lm_id IS NOT NULL").distinct()
    ids = ids.orderBy(F.xxhash64("__lm_id"), "__lm_id").limit(rule.most_labels).withColumn("__lm_target", F.lit(1))
    marked = docs.select(F.col(id_col).alias("__lm_id"), text_col).join(F.broadcast(ids), "__lm_id", "left")
    grams = _hashed(marked, text_col).select(F.coalesce("__lm_target", F.lit(0)).alias("t"), F.explode(_ngrams(F.col("__lm_hashes"), rule.buckets)).alias("b"))
    counts = grams.groupBy("b").agg(F.count("*").alias("raw"), F.sum("t").alias("target"))
    every = docs.sparkSession.range(rule.buckets).select(F.col("id").cast("int").alias("b")).join(counts, "b", "left").na.fill(0)
    listed = F.array_sort(F.collect_list(F.struct("b", "target", "raw")))
    sums = every.agg(listed.alias("c"), F.sum("raw").alias("nr"), F.sum("target").alias("nt"))
    per = F.col("nr") / F.col("nt")  # the raw multinomial gets the same smoothing in its own scale: no evidence, no verdict
    smooth, mass = rule.alpha * per, rule.alpha * rule.buckets
    ratio = lambda x: F.log((x["target"] + rule.alpha) / (F.col("nt") + mass)) - F.log((x["raw"] + smooth) / (F.col("nr") + mass * per))
    return sums.select(F.transform("c", lambda x: F.when(F.col("nt") > 0, ratio(x)).otherwise(0.0)).alias("weights"))


def judged(docs: DataFrame, weights: DataFrame, rule: RatioRule = RatioRule(), text_col: str = "text", name: str = "__lm") -> DataFrame:
    """``docs`` and ``name``, a struct of n_words, the base counts, llr (null without words), base_failed and kept. It is
    one expression whose parts are bound inside, so a filter on it may be pushed down without computing a part twice."""
    text, held = F.col(text_col), free_name(docs, "__lm_weights")

    def measures(h: Column) -> Column:
        n = F.size(h).cast("long")
        score = bound(_ngrams(h, rule.buckets), lambda g: F.aggregate(g, F.lit(0.0), lambda acc, b: acc + F.get(held, b)) / F.size(g))
        return F.struct(n.alias("n_words"), *[c.alias(k) for k, c in base_counts(text, h).items()], F.when(n > 0, score).alias("llr"))

    def verdict(m: Column) -> Column:
        failed = (m["n_words"] < LEAST_WORDS) | (100 * m["n_repeat_words"] > MOST_REPEATED * m["n_words"])
        kept = ~failed & (F.coalesce(m["llr"], F.lit(-1e9)) >= rule.threshold)
        return F.struct(*[m[k].alias(k) for k in ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "llr")], failed.alias("base_failed"), kept.alias("kept"))

    hashes = F.transform(words(text), lambda w: F.xxhash64(w))
    return docs.withColumn(held, weights.scalar()).select(*docs.columns, bound(bound(hashes, measures), verdict).alias(name))


def trusted_ids(labels: DataFrame) -> DataFrame:
    """Documents labelled good and not toxic."""
    return labels.where("quality = 1 AND toxic = 0").select("doc_id")


def digest(docs: DataFrame, labels: DataFrame, rule: RatioRule = RatioRule()) -> DataFrame:
    """The contract's columns, and the score."""
    names = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept", "llr")
    out = judged(docs.select("doc_id", "text"), fit(docs, trusted_ids(labels), rule), rule)
    return out.select("doc_id", *[F.col(f"__lm.{n}").alias(n) for n in names])


def kept_only(docs: DataFrame, labels: DataFrame, rule: RatioRule = RatioRule()) -> DataFrame:
    """``docs``, all columns, without those that the rules reject."""
    name = free_name(docs, "__lm")
    return judged(docs, fit(docs, trusted_ids(labels), rule), rule, name=name).where(f"{name}.kept").select(docs.columns)
