"""Operator 2's stage for near copies: exact Jaccard similarity of shingle sets of ``least`` or more, never less.

Each text is the set of its shingles' 64-bit hashes, with operator 2's majority fingerprint of that set. Two sources
give candidates: fingerprints that pigeonring chains link, and shared rare shingles. For the latter all sets are put in
one order, common shingles last, so two sets of the required similarity share one of the first
n - ceil(least*n) + 1 shingles of each. Such a pair goes on if the sizes, the places of the shingle and, for sets of
``FROM_SIZE`` shingles or more, the distance of the fingerprints (``NEAR_BITS``) still allow the similarity; then the
whole sets are compared, which alone decides. At similarity 0.8 fingerprints differ in 10 of 64 bits with a deviation of
3, so a limit of 24 loses a pair in some 10^7.

How common a shingle is comes from a sample (``sample_docs``). It only orders the keys: the result is the same for
any sample. A key that more than ``wide_key`` sets share is not joined with itself: its members are compared with
its centre, the member whose shingles are the commonest, and those that are then in another component than most
members of the key with all of them. Where these would be many pairs, further centres are taken first, so that what is
left falls into few components. So every pair that is left out is already connected.

Equal sets are one row here, and a task hands on each set once, so copies cost nothing. Texts without words have the
empty set and are alike. Two sets count as equal if their sizes and the sums of their hashes modulo 2**64 are.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ditherspark.llm import common, simhash
from ditherspark.llm.common import NARROW_BYTES, among, buffers, free_name, mapped, merged, released, row_hash, sliced, words, written

SAMPLE_DOCS, MOST_COMMON = 8_000, 200_000
#: Fingerprint bits in which sets of the similarity may differ, from what size; sets that a task remembers to have handed
#: on; sets to compare whose numbers are broadcast (24 bytes each).
NEAR_BITS, FROM_SIZE, SEEN_SETS, BROADCAST_SETS = 24, 32, 1_000_000, 400_000
#: Pairs of a last join, beyond which further centres are tried first, and how many times.
MANY_PAIRS, MORE_CENTRES = 20_000_000, 6
_ODD = np.uint64(0x9E3779B97F4A7C15)
_MIX = np.uint64(0xD6E8FEB86659FD93)


def _mixed(h: np.ndarray) -> np.ndarray:
    h = (h ^ (h >> np.uint64(32))) * _MIX
    return h ^ (h >> np.uint64(29))


def shingle_hashes(texts: pa.Array, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all shingles of all texts, repeats included, and the row of each. Fewer words are one shingle."""
    found, n = words(*buffers(texts))
    coded = found.dictionary_encode()
    own = np.fromiter(map(xxhash.xxh64_intdigest, coded.dictionary.to_pylist()), np.uint64, len(coded.dictionary))
    word = own[coded.indices.to_numpy(zero_copy_only=False)] if len(own) else np.zeros(0, np.uint64)
    end = np.cumsum(n)
    many = np.where(n > 0, np.maximum(n - shingle + 1, 1), 0)
    row = np.repeat(np.arange(len(n)), many)
    if not len(row):
        return np.zeros(0, np.uint64), row
    at = np.arange(len(row)) - np.repeat(np.cumsum(many) - many, many) + (end - n)[row]
    wide, rolled = np.concatenate([word, np.zeros(shingle, np.uint64)]), np.zeros(len(word), np.uint64)
    for j in range(shingle):
        rolled = rolled * _ODD + wide[j : j + len(word)]
    out = rolled[at]
    short = np.flatnonzero((n > 0) & (n < shingle))  # their one shingle must not reach into the next text
    begin, total = (end - n)[short], np.zeros(len(short), np.uint64)
    for j in range(shingle - 1):
        total = np.where(j < n[short], total * _ODD + wide[begin + j], total)
    out[np.searchsorted(row, short)] = total
    return _mixed(out), row


def common_shingles(docs: DataFrame, shingle: int, sample_docs: int = SAMPLE_DOCS, most: int = MOST_COMMON) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that repeat in a sample of the texts, ascending, and in how many of its texts each is."""

    def kernel():
        def step(batch):
            h, row = shingle_hashes(batch["text"], shingle)
            order = np.lexsort((row, h))
            h, row = h[order], row[order]
            new = np.ones(len(h), bool)
            new[1:] = (h[1:] != h[:-1]) | (row[1:] != row[:-1])
            grams, n = np.unique(h[new], return_counts=True)
            return pa.RecordBatch.from_arrays([pa.array(grams.view(np.int64)), pa.array(n)], ["gram", "n"])

        return step

    share = min(1.0, sample_docs / max(1, docs.count()))
    sample = docs.where(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < share * (1 << 20)).select("text")
    found = mapped(sample, kernel, "gram bigint, n bigint").groupBy("gram").agg(F.sum("n").alias("n")).where("n > 2").orderBy(F.desc("n"), "gram").limit(most).toArrow()
    grams = found["gram"].to_numpy().view(np.uint64)
    order = np.argsort(grams)
    return grams[order], found["n"].to_numpy()[order]


def _by_row(flags: np.ndarray, row: np.ndarray, rows: int) -> np.ndarray:
    return np.bincount(row, flags, rows).astype(np.int64)


def sets(docs: DataFrame, shingle: int, least: float, frequent: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """(doc_id, row, fp, sid, n, weight, prefix): the set's fingerprint, number, size, how common its shingles are, and its
    keys in the common order, which a task gives once for each set."""
    held = docs.sparkSession.sparkContext.broadcast(frequent)
    lists = pa.list_(pa.int64())

    def run(batches):
        grams, count = held.value
        seen: set[int] = set()
        for batch in batches:
            released()
            for part in sliced(batch, budget=NARROW_BYTES):
                yield one(part, grams, count, seen)
        seen.clear()
        released()

    def one(batch, grams, count, seen):
        rows = batch.num_rows
        h, row = shingle_hashes(batch["text"], shingle)
        rank = np.zeros(len(h), np.int64)  # 0: not common
        if len(grams) and len(h):
            at = np.minimum(np.searchsorted(grams, h), len(grams) - 1)
            rank = np.where(grams[at] == h, count[at], 0)
        order = np.lexsort((h, (row << 32) + rank))
        h, row, rank = h[order], row[order], rank[order]
        new = np.ones(len(h), bool)
        new[1:] = (h[1:] != h[:-1]) | (row[1:] != row[:-1])
        h, row, rank = h[new], row[new], rank[new]
        n = np.bincount(row, minlength=rows)
        edge = np.concatenate([[0], np.cumsum(n)])
        full = np.flatnonzero(n)
        sid, fp = np.zeros(rows, np.uint64), np.zeros(rows, np.uint64)
        if len(full):
            sid[full] = _mixed(np.add.reduceat(h, edge[full]) + n[full].astype(np.uint64) * _ODD)
            fp[full] = simhash.majorities(h, n[full])
        weight = _by_row(rank, row, rows) / np.maximum(1, n)
        first = np.where(n > 0, n - np.ceil(least * n - 1e-9).astype(np.int64) + 1, 0)
        here = np.zeros(rows, bool)
        for i, s in enumerate(sid.tolist()):
            if s not in seen:
                if len(seen) >= SEEN_SETS:
                    seen.clear()
                seen.add(s)
                here[i] = True
        signed = h.view(np.int64)
        off = lambda size: pa.array(np.concatenate([[0], np.cumsum(size)]).astype(np.int32))
        keep = here[row]
        inner = np.arange(len(h)) - edge[row]
        prefix = pa.ListArray.from_arrays(off(np.where(here, first, 0)), pa.array(signed[keep & (inner < first[row])]))
        cols = [batch["doc_id"], batch["row"], pa.array(fp.view(np.int64)), pa.array(sid.view(np.int64)), pa.array(n.astype(np.int32)), pa.array(weight), prefix.cast(lists)]
        return pa.RecordBatch.from_arrays(cols, ["doc_id", "row", "fp", "sid", "n", "weight", "prefix"])

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "row", "text").mapInArrow(run, f"doc_id {kind}, row bigint, fp bigint, sid bigint, n int, weight double, prefix array<bigint>")


def _allowed(least: float) -> str:
    """Sizes and places of the common key, and fingerprints: if the key is the first shingle that both sets have, what
    both can share is it and what follows it."""
    needed = f"{least} / (1 + {least}) * (a_n + b_n) - 1e-6"
    return f"a_sid <> b_sid AND least(a_n - a_at, b_n - b_at) >= {needed} AND (least(a_n, b_n) < {FROM_SIZE} OR bit_count(a_fp ^ b_fp) <= {NEAR_BITS})"


def _paired(a: DataFrame, b: DataFrame, least: float) -> DataFrame:
    """The rows of ``a`` and ``b`` that share a key and may be alike."""
    a = a.select("key", *[F.col(c).alias(f"a_{c}") for c in a.columns if c != "key"])
    b = b.select("key", *[F.col(c).alias(f"b_{c}") for c in b.columns if c != "key"])
    return a.join(merged(b), "key").where(_allowed(least))


def _ordered(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("a_sid", "b_sid").alias("u"), F.greatest("a_sid", "b_sid").alias("v"))


def asked_texts(texts: DataFrame, asked: DataFrame) -> DataFrame:
    """(sid, text) of the ``asked`` sets (sid, doc_id, row), from one row each (and rows that are identical to it). Other
    texts are not shuffled, up to ``HELD_ROWS`` sets."""
    rows = asked.count()
    if rows <= BROADCAST_SETS:
        asked = F.broadcast(asked)
    else:
        asked, texts = merged(asked), texts.where(among(asked, "doc_id", "row")) if rows <= common.HELD_ROWS else texts
    return texts.join(asked, ["doc_id", "row"]).select("sid", "text")


def _own_sets(texts: pa.Array, shingle: int) -> tuple[np.ndarray, np.ndarray]:
    """The different shingle hashes of each text, and the row of each."""
    h, row = shingle_hashes(texts, shingle)
    order = np.lexsort((h, row))
    h, row = h[order], row[order]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (row[1:] != row[:-1])
    return h[new], row[new]


def _compared(both: DataFrame, shingle: int, least: float) -> DataFrame:
    """The (u, v) of ``both`` (u, v, tu, tv: texts) whose whole sets have the similarity."""

    def one(batch):
        (hu, ru), (hv, rv) = _own_sets(batch["tu"], shingle), _own_sets(batch["tv"], shingle)
        h, row = np.concatenate([hu, hv]), np.concatenate([ru, rv])
        order = np.lexsort((h, row))
        h, row = h[order], row[order]
        twice = (h[1:] == h[:-1]) & (row[1:] == row[:-1])
        shared, total = np.bincount(row[1:][twice], minlength=batch.num_rows), np.bincount(row, minlength=batch.num_rows)
        return batch.select(["u", "v"]).filter(pa.array(shared >= least * (total - shared) - 1e-6))

    def run(batches):
        for batch in batches:
            released()
            for part in sliced(batch, "tu", NARROW_BYTES):
                yield from map(one, sliced(part, "tv", NARROW_BYTES))
        released()

    return both.select("u", "v", "tu", "tv").mapInArrow(run, "u bigint, v bigint")


def alike(pairs: DataFrame, texts: DataFrame, own: DataFrame, shingle: int, least: float) -> DataFrame:
    """The (u, v) of ``pairs`` whose whole sets have the similarity, stored. Texts move to their pairs and sets are made
    there, as words compress and hashes don't."""
    pairs = written(pairs.distinct(), "candidates")
    asked = written(pairs.select(F.explode(F.array("u", "v")).alias("sid")).distinct().join(merged(own.select("sid", "doc_id", "row"), own.count()), "sid"), "asked")
    found = written(asked_texts(texts, asked), "texts")
    side = lambda sid, text: merged(found.select(F.col("sid").alias(sid), F.col("text").alias(text)))
    both = pairs.join(side("u", "tu"), "u").join(side("v", "tv"), "v")
    return written(_compared(both, shingle, least).distinct(), "alike")


def _crowd(placed: DataFrame, roots: DataFrame) -> tuple[DataFrame, DataFrame, int]:
    """(members of wide keys with their present component, those outside their key's main component, pairs left)."""
    now = written(placed.drop("root").join(merged(roots.withColumnRenamed("node", "sid"), roots.count()), "sid", "left").withColumn("root", F.coalesce("root", "sid")), "placed")
    most = now.groupBy("key", "root").agg(F.count("*").alias("c")).groupBy("key").agg(F.max_by("root", F.struct("c", "root")).alias("main"), F.sum("c").alias("all"))
    rest = written(now.join(merged(most), "key").where("root <> main AND NOT done").drop("main", "done"), "rest")
    return now, rest, int(rest.agg(F.sum("all")).first()[0] or 0)


def shared_keys(whole: DataFrame, own: DataFrame) -> DataFrame:
    """(key, sid, n, at, fp, weight, many, centre, b_...: the centre's numbers) of keys that several sets have. Only keys and sets' numbers are shuffled
    for all rows, first as the least and largest hash of a set's number of each key; the rest is joined to what is left."""
    keys = whole.select("sid", "n", F.posexplode("prefix").alias("at", "key")).select("key", "sid", (F.shiftleft(F.col("at").cast("long"), 32) + F.col("n")).alias("place"))
    short = F.hash("sid")  # 32 bits tell the sets of one key apart
    several = keys.groupBy("key").agg(F.min(short).alias("lo"), F.max(short).alias("hi")).where("lo <> hi").select("key")
    left = keys.join(merged(several), "key").distinct()
    about = left.join(merged(own.select("sid", "fp", "weight"), own.count()), "sid")
    about = about.select("key", "sid", F.col("place").bitwiseAND(F.lit((1 << 32) - 1)).cast("int").alias("n"), F.shiftright("place", 32).cast("int").alias("at"), "fp", "weight")
    about = written(about, "about")
    sizes = written(about.groupBy("key").agg(F.count("*").alias("many"), F.max(F.struct("weight", "sid", "n", "at", "fp")).alias("c")), "sizes")
    sizes = sizes.select("key", "many", F.col("c.sid").alias("centre"), *[F.col(f"c.{x}").alias(f"b_{x}") for x in ("sid", "n", "at", "fp")])
    return written(about.join(merged(sizes), "key"), "shared")


def links(whole: DataFrame, texts: DataFrame, own: DataFrame, shingle: int, least: float, wide_key: int = simhash.WIDE_KEY) -> DataFrame:
    """(node, root) over the sets of ``whole`` that have a similar one."""
    shared = shared_keys(whole, own)
    plain = ["key", "sid", "n", "at", "fp"]
    narrow = shared.where(F.col("many") <= wide_key).select(plain)
    wide = shared.where(F.col("many") > wide_key)
    found = _ordered(_paired(narrow, narrow, least).where("a_sid < b_sid"))
    stars = _ordered(wide.select(*[F.col(x).alias(f"a_{x}") for x in ("sid", "n", "at", "fp")], "b_sid", "b_n", "b_at", "b_fp").where(_allowed(least)))
    # operator 2's links, between one set of each fingerprint, and from it to the others of the fingerprint
    of = own.where("n > 0").groupBy("fp").agg(F.min("sid").alias("one"), F.max("sid").alias("last"))
    near = simhash.links(of.select("fp"))
    rows = own.count()
    near = near.join(merged(of.select(F.col("fp").alias("u"), F.col("one").alias("a_sid")), rows), "u").join(merged(of.select(F.col("fp").alias("v"), F.col("one").alias("b_sid")), rows), "v")
    same = own.where("n > 0").select("fp", "sid").join(merged(of.where("one <> last"), rows), "fp").where("sid <> one").select(F.col("sid").alias("a_sid"), F.col("one").alias("b_sid"))
    edges = alike(found.union(stars).union(_ordered(near)).union(_ordered(same)), texts, own, shingle, least)
    roots = written(simhash.components(edges), "roots")
    if wide.isEmpty():
        return roots
    placed = wide.select(*plain, "weight", F.col("sid").alias("root"), (F.col("sid") == F.col("centre")).alias("done"))
    for _ in range(MORE_CENTRES):
        placed, rest, pairs = _crowd(placed, roots)
        if not pairs:
            return roots
        if pairs <= MANY_PAIRS:
            break
        centres = written(rest.groupBy("key").agg(F.max(F.struct("weight", "sid", "n", "at", "fp", "root")).alias("c")).select("key", "c.*"), "centres")
        more = alike(_ordered(_paired(centres.drop("weight"), placed.drop("weight", "done"), least).where("a_root <> b_root")), texts, own, shingle, least)
        placed = placed.join(merged(centres.select("key", "sid", F.lit(True).alias("was"))), ["key", "sid"], "left").withColumn("done", F.col("done") | F.coalesce("was", F.lit(False))).drop("was")
        edges = edges.union(more)
        roots = written(simhash.components(edges), "roots")
    else:
        placed, rest, pairs = _crowd(placed, roots)
    more = alike(_ordered(_paired(rest.drop("weight", "all"), placed.drop("weight", "done"), least).where("a_root <> b_root")), texts, own, shingle, least)
    return roots if more.isEmpty() else simhash.components(edges.union(more))


def one_of_each(docs: DataFrame, shingle: int = 5, least: float = 0.8, wide_key: int = simhash.WIDE_KEY) -> DataFrame:
    """``docs``, all columns, with one row of each group that is connected by similarities of ``least`` or more: that with
    the smallest id, of rows with one id that with the smallest hash of all columns. Rows that repeat an id with another
    text are rows of their own. Rows without an id can't be ordered by it and all stay. Texts are not shuffled where the
    rows that go are few enough to be broadcast."""
    row = free_name(docs, "lm_row")
    src = docs.select("doc_id", row_hash(docs).alias("row"), F.col("text").cast("string").alias("text")).where("doc_id IS NOT NULL")
    whole = written(sets(src, shingle, least, common_shingles(src, shingle)), "sets")
    own = written(whole.groupBy("sid").agg(F.min(F.struct("doc_id", "row")).alias("one"), F.first("fp").alias("fp"), F.first("n").alias("n"), F.first("weight").alias("weight")).select("sid", "one.*", "fp", "n", "weight"), "own")
    roots = links(whole, src, own, shingle, least, wide_key).withColumnRenamed("node", "sid")
    return simhash.keep_least(docs, row, whole.select("sid", "doc_id", "row"), roots, "sid")
