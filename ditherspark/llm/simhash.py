"""SimHash near-duplicates: 64-bit fingerprints of 3-word shingles, linked within 2 bits by pigeonring filtering.

The fingerprint is cut into ``segments`` pieces on a ring. If two fingerprints differ in at most t bits, then on some
start of the ring every chain of l consecutive pieces differs in at most floor(l*t/segments) bits in all. The chains
whose budget is zero must be equal, which gives the join key of a start: with 16 pieces and t=2 the first 7 pieces, 28
bits. Candidates that share a key go through the longer chains' budgets and then the full Hamming check, both as bit
arithmetic in generated code.

Equal fingerprints are one row here, so copies cost nothing. A key that many different fingerprints share is not joined
with itself: each of its members is dealt to its own value and to those one bit flip away among the bits outside the
key. Members that meet at one value differ in at most 2 bits, members within 2 bits always meet, and no more than 37
can meet, so this is exact and linear. Components come from large-star and small-star rounds over the links, each
written to the shared folder.

Null and empty texts, and texts of white space alone, have fingerprint zero and are linked like any other. A text of
one or two words is one shingle. Repeated rows share their fingerprint. An empty table gives an empty result. Columns
other than the id and the text are not read.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from ditherspark.llm import common
from ditherspark.llm.common import among, free_name, mapped, merged, row_hash, written

SEED, BITS = 42, 64
#: A key shared by more fingerprints than this takes the linear way instead of the join.
WIDE_KEY = 24
#: Edges from which a round's minima are stored.
STORED_FROM = 1_000_000


def fingerprint_of(text: str | None, shingle: int = 3) -> int:
    """The fingerprint of one text as an unsigned integer."""
    w = (text or "").encode().lower().split()
    if not w:
        return 0
    parts = [b" ".join(w)] if len(w) < shingle else list(map(b" ".join, zip(*(w[i:] for i in range(shingle)), strict=False)))
    h = xxhash.xxh64_intdigest
    return _majority(np.fromiter((h(s, SEED) for s in parts), np.uint64, len(parts)))


#: SPREAD[k][v]: bits of the byte v, each in its own 8-bit lane of an unsigned 64-bit number.
_SPREAD = np.array([sum(((v >> b) & 1) << (8 * b) for b in range(8)) for v in range(256)], np.uint64)


def _majority(hashes: np.ndarray) -> int:
    """Bits set in over half the hashes. Eight 8-bit counters share a word and are emptied every 255 hashes."""
    octets = hashes.view(np.uint8).reshape(-1, 8)
    n = len(hashes)
    if n <= 255:
        count = _SPREAD[octets].sum(axis=0, dtype=np.uint64).view(np.uint8)
    else:
        edges = np.arange(0, n, 255)
        count = np.add.reduceat(_SPREAD[octets], edges, axis=0).view(np.uint8).reshape(len(edges), 64).sum(axis=0, dtype=np.int64)
    return int(np.packbits(2 * count.astype(np.int64) > n, bitorder="little").view(np.uint64)[0])


def majorities(hashes: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The same for many texts at once: ``counts`` hashes each, none of them zero."""
    first = np.cumsum(counts) - counts
    parts = -(-counts // 255)
    inner = np.arange(parts.sum()) - np.repeat(np.cumsum(parts) - parts, parts)
    octets = _SPREAD[hashes.view(np.uint8).reshape(-1, 8)]
    lanes = np.add.reduceat(octets, np.repeat(first, parts) + 255 * inner, axis=0).view(np.uint8).reshape(-1, 64)
    ones = np.add.reduceat(lanes, np.cumsum(parts) - parts, axis=0, dtype=np.int64)
    return np.packbits(2 * ones > counts[:, None], axis=1, bitorder="little").view(np.uint64)[:, 0]


def fingerprints(docs: DataFrame, shingle: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, fp): the fingerprint as a signed long with the same bits."""

    def kernel():
        def step(batch):
            fps = np.fromiter((fingerprint_of(t.as_py(), shingle) for t in batch["text"]), np.uint64, batch.num_rows)
            return pa.RecordBatch.from_arrays([batch["id"], pa.array(fps.view(np.int64))], ["id", "fp"])

        return step

    src = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return mapped(src, kernel, f"id {dict(docs.dtypes)[id_col]}, fp bigint").withColumnRenamed("id", id_col)


def _mask(bits: int) -> int:
    """The low ``bits`` bits as a signed long."""
    m = (1 << bits) - 1
    return m - (1 << 64) if m >= 1 << 63 else m


def ring_keys(distinct: DataFrame, distance: int = 2, segments: int = 16) -> DataFrame:
    """(start, key, rest, fp): for each start of the ring the chain that must be equal, and the turned fingerprint."""
    width = BITS // segments
    if BITS % segments or segments <= distance:
        raise ValueError("segments must divide 64 and exceed the distance")
    exact = -(-segments // distance) - 1 if distance else segments
    turned = F.explode(F.sequence(F.lit(0), F.lit(segments - 1)))
    rows = distinct.select("fp", turned.alias("start")).withColumn("by", F.col("start") * width)
    left = F.expr("CASE WHEN by = 0 THEN fp ELSE shiftrightunsigned(fp, by) | shiftleft(fp, 64 - by) END")
    return rows.select("start", left.alias("ring"), "fp").withColumn("key", F.col("ring").bitwiseAND(F.lit(_mask(exact * width))))


def chain_holds(diff: Column, distance: int = 2, segments: int = 16) -> Column:
    """Every chain from the start stays within its proportional budget; the last chain is the Hamming check."""
    width, out = BITS // segments, F.lit(True)
    for n in range(1, segments + 1):
        budget = n * distance // segments
        if n == segments or (n + 1) * distance // segments != budget:  # a longer chain with this budget covers it
            out = out & (F.bit_count(diff.bitwiseAND(F.lit(_mask(n * width)))) <= budget)
    return out


def links(distinct: DataFrame, distance: int = 2, segments: int = 16, wide_key: int = WIDE_KEY) -> DataFrame:
    """(u, v) with u < v over different fingerprints: every pair in reach from narrow keys, stars that join the same
    fingerprints from wide ones."""
    keys = ring_keys(distinct, distance, segments)
    sizes = keys.groupBy("start", "key").agg(F.count("*").alias("n")).where("n > 1")
    shared = keys.join(merged(sizes), ["start", "key"])
    narrow = shared.where(F.col("n") <= wide_key)
    a = narrow.select("start", "key", F.col("ring").alias("ra"), F.col("fp").alias("u"))
    b = narrow.select("start", "key", F.col("ring").alias("rb"), F.col("fp").alias("v"))
    pairs = a.join(merged(b), ["start", "key"]).where(F.col("u") < F.col("v"))
    pairs = pairs.where(chain_holds(F.col("ra").bitwiseXOR(F.col("rb")), distance, segments)).select("u", "v")
    if distance != 2:
        raise ValueError("wide keys are resolved for a distance of 2")
    free = (-(-segments // distance) - 1) * (BITS // segments)
    flips = F.array(F.lit(0).cast("long"), *[F.lit((1 << i) - (1 << 64) if i == 63 else 1 << i) for i in range(free, 64)])
    dealt = shared.where(F.col("n") > wide_key).select("start", "fp", F.explode(F.transform(flips, lambda x: F.col("ring").bitwiseXOR(x))).alias("meet"))
    met = dealt.groupBy("start", "meet").agg(F.min("fp").alias("u"), F.collect_set("fp").alias("all")).where(F.size("all") > 1)
    stars = met.select("u", F.explode("all").alias("v")).where(F.col("u") < F.col("v"))
    return pairs.union(stars).distinct()


def components(edges: DataFrame, most: int = 60) -> DataFrame:
    """(node, root): the smallest node reachable, for every node of ``edges`` (u, v), by alternating star rounds. Where
    there are more edges than a task may well hold (``STORED_FROM``), minima are stored before they are joined back, so that
    a hub's edges can be split between tasks or meet a broadcast minimum."""
    edges = edges.select(F.greatest("u", "v").alias("a"), F.least("u", "v").alias("b")).where("a <> b").distinct()
    edges = written(edges, "links")
    rows, before = edges.count(), None
    for _ in range(most):
        kept = (lambda df, name: written(df, name, rows)) if rows > STORED_FROM else (lambda df, _: df)  # noqa: B023
        both = edges.union(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = kept(both.groupBy("a").agg(F.min("b").alias("m")).withColumn("m", F.least("a", "m")), "least")
        large = both.where("b > a").join(merged(least, rows), "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        large = kept(large, "large")
        least = kept(large.groupBy("a").agg(F.min("b").alias("m")), "least")
        small = large.join(merged(least, rows), "a").select(F.explode(F.array(F.struct("a", F.col("m").alias("b")), F.struct(F.col("b").alias("a"), F.col("m").alias("b")))).alias("e"))
        seen = Observation()
        after = small.select("e.*").where("a <> b").distinct().observe(seen, F.count(F.lit(1)).alias("n"), F.sum(F.hash("a", "b").cast("long")).alias("h"))
        edges = written(after, "links", rows)
        state = (seen.get["n"], seen.get["h"])
        if state == before or not state[0]:
            break
        rows, before = state[0], state
    else:
        raise RuntimeError("components did not settle")
    roots = edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return roots.union(edges.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())


def classes(docs: DataFrame, shingle: int = 3, distance: int = 2, segments: int = 16, wide_key: int = WIDE_KEY) -> tuple[DataFrame, DataFrame]:
    """((doc_id, fp) of every row, (fp, component_id) of every different fingerprint), both stored."""
    fps = written(fingerprints(docs, shingle), "fingerprints")
    distinct = written(fps.groupBy("fp").agg(F.min("doc_id").alias("least_id")), "distinct", fps.count())
    rows = distinct.count()
    found = components(links(distinct.select("fp"), distance, segments, wide_key))
    labelled = written(distinct.join(merged(found, rows), distinct.fp == found.node).select("fp", "root", "least_id"), "labelled")
    ids = written(labelled.groupBy("root").agg(F.min("least_id").alias("linked_id")), "ids")
    linked = labelled.join(merged(ids, rows), "root").select("fp", "linked_id")
    named = distinct.join(merged(linked, rows), "fp", "left").select("fp", F.coalesce("linked_id", "least_id").alias("component_id"))
    return fps, written(named, "classes", rows)


def near_duplicates(docs: DataFrame, shingle: int = 3, distance: int = 2, segments: int = 16, wide_key: int = WIDE_KEY) -> DataFrame:
    """(doc_id, fp, component_id): one row per row of ``docs`` with the smallest id reachable over links. Both sides of
    this last join are stored tables, so a fingerprint that many rows share can be split between tasks."""
    fps, named = classes(docs, shingle, distance, segments, wide_key)
    return fps.join(merged(named, named.count()), "fp").select("doc_id", "fp", "component_id")


def digest(docs: DataFrame) -> DataFrame:
    """The contract's columns."""
    return near_duplicates(docs).select("doc_id", F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"), "component_id")


def keep_least(docs: DataFrame, row: str, rows: DataFrame, roots: DataFrame, of: str) -> DataFrame:
    """``docs`` without the ``rows`` (``of``, doc_id, row: a hash of the row) that are not the least of their group;
    ``roots`` (``of``, root) joins groups. Identical rows are one. What goes is found among ids and hashes alone, so the
    documents are shuffled only where more than ``HELD_ROWS`` go."""
    ids = written(rows.groupBy(of, "doc_id", "row").agg(F.count("*").alias("times")), "ids")
    own = ids.groupBy(of).agg(F.min(F.struct("doc_id", "row")).alias("least"))
    kept = own.join(merged(roots, roots.count()), of, "left").groupBy(F.coalesce("root", of).alias("root")).agg(F.min("least").alias("least"))
    kept = written(kept.select("least.*"), "kept")
    few = merged(kept, kept.count())
    gone = written(ids.join(few, ["doc_id", "row"], "left_anti").select("doc_id", "row"), "gone")
    again = written(ids.where("times > 1").join(few, ["doc_id", "row"], "left_semi").select("doc_id", "row"), "again")
    out = without(docs, row, ids, gone.union(again))
    if again.isEmpty():
        return out
    return out.union(only(docs, row, again).dropDuplicates(["doc_id", row]).select(docs.columns))


def without(docs: DataFrame, row: str, ids: DataFrame, rows: DataFrame) -> DataFrame:
    """``docs`` without the ``rows`` (doc_id, row), which are some of the stored ``ids``. Up to ``HELD_ROWS`` of them, numbers
    tell them, if among ``ids`` these mean no other row; else documents and rows are merged."""
    marked, n = docs.withColumn(row, row_hash(docs)), rows.count()
    if n <= common.HELD_ROWS and ids.where(among(rows, "doc_id", "row")).count() == n:
        named = rows.withColumnRenamed("row", row)
        return marked.where(F.col("doc_id").isNull() | ~among(named, "doc_id", row)).select(docs.columns)
    return marked.join(merged(rows), (marked["doc_id"] == rows["doc_id"]) & (marked[row] == rows["row"]), "left_anti").select(docs.columns)


def only(docs: DataFrame, row: str, rows: DataFrame) -> DataFrame:
    """The ``rows`` (doc_id, row) of ``docs``, with their hash."""
    marked, named = docs.withColumn(row, row_hash(docs)), rows.withColumnRenamed("row", row)
    n = rows.count()
    near = marked.where(among(named, "doc_id", row)) if n <= common.HELD_ROWS else marked
    return near.join(merged(named, n), ["doc_id", row], "left_semi")


def one_of_each(docs: DataFrame, shingle: int = 3) -> DataFrame:
    """``docs``, all columns, with one row of each component: that with the smallest id, of rows with one id that with the
    smallest hash of all columns. Rows that repeat an id with another text are rows of their own, identical rows are one.
    Rows without an id can't be ordered by it and all stay."""
    row = free_name(docs, "lm_row")
    src = docs.select("doc_id", row_hash(docs).alias("row"), "text").where("doc_id IS NOT NULL")
    fps = written(fingerprints(src.withColumn("key", F.struct("doc_id", "row")), shingle, "key"), "fingerprints")
    distinct = written(fps.select("fp").distinct(), "distinct")
    roots = components(links(distinct)).withColumnRenamed("node", "fp")
    return keep_least(docs, row, fps.select("fp", "key.doc_id", "key.row"), roots, "fp")
