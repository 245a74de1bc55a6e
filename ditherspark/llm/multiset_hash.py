"""Document fingerprints by a homomorphic multiset hash of paragraphs.

Each paragraph is hashed to wide vectors, and a text's fingerprint is their sum, so it does not depend on order, and
inserting or deleting a paragraph adds or subtracts one vector. A fingerprint has three parts, each a sum modulo a power
of two: the number of paragraphs (2**32); 32 lanes of uniform 16-bit numbers (2**16), for equality; and 160 lanes of +1
or -1 (2**32, above any text's number of paragraphs). The inner product of two fingerprints' sign lanes, over the number
of lanes, estimates that of the two multisets' counts, so their cosine is the likeness, within some 0.08: two thirds
where a third of different paragraphs was replaced, whatever is repeated.

A paragraph is a line, and of a line with several sentences each sentence. One of more than ``LONG`` bytes is cut on by
content: after a blank whose four bytes before it hash to one of eight values in sixty-four, or in a run without blanks
of more than ``RUN`` bytes at a character whose bytes before it do. Such cuts move with the text, so what is put in or taken out changes the paragraphs it
touches and no others. No character is dropped but white space around paragraphs; blank ones don't count. Nulls count
as empty texts, whose fingerprint is zero; two texts without paragraphs are alike (1.0). Of two rows with one id, the one
with the lesser text comes first. The next document of a table's only row is that row. Ids are numbers, other types are
refused; null ids come last. An empty table gives an empty result. Columns other than the id and the text are not read.
"""

from __future__ import annotations

import hashlib
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import NullType, NumericType

from ditherspark.llm.common import SPACE_LUT, SPACES

UNIFORM, SIGNS = 32, 160
UNIFORM_MOD, SIGN_MOD, COUNT_MOD = 1 << 16, 1 << 32, 1 << 32
#: Bytes from which a paragraph is cut by content, bytes without a blank from which it is cut between characters, and
#: bytes of text that a range of ids is meant for.
LONG, RUN, RANGE_BYTES = 48, 64, 256 << 20
_STOP = np.zeros(256, bool)
_STOP[list(b".!?")] = True


@dataclass
class Fingerprint:
    """Sums of paragraph vectors. ``+`` and ``-`` join and take away multisets."""

    count: int
    uniform: np.ndarray
    signs: np.ndarray

    def __add__(self, other: Fingerprint) -> Fingerprint:
        return Fingerprint((self.count + other.count) % COUNT_MOD, (self.uniform + other.uniform) % UNIFORM_MOD, (self.signs + other.signs) % SIGN_MOD)

    def __sub__(self, other: Fingerprint) -> Fingerprint:
        return Fingerprint((self.count - other.count) % COUNT_MOD, (self.uniform - other.uniform) % UNIFORM_MOD, (self.signs - other.signs) % SIGN_MOD)

    def hex(self) -> str:
        """Fixed width, so equal fingerprints are equal strings."""
        return f"{self.count:08x}" + self.uniform.astype(">u2").tobytes().hex() + self.signs.astype(">u4").tobytes().hex()

    def likeness(self, other: Fingerprint) -> float:
        """Estimated cosine of the two multisets, 0 to 1; exactly 1 for equal fingerprints."""
        if self.count == other.count and (self.signs == other.signs).all() and (self.uniform == other.uniform).all():
            return 1.0
        a, b = (((x.signs + SIGN_MOD // 2) % SIGN_MOD - SIGN_MOD // 2).astype(np.float64) for x in (self, other))
        norm = float(a @ a) * float(b @ b)
        return min(1.0, max(0.0, float(a @ b) / norm**0.5)) if norm else 0.0


def empty() -> Fingerprint:
    return Fingerprint(0, np.zeros(UNIFORM, np.int64), np.zeros(SIGNS, np.int64))


def paragraphs(text: bytes) -> list[bytes]:
    """Parts that are hashed, without surrounding white space."""
    if len(text) <= LONG and b"\n" not in text:
        out = []
        for part in _sentences(text):
            if part := part.strip():
                out.append(part)
        return out
    b = np.frombuffer(text, np.uint8)
    n = len(b)
    blank = SPACE_LUT[b]
    hard = np.zeros(n + 1, bool)  # a part begins here: after a newline, or after blanks behind a sentence's end
    hard[0] = hard[n] = True
    hard[1:] |= b == 10
    hard[2:n] |= _STOP[b[:-2]] & blank[1:-1]
    mixed = np.zeros(n + 1, np.uint32)  # of the four bytes before each position
    for k in range(1, 5):
        mixed[k:] += b[: n + 1 - k].astype(np.uint32) * np.uint32((0x01000193, 0x9E3779B1, 0x85EBCA77, 0xC2B2AE3D)[k - 1])
    mixed = (mixed ^ (mixed >> np.uint32(15))) * np.uint32(0x2C1B3C6D)
    pick = (mixed >> np.uint32(24)) & np.uint32(63)
    soft = np.zeros(n + 1, bool)
    soft[1:-1] = blank[:-1] & ~blank[1:] & (np.concatenate([[63], pick[1:-2]]) < 8)
    edge = np.flatnonzero(np.concatenate([[True], blank, [True]]))  # runs without blanks
    far = np.flatnonzero(np.diff(edge) > RUN)
    if len(far):
        inside = np.zeros(n + 1, np.int32)
        np.add.at(inside, edge[far], 1)
        np.add.at(inside, np.minimum(edge[far + 1], n), -1)
        starts = np.concatenate([(b & 0xC0) != 0x80, [True]])
        soft |= (np.cumsum(inside) > 0) & starts & (pick < 2)
    at = np.flatnonzero(hard)
    long = np.repeat(np.diff(at) > LONG, np.diff(at))
    hard[:n] |= soft[:n] & long
    at = np.flatnonzero(hard).tolist()
    return [q for i, j in zip(at[:-1], at[1:], strict=True) if (q := text[i:j].strip())]


def _sentences(text: bytes) -> list[bytes]:
    """A short line cut after blanks behind sentence ends."""
    out, at = [], 0
    for i in range(2, len(text)):
        if text[i - 2] in b".!?" and text[i - 1] in SPACES:
            out.append(text[at:i])
            at = i
    return [*out, text[at:]]


def of_paragraphs(parts: list[bytes]) -> Fingerprint:
    """The fingerprint of a multiset of paragraphs."""
    if not parts:
        return empty()
    raw = np.frombuffer(b"".join([hashlib.blake2b(p).digest() for p in parts]), np.uint8).reshape(len(parts), 64)
    uniform = raw.view("<u2").sum(axis=0, dtype=np.int64) % UNIFORM_MOD
    ones = np.unpackbits(raw[:, : SIGNS // 8], axis=1).sum(axis=0, dtype=np.int64)
    return Fingerprint(len(parts) % COUNT_MOD, uniform, (2 * ones - len(parts)) % SIGN_MOD)


def fingerprint(text: str | None) -> Fingerprint:
    return of_paragraphs(paragraphs((text or "").encode()))


def edited(text: str, following: str) -> str:
    """``text`` with its last third replaced by as many characters of ``following``, or all it has."""
    k = len(text) // 3
    return text[: len(text) - k] + following[:k] if k else text


def with_following(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Rows (range, id, text, border), each range sorted by falling id within a partition, its last row the first one
    of the next range (``border``). Range limits are quantiles of the ids, a few numbers a partition; a border is one row
    a range, so what crosses ranges doesn't grow with the rows, and a text is shuffled once."""
    spark = docs.sparkSession
    src = docs.select(F.col(id_col).alias("id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    if not isinstance(src.schema["id"].dataType, (NumericType, NullType)):
        raise TypeError("documents are ordered by a number")
    size = src.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    n = max(1, int(spark.conf.get("spark.sql.shuffle.partitions")), -(-size // RANGE_BYTES))
    limits = sorted(set(src.select(F.col("id").cast("double").alias("x")).stat.approxQuantile("x", [i / n for i in range(1, n)], 0.2 / n))) if n > 1 else []

    stride = max(1, int(len(limits) ** 0.5))

    def range_of(col: Column) -> Column:
        """How many limits lie below the id, found in two steps of about the square root of their number."""
        below = lambda some: F.size(F.filter(some, lambda x: x < col.cast("double")))
        base = F.greatest(below(F.lit(limits[::stride])) - 1, F.lit(0)) * stride
        return F.coalesce(base + below(F.slice(F.lit(limits), base + 1, stride)), F.lit(0)).cast("int") if limits else F.lit(0)

    rows = src.withColumn("range", range_of(F.col("id")))
    heads = rows.groupBy("range").agg(F.max("id").alias("id")).orderBy("range").collect()  # a row a range
    to = {}
    for at, r in enumerate(heads):  # each range's first row also ends the range above; the topmost one's ends the lowest
        to[r["range"]] = heads[(at + 1) % len(heads)]["range"]
    if not heads:
        return rows.withColumn("border", F.lit(False))
    kind, slots = src.schema["id"].dataType, max(to) + 1
    top = {r["range"]: r["id"] for r in heads}
    first = F.array(*[F.lit(top.get(i)).cast(kind) for i in range(slots)])
    above = F.array(*[F.lit(to.get(i)).cast("int") for i in range(slots)])
    borders = rows.where(F.col("id").eqNullSafe(F.get(first, F.col("range")))).groupBy("range", "id").agg(F.min("text").alias("text"))
    borders = borders.select(F.get(above, F.col("range")).alias("range"), "id", "text", F.lit(True).alias("border"))
    every = rows.select("range", "id", "text", F.lit(False).alias("border")).union(borders)
    key = slot_keys(spark, slots)
    return every.repartition(slots, F.get(F.array(*map(F.lit, key)), F.col("range"))).sortWithinPartitions("range", "border", F.desc("id"), "text")


def slot_keys(spark: SparkSession, slots: int) -> list[int]:
    """For each of ``slots`` partitions a number that hash partitioning sends there, so that no two ranges meet."""
    found: dict[int, int] = {}
    tries = 16 * slots + 64
    while len(found) < slots:
        rows = spark.range(tries).select(F.col("id").cast("int").alias("k"), F.pmod(F.hash(F.col("id").cast("int")), F.lit(slots)).alias("to"))
        found = {r["to"]: r["k"] for r in rows.groupBy("to").agg(F.min("k").alias("k")).collect()}  # a row a range
        tries *= 4
    return [found[i] for i in range(slots)]


def digest(docs: DataFrame) -> DataFrame:
    """The contract's columns: each text, its edited text and the next document by falling id."""

    def pair(row, following) -> tuple:
        ident, text, own = row
        new = edited(text, following[1])
        changed = fingerprint(new)
        return (ident, len(text), hashlib.sha256(new.encode()).hexdigest(), own.hex(), changed.hex(), own.likeness(changed), own.likeness(following[2]))

    names = ["doc_id", "n_chars", "edited_sha256", "fingerprint", "edited_fingerprint", "near_edited", "near_next"]
    kind = docs.schema["doc_id"].dataType

    def run(batches):
        held, at = None, None
        for batch in batches:
            out, ids, texts, ranges, borders = [], *(batch[c].to_pylist() for c in ("id", "text", "range", "border"))
            for ident, text, rng, border in zip(ids, texts, ranges, borders, strict=True):
                row = (ident, text, fingerprint(text))
                if held is not None and rng == at:
                    out.append(pair(held, row))
                held, at = (None if border else row), rng
            cols = list(zip(*out, strict=True)) if out else [[]] * 7
            types = [batch["id"].type, pa.int64(), pa.string(), pa.string(), pa.string(), pa.float64(), pa.float64()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(cols, types, strict=True)], names)

    schema = f"doc_id {kind.simpleString()}, n_chars bigint, edited_sha256 string, fingerprint string, edited_fingerprint string, near_edited double, near_next double"
    return with_following(docs).mapInArrow(run, schema)
