"""Token counts by a map-side two-tier lookup; no pre-token is shuffled.

Tier one is a compact hash table of frequent pre-tokens and their token counts, broadcast as flat buffers: an open
table of entry numbers, the entries' bytes and their counts. A pre-token is in it only if its bytes are equal. Tier two
is each worker's own cache, which holds what the table lacks and starts anew when it is full. Both only save time: a
count never depends on them.

What is frequent is found by Misra-Gries summaries: a task keeps at most ``table_size`` candidates over all its texts,
and summaries are merged in a tree, ``FAN_IN`` at a time, so what moves is bounded by the number of tasks and what the
driver gets by the table. A pre-token that is more than one in ``table_size`` of all is surely in the table. Pre-tokens of
more than ``LONGEST`` bytes enter neither tier.

Nulls count as empty texts, which have no bytes and no tokens. Rows are independent, so repeated rows and empty tables
need no rule. Columns other than the id and the text are not read.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ditherspark.llm.common import buffers, mapped, sliced
from ditherspark.llm.pretoken import CACHE_ENTRIES, LONGEST, mark_pieces, per_text

#: Entries of the broadcast table, and summaries that one merging task takes.
TABLE_SIZE, FAN_IN = 1 << 14, 32


class PieceCounts:
    """Token counts of pre-tokens under a sentencepiece model, and the worker's cache of them."""

    def __init__(self, path: str):
        import sentencepiece

        self.model = sentencepiece.SentencePieceProcessor(model_file=path)
        m = self.model
        inner = any("▁" in m.id_to_piece(i).lstrip("▁") for i in range(m.vocab_size()))
        begins = [len(m.encode(t)) for t in ("a", " a", "a ")] == [1, len(m.encode("  a")) - len(m.encode("a")) + 1, 2]
        self.local = not inner and m.encode("a", out_type=str) == ["▁a"] and begins
        self.space = len(m.encode("a ")) - len(m.encode("a"))
        self.cache: dict[bytes, int] = {}

    def count(self, pieces: list[bytes]) -> list[int]:
        """Counts of pieces that begin with a space, which stands for the mark that the model puts first itself."""
        ids = self.model.encode([p[1:].decode() for p in pieces], num_threads=1)
        return [len(i) if len(p) > 1 else self.space for p, i in zip(pieces, ids, strict=True)]

    def cached(self, pieces: list[bytes]) -> np.ndarray:
        """The same through the cache, which keeps no long piece."""
        missing = [p for p in pieces if p not in self.cache]
        if len(self.cache) + len(missing) > CACHE_ENTRIES:
            self.cache.clear()
            missing = pieces
        new = dict(zip(missing, self.count(missing), strict=True))
        out = np.fromiter((new[p] if p in new else self.cache[p] for p in pieces), np.int64, len(pieces))
        self.cache.update((p, n) for p, n in new.items() if len(p) <= LONGEST)
        return out


@lru_cache(maxsize=2)
def worker_counts(path: str) -> PieceCounts:
    """The model of a Python worker, whose cache serves all the tasks it runs."""
    return PieceCounts(path)


def _trimmed(pieces: pa.Array, counts: np.ndarray, size: int) -> tuple[pa.Array, np.ndarray]:
    """A summary of at most ``size`` entries: all counts less the next largest, which is what each may be short of."""
    if len(counts) > size:
        counts = counts - np.partition(counts, len(counts) - size - 1)[len(counts) - size - 1]
    keep = np.flatnonzero(counts > 0)
    return pieces.take(pa.array(keep)), counts[keep]


def _united(pieces: list[pa.Array], counts: list[np.ndarray]) -> tuple[pa.Array, np.ndarray]:
    table = pa.table({"p": pa.concat_arrays(pieces), "n": np.concatenate(counts)}).group_by("p").aggregate([("n", "sum")])
    return table["p"].combine_chunks(), table["n_sum"].to_numpy()


class Summary:
    """A Misra-Gries summary of a stream of pre-tokens."""

    def __init__(self, size: int):
        self.size, self.pieces, self.counts = size, [pa.array([], pa.large_binary())], [np.zeros(0, np.int64)]

    def add(self, pieces: pa.Array, counts: np.ndarray) -> None:
        self.pieces.append(pieces)
        self.counts.append(counts)
        if sum(map(len, self.counts)) > 8 * self.size:
            self.trim()

    def trim(self) -> tuple[pa.Array, np.ndarray]:
        p, n = _trimmed(*_united(self.pieces, self.counts), self.size)
        self.pieces, self.counts = [p], [n]
        return p, n

    def batch(self) -> pa.RecordBatch:
        p, n = self.trim()
        listed = lambda a: pa.LargeListArray.from_arrays([0, len(a)], a).cast(pa.list_(a.type))
        return pa.RecordBatch.from_arrays([listed(p.cast(pa.binary())), listed(pa.array(n))], ["pieces", "counts"])


_SUMMARY = "pieces array<binary>, counts array<bigint>"


def frequent(docs: DataFrame, table_size: int = TABLE_SIZE) -> list[bytes]:
    """The most frequent pre-tokens over all texts (text), commonest first."""

    def observe(batches):
        own = Summary(table_size)
        for batch in batches:
            for part in sliced(batch):
                pieces, _ = mark_pieces(*buffers(part["text"]))
                seen = pieces.value_counts()
                short = pc.less_equal(pc.binary_length(seen.field("values")), LONGEST)
                seen = seen.filter(short)
                own.add(seen.field("values").cast(pa.large_binary()), seen.field("counts").to_numpy())
        yield own.batch()

    def merge(batches):
        own = Summary(table_size)
        for batch in batches:
            for p, n in zip(batch["pieces"], batch["counts"], strict=True):
                own.add(p.values.cast(pa.large_binary()), n.values.to_numpy())
        yield own.batch()

    level = docs.select("text").mapInArrow(observe, _SUMMARY)
    parts = int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    while parts > 1:
        parts = -(-parts // FAN_IN)
        level = level.repartition(parts).mapInArrow(merge, _SUMMARY)
    rows = level.collect()  # one summary
    found = [(-n, bytes(p)) for r in rows for p, n in zip(r.pieces, r.counts, strict=True)]
    return [p for _, p in sorted(found)[:table_size]]


class Table:
    """An open hash table over flat buffers: ``slots`` has entry numbers or -1, at most half of it filled."""

    def __init__(self, slots: np.ndarray, hashes: np.ndarray, entries: pa.Array, lens: np.ndarray):
        self.slots, self.hashes, self.entries, self.lens = slots, hashes, entries, lens

    @staticmethod
    def build(keys: list[bytes], lens: list[int]) -> Table:
        hashes = np.fromiter(map(xxhash.xxh64_intdigest, keys), np.uint64, len(keys))
        slots = np.full(1 << max(4, (2 * len(keys)).bit_length()), -1, np.int32)
        mask = len(slots) - 1
        for i, h in enumerate(hashes.tolist()):
            at = h & mask
            while slots[at] >= 0:
                at = (at + 1) & mask
            slots[at] = i
        return Table(slots, hashes, pa.array(keys, pa.large_binary()), np.array(lens, np.int64))

    def packed(self) -> tuple[bytes, bytes, bytes, bytes, bytes]:
        ends = np.cumsum([0, *pc.binary_length(self.entries).to_pylist()], dtype=np.int64)
        return self.slots.tobytes(), self.hashes.tobytes(), b"".join(self.entries.to_pylist()), ends.tobytes(), self.lens.tobytes()

    @staticmethod
    def of(packed) -> Table:
        slots, hashes, blob, ends, lens = packed
        entries = pa.Array.from_buffers(pa.large_binary(), len(lens) // 8, [None, pa.py_buffer(ends), pa.py_buffer(blob)])
        return Table(np.frombuffer(slots, np.int32), np.frombuffer(hashes, np.uint64), entries, np.frombuffer(lens, np.int64))

    def find(self, pieces: pa.Array) -> np.ndarray:
        """Entry numbers of ``pieces``, -1 for those that the table lacks."""
        out = np.full(len(pieces), -1, np.int64)
        if not len(self.lens) or not len(pieces):
            return out
        h = np.fromiter(map(xxhash.xxh64_intdigest, pieces.to_pylist()), np.uint64, len(pieces))
        mask = np.uint64(len(self.slots) - 1)
        at, open_ = (h & mask).astype(np.int64), np.arange(len(pieces))
        while len(open_):
            entry = self.slots[at[open_]]
            hit = (entry >= 0) & (self.hashes[np.maximum(entry, 0)] == h[open_])
            out[open_[hit]] = entry[hit]
            open_ = open_[(entry >= 0) & ~hit]
            at[open_] = (at[open_] + 1) & int(mask)
        held = np.flatnonzero(out >= 0)
        equal = pc.equal(self.entries.take(pa.array(out[held])), pieces.take(pa.array(held)).cast(pa.large_binary()))
        out[held[~equal.to_numpy(zero_copy_only=False)]] = -1
        return out


def count_tokens(docs: DataFrame, model_path: str, table_size: int = TABLE_SIZE, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_bytes, n_tokens) for every row."""
    src = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    counts = PieceCounts(model_path)
    if not counts.local:
        raise ValueError("this model's pieces cross spaces")
    keys = frequent(src, table_size)
    held = docs.sparkSession.sparkContext.broadcast(Table.build(keys, counts.count(keys)).packed())

    def kernel():
        table, model = Table.of(held.value), worker_counts(model_path)

        def step(batch):
            data, off = buffers(batch["text"])
            pieces, per = mark_pieces(data, off)
            coded = pieces.dictionary_encode()
            at = table.find(coded.dictionary)
            out = np.zeros(len(at), np.int64)
            out[at >= 0] = table.lens[at[at >= 0]]
            rare = np.flatnonzero(at < 0)
            out[rare] = model.cached(coded.dictionary.take(pa.array(rare)).to_pylist())
            code = coded.indices.to_numpy(zero_copy_only=False)
            return pa.RecordBatch.from_arrays([batch["id"], pa.array(np.diff(off)), pa.array(per_text(out[code], per))], ["id", "n_bytes", "n_tokens"])

        return step

    out = mapped(src, kernel, f"id {docs.schema[id_col].dataType.simpleString()}, n_bytes bigint, n_tokens bigint")
    return out.withColumnRenamed("id", id_col)


def digest(docs: DataFrame, model_path: str, limit: int = 4096) -> DataFrame:
    """The contract's columns."""
    return count_tokens(docs, model_path).withColumn("over_limit", F.col("n_tokens") > limit)
