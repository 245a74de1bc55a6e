"""LM scoring by an Elias-Fano n-gram trie in memory-mapped levels.

Words are known by 64-bit hashes. Level one is the rising sequence of the hashes of all training words: the position is
the word's id, and its count stands beside it. Level two holds, for each word, the words that follow it. The context
chooses the shard, so its successors lie together; only a context of more than ``SPLIT_TOKENS`` tokens is dealt to
several, by the word that follows. In a shard the contexts' ids rise, a monotone pointer sequence gives where each one's
successors begin, and these are stored as the context's place times the vocabulary plus the word's id, which rises over
the whole level. A bigram is found by looking up its context, reading the two pointers, and a successor search from the
context's base between them, once for each different pair of a slice of texts. Beside each bigram stands its smoothed
log10 probability, quantised to one of 256 levels. Probabilities are interpolated with a Dirichlet prior on the next
lower order: (c(v,w) + strength * p(w)) / (c(v) + strength), p(w) = (c(w) + 0.5) / (N + 0.5 (V + 1)); what a bigram lacks
is backed off with weight strength / (c(v) + strength). A text is a chain that begins and ends with the end token.

Levels are built in shards whose number follows the bytes and the tokens, each about the same size whatever the words'
frequencies, as counts are summed in each task first. Tasks write shard files into the shared folder (a task run again
writes the same bytes) and score texts by mapping them, once a worker; where the folder is not a mounted one, a worker
copies a shard to a local file that is unlinked as soon as it is mapped. No n-gram is pruned, and the driver holds only
the shards' sizes.

Nulls count as empty texts, which are the end token alone. Without training rows N and V are zero and every score comes
from the floor p = 1. Repeated rows are scored each and count each. An empty table gives an empty result. Columns other
than the id and the text are not read. Two words with one 64-bit hash would share a count, one pair in 10^7 for a
vocabulary of a million.
"""

from __future__ import annotations

import json
import os
import tempfile
import uuid
from dataclasses import dataclass
from functools import lru_cache

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ditherspark.llm import elias_fano
from ditherspark.llm.common import buffers, doc_crc, mapped, shared_folder, sliced, words
from ditherspark.llm.pretoken import per_text

#: Hash of the end token: that of a string no word can equal, as it holds a space.
END = np.uint64(xxhash.xxh64_intdigest(b" end", 7))
#: Training tokens a level-two shard is meant for, and keys that a task gathers before it hands them on.
SHARD_TOKENS, GATHER = 2_000_000, 4_000_000
#: Bytes of text for which one word shard is made, and tokens of a context in one shard.
WORD_SHARD_BYTES, SPLIT_TOKENS = 64 << 20, 250_000
LEVELS = 256


@dataclass(frozen=True)
class Model:
    """Where the shards are and what is common to them."""

    folder: str
    word_bits: int
    first_ids: tuple[int, ...]
    pair_bits: int
    tokens: int
    vocabulary: int
    strength: float
    split_tokens: int = SPLIT_TOKENS


def _store(folder: str, name: str, arrays: dict[str, np.ndarray]) -> None:
    """One file of all arrays: a JSON header, then the arrays at multiples of 64 bytes."""
    at, head, parts = 0, {}, []
    for k, a in arrays.items():
        raw = np.ascontiguousarray(a).tobytes()
        head[k] = (a.dtype.str, list(a.shape), at)
        parts.append(raw + b"\0" * (-len(raw) % 64))
        at += len(parts[-1])
    text = json.dumps(head).encode()
    blob = len(text).to_bytes(8, "little") + text + b" " * (-(len(text) + 8) % 64) + b"".join(parts)
    if "://" not in folder or folder.startswith("file:"):
        path = folder.removeprefix("file://").removeprefix("file:")
        os.makedirs(path, exist_ok=True)
        draft = f"{path}/.{name}.{uuid.uuid4().hex}"
        with open(draft, "wb") as f:
            f.write(blob)
        os.replace(draft, f"{path}/{name}")
    else:
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(folder)
        store.create_dir(path, recursive=True)
        with store.open_output_stream(f"{path}/{name}") as f:
            f.write(blob)


def _mapped_file(folder: str, name: str) -> dict[str, np.ndarray]:
    if "://" not in folder or folder.startswith("file:"):
        raw = np.memmap(folder.removeprefix("file://").removeprefix("file:") + "/" + name, np.uint8, "r")
    else:
        from pyarrow import fs

        store, path = fs.FileSystem.from_uri(folder)
        with tempfile.NamedTemporaryFile() as local:
            with store.open_input_stream(f"{path}/{name}") as f:
                while part := f.read(1 << 24):
                    local.write(part)
            local.flush()
            raw = np.memmap(local.name, np.uint8, "r")  # unlinked when the block ends
    size = int.from_bytes(raw[:8].tobytes(), "little")
    start = 8 + size + -(size + 8) % 64
    out = {}
    for k, (kind, shape, at) in json.loads(raw[8 : 8 + size].tobytes()).items():
        n = int(np.prod(shape)) * np.dtype(kind).itemsize
        out[k] = np.asarray(raw[start + at : start + at + n]).view(kind).reshape(shape)
    return out


class Trie:
    """The model's levels as a task sees them."""

    def __init__(self, model: Model, pairs: bool = True):
        self.model = model
        files = [_mapped_file(model.folder, f"words-{s}") for s in range(1 << model.word_bits)]
        self.words = [elias_fano.Sequence(f) for f in files]
        self.by_shard = [f["counts"] for f in files]
        self.first = np.array(model.first_ids, np.int64)
        self.pairs = [PairShard(_mapped_file(model.folder, f"pairs-{s}"), model.vocabulary) for s in range(1 << model.pair_bits)] if pairs else []
        self.end_id, _ = self.lookup(np.array([END], np.uint64))
        self.end_id = int(self.end_id[0])

    def lookup(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids and counts of words; -1 and 0 for unknown ones."""
        ids, counts = np.full(len(hashes), -1), np.zeros(len(hashes), np.int64)
        shard = _top(hashes, self.model.word_bits)
        order = np.argsort(shard, kind="stable")
        edge = np.searchsorted(shard[order], np.arange(len(self.words) + 1))
        for s, seq in enumerate(self.words):
            rows = order[edge[s] : edge[s + 1]]
            if len(rows):
                at = seq.find(hashes[rows])
                ok = at >= 0
                ids[rows[ok]] = at[ok] + self.first[s]
                counts[rows[ok]] = self.by_shard[s][at[ok]]
        return ids, counts

    def counts(self, ids: np.ndarray) -> np.ndarray:
        """Counts of words by their ids."""
        out, shard = np.zeros(len(ids), np.int64), np.searchsorted(self.first, ids, side="right") - 1
        for s in np.unique(shard):
            rows = shard == s
            out[rows] = self.by_shard[s][ids[rows] - self.first[s]]
        return out

    def shards(self, context: np.ndarray, word: np.ndarray) -> np.ndarray:
        """The shard of each pair: the context's, or for a large context that of the following word's part of it."""
        parts = 1 + self.counts(context) // self.model.split_tokens
        return _mix(context.astype(np.uint64) * np.uint64(0xC2B2AE3D27D4EB4F) + (word % parts).astype(np.uint64), self.model.pair_bits)

    def pair_logs(self, context: np.ndarray, word: np.ndarray) -> np.ndarray:
        """Quantised log10 probability of each pair; nan where level two lacks it."""
        v = np.uint64(self.model.vocabulary)
        keys, back = np.unique(context.astype(np.uint64) * v + word.astype(np.uint64), return_inverse=True)
        context, word = (keys // v).astype(np.int64), (keys % v).astype(np.int64)
        out, shard = np.full(len(keys), np.nan), self.shards(context, word)
        order = np.argsort(shard, kind="stable")
        edge = np.searchsorted(shard[order], np.arange(len(self.pairs) + 1))
        for s, held in enumerate(self.pairs):
            rows = order[edge[s] : edge[s + 1]]
            if len(rows):
                out[rows] = held.logs(context[rows], word[rows])
        return out[back]


class PairShard:
    """A shard of level two: contexts, pointers to their successors, successors from each context's base."""

    def __init__(self, f: dict[str, np.ndarray], vocabulary: int):
        part = lambda p: elias_fano.Sequence({k.removeprefix(p): a for k, a in f.items() if k.startswith(p)})
        self.contexts, self.pointers, self.level = part("ctx_"), part("ptr_"), elias_fano.Sequence(f)
        self.codes, self.book, self.vocabulary = f["codes"], f["book"], np.uint64(vocabulary)

    @staticmethod
    def build(context: np.ndarray, word: np.ndarray, logs: np.ndarray, vocabulary: int) -> dict[str, np.ndarray]:
        """Arrays of pairs in rising order of context and word."""
        low, high = (float(logs.min()), float(logs.max())) if len(logs) else (0.0, 0.0)
        codes = np.minimum((logs - low) * (LEVELS / max(high - low, 1e-9)), LEVELS - 1).astype(np.uint8)  # equal steps bound the error
        total = np.bincount(codes, logs, minlength=LEVELS)
        book = (total / np.maximum(1, np.bincount(codes, minlength=LEVELS))).astype(np.float32)
        new = np.concatenate([[True], context[1:] != context[:-1]])[: len(context)]
        begin = np.flatnonzero(new)
        level = (np.cumsum(new) - 1).astype(np.uint64) * np.uint64(vocabulary) + word.astype(np.uint64)
        pointers = elias_fano.build(np.append(begin, len(context))) if len(context) else elias_fano.build(np.zeros(0, np.uint64))
        parts = {f"ptr_{k}": a for k, a in pointers.items()} | {f"ctx_{k}": a for k, a in elias_fano.build(context[begin]).items()}
        return elias_fano.build(level) | parts | {"codes": codes, "book": book}

    def ranges(self, context: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """(place, first, stop) of each context's successors; an empty range where the shard lacks it."""
        at = self.contexts.find(context.astype(np.uint64))
        first, stop = np.zeros(len(at), np.int64), np.zeros(len(at), np.int64)
        ok = np.flatnonzero(at >= 0)
        first[ok], stop[ok] = self.pointers.access(at[ok]), self.pointers.access(at[ok] + 1)
        return at, first, stop

    def logs(self, context: np.ndarray, word: np.ndarray) -> np.ndarray:
        """Log10 probabilities of pairs in order of context; each different context is looked up once."""
        new = np.concatenate([[True], context[1:] != context[:-1]])
        own = np.cumsum(new) - 1
        at, first, stop = (x[own] for x in self.ranges(context[new]))
        found = self.level.find(np.maximum(at, 0).astype(np.uint64) * self.vocabulary + word.astype(np.uint64), first, stop)
        out, ok = np.full(len(word), np.nan), found >= 0
        out[ok] = self.book[self.codes[found[ok]]]
        return out


@lru_cache(maxsize=2)
def worker_trie(model: Model) -> Trie:
    """The levels as a Python worker maps them, for all the tasks it runs."""
    return Trie(model)


def _top(hashes: np.ndarray, bits: int) -> np.ndarray:
    return (hashes >> np.uint64(64 - bits)).astype(np.int64) if bits else np.zeros(len(hashes), np.int64)


def _mix(keys: np.ndarray, bits: int) -> np.ndarray:
    """A shard for each level-two key, even over any key distribution."""
    k = keys.astype(np.uint64)
    k = (k ^ (k >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    return _top(k, bits)


def tokens(texts: pa.Array) -> tuple[pa.Array, np.ndarray, np.ndarray, np.ndarray]:
    """Different words, their hashes (the end token's last), each token's index into them, and tokens per text."""
    found, n = words(*buffers(texts))
    coded = found.dictionary_encode()
    h = xxhash.xxh64_intdigest
    hashes = np.fromiter((h(w) for w in coded.dictionary.to_pylist()), np.uint64, len(coded.dictionary))
    code = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    code = np.insert(code, np.cumsum(n), len(hashes))
    return coded.dictionary, np.append(hashes, END), code, n + 1


def _summed(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys, kind="stable")
    keys, counts = keys[order], counts[order]
    first = np.flatnonzero(np.concatenate([[True], keys[1:] != keys[:-1]])) if len(keys) else np.zeros(0, np.int64)
    return keys[first], np.add.reduceat(counts, first) if len(first) else counts


def _counted(docs: DataFrame, kernel) -> DataFrame:
    """(shard, keys, counts): packed sums that tasks hand on, at most once per shard and ``GATHER`` keys."""

    def run(batches):
        (count, shard_of), keys, sums, held = kernel(), [], [], 0

        def summed():
            nonlocal keys, sums, held
            k, c = _summed(np.concatenate(keys), np.concatenate(sums))
            keys, sums, held = [k], [c], len(k)

        def blobs():
            summed()
            k, c = keys[0], sums[0]
            shard = shard_of(k)
            order = np.argsort(shard, kind="stable")
            ids, edge = np.unique(shard[order], return_index=True)
            edge = np.append(edge, len(k))
            rows = [(int(s), k[o].tobytes(), c[o].astype(np.uint32).tobytes()) for s, o in ((s, order[edge[i] : edge[i + 1]]) for i, s in enumerate(ids))]
            return pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.int32()), pa.array([r[1] for r in rows], pa.binary()), pa.array([r[2] for r in rows], pa.binary())], ["shard", "keys", "counts"])

        for batch in batches:
            for part in sliced(batch):
                k, c = count(part["text"])
                keys.append(k)
                sums.append(c)
                held += len(k)
                if held > GATHER:
                    summed()
                    if held > GATHER // 2:
                        yield blobs()
                        keys, sums, held = [], [], 0
        if held:
            yield blobs()

    return docs.select("text").mapInArrow(run, "shard int, keys binary, counts binary")


def _merged(group: pa.Table) -> tuple[np.ndarray, np.ndarray]:
    keys = [np.frombuffer(x, np.uint64) for x in group["keys"].to_pylist()]
    counts = [np.frombuffer(x, np.uint32) for x in group["counts"].to_pylist()]
    return _summed(np.concatenate(keys), np.concatenate(counts).astype(np.int64))


def train(docs: DataFrame, strength: float = 100.0, shard_tokens: int = SHARD_TOKENS, split_tokens: int = SPLIT_TOKENS) -> Model:
    """A model of ``docs`` (text): one pass for words, one for pairs."""
    spark = docs.sparkSession
    folder = shared_folder(spark)
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    word_bits = max(4, (max(1, -(-size // WORD_SHARD_BYTES)) - 1).bit_length())

    def word_kernel():
        def count(texts):
            _, hashes, code, _ = tokens(texts)
            return hashes, np.bincount(code, minlength=len(hashes)).astype(np.int64)

        return count, lambda k: _top(k, word_bits)

    def build_words(group: pa.Table) -> pa.Table:
        keys, counts = _merged(group)
        shard = group["shard"][0].as_py()
        _store(folder, f"words-{shard}", elias_fano.build(keys) | {"counts": counts})
        return pa.table({"shard": pa.array([shard], pa.int32()), "n": pa.array([len(keys)]), "total": pa.array([int(counts.sum())])})

    blobs = _counted(docs, word_kernel)
    made = {r["shard"]: r for r in blobs.groupBy("shard").applyInArrow(build_words, "shard int, n bigint, total bigint").collect()}
    sizes = [made[s]["n"] if s in made else 0 for s in range(1 << word_bits)]
    for s in set(range(1 << word_bits)) - set(made):
        _store(folder, f"words-{s}", elias_fano.build(np.zeros(0, np.uint64)) | {"counts": np.zeros(0, np.int64)})
    first = tuple(int(x) for x in np.cumsum([0, *sizes])[:-1])
    total = sum(r["total"] for r in made.values())
    pair_bits = max(0, (max(1, -(-total // shard_tokens)) - 1).bit_length())
    model = Model(folder, word_bits, first, pair_bits, total, sum(sizes), strength, split_tokens)

    def pair_kernel():
        trie = Trie(model, pairs=False)

        def count(texts):
            _, hashes, code, n = tokens(texts)
            ids, _ = trie.lookup(hashes)
            keys = _pair_keys(ids[code], n, trie)
            return _summed(keys, np.ones(len(keys), np.int64))

        v = np.uint64(model.vocabulary)
        return count, lambda k: trie.shards((k // v).astype(np.int64), (k % v).astype(np.int64))

    def build_pairs(group: pa.Table) -> pa.Table:
        keys, counts = _merged(group)
        shard, trie = group["shard"][0].as_py(), Trie(model, pairs=False)
        v = np.uint64(model.vocabulary)
        context, word = (keys // v).astype(np.int64), (keys % v).astype(np.int64)
        p = (trie.counts(word) + 0.5) / (model.tokens + 0.5 * (model.vocabulary + 1))
        logs = np.log10((counts + strength * p) / (trie.counts(context) + strength))
        _store(folder, f"pairs-{shard}", PairShard.build(context, word, logs, model.vocabulary))
        return pa.table({"shard": pa.array([shard], pa.int32()), "n": pa.array([len(keys)])})

    built = {r["shard"] for r in _counted(docs, pair_kernel).groupBy("shard").applyInArrow(build_pairs, "shard int, n bigint").collect()}
    for s in set(range(1 << pair_bits)) - built:
        none = np.zeros(0, np.int64)
        _store(folder, f"pairs-{s}", PairShard.build(none, none, np.zeros(0), model.vocabulary))
    return model


def _pair_keys(ids: np.ndarray, n: np.ndarray, trie: Trie) -> np.ndarray:
    """Level-two keys of known tokens: context id times vocabulary, plus word id. The first context is the end token."""
    context = np.empty(len(ids), np.int64)
    context[1:] = ids[:-1]
    context[np.cumsum(n) - n] = trie.end_id
    return context.astype(np.uint64) * np.uint64(trie.model.vocabulary) + ids.astype(np.uint64)


def successors(model: Model, word: bytes) -> dict[int, float]:
    """Word ids that follow ``word`` and their log10 probabilities."""
    trie, out = Trie(model), {}
    ids, _ = trie.lookup(np.array([xxhash.xxh64_intdigest(word)], np.uint64))
    for held in trie.pairs if ids[0] >= 0 else ():
        at, first, stop = held.ranges(ids)
        if at[0] >= 0:
            base = at.astype(np.uint64)[0] * held.vocabulary
            found = held.level.access(np.arange(first[0], stop[0])) - base
            out |= dict(zip(found.tolist(), held.book[held.codes[first[0] : stop[0]]].tolist(), strict=True))
    return out


def score_batch(texts: pa.Array, trie: Trie) -> dict[str, np.ndarray]:
    """n_tokens, n_known, base and score of each text."""
    m = trie.model
    _, hashes, code, n = tokens(texts)
    ids, counts = trie.lookup(hashes)
    floor = m.tokens + 0.5 * (m.vocabulary + 1)
    single = np.log10((counts + 0.5) / floor)[code]
    behind = np.empty(len(code), np.int64)
    behind[1:] = code[:-1]
    begin = np.cumsum(n) - n
    behind[begin] = len(hashes) - 1
    back = np.log10(m.strength / (counts + m.strength))[behind] + single
    known = (ids[code] >= 0) & (ids[behind] >= 0)
    logs = back
    if known.any():
        got = trie.pair_logs(ids[behind[known]], ids[code[known]])
        logs[known] = np.where(np.isnan(got), logs[known], got)
    add = lambda x: np.add.reduceat(x, begin) if len(begin) else np.zeros(0)
    return {"n_tokens": n, "n_known": per_text((counts > 0).astype(np.int64)[code], n), "base": add(single), "score": add(logs)}


def score(docs: DataFrame, model: Model, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, n_tokens, n_known, base_score, score) for every row."""

    def kernel():
        trie = worker_trie(model)

        def step(batch):
            r = score_batch(batch["text"], trie)
            return pa.RecordBatch.from_arrays([batch["id"], pa.array(r["n_tokens"]), pa.array(r["n_known"]), pa.array(r["base"]), pa.array(r["score"])], ["id", "n_tokens", "n_known", "base_score", "score"])

        return step

    src = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    out = mapped(src, kernel, f"id {dict(docs.dtypes)[id_col]}, n_tokens bigint, n_known bigint, base_score double, score double")
    return out.withColumnRenamed("id", id_col)


def digest(docs: DataFrame, strength: float = 100.0) -> DataFrame:
    """The contract's columns."""
    model = train(docs.where(doc_crc() % 5 != 1), strength)
    out = score(docs, model)
    held = (doc_crc() % 5 == 1).alias("held_out")
    return out.select("doc_id", held, "n_tokens", "n_known", F.lit(model.tokens).cast("long").alias("train_tokens"), "base_score", "score")
