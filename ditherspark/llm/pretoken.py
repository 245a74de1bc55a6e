"""Cutting texts where no token can cross, and encoding each different piece once.

A byte-level BPE with the usual pattern never joins a non-space character to a space after it, and a piece vocabulary
without a space mark after another character doesn't either, so a text's ids are those of its pieces in a row. A cut
is left out where the character before might be any kind of space; a longer piece gives the same ids.
"""

from __future__ import annotations

import json
from functools import cached_property

import numpy as np
import pyarrow as pa

from ditherspark.llm.common import SPACE_LUT, buffers, strings

#: Different pieces that a worker's cache holds before it starts anew; an entry takes about 200 bytes.
CACHE_ENTRIES = 400_000
#: Bytes of the longest piece that a cache keeps: what it holds is bounded, and longer pieces hardly repeat.
LONGEST = 256


def _behind(data: np.ndarray, by: int) -> np.ndarray:
    out = np.zeros(len(data), np.uint8)
    out[by:] = data[: len(data) - by]
    return out


def byte_pieces(data: np.ndarray, offsets: np.ndarray) -> tuple[pa.Array, np.ndarray]:
    """Pieces for byte-level BPE: a run of white space and what follows it. Returns them and the count per text."""
    p1, p2, p3 = (_behind(data, k) for k in (1, 2, 3))
    wide = (p2 == 0xC2) | (((p3 >= 0xE1) & (p3 <= 0xE3)) & ((p2 == 0x9A) | (p2 == 0x80) | (p2 == 0x81)))
    cut = SPACE_LUT[data] & ~SPACE_LUT[p1] & ~((p1 >= 0x80) & wide)
    return _cut(data, offsets, cut)


def mark_pieces(data: np.ndarray, offsets: np.ndarray) -> tuple[pa.Array, np.ndarray]:
    """Pieces for a vocabulary with space marks, which begins each text with a space: a run of spaces and the rest."""
    full = np.flatnonzero(np.diff(offsets))
    data = np.insert(data, offsets[:-1][full], 32)
    shift = np.zeros(len(offsets), np.int64)
    shift[full + 1] = 1
    offsets = offsets + np.cumsum(shift)
    p1, p2, p3 = (_behind(data, k) for k in (1, 2, 3))
    mark = (p3 == 0xE2) & (p2 == 0x96) & (p1 == 0x81)
    return _cut(data, offsets, (data == 32) & (p1 != 32) & ~mark)


def _cut(data: np.ndarray, offsets: np.ndarray, cut: np.ndarray) -> tuple[pa.Array, np.ndarray]:
    first = offsets[:-1][np.diff(offsets) > 0]
    cut[first] = True
    start = np.flatnonzero(cut)
    counts = np.diff(np.searchsorted(start, offsets))
    return strings(data, np.append(start, len(data)).astype(np.int64)), counts


def per_text(values: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """Sums of ``values`` by text."""
    total = np.zeros(len(values) + 1, np.int64)
    np.cumsum(values, out=total[1:])
    edge = np.zeros(len(counts) + 1, np.int64)
    np.cumsum(counts, out=edge[1:])
    return total[edge[1:]] - total[edge[:-1]]


def ragged(starts: np.ndarray, lens: np.ndarray) -> np.ndarray:
    """Indices of ranges laid end to end."""
    total = np.zeros(len(lens) + 1, np.int64)
    np.cumsum(lens, out=total[1:])
    return np.repeat(starts - total[:-1], lens) + np.arange(total[-1])


def gathered(pieces: pa.Array, counts: np.ndarray, encode, cache: dict[bytes, bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Ids of all texts end to end, and how many each has; ``encode`` is asked once for what ``cache`` lacks."""
    coded = pieces.dictionary_encode()
    if len(cache) > CACHE_ENTRIES:
        cache.clear()
    packed = []
    for p in coded.dictionary.to_pylist():
        got = cache.get(p)
        if got is None:
            got = encode(p)
            if len(p) <= LONGEST:
                cache[p] = got
        packed.append(got)
    lens = np.fromiter(map(len, packed), np.int64, len(packed)) >> 2
    flat = np.frombuffer(b"".join(packed), "<u4")
    starts = np.cumsum(lens) - lens
    code = coded.indices.to_numpy(zero_copy_only=False)
    if not len(code):
        return flat, np.zeros(len(counts), np.int64)
    return flat[ragged(starts[code], lens[code])], per_text(lens[code], counts)


class BytePairs:
    """Byte-level BPE read from a tokenizers file, run by tiktoken's merge loop where the file allows it.

    The loop merges by the merged token's rank; the file's own order of merges is the same if each merge makes the
    next id, which is checked. Otherwise, or if a text holds an added token, the tokenizers library encodes it.
    """

    PATTERN = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""  # fixed value

    def __init__(self, path: str):
        self.path = path
        with open(path, encoding="utf-8") as f:
            spec = json.load(f)
        self.added = [t["content"] for t in spec.get("added_tokens") or []]
        pre, model, vocab = spec.get("pre_tokenizer") or {}, spec["model"], spec["model"]["vocab"]
        merges = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in model["merges"]]
        printable = [*range(33, 127), *range(161, 173), *range(174, 256)]
        letters = dict(zip(map(chr, printable), printable, strict=True))
        letters |= {chr(256 + i): b for i, b in enumerate(b for b in range(256) if b not in set(printable))}
        ordered = all(vocab.get(a + b) == 256 + i for i, (a, b) in enumerate(merges)) and all(vocab.get(c, 999) < 256 for c in letters)
        plain = pre.get("type") == "ByteLevel" and pre.get("use_regex", True) and not pre.get("add_prefix_space") and not spec.get("normalizer")
        self.core = None
        if ordered and plain and not model.get("dropout") and not model.get("ignore_merges"):
            import tiktoken

            ranks = {bytes(letters[c] for c in t): i for t, i in vocab.items() if t not in self.added}
            self.core = tiktoken.Encoding("file", pat_str=self.PATTERN, mergeable_ranks=ranks, special_tokens={})
            self.size = np.zeros(max(ranks.values()) + 1, np.int64)
            self.size[list(ranks.values())] = list(map(len, ranks))
        self.cache: dict[bytes, bytes] = {}

    @cached_property
    def library(self):
        """The tokenizers library's own object, which takes as much memory as all else here: made when first asked."""
        from tokenizers import Tokenizer

        return Tokenizer.from_file(self.path)

    def encode(self, piece: bytes) -> bytes:
        """The piece's ids as little-endian 32-bit numbers."""
        ids = self.core.encode_ordinary(piece.decode()) if self.core else self.library.encode(piece.decode(), add_special_tokens=False).ids
        return np.array(ids, "<u4").tobytes()

    def ids(self, data: np.ndarray, offsets: np.ndarray, tail: int | None = None) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts end to end, each followed by ``tail`` if given, and how many each text has."""
        pieces, counts = byte_pieces(data, offsets)
        out, n = self._at_once(pieces, counts) if self.core and len(pieces) else gathered(pieces, counts, self.encode, self.cache)
        if self.added:
            out, n = self._with_added(data, offsets, out, n)
        if tail is not None:
            out, n = np.insert(out, np.cumsum(n), tail), n + 1
        return out, n

    def _at_once(self, pieces: pa.Array, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """What ``gathered`` returns. The merge loop takes the different pieces laid end to end, where each begins with a
        space and ends with none, so no token crosses; the few others go alone. Nothing is kept for later slices."""
        coded = pieces.dictionary_encode()
        data, off = buffers(coded.dictionary)
        last = data[off[1:] - 1]
        joins = SPACE_LUT[data[off[:-1]]] & (last > 0x20) & (last < 0x7F) & (np.diff(off) <= LONGEST)
        held, edge = buffers(coded.dictionary.filter(pa.array(joins)))
        flat = self.core.encode_to_numpy(held.tobytes().decode(), disallowed_special=()) if len(held) else np.zeros(0, np.uint32)
        total = np.cumsum(self.size[flat])
        ends = np.searchsorted(total, edge[1:]) + 1
        if len(held) and not np.array_equal(total[ends - 1], edge[1:]):
            raise ValueError("a token crosses two pieces")
        alone = [self.encode(p) for p in coded.dictionary.filter(pa.array(~joins)).to_pylist()]
        lens, starts = np.zeros(len(joins), np.int64), np.zeros(len(joins), np.int64)
        lens[joins], lens[~joins] = np.diff(ends, prepend=0), np.fromiter(map(len, alone), np.int64, len(alone)) >> 2
        starts[joins], starts[~joins] = ends - lens[joins], len(flat) + np.cumsum(lens[~joins]) - lens[~joins]
        flat = np.concatenate([flat, np.frombuffer(b"".join(alone), "<u4")])
        code = coded.indices.to_numpy(zero_copy_only=False)
        return flat[ragged(starts[code], lens[code])], per_text(lens[code], counts)

    def _with_added(self, data, offsets, out, n):
        """Texts that hold an added token's string, as the library takes it."""
        blob = data.tobytes()
        hits = set()
        for t in self.added:
            t, at = t.encode(), -1
            while (at := blob.find(t, at + 1)) >= 0:
                hits.add(int(np.searchsorted(offsets, at, side="right")) - 1)
        if not hits:
            return out, n
        edge = np.concatenate([[0], np.cumsum(n)])
        rows = [out[edge[i] : edge[i + 1]] for i in range(len(n))]
        for i in hits:
            text = blob[offsets[i] : offsets[i + 1]].decode()
            rows[i] = np.array(self.library.encode(text, add_special_tokens=False).ids, "<u4")
        return np.concatenate(rows), np.array([len(r) for r in rows], np.int64)
