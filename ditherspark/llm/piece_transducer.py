"""SentencePiece encoding and decoding by a weighted finite-state transducer.

Machines are compiled from the model file and composed with each input:

* the normaliser (``Normaliser``) is read from the model's own character map: its states are those of the map's trie,
  an arc reads a byte, and a final state writes its replacement, the longest match first; what no arc reads is copied. It
  trims and joins spaces where the model asks for it, puts a space first and turns spaces to marks;
* the lexicon (``Lexicon``) is a trie of characters whose final states emit a piece at its weight, the negative score. A
  character that no piece holds goes through the byte machine, which emits one piece for each byte of its UTF-8 form;
* the merge acceptor (``Merges``) has a state for each last piece and an arc for each piece that may follow it: one that
  merging leaves beside it. A sequence of which all neighbours may stand together is what merging gives, as the first
  merge over a border would already happen between the two pieces beside it. Whether two pieces stay apart follows from
  undoing their merges, the latest first: they don't if some pair over the border would merge before the one undone.

``Composed`` is the lazy product of an input with lexicon and acceptor: its states are (place, last piece). For a model of
merges it has one path, so the shortest path is the one that a depth-first search finds, longest pieces first; a place
from which it has turned back is on no path. For a unigram model the acceptor is left out, and the path is the shortest
in the tropical semiring, found forward over places: the most likely segmentation. Texts are composed piece of text by
piece of text, cut where no vocabulary entry crosses, and a worker's cache keeps the paths of those it has seen. Decoding
runs the transducer backwards: emitted bytes in a row, marks to spaces, the first space taken off; it gives the
normalised text back except for literal marks, which become spaces as in the library.

Nulls count as empty texts and have no ids. Rows are independent; an empty table gives an empty result; columns other
than the id and the text are not read.
"""

from __future__ import annotations

import heapq
import zlib
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ditherspark.llm.common import buffers, mapped
from ditherspark.llm.pretoken import gathered, mark_pieces, per_text, ragged

MARK = "▁"
#: Neighbour pairs that the acceptor remembers before it starts anew.
PAIR_ENTRIES = 1_000_000
START, SPELLED = -1, -2  # states of the acceptor beside pieces: nothing yet, and after bytes, which stand beside anything


def fields(message: bytes) -> Iterator[tuple[int, int | bytes]]:
    """(number, value) of a protocol-buffer message: whole numbers and byte strings; fixed-width values as bytes."""
    at = 0

    def varint() -> int:
        nonlocal at
        out = shift = 0
        while True:
            byte = message[at]
            at += 1
            out |= (byte & 127) << shift
            shift += 7
            if byte < 128:
                return out

    while at < len(message):
        key = varint()
        kind = key & 7
        if kind == 0:
            yield key >> 3, varint()
        else:
            size = varint() if kind == 2 else {1: 8, 5: 4}[kind]
            yield key >> 3, message[at : at + size]
            at += size


class Normaliser:
    """The normaliser of a model file's bytes. ``arcs[s]`` maps a byte to the next state, ``writes[s]`` is what a final
    state writes."""

    def __init__(self, model: bytes):
        spec = dict(fields(next((v for k, v in fields(model) if k == 3), b"")))
        self.prefix, self.squeeze, self.escape = (bool(spec.get(k, 1)) for k in (3, 4, 5))
        self.arcs: list[dict[int, int]] = [{}]
        self.writes: list[bytes | None] = [None]
        for text, out in self._rules(spec.get(2, b"")):
            state = 0
            for byte in text:
                if byte not in self.arcs[state]:
                    self.arcs[state][byte] = len(self.arcs)
                    self.arcs.append({})
                    self.writes.append(None)
                state = self.arcs[state][byte]
            self.writes[state] = out
        self.plain = not self.arcs[0] and not self.squeeze

    @staticmethod
    def _rules(charsmap: bytes) -> Iterator[tuple[bytes, bytes]]:
        """(text, replacement) out of the map: its size, a double-array trie of 32-bit units, replacements ended by zero."""
        if not charsmap:
            return
        size = int.from_bytes(charsmap[:4], "little")
        units, texts = np.frombuffer(charsmap[4 : 4 + size], "<u4").tolist(), charsmap[4 + size :]
        base = lambda unit: (unit >> 10) << ((unit & (1 << 9)) >> 6)
        stack = [(base(units[0]), b"")]
        while stack:
            node, text = stack.pop()
            for label in range(1, 256):
                at = node ^ label
                if at < len(units) and units[at] & 0x800000FF == label:
                    below = at ^ base(units[at])
                    if units[at] >> 8 & 1:
                        value = units[below] & 0x7FFFFFFF
                        yield text + bytes([label]), texts[value : texts.index(0, value)]
                    stack.append((below, text + bytes([label])))

    def rewritten(self, text: bytes) -> bytes:
        """The map's output: the longest match at each character, or the character itself."""
        if not self.arcs[0]:
            return text
        out, at, n = [], 0, len(text)
        while at < n:
            state, best, end = 0, None, at
            for j in range(at, n):
                state = self.arcs[state].get(text[j])
                if state is None:
                    break
                if self.writes[state] is not None:
                    best, end = self.writes[state], j + 1
            if best is None:
                end = at + 1
                while end < n and text[end] & 0xC0 == 0x80:
                    end += 1
                best = text[at:end]
            out.append(best)
            at = end
        return b"".join(out)

    def __call__(self, text: bytes) -> bytes:
        """The normalised text, without the space in front and with spaces for marks."""
        text = self.rewritten(text)
        return b" ".join(x for x in text.split(b" ") if x) if self.squeeze else text


class Lexicon:
    """A trie of pieces: nested dictionaries of characters, "" holding what a final state emits."""

    def __init__(self, ids: dict[str, int]):
        self.root: dict = {}
        for p, i in ids.items():
            node = self.root
            for ch in p:
                node = node.setdefault(ch, {})
            node[""] = i

    def arcs(self, text: str, at: int) -> list[tuple[int, int]]:
        """(end, piece) of every piece at a place, the longest last."""
        out, node = [], self.root
        for j in range(at, len(text)):
            node = node.get(text[j])
            if node is None:
                break
            if "" in node:
                out.append((j + 1, node[""]))
        return out


class Merges:
    """The acceptor of sequences that merging leaves."""

    def __init__(self, pieces: list[str], ids: dict[str, int], costs: list[float]):
        self.pieces, self.ids, self.costs = pieces, ids, costs
        self.made: dict[int, tuple[int, int] | None] = {}
        self.pairs: dict[int, bool] = {}

    def merged(self, text: str) -> tuple[list[str], tuple[str, str] | None]:
        """(what merging leaves, the last merge): the best-scored neighbours first, the leftmost of equals."""
        parts: list[str | None] = list(text)
        after, before = list(range(1, len(parts) + 1)), list(range(-1, len(parts) - 1))
        heap, last = [], None

        def offer(a: int, b: int) -> None:
            if a >= 0 and b < len(parts):
                i = self.ids.get(parts[a] + parts[b])
                if i is not None:
                    heapq.heappush(heap, (self.costs[i], a, b, parts[a] + parts[b]))

        for a in range(len(parts) - 1):
            offer(a, a + 1)
        while heap:
            _, a, b, whole = heapq.heappop(heap)
            if parts[a] is None or parts[b] is None or parts[a] + parts[b] != whole or after[a] != b:
                continue
            last = (parts[a], parts[b])
            parts[a], parts[b] = whole, None
            after[a] = after[b]
            if after[b] < len(parts):
                before[after[b]] = a
            offer(before[a], a)
            offer(a, after[a])
        return [p for p in parts if p is not None], last

    def making(self, i: int) -> tuple[int, int] | None:
        """The two pieces whose merge makes piece ``i``: (-1, -1) for one character, None if merging never makes it."""
        if i not in self.made:
            left, last = self.merged(self.pieces[i])
            whole = left == [self.pieces[i]]
            self.made[i] = (tuple(self.ids[x] for x in last) if last else (-1, -1)) if whole else None
        return self.made[i]

    def apart(self, left: int, right: int) -> bool:
        """Whether merging leaves the border between two pieces that it makes: their merges are undone from the latest on,
        and a pair over the border that would merge earlier than the one undone (or with it, further left) joins them."""
        limit, further = float("inf"), False
        while True:
            i = self.ids.get(self.pieces[left] + self.pieces[right])
            if i is not None and (self.costs[i] < limit or (further and self.costs[i] == limit)):
                return False
            a, b = self.making(left), self.making(right)
            if a is None or b is None:  # a part that is made in another order: look at the whole
                return self.merged(self.pieces[left] + self.pieces[right])[0] == [self.pieces[left], self.pieces[right]]
            if a[0] < 0 and b[0] < 0:
                return True
            if b[0] < 0 or (a[0] >= 0 and self.costs[left] > self.costs[right]):
                limit, further, left = self.costs[left], False, a[1]
            else:
                limit, further, right = self.costs[right], True, b[0]

    def may_follow(self, last: int, piece: int) -> bool:
        """An arc: from the state of the last piece by ``piece``."""
        key = (last + 1) << 32 | piece
        got = self.pairs.get(key)
        if got is None:
            if len(self.pairs) >= PAIR_ENTRIES:
                self.pairs.clear()
            got = self.pairs[key] = self.making(piece) is not None and (last < 0 or self.apart(last, piece))
        return got


class Composed:
    """The lazy product of a normalised input, the lexicon with its byte machine, and the acceptor, if any."""

    def __init__(self, text: str, lexicon: Lexicon, byte_ids: dict[int, int], costs: list[float], merges: Merges | None):
        self.text, self.lexicon, self.byte_ids, self.costs, self.merges = text, lexicon, byte_ids, costs, merges

    def arcs(self, state: tuple[int, int]) -> Iterator[tuple[tuple[int, int], tuple[int, ...], float]]:
        """(next state, what is emitted, weight) from (place, last piece)."""
        at, last = state
        for end, piece in self.lexicon.arcs(self.text, at):
            if self.merges is None or self.merges.may_follow(START if last == SPELLED else last, piece):
                yield (end, piece), (piece,), self.costs[piece]
        ch = self.text[at]
        if "" not in self.lexicon.root.get(ch, {}):
            spelled = tuple(self.byte_ids[x] for x in ch.encode())
            yield (at + 1, SPELLED), spelled, sum(self.costs[x] for x in spelled) + 1e6

    def shortest(self) -> tuple[float, tuple[int, ...]]:
        """Weight and emission of the shortest path in the tropical semiring, over all states, forward by place."""
        best: list[dict[int, tuple[float, tuple[int, ...]]]] = [{} for _ in range(len(self.text) + 1)]
        best[0][START] = (0.0, ())
        for at in range(len(self.text)):
            for last, (weight, out) in best[at].items():
                for (end, piece), emitted, more in self.arcs((at, last)):
                    if weight + more < best[end].get(piece, (float("inf"),))[0]:
                        best[end][piece] = (weight + more, out + emitted)
        return min(best[-1].values())


class PieceTransducer:
    """The machines of one model file."""

    def __init__(self, path: str, merges: bool = True):
        import sentencepiece

        m = sentencepiece.SentencePieceProcessor(model_file=path)
        with open(path, "rb") as f:
            self.normaliser = Normaliser(f.read())
        n = m.vocab_size()
        self.pieces = [m.id_to_piece(i) for i in range(n)]
        self.byte_ids = {int(self.pieces[i][3:5], 16): i for i in range(n) if m.is_byte(i)}
        self.ids = {p: i for i, p in enumerate(self.pieces) if not (m.is_byte(i) or m.is_control(i) or m.is_unknown(i))}
        self.weights = np.array([-m.get_score(i) for i in range(n)])
        self.costs = self.weights.tolist()
        inner = any(MARK in p.lstrip(MARK) for p in self.ids)
        if len(self.byte_ids) != 256 or not (self.normaliser.prefix and self.normaliser.escape) or inner:
            raise ValueError("needs byte pieces, a space put first, marks for spaces, and none inside a piece")
        self.lexicon = Lexicon(self.ids)
        self.merges = Merges(self.pieces, self.ids, self.costs) if merges else None
        shorter = {i: [self.ids[p[:j]] for j in range(len(p) - 1, 0, -1) if p[:j] in self.ids] for p, i in self.ids.items()}
        self.shorter = [shorter.get(i, []) for i in range(n)]  # pieces that a piece begins with, the longest first
        self.length = [len(p) for p in self.pieces]
        self.longest = max(map(len, self.ids))
        self.cache: dict[bytes, bytes] = {}
        surface = [bytes([b]) for b in range(256)]
        texts = [surface[int(p[3:5], 16)] if m.is_byte(i) else b"" if m.is_control(i) else p.replace(MARK, " ").encode() for i, p in enumerate(self.pieces)]
        self.blob = np.frombuffer(b"".join(texts), np.uint8)
        self.lens = np.array([len(t) for t in texts], np.int64)
        self.starts = np.cumsum(self.lens) - self.lens

    def composed(self, text: str) -> Composed:
        return Composed(text, self.lexicon, self.byte_ids, self.costs, self.merges)

    def shortest(self, text: str) -> list[int]:
        """Ids of the shortest path through normalised ``text``."""
        return self._only(text) if self.merges else self._cheapest(text)

    def _only(self, text: str) -> list[int]:
        """The one path of the machine with merges, depth first."""
        n, root, longest = len(text), self.lexicon.root, self.longest
        pairs, follow, shorter, length = self.merges.pairs, self.merges.may_follow, self.shorter, self.length
        out: list[int] = []
        path: list[tuple[int, int, int, int]] = []  # (place, longest piece there, how many were left out, state before)
        at, last, dead = 0, START, None
        piece, skip = -1, -1  # the longest piece at this place, and how many are left out; -1 before it is looked up
        while at < n:
            if skip < 0:
                node, piece = root, -1
                for ch in text[at : at + longest]:
                    node = node.get(ch)
                    if node is None:
                        break
                    i = node.get("")
                    if i is not None:
                        piece = i
                skip = 0
                if piece < 0:  # no piece begins here: bytes
                    path.append((at, -1, 0, last))
                    at, last, skip = at + 1, SPELLED, -1
                    continue
            rest = shorter[piece]
            base = ((START if last == SPELLED else last) + 1) << 32
            while skip <= len(rest):
                b = piece if not skip else rest[skip - 1]
                end = at + length[b]
                if dead is None or end not in dead:
                    ok = pairs.get(base | b)
                    if follow(START if last == SPELLED else last, b) if ok is None else ok:
                        break
                skip += 1
            if skip <= len(rest):
                path.append((at, piece, skip, last))
                at, last, skip = end, b, -1
                continue
            if text[at] not in root or "" not in root[text[at]]:  # the character itself is no piece: bytes are the other arc
                path.append((at, -1, 0, last))
                at, last, skip = at + 1, SPELLED, -1
                continue
            while True:  # turn back to the last place with another arc
                dead = dead or set()
                dead.add(at)
                at, piece, skip, last = path.pop()
                if piece >= 0:
                    skip += 1
                    break
        for place, first, left_out, _ in path:
            if first < 0:
                out += [self.byte_ids[x] for x in text[place].encode()]
            else:
                out.append(first if not left_out else shorter[first][left_out - 1])
        return out

    def _cheapest(self, text: str) -> list[int]:
        """The cheapest path without an acceptor, where a place is a state."""
        n, weights, root = len(text), self.costs, self.lexicon.root
        cost = [0.0] + [float("inf")] * n
        back, emitted = [0] * (n + 1), [None] * (n + 1)
        for i in range(n):
            c, node = cost[i], root
            for j in range(i, n):
                node = node.get(text[j])
                if node is None:
                    break
                b = node.get("")
                if b is not None and c + weights[b] < cost[j + 1]:
                    cost[j + 1], back[j + 1], emitted[j + 1] = c + weights[b], i, (b,)
            if text[i] not in root or "" not in root[text[i]]:
                spelled = tuple(self.byte_ids[x] for x in text[i].encode())
                step = c + sum(weights[x] for x in spelled) + 1e6
                if step < cost[i + 1]:
                    cost[i + 1], back[i + 1], emitted[i + 1] = step, i, spelled
        out, at = [], n
        while at:
            out.append(emitted[at])
            at = back[at]
        return [x for group in reversed(out) for x in group]

    def encode_piece(self, piece: bytes) -> bytes:
        return array("I", self.shortest(piece.decode().replace(" ", MARK))).tobytes()

    def normalised(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Normalised texts, as the bytes of all and their offsets."""
        if self.normaliser.plain:
            return data, offsets
        blob = data.tobytes()
        texts = [self.normaliser(blob[a:b]) for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
        return np.frombuffer(b"".join(texts), np.uint8), np.cumsum([0, *map(len, texts)], dtype=np.int64)

    def encode(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts end to end, and how many each has."""
        return self.encode_normal(*self.normalised(data, offsets))

    def encode_normal(self, data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """The same for normalised texts."""
        return gathered(*mark_pieces(data, offsets), self.encode_piece, self.cache)

    def decode(self, ids: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Bytes of all texts end to end with their first space, and how many each has."""
        lens = self.lens[ids]
        return self.blob[ragged(self.starts[ids], lens)], per_text(lens, counts)

    def text_of(self, ids: list[int]) -> str:
        got, _ = self.decode(np.array(ids, np.int64), np.array([len(ids)]))
        return got.tobytes().removeprefix(b" ").decode(errors="replace")


@lru_cache(maxsize=2)
def worker_machine(path: str, merges: bool = True) -> PieceTransducer:
    """The machine of a Python worker, whose caches serve all the tasks it runs."""
    return PieceTransducer(path, merges)


def encode(docs: DataFrame, model_path: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, ids) for every row."""

    def kernel():
        machine = worker_machine(model_path)

        def step(batch):
            ids, n = machine.encode(*buffers(batch["text"]))
            listed = pa.ListArray.from_arrays(pa.array(np.concatenate([[0], np.cumsum(n)]).astype(np.int32)), pa.array(ids.astype(np.int32)))
            return pa.RecordBatch.from_arrays([batch["id"], listed], ["id", "ids"])

        return step

    src = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    return mapped(src, kernel, f"id {dict(docs.dtypes)[id_col]}, ids array<int>").withColumnRenamed("id", id_col)


def decode(encoded: DataFrame, model_path: str, id_col: str = "doc_id", ids_col: str = "ids") -> DataFrame:
    """(id, text) for every row; null ids give an empty text."""
    kind = dict(encoded.dtypes)[id_col]

    def run(batches):
        machine = worker_machine(model_path)
        for batch in batches:
            texts = [machine.text_of(x or []) for x in batch["ids"].to_pylist()]
            yield pa.RecordBatch.from_arrays([batch["id"], pa.array(texts, pa.string())], ["id", "text"])

    src = encoded.select(F.col(id_col).alias("id"), F.col(ids_col).alias("ids"))
    return src.mapInArrow(run, f"id {kind}, text string").withColumnRenamed("id", id_col)


def digest(docs: DataFrame, model_path: str) -> DataFrame:
    """doc_id, n_tokens, n_byte_tokens, ids_crc32 (unsigned, little-endian 32-bit ids), path_weight (the sum of negative
    scores) and round_trip: whether decoding the ids gives the normalised text back, its literal marks as spaces."""

    def kernel():
        machine = worker_machine(model_path)
        is_byte = np.zeros(len(machine.pieces), np.int64)
        is_byte[list(machine.byte_ids.values())] = 1
        whole = machine.weights.astype(np.int64)  # scores of merge models are whole numbers

        def step(batch):
            data, off = machine.normalised(*buffers(batch["text"]))
            ids, n = machine.encode_normal(data, off)
            edge = np.concatenate([[0], np.cumsum(n)])
            raw = memoryview(np.ascontiguousarray(ids, "<u4").view(np.uint8))
            crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(edge[:-1].tolist(), edge[1:].tolist(), strict=True)]
            got, lens = machine.decode(ids, n)
            at = np.concatenate([[0], np.cumsum(lens)])
            back, blob = got.tobytes(), data.tobytes()
            same = [(back[a:b] == (b" " + blob[c:d] if d > c else b"")) or back[a:b] == b" " + blob[c:d].replace(MARK.encode(), b" ") for a, b, c, d in zip(at[:-1].tolist(), at[1:].tolist(), off[:-1].tolist(), off[1:].tolist(), strict=True)]
            cols = [batch["doc_id"], pa.array(n), pa.array(per_text(is_byte[ids], n)), pa.array(crc, pa.int64()), pa.array(per_text(whole[ids], n).astype(np.float64)), pa.array(same, pa.bool_())]
            return pa.RecordBatch.from_arrays(cols, ["doc_id", "n_tokens", "n_byte_tokens", "ids_crc32", "path_weight", "round_trip"])

        return step

    src = docs.select("doc_id", F.col("text").cast("string").alias("text"))
    return mapped(src, kernel, f"doc_id {dict(docs.dtypes)['doc_id']}, n_tokens bigint, n_byte_tokens bigint, ids_crc32 bigint, path_weight double, round_trip boolean")
