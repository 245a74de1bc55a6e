"""Packing token pieces into sequences by vector best-fit.

A sequence has three capacities: tokens, documents, and attention cost (the sum of squared piece lengths). Pieces come
longest first. Each goes to a sequence that still has room in all three, chosen by the smallest weighted norm of what
would remain (``norm``) or by the largest weighted dot product of demand and room (``dot``); if none has room, a new one
opens. Sequences in the same state are interchangeable, so the choice is made among states.

Pieces are dealt at random to shards of about ``shard_items``, packed independently: memory is bounded, and a shard
wastes less than one sequence against packing all together, some 0.01 %. A lost executor's shards are packed again to
the same result, as the pieces are stored first and dealt by a hash of their place in the stored table, so that repeated
rows are spread, too.

Nulls count as empty texts, which are one piece that holds the end token alone. Only a document longer than a sequence
is cut; its first piece is the shorter one. Repeated rows are packed each. An empty table gives an empty result. Columns
other than the id and the text are not read.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ditherspark.llm.common import NARROW_BYTES, buffers, mapped, written
from ditherspark.llm.pretoken import BytePairs

SHARD_ITEMS = 20_000


@dataclass(frozen=True)
class Capacity:
    """What a sequence holds, the weights of the three dimensions, and the rule that selects."""

    tokens: int = 1024
    documents: int = 1024
    attention: int = 1024 * 1024
    weights: tuple[float, float, float] = (1.0, 0.05, 0.05)
    rule: str = "norm"


def best_fit(lengths: np.ndarray, cap: Capacity = Capacity()) -> tuple[np.ndarray, np.ndarray]:
    """(bin, offset) of each piece. Raises if a piece fits no empty sequence."""
    lengths = np.asarray(lengths, np.int64)
    order = np.argsort(-lengths, kind="stable")
    bins, offset = np.zeros(len(lengths), np.int64), np.zeros(len(lengths), np.int64)
    full = np.array([cap.tokens, cap.documents, cap.attention], np.float64)
    w = np.asarray(cap.weights) ** 2 if cap.rule == "norm" else np.asarray(cap.weights)
    if len(lengths) and (lengths.max() > cap.tokens or lengths.max() ** 2 > cap.attention or cap.documents < 1):
        raise ValueError("a piece exceeds a sequence")
    least = int(lengths.min()) if len(lengths) else 0
    room, members, index, n = np.zeros((64, 3)), [], {}, 0  # states: what is left, the bins in it, its row
    filled, opened = [], 0
    for i in order:
        need = np.array([lengths[i], 1, lengths[i] ** 2], np.float64)
        have = room[:n]
        ok = (have >= need).all(axis=1)
        if ok.any():
            rows = np.flatnonzero(ok)
            after = (have[rows] - need) / full
            score = (after * after) @ w if cap.rule == "norm" else -((have[rows] / full) * (need / full)) @ w
            row = int(rows[np.argmin(score)])
            b = members[row].pop()
            state = have[row] - need
            if not members[row]:  # the last state moves to its place
                n -= 1
                del index[tuple(room[row])]
                if row != n:
                    room[row], members[row] = room[n], members[n]
                    index[tuple(room[row])] = row
                members.pop()
        else:
            b, opened = opened, opened + 1
            filled.append(0)
            state = full - need
        bins[i], offset[i] = b, filled[b]
        filled[b] += int(lengths[i])
        if state[0] >= least and state[1] >= 1:
            key = tuple(state)
            if key not in index:
                if n == len(room):
                    room = np.concatenate([room, np.zeros_like(room)])
                room[n], index[key] = state, n
                members.append([])
                n += 1
            members[index[key]].append(b)
    return bins, offset


def token_pieces(docs: DataFrame, tokenizer: str, end_id: int = 2, most: int = 1024, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(id, piece, start, length, ids_crc32) of every document's pieces."""

    def kernel():
        pairs = BytePairs(tokenizer)

        def step(batch):
            ids, n = pairs.ids(*buffers(batch["text"]), tail=end_id)
            k = np.maximum(1, -(-n // most))
            row = np.repeat(np.arange(len(n)), k)
            piece = np.arange(len(row)) - np.repeat(np.cumsum(k) - k, k)
            head = (n - (k - 1) * most)[row]
            start = np.where(piece == 0, 0, head + (piece - 1) * most)
            length = np.where(piece == 0, head, most)
            at = (np.cumsum(n) - n)[row] + start
            raw = memoryview(np.ascontiguousarray(ids, "<u4").view(np.uint8))
            crc = [zlib.crc32(raw[4 * a : 4 * (a + m)]) for a, m in zip(at.tolist(), length.tolist(), strict=True)]
            cols = [batch["id"].take(pa.array(row)), pa.array(piece, pa.int32()), pa.array(start), pa.array(length), pa.array(crc, pa.int64())]
            return pa.RecordBatch.from_arrays(cols, ["id", "piece", "start", "length", "ids_crc32"])

        return step

    src = docs.select(F.col(id_col).alias("id"), F.col(text_col).cast("string").alias("text"))
    kind = dict(docs.dtypes)[id_col]
    return mapped(src, kernel, f"id {kind}, piece int, start bigint, length bigint, ids_crc32 bigint", budget=NARROW_BYTES).withColumnRenamed("id", id_col)


def pack(pieces: DataFrame, cap: Capacity = Capacity(), shard_items: int = SHARD_ITEMS) -> DataFrame:
    """``pieces`` (with ``length``) and their ``sequence_id`` and ``offset``."""
    pieces = written(pieces, "pieces")
    shards = max(1, -(-pieces.count() // shard_items))
    dealt = pieces.withColumn("__shard", F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(shards)).cast("int"))  # identical rows apart
    schema = f"{', '.join(f'`{f.name}` {f.dataType.simpleString()}' for f in pieces.schema)}, sequence_id bigint, offset bigint"

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values([c for c in pdf.columns if c != "__shard"], kind="stable")
        bins, offset = best_fit(pdf["length"].to_numpy(), cap)
        shard = int(pdf["__shard"].iloc[0]) if len(pdf) else 0
        return pdf.drop(columns="__shard").assign(sequence_id=bins + (shard << 32), offset=offset)

    return dealt.groupBy("__shard").applyInPandas(one, schema)


def digest(docs: DataFrame, tokenizer: str, cap: Capacity = Capacity()) -> DataFrame:
    """The contract's columns."""
    return pack(token_pieces(docs, tokenizer, most=cap.tokens), cap)
