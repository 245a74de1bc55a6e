"""What a worker holds while it tokenizes, and the ids of pieces that are encoded together."""

import gc
import tracemalloc

import numpy as np
import pyarrow as pa
import pytest

from ditherspark.llm.common import buffers
from ditherspark.llm.pretoken import BytePairs
from ditherspark.llm.queries import tokenizer_path

BYTES = tokenizer_path("byte_bpe_50k.json")
ENDS = ["é a", "a é b é", " a ", "a  ", "  a", "\t\n a\n\nb \n", "x  y　 z", "\x1c a\x1c b\x85 c", "a\x7f b", "'s 's it's", " " * 300 + "a", "b" * 300 + " b c", "\U0001f600 \U0001f600", "", None, " ", "a"]


@pytest.fixture
def pairs():
    return BytePairs(BYTES)


def test_ids_are_the_librarys_whatever_lies_side_by_side(pairs, texts):
    g = np.random.default_rng(5)
    signs = [" ", "  ", "\n", "a", "é", ".", "'s", "7", "　", " ", "\x85", "\x1f", "\U0001f600", "_b"]
    made = ["".join(signs[i] for i in g.integers(0, len(signs), g.integers(0, 30))) for _ in range(3000)]
    given = [*ENDS, *made, *[t for t in texts.values() if t][:300]]
    ids, n = pairs.ids(*buffers(pa.array(given)))
    want = [e.ids for e in pairs.library.encode_batch([t or "" for t in given], add_special_tokens=False)]
    assert n.tolist() == list(map(len, want))
    assert ids.tolist() == [x for e in want for x in e]


def test_nothing_is_held_after_many_different_words(pairs):
    g = np.random.default_rng(6)
    tracemalloc.start()
    try:
        for _ in range(4):
            words = g.integers(97, 123, (100_000, 8)).astype(np.uint8)
            words[:, 0] = 32
            pairs.ids(*buffers(pa.array([words.tobytes()])))
        gc.collect()
        assert tracemalloc.get_traced_memory()[0] < 8 << 20
    finally:
        tracemalloc.stop()
    assert "library" not in vars(pairs)  # it takes as much as the rest, and no text asked for it
