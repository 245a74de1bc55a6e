"""The transducer's machines one by one: the normaliser against the library's, the product against all its paths."""

import numpy as np
import pytest

from ditherspark.llm import piece_transducer as P
from ditherspark.llm.queries import tokenizer_path

PIECES = tokenizer_path("piece_bpe_32k.model")


@pytest.fixture(scope="module")
def machine():
    return P.PieceTransducer(PIECES)


def paths(m, state, n):
    if state[0] == n:
        return [((), 0.0)]
    return [(out + rest, w + more) for to, out, w in m.arcs(state) for rest, more in paths(m, to, n)]


def words():
    g = np.random.default_rng(21)
    yield from ("▁the", "▁unbelievable", "▁▁▁a", "▁aaaaaaa", "▁x\U0001f600y", "▁１２", "▁Ünïcödé", "▁", "▁0000000", "▁ababababab", "▁日本語x")
    for alphabet in ("ab", "ers", "tionat", "01", "▁ae", "aé\U0001f600", "nig"):
        for _ in range(40):
            yield "▁" + "".join(alphabet[i] for i in g.integers(0, len(alphabet), g.integers(1, 12)))


def test_the_product_has_one_path_and_it_is_what_merging_leaves(machine):
    for w in words():
        m = machine.composed(w)
        (only, weight), *more = paths(m, (0, P.START), len(w))
        assert not more, w
        left, _ = machine.merges.merged(w)
        want = [x for p in left for x in ([machine.ids[p]] if p in machine.ids else [machine.byte_ids[b] for b in p.encode()])]
        assert list(only) == want == machine.shortest(w), w
        best, out = m.shortest()
        assert out == only and best == pytest.approx(weight)


def test_borders_are_those_of_replayed_merges(machine):
    g = np.random.default_rng(22)
    few = [i for p, i in machine.ids.items() if len(p) <= 4 and set(p) <= set("▁etaoinsr")]
    for a, b in g.choice(few, (4000, 2)).tolist():
        if machine.merges.making(a) and machine.merges.making(b):
            pa, pb = machine.pieces[a], machine.pieces[b]
            assert machine.merges.apart(a, b) == (machine.merges.merged(pa + pb)[0] == [pa, pb])


def test_long_pieces(machine):
    import sentencepiece

    lib = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    for t in ("ab" * 20_000, "x" * 30_000, "é" * 5_000, "\U0001f600" * 2_000):
        assert machine.shortest(P.MARK + t) == lib.encode(t)


@pytest.mark.parametrize("rule", ["identity", "nmt_nfkc", "nfkc", "nmt_nfkc_cf"])
def test_normaliser_against_the_library(rule, texts):
    import sentencepiece

    lib = sentencepiece.SentencePieceNormalizer(rule_name=rule)
    own = P.Normaliser(lib.serialized_model_proto())
    assert own.plain == (rule == "identity") or own.squeeze
    probes = ["ﬁ Å  é Ａ ", "１２３ ｶﾞ", " a​b\tc  d ", "ＡＢＣ㍿", "①②½", "", "  ", "Straße İ"] + [t for t in texts.values() if t][:60]
    for t in probes:
        got = own.rewritten(t.encode()).decode()
        want = lib.normalize(t)
        assert "".join(got.split()) == "".join(want.replace("▁", " ").split()), t[:60]


def test_normaliser_of_the_given_model_changes_nothing(machine):
    assert machine.normaliser.plain and machine.normaliser.prefix and machine.normaliser.escape
    assert machine.normaliser(b"  a  b ") == b"  a  b "
