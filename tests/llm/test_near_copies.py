"""The pipeline's near-duplicate stage against all pairs compared."""

import numpy as np
import pytest

import corpus_pipeline as C
from ditherspark.llm import near_copies, simhash


def planted(g, n_words=200):
    return [f"w{x}" for x in g.integers(0, 5000, n_words)]


def changed(words, g, k):
    """``k`` words replaced, each in shingles of its own."""
    out = list(words)
    for i in g.choice(np.arange(10, len(words) - 10, 12), k, replace=False):
        out[i] = f"new{g.integers(0, 1 << 40)}"
    return out


def similarity(a, b):
    x, y = ({tuple(w[i : i + 5]) for i in range(len(w) - 4)} for w in (a, b))
    return len(x & y) / len(x | y)


def kept_of(rows):
    """Smallest id of each component over all pairs of similarity 0.8 or more."""
    root = list(range(len(rows)))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for i in range(len(rows)):
        for j in range(i):
            if similarity(rows[i], rows[j]) >= 0.8:
                a, b = find(i), find(j)
                root[max(a, b)] = min(a, b)
    return sorted({find(i) for i in range(len(rows))})


def ids(df):
    return sorted(r.doc_id for r in df.select("doc_id").collect())


def test_planted_near_copies_go(spark, sf):
    """1 to 4 of 200 words replaced are similarities of 0.95 to 0.81; 5 are 0.77."""
    g = np.random.default_rng(11)
    rows, want = [], []
    for k in (1, 2, 3, 4, 5) * 6:
        base = planted(g)
        copy = changed(base, g, k)
        assert (0.8 <= similarity(base, copy) <= 0.96) == (k < 5)
        want += [len(rows)] + ([len(rows) + 1] if k == 5 else [])
        rows += [base, copy]
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(rows)], "doc_id long, text string")
    assert ids(C.near_duplicates(spark, df, sf)) == want == kept_of(rows)


@pytest.mark.parametrize("wide_key", [1, 24])
def test_crowded_keys_against_all_pairs(spark, wide_key):
    """A large group of near copies, chains of copies of copies, and a passage that unrelated texts share."""
    g = np.random.default_rng(12)
    base, passage = planted(g), planted(g, 60)
    rows = [changed(base, g, int(g.integers(1, 5))) for _ in range(60)]
    far = base
    for _ in range(12):
        far = changed(far, g, 3)
        rows.append(far)
    rows += [passage + planted(g, int(g.integers(4, 90))) for _ in range(50)]
    rows = [rows[i] for i in g.permutation(len(rows))]
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(rows)], "doc_id long, text string")
    assert ids(near_copies.one_of_each(df, wide_key=wide_key)) == kept_of(rows)


def test_odd_rows(spark, odd, none):
    assert near_copies.one_of_each(odd).columns == odd.columns and near_copies.one_of_each(none).count() == 0
    df = spark.createDataFrame([(None, "a b c"), (None, None), (7, "one two"), (7, "one two"), (8, "ONE two"), (3, None), (4, "")], "doc_id long, text string")
    assert sorted(r.doc_id or 0 for r in near_copies.one_of_each(df).collect()) == [0, 0, 3, 7]


def test_repeated_ids_with_other_texts_are_rows_of_their_own(spark):
    a, b = "one two three four five six seven eight", "nothing in here is like the other text at all"
    for one in (near_copies.one_of_each, simhash.one_of_each):
        for rows, want in (([(5, a), (7, a), (7, b)], [(5, a), (7, b)]), ([(7, a), (7, b)], [(7, a), (7, b)]), ([(7, a), (7, a), (3, b), (3, b)], [(3, b), (7, a)])):
            got = one(spark.createDataFrame(rows, "doc_id long, text string")).collect()
            assert sorted((r.doc_id, r.text) for r in got) == sorted(want)
    clash = spark.createDataFrame([(1, a, 2), (1, a, 3), (2, a, 1)], "doc_id long, text string, lm_row int")
    assert [(r.doc_id, len(r)) for r in near_copies.one_of_each(clash).collect()] == [(1, 3)]


def test_crowded_keys_without_a_common_centre(spark):
    """Texts that share a rare passage but are unlike, and groups among them; further centres are taken first."""
    g = np.random.default_rng(15)
    shared = planted(g, 120)
    rows = [shared + planted(g, 90) for _ in range(60)]
    rows += [changed(rows[i], g, 3) for i in range(0, 60, 2)] + [changed(rows[i], g, 2) for i in range(0, 60, 4)]
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in enumerate(rows)], "doc_id long, text string")
    near_copies.MANY_PAIRS, kept = 10, near_copies.MANY_PAIRS
    try:
        assert ids(near_copies.one_of_each(df, wide_key=2)) == kept_of(rows)
    finally:
        near_copies.MANY_PAIRS = kept
