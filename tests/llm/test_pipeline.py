"""The pipeline stage by stage against plain Python."""

import numpy as np

import corpus_pipeline as C
from ditherspark.llm import language_id, quality, secret_scan
from test_operators import LOWER, WORD


def shingle_set(text):
    w = WORD.findall((text or "").translate(LOWER))
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def grouped(sets):
    """The smallest id of each group that similarities of 0.8 or more connect."""
    root = {k: k for k in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    keys = sorted(sets)
    for i, a in enumerate(keys):
        for b in keys[:i]:
            x, y = sets[a], sets[b]
            if x == y or (min(len(x), len(y)) >= 0.8 * max(len(x), len(y)) and len(x & y) >= 0.8 * len(x | y)):
                p, q = find(a), find(b)
                root[max(p, q)] = min(p, q)
    return {k: find(k) for k in keys}


def test_stages(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    before = {r.doc_id: r for r in docs.collect()}
    labels = spark.read.parquet(f"{sf}/labels.parquet")
    seen, cur = {}, docs
    for name, stage in C.STAGES:
        out = stage(spark, cur, sf).cache()
        seen[name] = out
        if name != "best_fit_packing":
            assert out.columns == docs.columns
        cur = out
    ids = {k: [r.doc_id for r in v.select("doc_id").collect()] for k, v in seen.items()}
    # language
    pred = {r.doc_id: r for r in language_id.digest(docs).collect()}
    want = {d for d, r in pred.items() if r.lang_pred != "und" and (r.score >= 0.02 or len(before[d].text) < 20)}
    assert set(ids["language_id"]) == want
    # quality, judged on what the stage got
    kept = {r.doc_id for r in quality.digest(seen["language_id"], labels).collect() if r.kept}
    assert set(ids["quality_rules"]) == kept and kept < want
    # near duplicates: all pairs of five-word shingle sets compared
    root = grouped({d: shingle_set(before[d].text) for d in kept})
    assert sorted(ids["simhash_near_dedup"]) == sorted(set(root.values()))
    # secrets
    for r in seen["secret_scan"].collect():
        spans = secret_scan.find_spans(before[r.doc_id].text)
        assert (r.text == before[r.doc_id].text) == (not spans) and r.n_chars == len(r.text)
        assert not [s for s in secret_scan.find_spans(r.text) if s[0] != "entropy"]
    assert set(ids["best_fit_packing"]) == set(ids["secret_scan"]) == set(ids["simhash_near_dedup"])
    total = seen["best_fit_packing"].groupBy("sequence_id").sum("length").toPandas()["sum(length)"]
    assert np.max(total) <= 1024


def test_run_is_the_stages(spark, sf):
    got = C.run(spark, sf)
    assert got.columns == ["doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset"] and got.count() > 0
