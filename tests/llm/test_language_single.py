"""Language identification where only one language is labelled."""

from ditherspark.llm import language_id


def test_a_corpus_in_one_language_is_kept(docs):
    lang = docs.where("lang IS NOT NULL AND doc_id < 1000000").groupBy("lang").count().orderBy("count").collect()[-1]["lang"]
    own = docs.where(docs.lang == lang).where("doc_id < 1000000 AND text rlike '[a-z]'").cache()
    assert language_id.kept_only(own).count() == own.count() > 20
    long = [r for r in language_id.digest(own).collect() if r.held_out]
    assert all(r.lang_pred == lang and 0 < r.score <= 1 for r in long)


def test_one_language_scores_the_share_it_has(spark):
    words = "the quick brown fox jumps over the lazy dog and runs home again".split()
    rows = [(i, " ".join(words[(i * k) % 13] for k in range(1, 40)), "en") for i in range(60)]
    rows += [(1000, "быстрая лиса прыгает через ленивую собаку", None), (1001, "12345 67890 12345 67890 !!", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    assert {r.doc_id for r in language_id.kept_only(df).collect()} == set(range(60))
    got = {r.doc_id: r for r in language_id.digest(df).collect()}
    assert min(got[i].score for i in range(60)) > 0.5 > 0.02 > got[1000].score and got[1001].lang_pred == "und"
