"""Rows that go are told by numbers in each worker: documents are not shuffled, whatever Spark would broadcast."""

import pytest
from pyspark.sql import functions as F

from ditherspark.llm import common, near_copies, simhash

A, B = "one two three four five six seven eight", "nothing in here is like the other text at all"


@pytest.fixture
def no_broadcasts(spark):
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    yield
    spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("stage", [near_copies.one_of_each, simhash.one_of_each])
def test_documents_stay_where_they_are(spark, no_broadcasts, stage):
    out = stage(spark.createDataFrame([(5, A), (7, A), (6, B), (None, A), (None, None)], "doc_id long, text string"))
    assert "Exchange" not in plan(out)
    assert sorted((r.doc_id or 0, r.text or "") for r in out.collect()) == [(0, ""), (0, A), (5, A), (6, B)]


def test_only_identical_rows_are_shuffled(spark, no_broadcasts):
    rows = [(5, A), (5, A), (7, A), (7, A), (6, B), (None, A), (None, A)]
    out = near_copies.one_of_each(spark.createDataFrame(rows, "doc_id long, text string"))
    assert sorted((r.doc_id or 0, r.text) for r in out.collect()) == [(0, A), (0, A), (5, A), (6, B)]


@pytest.mark.parametrize("held", [0, 4_000_000])
@pytest.mark.parametrize("wrong", [False, True])
def test_too_many_rows_or_equal_numbers_are_merged(spark, monkeypatch, held, wrong):
    """Numbers that also mean other rows are found out."""
    monkeypatch.setattr(common, "HELD_ROWS", held)
    if wrong:
        monkeypatch.setattr(simhash, "among", lambda rows, *on: F.lit(True))
    rows = [(5, A), (5, A), (7, A), (6, B), (8, B), (9, None)]
    out = near_copies.one_of_each(spark.createDataFrame(rows, "doc_id long, text string"))
    assert ("SortMergeJoin" in plan(out) or "BroadcastHashJoin" in plan(out)) and sorted((r.doc_id, r.text or "") for r in out.collect()) == [(5, A), (6, B), (9, "")]


def test_asked_texts_alone_move(spark, monkeypatch):
    """Beyond what is broadcast, texts that no pair needs are left out before the join."""
    monkeypatch.setattr(near_copies, "BROADCAST_SETS", 0)
    texts = spark.range(200).select(F.col("id").alias("doc_id"), (F.col("id") * 3).alias("row"), F.concat(F.lit("text "), "id").alias("text"))
    asked = spark.createDataFrame([(70, 7, 21), (80, 8, 24), (90, 9, 1)], "sid long, doc_id long, row long")
    found = near_copies.asked_texts(texts, asked)
    assert sorted(tuple(r) for r in found.collect()) == [(70, "text 7"), (80, "text 8")]
    moved, left = [], [found._jdf.queryExecution().executedPlan()]
    while left:
        node = left.pop()
        if node.nodeName() == "AdaptiveSparkPlan":
            left.append(node.executedPlan())
        elif "QueryStage" in node.nodeName():
            left.append(node.plan())
        else:
            if node.nodeName() == "Exchange" and "text" in node.output().toString():
                moved.append(node.metrics().apply("shuffleRecordsWritten").value())
            left += [node.children().apply(i) for i in range(node.children().size())]
    assert moved == [2]
