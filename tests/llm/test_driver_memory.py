"""Joins whose sides grow with the input are merges: nothing of them may be sent to the driver."""

import pytest
from pyspark.sql import functions as F

from ditherspark.llm import common, near_copies, simhash


def broadcasts(df):
    """Broadcasts in the plan, before and after it has run."""
    df = df.select("*")
    plan = df._jdf.queryExecution().executedPlan()
    before = plan.toString()
    df.collect()
    return before.count("Broadcast") + plan.toString().count("Broadcast")


@pytest.fixture
def default_broadcasts(spark):
    """Spark's own limit of 10 MB, under which files or exploded rows are taken for small."""
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "10m")
    yield
    spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")


def test_links_send_no_keys_to_the_driver(spark, default_broadcasts):
    """16 keys a fingerprint, which the size of the fingerprints does not show."""
    fps = spark.range(300).select(F.xxhash64("id").alias("fp")).union(spark.range(40).select((F.lit(1 << 40) + F.col("id")).alias("fp")))
    assert broadcasts(simhash.links(fps)) == 0

def test_near_copies_send_no_keys_to_the_driver(spark, default_broadcasts, monkeypatch):
    """Keys that sets share, and the sets themselves, whatever their files' size."""
    tables = {}
    monkeypatch.setattr(near_copies, "written", lambda df, name: tables.setdefault(name, []).append(broadcasts(df)) or df.localCheckpoint())
    words = [" ".join(f"w{(i // 3) * 1000 + j}" for j in range(60)) + f" end{i}" for i in range(30)]
    docs = spark.createDataFrame([(i, i, t) for i, t in enumerate(words)], "doc_id long, row long, text string").coalesce(1)
    monkeypatch.setattr(common, "BROADCAST_ROWS", 0)
    whole = near_copies.sets(docs, 5, 0.8, near_copies.common_shingles(docs, 5)).localCheckpoint()
    own = whole.select("sid", "doc_id", "row", "fp", "n", "weight")
    assert near_copies.shared_keys(whole, own).count()
    assert set(tables) == {"about", "sizes", "shared"} and not any(map(sum, tables.values()))


def test_compared_sets_are_neither_stored_nor_moved(spark, monkeypatch):
    """Texts go to their pairs, and whole sets decide there: 8 of 9 shingles are alike, 6 of 11 are not."""
    schemas, kept = {}, near_copies.written
    monkeypatch.setattr(near_copies, "written", lambda df, name: schemas.setdefault(name, df.dtypes) and kept(df, name))
    texts = spark.createDataFrame([(1, 1, "a b c d e f g h i"), (2, 2, "a b c d e f g h i j"), (3, 3, "a b c d e f g x y z"), (4, 4, "a A b a b")], "doc_id long, row long, text string")
    own = texts.select(F.col("doc_id").alias("sid"), "doc_id", "row")
    pairs = spark.createDataFrame([(1, 2), (1, 3), (2, 3), (1, 2), (1, 4)], "u long, v long")
    assert [tuple(r) for r in near_copies.alike(pairs, texts, own, 2, 0.8).collect()] == [(1, 2)]
    assert not any("array" in kind for columns in schemas.values() for _, kind in columns)
