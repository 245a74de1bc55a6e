"""Queries follow the given tables: with other rows there are other results."""

import pytest
from pyspark.sql import functions as F

from ditherspark.plans import replays


@pytest.mark.parametrize("name, table, change", [
    ("bits_ledger", "events", lambda df: df.where("event_id % 50 = 0")),
    ("bound_terms", "embeddings", lambda df: df.withColumn("embedding", F.transform("embedding", lambda x: (x * 2).cast("float")))),
])
def test_results_follow_the_table(spark, sf, tmp_path, name, table, change):
    change(spark.read.parquet(f"{sf}/{table}.parquet")).write.parquet(f"{tmp_path}/{table}.parquet")
    run = replays.QUERIES[name]
    rows = lambda d: sorted(map(tuple, run(spark, str(d)).collect()))
    assert rows(sf) != rows(tmp_path)
