"""Best fit where documents or attention bind before tokens."""

import numpy as np

from ditherspark.llm import packing


def test_documents_and_attention_bind():
    lens = np.full(60, 10)
    for cap, want in ((packing.Capacity(1000, 4, 10**9), 15), (packing.Capacity(1000, 1000, 300), 20), (packing.Capacity(50, 1000, 10**9), 12)):
        bins, _ = packing.best_fit(lens, cap)
        assert len(np.unique(bins)) == want and np.bincount(bins).max() == 60 // want


def test_every_capacity_binds_somewhere(spark, sf):
    """A sequence that no other piece may join is full by documents, by attention, or by tokens; all three occur."""
    from ditherspark.llm.queries import packing_under_limits

    got = packing_under_limits(spark, sf).toPandas()
    g = got.assign(cost=got.length**2).groupby("sequence_id").agg(tokens=("length", "sum"), n=("length", "size"), cost=("cost", "sum"))
    assert (g.tokens <= 4096).all() and (g.n <= 8).all() and (g.cost <= 2 << 20).all()
    least = got.length.min()
    full = [(4096 - g.tokens < least).sum(), (g.n == 8).sum(), ((2 << 20) - g.cost < least**2).sum() + (g.cost > 1.9 * (1 << 20)).sum()]
    assert full[1] > 0 and full[2] > 0


def test_repeated_rows_are_spread(spark):
    rows = spark.range(3000, numPartitions=6).selectExpr("7L doc_id", "0 piece", "0L start", "5L length", "1L ids_crc32")
    out = packing.pack(rows, packing.Capacity(50), shard_items=500).toPandas()
    shards = (out.sequence_id.to_numpy() >> 32)
    assert len(out) == 3000 and len(np.unique(shards)) == 6 and np.bincount(shards).max() < 1000
