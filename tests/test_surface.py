"""SQL functions, stored runs, plans and the registry."""

import numpy as np
from pyspark.sql import functions as F

import __spark_entry__ as entry_points
from ditherspark.functions.sqlfuncs import register
from ditherspark.operators.gradients import OneSparseOracle
from ditherspark.plans import portable
from ditherspark.sources.runs import read_trace, write_messages, write_trace
from ditherspark.sources.tables import load


def test_sql_functions(spark, sf):
    register(spark)
    load(spark, sf, "embeddings", "vec_id", "embedding").limit(8).createOrReplaceTempView("e8")
    r = spark.sql("SELECT embedding, ds_unflatten(ds_flatten(embedding, vec_id), vec_id) back, ds_encode(embedding, 0.51D, 7, vec_id) q, vec_id FROM e8")
    r.createOrReplaceTempView("enc8")
    for x in r.collect():
        assert np.allclose(x.back, x.embedding) and all(abs(q) <= 7 and q % 2 for q in x.q)
    same = spark.sql("SELECT q, ds_unpack(ds_pack(q, 7), 7, 64) u, ds_decode(q, 0.51D, 7, vec_id) d FROM enc8").collect()
    assert all(x.q == x.u and len(x.d) == 64 for x in same)
    total = spark.sql("SELECT ds_vector_sum(cast(embedding as array<double>)) s FROM e8").first().s
    assert np.allclose(total, np.sum([x.embedding for x in r.collect()], axis=0))
    packed = spark.sql("SELECT ds_pack(q, 7) p, q FROM enc8 LIMIT 1").first()
    rows = spark.sql(f"SELECT * FROM ds_unpack_rows(X'{bytes(packed.p).hex()}', 7, 64)").collect()
    assert [x.q for x in sorted(rows)] == packed.q


def test_stored_runs(spark, tmp_path):
    t = spark.createDataFrame([("a", 0, 1.0), ("b", 0, 2.0)], "run string, t int, f double")
    write_trace(t, f"{tmp_path}/trace")
    one = read_trace(spark, f"{tmp_path}/trace", "b")
    assert [r.f for r in one.collect()] == [2.0]
    assert "PartitionFilters: [isnotnull(run" in one._jdf.queryExecution().toString()
    write_messages(spark.range(5), f"{tmp_path}/m", 2)
    assert spark.read.parquet(f"{tmp_path}/m").count() == 5


def test_plans_prune_and_broadcast(spark, sf):
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    p = plan(portable.lsq_full_gradient(spark, sf))
    assert "l_shipdate" not in p and "ReadSchema: struct<l_quantity:double" in p
    p = plan(portable.vote_halfspace(spark, sf))
    assert "BroadcastHashJoin" in p and "CartesianProduct" not in p and "NestedLoop" not in p
    for q in (portable.codec_encode_k7, portable.onebit_events_round, portable.star_lsq_gradient):
        p = plan(q(spark, sf))
        assert "Python" not in p and "Cartesian" not in p


def test_round_plan_is_the_same_every_round(spark, sf):
    from ditherspark.operators.protocol import RunConfig

    o = OneSparseOracle(portable.event_rows(spark, sf), m=1000)
    cfg = RunConfig(d=16, n_workers=4)
    sizes = {len(o.worker_gradients(np.zeros(16), t, cfg)._jdf.queryExecution().executedPlan().toString().split("\n")) for t in (0, 1, 7)}
    assert len(sizes) == 1


def test_registry_names_match(spark, sf):
    q, o = entry_points.queries(), entry_points.oracle_sql()
    assert set(o) <= set(q) and len(q) >= 60
    assert entry_points.entry(spark).count() == 6


def test_stream_means_need_zoned_time(spark):
    from ditherspark.streaming.rounds import running_means

    s = spark.readStream.format("rate").load().select(F.col("timestamp").alias("ts"), F.lit(1).alias("coord"), F.lit(1.0).alias("y"))
    assert running_means(s).isStreaming
