"""Every query that SQL can express, against DuckDB on the same tables."""

import duckdb
import pandas as pd
import pytest

from ditherspark.plans import experiments, portable, replays
from ditherspark.sources.tables import TABLES

ALL = portable.QUERIES | experiments.QUERIES | replays.QUERIES
SQL = portable.ORACLES | experiments.ORACLES | replays.ORACLES


@pytest.fixture(scope="module")
def duck(sf):
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return con


@pytest.mark.parametrize("name", sorted(SQL))
def test_same_rows(spark, sf, duck, name):
    got, want = ALL[name](spark, sf).toPandas(), duck.sql(SQL[name]).df()
    cols = sorted(got.columns)
    assert cols == sorted(want.columns)
    order = lambda d: d[cols].sort_values(cols).reset_index(drop=True)
    pd.testing.assert_frame_equal(order(got), order(want), check_dtype=False, check_exact=True)


def test_partitioning_does_not_matter(spark, sf):
    from ditherspark.plans.portable import flattened_fx, long_form, messages_fx, vectors_fx

    base = vectors_fx(spark, sf)
    digest = lambda df: df.selectExpr("sum(hash(vec_id, coord, q))").first()[0]
    seen = {digest(long_form(messages_fx(flattened_fx(base.repartition(n)), 7), "q", "q")) for n in (1, 4, 17)}
    assert len(seen) == 1
