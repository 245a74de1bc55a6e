"""Workloads in whole numbers, with column expressions only, so any SQL engine can check them to the last digit.

A vector enters as floor(x * 2^20). The +-1 transform is not normalised; instead the dither's half-width is scaled up by
sqrt(d): tau is uniform on -L..L-1 and a level counts z + tau >= 0, whose mean is exactly z/L within the limits. Every
query has its SQL beside it, which uses the dense form of the transform where the query uses the fast one.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ditherspark.functions.closed_forms import clamp, sgn1, soft_threshold
from ditherspark.functions.rng import draw_indices, hash60, rademacher, sql_hash60, uniform_int
from ditherspark.operators.basis import bound, butterfly_expr
from ditherspark.sources.tables import load

QUERIES, ORACLES = {}, {}
D, FRACTION = 64, 1 << 20
LIMIT = round(8 * 2 * math.sqrt(math.log(64) / 64) * FRACTION)  # alpha = 2, unit vectors
EVENT_D, EVENT_N = 16, 64
EVENT_LIMIT = round(4 * 2 * 12 * math.sqrt(math.log(16) / 16) * FRACTION)
SERVER_LIMIT, SERVER_K = round(2 * math.sqrt(math.log(16)) * EVENT_N * EVENT_D), 7


def query(sql: str):
    def add(f):
        QUERIES[f.__name__], ORACLES[f.__name__] = f, sql
        return f

    return add


def vectors_fx(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = F.transform("embedding", lambda x: F.floor(x.cast("double") * FRACTION))
    return load(spark, sf_dir, "embeddings", "vec_id", "embedding").select("vec_id", g.alias("g"))


def flattened_fx(df: DataFrame, d: int = D) -> DataFrame:
    """Adds ``z``, the transform of the entries with random signs, d log d additions a vector."""
    signed = F.transform("g", lambda x, i: x * rademacher(0, "eps", F.col("vec_id"), i))
    return df.withColumn("z", butterfly_expr(signed, d))


def level(z: Column, k: int, limit: int, *key) -> Column:
    """Sum of k signs of z + tau."""
    return F.aggregate(F.sequence(F.lit(0), F.lit(k - 1)), F.lit(0), lambda acc, j: acc + sgn1(z + uniform_int(2 * limit, *key, j) - limit))


def messages_fx(df: DataFrame, k: int) -> DataFrame:
    return df.withColumn("q", F.transform("z", lambda z, i: level(z, k, LIMIT, 0, "tau", F.col("vec_id"), i)))


def long_form(df: DataFrame, column: str, name: str) -> DataFrame:
    return df.select("vec_id", F.posexplode(column).alias("coord", name)).withColumn(name, F.col(name).cast("long"))


_SIGN = f"(1 - 2 * ({sql_hash60('0', repr('eps'), 'vec_id', 'coord')} % 2))"
_PARITY = "(1 - 2 * (bit_count(k & coord) % 2))"
_Z = f"""
v AS (SELECT vec_id, unnest(range(64)) AS coord, unnest(embedding) AS x FROM embeddings),
g AS (SELECT vec_id, coord, CAST(floor(CAST(x AS DOUBLE) * {FRACTION}) AS BIGINT) AS g FROM v),
s AS (SELECT vec_id, coord, g, g * {_SIGN} AS y, {_SIGN} AS e FROM g),
ks AS (SELECT unnest(range(64)) AS k),
z AS (SELECT vec_id, CAST(k AS INTEGER) AS coord, CAST(sum(y * {_PARITY}) AS BIGINT) AS z FROM s, ks GROUP BY vec_id, k)"""


def _q(k: int) -> str:
    tau = sql_hash60("0", repr("tau"), "vec_id", "coord", "j")
    return f"""q AS (SELECT vec_id, coord, any_value(z) AS z, CAST(sum(CASE WHEN z + {tau} % {2 * LIMIT} - {LIMIT} >= 0 THEN 1 ELSE -1 END) AS BIGINT) AS q
  FROM z, (SELECT unnest(range({k})) AS j) GROUP BY vec_id, coord)"""


_W = f"""w AS (SELECT vec_id, CAST(k AS INTEGER) AS coord, CAST(sum(q * {_PARITY}) AS BIGINT) AS w0 FROM q, ks GROUP BY vec_id, k),
x AS (SELECT w.vec_id, w.coord, w0 * {_SIGN.replace('vec_id', 'w.vec_id').replace('coord', 'w.coord')} AS w FROM w)"""


@query(f"WITH {_Z} SELECT vec_id, coord, z FROM z")
def codec_flatten(spark, sf_dir):
    return long_form(flattened_fx(vectors_fx(spark, sf_dir)), "z", "z")


@query(f"WITH {_Z}, {_q(1)} SELECT vec_id, coord, q FROM q")
def codec_encode_k1(spark, sf_dir):
    return long_form(messages_fx(flattened_fx(vectors_fx(spark, sf_dir)), 1), "q", "q")


@query(f"WITH {_Z}, {_q(7)} SELECT vec_id, coord, q FROM q")
def codec_encode_k7(spark, sf_dir):
    return long_form(messages_fx(flattened_fx(vectors_fx(spark, sf_dir)), 7), "q", "q")


def _unflattened(df: DataFrame, column: str) -> Column:
    back = butterfly_expr(F.transform(column, lambda x: x.cast("long")), D)
    return bound(back, lambda a: F.transform(a, lambda x, i: x * rademacher(0, "eps", F.col("vec_id"), i)))


@query(f"WITH {_Z}, {_q(1)}, {_W} SELECT vec_id, coord, CAST(w AS BIGINT) AS w FROM x")
def codec_decode(spark, sf_dir):
    """Numerators: the decoded vector is w * lam / (K sqrt(d))."""
    df = messages_fx(flattened_fx(vectors_fx(spark, sf_dir)), 1)
    return long_form(df.select("vec_id", _unflattened(df, "q").alias("w")), "w", "w")


@query("SELECT vec_id, CAST(coord AS INTEGER) AS coord, 64 * CAST(floor(CAST(x AS DOUBLE) * 1048576) AS BIGINT) AS back FROM (SELECT vec_id, unnest(range(64)) AS coord, unnest(embedding) AS x FROM embeddings)")
def codec_inverse(spark, sf_dir):
    """Unflattening what was flattened gives d times the input."""
    df = flattened_fx(vectors_fx(spark, sf_dir))
    return long_form(df.select("vec_id", _unflattened(df, "z").alias("back")), "back", "back")


@query("SELECT CAST(k AS INTEGER) AS k, CAST(64 * CASE k WHEN 1 THEN 1 WHEN 3 THEN 2 WHEN 7 THEN 3 WHEN 15 THEN 4 ELSE 8 END / 8 AS INTEGER) AS bytes, 8 AS eps_bytes, count(*) AS n FROM embeddings, (SELECT unnest([1, 3, 7, 15, 255]) AS k) GROUP BY k")
def codec_pack_bytes(spark, sf_dir):
    from ditherspark.operators.codec import encode_many

    m = encode_many(load(spark, sf_dir, "embeddings", "vec_id", "embedding"), 0.51, (1, 3, 7, 15, 255))
    return m.groupBy("k", F.octet_length("packed").alias("bytes"), F.octet_length("eps").alias("eps_bytes")).agg(F.count("*").alias("n"))


@query(f"WITH {_Z}, b AS (SELECT vec_id, max(abs(g)) AS top_before FROM g GROUP BY vec_id) SELECT z.vec_id, CAST(any_value(top_before) AS BIGINT) AS top_before, CAST(max(abs(z)) AS BIGINT) AS top_after, CAST(sum(CASE WHEN abs(z) > {LIMIT} THEN 1 ELSE 0 END) AS BIGINT) AS clipped FROM z JOIN b ON b.vec_id = z.vec_id GROUP BY z.vec_id")
def flatness_dense(spark, sf_dir):
    """Largest entry before and after (times sqrt(d)), and how many exceed the amplitude of alpha = 2."""
    df = flattened_fx(vectors_fx(spark, sf_dir))
    top = lambda c: F.array_max(F.transform(c, lambda x: F.abs(x)))
    return df.select("vec_id", top("g").alias("top_before"), top("z").alias("top_after"), F.size(F.filter("z", lambda x: F.abs(x) > LIMIT)).cast("long").alias("clipped"))


_KS = (1, 3, 7, 15)


@query(" UNION ALL ".join(f"SELECT * FROM (WITH {_Z}, {_q(k)} SELECT {k} AS k, count(*) AS n, CAST(sum((({LIMIT} * q - {k} * z) >> 10) * (({LIMIT} * q - {k} * z) >> 10)) AS BIGINT) AS err_sq, CAST(sum({k} * (CAST({LIMIT >> 10} AS BIGINT) * {LIMIT >> 10} - (z >> 10) * (z >> 10))) AS BIGINT) AS expected FROM q)" for k in _KS))
def quantizer_mse_table(spark, sf_dir):
    """Squared error of K dithers against its exact mean, both times K^2 in units of 2^-10: their ratio is near 1."""
    base = flattened_fx(vectors_fx(spark, sf_dir)).select(F.col("vec_id"), F.posexplode("z").alias("coord", "z"))
    both = F.array(*[F.struct(F.lit(k).alias("k"), level(F.col("z"), k, LIMIT, 0, "tau", F.col("vec_id"), F.col("coord")).cast("long").alias("q")) for k in _KS])
    df = base.select("z", F.explode(both).alias("e")).select("z", "e.k", "e.q")
    err, zs = F.shiftright(F.lit(LIMIT).cast("long") * F.col("q") - F.col("k") * F.col("z"), 10), F.shiftright("z", 10)
    out = df.groupBy("k").agg(F.count("*").alias("n"), F.sum(err * err).alias("err_sq"), F.sum(F.col("k") * (F.lit((LIMIT >> 10) ** 2) - zs * zs)).alias("expected"))
    return out.select(F.col("k").cast("int").alias("k"), "n", "err_sq", "expected")


_BX = "CAST(floor((l_quantity - 25) * 1000) AS BIGINT)"


@query(f"""SELECT CAST(l_quantity AS BIGINT) AS quantity, count(*) AS n, any_value({_BX}) AS x, greatest(-20000, least(20000, any_value({_BX}))) AS clamped,
  any_value({_BX}) - greatest(-20000, least(20000, any_value({_BX}))) AS residual,
  CAST(sum(CASE WHEN {_BX} + {sql_hash60('0', repr('bias'), 'l_orderkey', 'l_linenumber')} % 40000 - 20000 >= 0 THEN 1 ELSE -1 END) AS BIGINT) AS sign_sum FROM lineitem GROUP BY l_quantity""")
def quantizer_bias_table(spark, sf_dir):
    """Mean of one-bit outputs against the clamped value, for inputs inside and beyond the amplitude."""
    df = load(spark, sf_dir, "lineitem", "l_quantity", "l_orderkey", "l_linenumber").withColumn("x", F.floor((F.col("l_quantity") - 25) * 1000))
    s = sgn1(F.col("x") + uniform_int(40000, 0, "bias", F.col("l_orderkey"), F.col("l_linenumber")) - 20000)
    out = df.withColumn("s", s).groupBy(F.col("l_quantity").cast("long").alias("quantity"), "x").agg(F.count("*").alias("n"), F.sum("s").alias("sign_sum"))
    lim = F.lit(20000).cast("long")
    return out.select("quantity", "n", "x", clamp(F.col("x"), lim).alias("clamped"), soft_threshold(F.col("x"), lim).alias("residual"), "sign_sum")


# Least squares.
_LA = ("CAST(1 AS BIGINT)", "CAST(l_quantity AS BIGINT)", "CAST(round(l_discount * 100) AS BIGINT)", "CAST(round(l_tax * 100) AS BIGINT)")
_LX = (900, 30, -40, 25)
_LR = "(" + " + ".join(f"{x} * {a}" for x, a in zip(_LX, _LA, strict=True)) + " - CAST(floor(l_extendedprice) AS BIGINT))"


@query(" UNION ALL ".join(f"SELECT {i} AS coord, CAST(sum(2 * {_LR} * {a}) AS BIGINT) AS grad, count(*) AS m FROM lineitem" for i, a in enumerate(_LA)))
def lsq_full_gradient(spark, sf_dir):
    """Sum of gradients of the price regression at a fixed point: one scan of four columns, no shuffle of rows."""
    df = load(spark, sf_dir, "lineitem", "l_quantity", "l_discount", "l_tax", "l_extendedprice")
    r = F.expr(_LR)
    sums = df.agg(*[F.sum(2 * r * F.expr(a)).alias(f"g{i}") for i, a in enumerate(_LA)], F.count("*").alias("m"))
    return sums.select("m", F.posexplode(F.array(*[f"g{i}" for i in range(4)])).alias("coord", "grad")).select("coord", "grad", "m")


@query("SELECT CAST(sum(r * r) AS BIGINT) AS total, count(*) AS m FROM (SELECT " + _LR + " AS r FROM lineitem)")
def lsq_value(spark, sf_dir):
    r = F.expr(_LR)
    return load(spark, sf_dir, "lineitem", "l_quantity", "l_discount", "l_tax", "l_extendedprice").agg(F.sum(r * r).alias("total"), F.count("*").alias("m"))


def _draw_sql(rounds, n, mp, table, seed=0):
    return f"""SELECT t, worker, slot, {sql_hash60(str(seed), repr('draw'), 't', 'worker', 'slot')} % (SELECT count(*) FROM {table}) AS row_id
  FROM (SELECT unnest(range({rounds})) AS t), (SELECT unnest(range({n})) AS worker), (SELECT unnest(range({mp})) AS slot)"""


@query(f"SELECT CAST(t AS INTEGER) AS t, CAST(worker AS INTEGER) AS worker, CAST(slot AS INTEGER) AS slot, row_id FROM ({_draw_sql(4, 8, 16, 'events')})")
def draws_with_replacement(spark, sf_dir):
    return draw_indices(spark, 4, 8, 16, load(spark, sf_dir, "events", "event_id").count())


def _drawn_embeddings(spark, sf_dir, n, mp) -> DataFrame:
    rows = load(spark, sf_dir, "embeddings", "vec_id", "embedding", "label")
    a = F.transform("embedding", lambda x: F.floor(x.cast("double") * 64))
    draws = F.broadcast(draw_indices(spark, 1, n, mp, rows.count()))
    df = rows.join(draws, rows.vec_id == draws.row_id).select("worker", "slot", a.alias("a"), "label")
    r = F.aggregate("a", F.lit(0).cast("long"), lambda s, x: s + x) - 64 * F.col("label")
    return df.withColumn("r", r).select("worker", "slot", F.posexplode(F.transform("a", lambda x: 2 * F.col("r") * x)).alias("coord", "g"))


def _emb_draw_sql(n, mp):
    return f"""d AS ({_draw_sql(1, n, mp, 'embeddings')}),
e AS (SELECT vec_id, label, unnest(range(64)) AS coord, CAST(floor(CAST(unnest(embedding) AS DOUBLE) * 64) AS BIGINT) AS a FROM embeddings),
r AS (SELECT vec_id, sum(a) - 64 * any_value(label) AS r FROM e GROUP BY vec_id),
gr AS (SELECT worker, slot, coord, 2 * r * a AS g FROM d JOIN e ON e.vec_id = d.row_id JOIN r ON r.vec_id = d.row_id)"""


@query(f"WITH {_emb_draw_sql(8, 16)} SELECT CAST(worker AS INTEGER) AS worker, CAST(coord AS INTEGER) AS coord, CAST(sum(g) AS BIGINT) AS grad FROM gr GROUP BY worker, coord")
def lsq_minibatch_gradient(spark, sf_dir):
    """Each worker's summed gradient over its draws, at the all-ones point."""
    return _drawn_embeddings(spark, sf_dir, 8, 16).groupBy("worker", "coord").agg(F.sum("g").alias("grad"))


@query(f"""WITH {_emb_draw_sql(32, 64)}, b AS (SELECT mp, worker, coord, CAST(sum(g) AS BIGINT) * (64 // mp) AS s FROM gr, (SELECT unnest([1, 4, 16, 64]) AS mp) WHERE slot < mp GROUP BY mp, worker, coord),
c AS (SELECT mp, coord, 32 * CAST(sum(s * s) AS HUGEINT) - CAST(sum(s) AS HUGEINT) * CAST(sum(s) AS HUGEINT) AS v FROM b GROUP BY mp, coord)
SELECT CAST(mp AS INTEGER) AS m_prime, CAST(sum(CAST(v // 4096 AS BIGINT)) AS BIGINT) AS variance FROM c GROUP BY mp""")
def lsq_oracle_variance(spark, sf_dir):
    """Variance of mini-batch gradients over 32 workers (scaled): falls as 1/m'."""
    g = _drawn_embeddings(spark, sf_dir, 32, 64).withColumn("mp", F.explode(F.array(*[F.lit(k) for k in (1, 4, 16, 64)]))).where("slot < mp")
    s = g.groupBy("mp", "worker", "coord").agg(F.sum("g").alias("s")).withColumn("s", F.expr("cast(s * (64 div mp) as decimal(20,0))"))
    v = s.groupBy("mp", "coord").agg((32 * F.sum(F.col("s") * F.col("s")) - F.sum("s") * F.sum("s")).alias("v"))
    return v.groupBy(F.col("mp").cast("int").alias("m_prime")).agg(F.sum(F.expr("cast(v div 4096 as bigint)")).alias("variance"))


# Star features.
_STAR = """st AS (SELECT CAST(floor(l_extendedprice / 100) AS BIGINT) AS y, ['one', 'nation:' || n_name, 'region:' || r_name, 'brand:' || p_brand, 'segment:' || c_mktsegment, 'priority:' || o_orderpriority, 'supplier:' || CAST(s_nationkey AS VARCHAR)] AS fs
FROM lineitem JOIN orders ON o_orderkey = l_orderkey JOIN customer ON c_custkey = o_custkey JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey JOIN part ON p_partkey = l_partkey JOIN supplier ON s_suppkey = l_suppkey)"""


def star_rows(spark, sf_dir, weigh=None) -> DataFrame:
    """(y, fs): one-hot features of a line over seven tables. With ``weigh``, which makes a number of a feature, also
    ``total``, their sum over the line: features are made and weighed once for each row of a dimension, before the joins.
    Nation and region have a fixed number of rows and are broadcast; the others are as far as their size allows."""
    t = lambda *a: load(spark, sf_dir, *a)

    def named(df, **features):
        """``df`` with its features, and ``w``, the sum of their weights so far."""
        for k, v in features.items():
            df = df.withColumn(f"f_{k}", F.concat(F.lit(k + ":"), F.col(v).cast("string"))).drop(v)
        if not weigh:
            return df
        total = sum((weigh(F.col(f"f_{k}")) for k in features), F.lit(0).cast("long"))
        return df.withColumn("w", total + (F.col("w") if "w" in df.columns else 0))

    def joined(big, small, on):
        small = small.withColumnRenamed("w", "w2")
        out = big.join(small, on)
        return out.withColumn("w", F.col("w") + F.col("w2")).drop("w2") if weigh else out

    region = named(t("region", "r_regionkey", "r_name"), region="r_name")
    nation = joined(named(t("nation", "n_nationkey", "n_name", "n_regionkey"), nation="n_name"), F.broadcast(region), F.col("r_regionkey") == F.col("n_regionkey"))
    customer = joined(named(t("customer", "c_custkey", "c_nationkey", "c_mktsegment"), segment="c_mktsegment"), F.broadcast(nation), F.col("n_nationkey") == F.col("c_nationkey"))
    orders = joined(named(t("orders", "o_orderkey", "o_custkey", "o_orderpriority"), priority="o_orderpriority"), customer, F.col("c_custkey") == F.col("o_custkey"))
    part, supplier = named(t("part", "p_partkey", "p_brand"), brand="p_brand"), named(t("supplier", "s_suppkey", "s_nationkey"), supplier="s_nationkey")
    df = t("lineitem", "l_orderkey", "l_partkey", "l_suppkey", "l_extendedprice")
    df = df.withColumn("w", weigh(F.lit("one"))) if weigh else df
    df = joined(df, part, F.col("p_partkey") == F.col("l_partkey"))
    df = joined(df, supplier, F.col("s_suppkey") == F.col("l_suppkey"))
    df = joined(df, orders, F.col("o_orderkey") == F.col("l_orderkey"))
    features = F.array(F.lit("one"), *[f"f_{k}" for k in ("nation", "region", "brand", "segment", "priority", "supplier")])
    return df.select(F.floor(F.col("l_extendedprice") / 100).alias("y"), features.alias("fs"), *([F.col("w").alias("total")] if weigh else []))


@query(f"WITH {_STAR} SELECT f AS feature, count(*) AS n, CAST(sum(y) AS BIGINT) AS total FROM (SELECT y, unnest(fs) AS f FROM st) GROUP BY f")
def star_features(spark, sf_dir):
    return star_rows(spark, sf_dir).select("y", F.explode("fs").alias("feature")).groupBy("feature").agg(F.count("*").alias("n"), F.sum("y").alias("total"))


_XF = sql_hash60("0", repr("star"), "f")


@query(f"WITH {_STAR}, i AS (SELECT row_number() OVER () AS id, y, fs FROM st), l AS (SELECT id, y, unnest(fs) AS f FROM i), r AS (SELECT id, sum({_XF} % 201 - 100) - any_value(y) AS r FROM l GROUP BY id) SELECT f AS feature, CAST(sum(2 * r) AS BIGINT) AS grad FROM l JOIN r ON r.id = l.id GROUP BY f")
def star_lsq_gradient(spark, sf_dir):
    """Sparse least-squares gradient: weights come with the dimensions, residuals stay in the row, so beside the joins one
    shuffle, of sums by feature."""
    df = star_rows(spark, sf_dir, lambda f: uniform_int(201, 0, "star", f) - 100).withColumn("r", F.col("total") - F.col("y"))
    return df.select("r", F.explode("fs").alias("feature")).groupBy("feature").agg(F.sum(2 * F.col("r")).alias("grad"))


# Events: 1-sparse gradients.
def event_rows(spark, sf_dir) -> DataFrame:
    """(row_id, coord, y): one coordinate a row, y = value / 100."""
    e = load(spark, sf_dir, "events", "event_id", "user_id", "value")
    return e.select(F.col("event_id").alias("row_id"), F.pmod("user_id", F.lit(EVENT_D)).cast("int").alias("coord"), (F.col("value") / 100).alias("y"))


@query("SELECT user_id, count(*) AS n, CAST(sum(CAST(floor(value * 1000) AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY user_id")
def event_user_means(spark, sf_dir):
    """The exact minimiser of the 1-sparse problem as (count, sum) a user."""
    e = load(spark, sf_dir, "events", "user_id", "value")
    return e.groupBy("user_id").agg(F.count("*").alias("n"), F.sum(F.floor(F.col("value") * 1000)).alias("total"))


_EV = f"ev AS (SELECT event_id, CAST(user_id % {EVENT_D} AS INTEGER) AS c, value / 100 AS y FROM events)"
_ED = f"""{_EV}, d AS ({_draw_sql(10, EVENT_N, 1, 'events')}),
n AS (SELECT t, c, sum(CASE WHEN -2 * y < 0 THEN 1 ELSE 0 END) AS neg FROM d JOIN ev ON ev.event_id = d.row_id GROUP BY t, c),
a AS (SELECT ts.t, cs.c, {EVENT_N} - 2 * coalesce(neg, 0) AS votes FROM (SELECT unnest(range(10)) AS t) ts CROSS JOIN (SELECT unnest(range({EVENT_D})) AS c) cs LEFT JOIN n ON n.t = ts.t AND n.c = cs.c)"""


def _votes(spark, sf_dir) -> DataFrame:
    """(t, votes) by touched coordinate: a coordinate's sum of signs is N - 2 * its negative workers, absent entries being
    +1, so only touched coordinates are shuffled."""
    rows = event_rows(spark, sf_dir)
    draws = F.broadcast(draw_indices(spark, 10, EVENT_N, 1, rows.count()))
    neg = F.sum(F.when(-2 * F.col("y") < 0, 1).otherwise(0))
    return rows.join(draws, "row_id").groupBy("t", "coord").agg((EVENT_N - 2 * neg).alias("votes"))


@query(f"WITH {_ED} SELECT CAST(t AS INTEGER) AS t, CAST(sum(CASE WHEN votes >= 0 THEN 1 ELSE -1 END) AS BIGINT) AS half_space FROM a GROUP BY t")
def vote_halfspace(spark, sf_dir):
    """<v, 1> of the majority vote: never negative."""
    v = _votes(spark, sf_dir)
    return v.groupBy("t").agg((F.sum(sgn1(F.col("votes"))) + EVENT_D - F.count("*")).alias("half_space"))


@query(f"WITH {_ED} SELECT CAST(t AS INTEGER) AS t, CAST(sum(votes) AS BIGINT) AS half_space_n FROM a GROUP BY t")
def signmean_halfspace(spark, sf_dir):
    """N times <v, 1> of the averaged signs: never negative."""
    v = _votes(spark, sf_dir)
    return v.groupBy("t").agg((F.sum("votes") + EVENT_N * (EVENT_D - F.count("*"))).alias("half_space_n"))


@query(f"WITH {_EV}, u AS (SELECT c, count(*) AS n, avg(y) AS mu FROM ev GROUP BY c) SELECT round(power(sum(mu), 2) / sum((SELECT count(*) FROM ev) / n), 6) AS floor, round(sum(mu * mu * n) / (SELECT count(*) FROM ev), 6) AS gap_at_zero FROM u")
def vote_gap_floor(spark, sf_dir):
    """The gap that sign methods cannot go below from zero, and the gap at zero."""
    u = event_rows(spark, sf_dir).groupBy("coord").agg(F.count("*").alias("n"), F.avg("y").alias("mu"))
    a = u.agg(F.sum("n").alias("m"), F.sum("mu").alias("s"), F.sum(1 / F.col("n")).alias("inv"), F.sum(F.col("mu") * F.col("mu") * F.col("n")).alias("q"))
    return a.select(F.round(F.pow("s", F.lit(2)) / (F.col("m") * F.col("inv")), 6).alias("floor"), F.round(F.col("q") / F.col("m"), 6).alias("gap_at_zero"))


_EG = f"CAST(floor(-2 * y * {FRACTION}) AS BIGINT)"


def _bits_of(coord: Column, g: Column, *key) -> Column:
    """One-bit message of a 1-sparse gradient as an array: its flattened entries are +-g."""
    k = F.sequence(F.lit(0), F.lit(EVENT_D - 1))
    e = rademacher(0, "eps", *key, coord)
    z = lambda i: (1 - 2 * (F.bit_count(i.bitwiseAND(coord)) % 2)) * e * g
    return F.transform(k, lambda i: sgn1(z(i) + uniform_int(2 * EVENT_LIMIT, 0, "tau", *key, i) - EVENT_LIMIT).cast("long"))


@query(f"""WITH {_EV}, d AS ({_draw_sql(1, EVENT_N, 1, 'events')}),
g AS (SELECT worker, c, {_EG} AS g FROM d JOIN ev ON ev.event_id = d.row_id),
cs AS (SELECT unnest(range({EVENT_D})) AS k),
q AS (SELECT worker, k, CASE WHEN (1 - 2 * (bit_count(k & c) % 2)) * (1 - 2 * ({sql_hash60('0', repr('eps'), 'worker', 'c')} % 2)) * g + {sql_hash60('0', repr('tau'), 'worker', 'k')} % {2 * EVENT_LIMIT} - {EVENT_LIMIT} >= 0 THEN 1 ELSE -1 END AS q FROM g, cs),
w AS (SELECT i.k AS c, CAST(sum(q * (1 - 2 * (bit_count(q.k & i.k) % 2)) * (1 - 2 * ({sql_hash60('0', repr('eps'), 'worker', 'i.k')} % 2))) AS BIGINT) AS w FROM q, cs i GROUP BY i.k),
z AS (SELECT cs.k, CAST(sum(w * (1 - 2 * ({sql_hash60('0', repr('server'), 'c')} % 2)) * (1 - 2 * (bit_count(cs.k & c) % 2))) AS BIGINT) AS z FROM w, cs GROUP BY cs.k),
p AS (SELECT k, sum(CASE WHEN z + {sql_hash60('0', repr('down'), 'k', 'j')} % {2 * SERVER_LIMIT} - {SERVER_LIMIT} >= 0 THEN 1 ELSE -1 END) AS q FROM z, (SELECT unnest(range({SERVER_K})) AS j) GROUP BY k)
SELECT CAST(cs.k AS INTEGER) AS coord, CAST(any_value(w.w) AS BIGINT) AS w, CAST(sum(p.q * (1 - 2 * (bit_count(p.k & cs.k) % 2))) * any_value(1 - 2 * ({sql_hash60('0', repr('server'), 'cs.k')} % 2)) AS BIGINT) AS v
FROM cs JOIN w ON w.c = cs.k, p GROUP BY cs.k""")
def onebit_events_round(spark, sf_dir):
    """A whole round in whole numbers: ``w`` is the server's sum of decoded messages, ``v`` what all workers decode."""
    rows = event_rows(spark, sf_dir)
    draws = F.broadcast(draw_indices(spark, 1, EVENT_N, 1, rows.count()))
    sent = rows.join(draws, "row_id").select("worker", "coord", F.floor(-2 * F.col("y") * FRACTION).alias("g"))
    sent = sent.withColumn("q", _bits_of(F.col("coord"), F.col("g"), F.col("worker")))
    back = bound(butterfly_expr(F.col("q"), EVENT_D), lambda a: F.transform(a, lambda x, i: x * rademacher(0, "eps", F.col("worker"), i)))
    w = sent.select(F.posexplode(back).alias("coord", "x")).groupBy("coord").agg(F.sum("x").alias("w"))
    mean = w.agg(F.array_sort(F.collect_list(F.struct("coord", "w"))).alias("l")).select(F.transform("l", lambda s: s["w"]).alias("w"))  # d numbers
    e = lambda i: rademacher(0, "server", i)
    z = butterfly_expr(F.transform("w", lambda x, i: x * e(i)), EVENT_D)
    q = F.transform(bound(z, lambda a: F.transform(a, lambda x, i: level(x, SERVER_K, SERVER_LIMIT, 0, "down", i))), lambda x: x.cast("long"))
    v = bound(butterfly_expr(q, EVENT_D), lambda a: F.transform(a, lambda x, i: x * e(i)))
    return mean.withColumn("v", v).select(F.posexplode(F.arrays_zip("w", "v")).alias("coord", "s")).select("coord", "s.w", "s.v")


@query(f"""WITH {_EV}, cs AS (SELECT unnest(range({EVENT_D})) AS k), g AS (SELECT event_id, c, {_EG} AS g FROM ev),
q AS (SELECT event_id, any_value(c) AS c, any_value(g) AS g, sum(CASE WHEN (1 - 2 * (bit_count(k & c) % 2)) * (1 - 2 * ({sql_hash60('0', repr('eps'), 'event_id', 'c')} % 2)) * g + {sql_hash60('0', repr('tau'), 'event_id', 'k')} % {2 * EVENT_LIMIT} - {EVENT_LIMIT} >= 0 THEN CAST(1 AS BIGINT) << k ELSE 0 END) AS b FROM g, cs GROUP BY event_id)
SELECT count(DISTINCT CASE WHEN g < 0 THEN c ELSE -1 END) AS before, count(DISTINCT b) AS after, count(*) AS n FROM q""")
def direction_diversity(spark, sf_dir):
    """Different one-bit messages of 1-sparse gradients: signs alone against flattened and dithered."""
    df = event_rows(spark, sf_dir).select("row_id", "coord", F.floor(-2 * F.col("y") * FRACTION).alias("g"))
    bits = F.aggregate(F.transform(_bits_of(F.col("coord"), F.col("g"), F.col("row_id")), lambda q, i: F.when(q > 0, F.pow(F.lit(2), i).cast("long")).otherwise(0)), F.lit(0).cast("long"), lambda a, x: a + x)
    plain = F.when(F.col("g") < 0, F.col("coord")).otherwise(-1)
    return df.withColumn("b", bits).agg(F.count_distinct(plain).alias("before"), F.count_distinct("b").alias("after"), F.count("*").alias("n"))


# Hashed words.
def hashed_words(df: DataFrame, text: Column, *ids: str, buckets: int = 1024) -> DataFrame:
    """(ids, coord, n): words between spaces, hashed. Counts are within a row, so nothing but the result is shuffled."""
    words = F.filter(F.split(text, " "), lambda w: w != "")
    hashed = F.array_sort(F.transform(words, lambda w: uniform_int(buckets, "word", w).cast("int")))

    def counted(h: Column) -> Column:
        """A struct for each different bucket: it and how often it stands in the sorted array."""
        n = F.size(h)
        ends = F.filter(F.sequence(F.lit(1), n), lambda i: (i == n) | (F.get(h, i) != F.get(h, i - 1)))
        pair = lambda e: F.transform(e, lambda i, k: F.struct(F.get(h, i - 1).alias("coord"), (i - F.when(k > 0, F.get(e, k - 1)).otherwise(0)).cast("long").alias("n")))
        return F.when(n > 0, bound(ends, pair))

    return df.select(*ids, F.explode(bound(hashed, counted)).alias("c")).select(*ids, "c.coord", "c.n")


def _words_sql(table: str, ids: str, text: str) -> str:
    return f"SELECT {ids}, CAST({sql_hash60(repr('word'), 'w')} % 1024 AS INTEGER) AS coord, count(*) AS n FROM (SELECT {ids}, unnest(string_split({text}, ' ')) AS w FROM {table}) WHERE w <> '' GROUP BY ALL"


@query(_words_sql("documents", "doc_id", "text"))
def text_features(spark, sf_dir):
    return hashed_words(load(spark, sf_dir, "documents", "doc_id", "text"), F.col("text"), "doc_id")


@query(_words_sql("pages", "page_id", "regexp_replace(html, '<[^>]*>', ' ', 'g')"))
def pages_features(spark, sf_dir):
    return hashed_words(load(spark, sf_dir, "pages", "page_id", "html"), F.regexp_replace("html", "<[^>]*>", " "), "page_id")


@query(_words_sql("conversations", "conv_id, turn", "text"))
def conversation_features(spark, sf_dir):
    return hashed_words(load(spark, sf_dir, "conversations", "conv_id", "turn", "text"), F.col("text"), "conv_id", "turn")


@query(_words_sql("benchmark", "item_id", "text"))
def benchmark_features(spark, sf_dir):
    return hashed_words(load(spark, sf_dir, "benchmark", "item_id", "text"), F.col("text"), "item_id")


# Around the methods: audits, features of nested columns, replay.
@query(f"WITH d AS ({_draw_sql(4, 8, 16, 'events')}) SELECT event_type, count(*) AS never FROM events WHERE event_id NOT IN (SELECT row_id FROM d) GROUP BY event_type")
def never_drawn(spark, sf_dir):
    """Rows that no worker drew, by type: an anti join against a broadcast draw table."""
    e = load(spark, sf_dir, "events", "event_id", "event_type")
    draws = draw_indices(spark, 4, 8, 16, e.count()).select(F.col("row_id").alias("event_id"))
    return e.join(F.broadcast(draws), "event_id", "left_anti").groupBy("event_type").agg(F.count("*").alias("never"))


@query("SELECT user_id, CAST(sum(CAST(floor(value * 1000) AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY user_id ORDER BY total DESC, user_id LIMIT 10")
def largest_coordinates(spark, sf_dir):
    """The ten coordinates with the largest gradient sums (top-k is the feature)."""
    e = load(spark, sf_dir, "events", "user_id", "value")
    return e.groupBy("user_id").agg(F.sum(F.floor(F.col("value") * 1000)).alias("total")).orderBy(F.desc("total"), "user_id").limit(10)


@query("SELECT event_type, CAST(json_extract_string(props, '$.k') AS BIGINT) % 8 AS coord, count(*) AS n, CAST(sum(CAST(floor(value * 1000) AS BIGINT)) AS BIGINT) AS total FROM events GROUP BY ALL")
def json_features(spark, sf_dir):
    """Sparse features out of a JSON column."""
    e = load(spark, sf_dir, "events", "event_type", "props", "value")
    k = F.get_json_object("props", "$.k").cast("long") % 8
    return e.groupBy("event_type", k.alias("coord")).agg(F.count("*").alias("n"), F.sum(F.floor(F.col("value") * 1000)).alias("total"))


_HOURS = "h AS (SELECT user_id % 16 AS run, CAST(floor(epoch(ts) / 86400) AS BIGINT) AS t, CAST(sum(CAST(floor(value * 1000) AS BIGINT)) AS BIGINT) AS loss, count(*) AS bits FROM events GROUP BY 1, 2)"


@query(f"WITH {_HOURS} SELECT run, t, loss, loss - lag(loss) OVER w AS step, CAST(sum(bits) OVER (PARTITION BY run ORDER BY t) AS BIGINT) AS bits_so_far, CAST(sum(loss) OVER (PARTITION BY run ORDER BY t ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS last_three, row_number() OVER (PARTITION BY run ORDER BY loss, t) AS place FROM h WINDOW w AS (PARTITION BY run ORDER BY t)")
def trace_windows(spark, sf_dir):
    """Decrease, running traffic, smoothed loss and rank along traces (here: daily sums by coordinate)."""
    from pyspark.sql import Window

    e = load(spark, sf_dir, "events", "user_id", "ts", "value")
    day = F.datediff(F.to_date("ts"), F.lit("1970-01-01")).cast("long")
    h = e.groupBy((F.col("user_id") % 16).alias("run"), day.alias("t")).agg(F.sum(F.floor(F.col("value") * 1000)).alias("loss"), F.count("*").alias("bits"))
    w = Window.partitionBy("run").orderBy("t")
    return h.select(
        "run", "t", "loss", (F.col("loss") - F.lag("loss").over(w)).alias("step"), F.sum("bits").over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("bits_so_far"),
        F.sum("loss").over(w.rowsBetween(-2, 0)).alias("last_three"), F.row_number().over(Window.partitionBy("run").orderBy("loss", "t")).cast("long").alias("place"),
    )


@query("""WITH i AS (SELECT CAST(floor(epoch(ts) / 21600) AS BIGINT) AS b, max(event_id) AS version, max(epoch_us(ts)) AS at FROM events WHERE event_id % 10 = 0 GROUP BY 1)
SELECT e.event_type, count(*) AS n, count(i.version) AS matched, CAST(sum(e.event_id - i.version) AS BIGINT) AS lag FROM events e ASOF LEFT JOIN i ON epoch_us(e.ts) >= i.at GROUP BY e.event_type""")
def asof_iterate(spark, sf_dir):
    """Latest iterate at or before each event: iterates are bucketed by time, each bucket carries the last one before it,
    so the as-of join is an equi-join on the bucket and a pick within it."""
    e = load(spark, sf_dir, "events", "event_id", "event_type", "ts").withColumn("us", F.expr("unix_micros(cast(ts as timestamp))"))
    six_hours = 21_600_000_000
    e = e.withColumn("b", F.floor(F.col("us") / six_hours))
    its = e.where("event_id % 10 = 0").groupBy("b").agg(F.max("event_id").alias("version"), F.max("us").alias("at"))
    span = its.agg(F.min("b"), F.max("b"), F.max_by("version", "b")).first()
    if span[0] is None:
        return e.groupBy("event_type").agg(F.count("*").alias("n"), F.lit(0).cast("long").alias("matched"), F.lit(None).cast("long").alias("lag"))
    from pyspark.sql import Window

    grid = spark.range(span[0], span[1] + 1).withColumnRenamed("id", "b").join(its, "b", "left")  # a row for each six hours
    got = grid.withColumn("it", F.when(F.col("at").isNotNull(), F.struct("version", "at")))
    before = Window.orderBy("b").rowsBetween(Window.unboundedPreceding, -1)
    carried = got.select("b", "it", F.last("it", ignorenulls=True).over(before).alias("prev"))
    joined = e.alias("e").join(F.broadcast(carried), "b", "left")
    pick = F.when(F.col("it.at") <= F.col("us"), F.col("it.version")).otherwise(F.col("prev.version"))
    beyond = F.when(F.col("e.b") > span[1], F.lit(span[2])).otherwise(pick)
    return joined.withColumn("v", beyond).groupBy("event_type").agg(F.count("*").alias("n"), F.count("v").alias("matched"), F.sum(F.col("event_id") - F.col("v")).alias("lag"))
