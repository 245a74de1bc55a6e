"""The production kernels against SQL: messages byte by byte, whole rounds, replays of runs, roundtrip errors, closed forms.

The kernels draw their signs and dithers from ``counter_hash``, which SQL can compute, so each query here runs the code
that runs use, and its SQL the dense form of the same definitions.
"""

from __future__ import annotations

from dataclasses import replace

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ditherspark.functions import closed_forms as C
from ditherspark.functions.rng import sql_counter_hash, sql_hash60
from ditherspark.operators import measures
from ditherspark.operators.codec import decode, encode
from ditherspark.operators.descent import descend, telescoping, trajectories, worker_messages
from ditherspark.operators.gradients import GradientOracle, OneSparseOracle
from ditherspark.operators.protocol import RunConfig, method, traffic
from ditherspark.plans.experiments import planted, planted_rows
from ditherspark.plans.portable import EVENT_D, _draw_sql, event_rows
from ditherspark.sources.tables import load

QUERIES, ORACLES = {}, {}


def query(sql: str):
    def add(f):
        QUERIES[f.__name__], ORACLES[f.__name__] = f, sql
        return f

    return add


def _uniform(*key: str) -> str:
    """A dither of unit amplitude."""
    return f"((2 * {sql_counter_hash(*key)} + 1) / 4294967296.0 - 1)"


def _sign(stream: int, ident: str, coord: str, seed: str = "0") -> str:
    keys = [sql_counter_hash(seed, str(stream), "0", ident, j) for j in ("0", "1")]
    return f"(1 - 2 * ({sql_counter_hash(*keys, coord)} & 1))"


_HEX = "string_agg(printf('%02x', CAST(byte AS INTEGER)), '' ORDER BY pos)"
_MINUS = "(1 - 2 * (bit_count(k & c) % 2))"

# Messages of the codec.
_X64 = "x AS (SELECT vec_id AS id, unnest(range(64)) AS c, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings), ks AS (SELECT unnest(range(64)) AS k)"
_LAM = repr(C.amplitudes(3.0, 1.0, 1.0, 64)[0])
_E64 = f"""{_X64}, e AS (SELECT id, c, x, {_sign(1, 'id', 'c')} AS e FROM x),
z AS (SELECT id, k, sum(x * e * {_MINUS}) / 8 AS z FROM e, ks GROUP BY id, k),
q AS (SELECT id, k, CAST(sum(CASE WHEN z + {_LAM} * {_uniform('0', '3', '0', 'id', 'k', 'j')} >= 0 THEN 1 ELSE -1 END) AS BIGINT) AS q FROM z, (SELECT unnest(range(7)) AS j) GROUP BY id, k)"""


@query(f"""WITH {_E64}, b AS (SELECT id, (3 * k + i) // 8 AS pos, sum((((q + 7) // 2) >> i & 1) << ((3 * k + i) % 8)) AS byte FROM q, (SELECT unnest(range(3)) AS i) GROUP BY 1, 2),
s AS (SELECT id, c // 8 AS pos, sum(((e + 1) // 2) << (c % 8)) AS byte FROM e GROUP BY 1, 2)
SELECT m.id, m.packed, n.eps FROM (SELECT id, {_HEX} AS packed FROM b GROUP BY id) m JOIN (SELECT id, {_HEX} AS eps FROM s GROUP BY id) n ON n.id = m.id""")
def codec_messages(spark, sf_dir):
    """Every byte of the encoder's messages, K = 7, alpha = 3."""
    m = encode(load(spark, sf_dir, "embeddings", "vec_id", "embedding"), float(_LAM), 7)
    return m.select("id", F.lower(F.hex("packed")).alias("packed"), F.lower(F.hex("eps")).alias("eps"))


@query(f"WITH {_E64} SELECT e.id, CAST(e.c AS INTEGER) AS coord, round(any_value(e.e) * {_LAM} / 56 * sum(q * {_MINUS}), 9) AS v FROM e JOIN q ON q.id = e.id GROUP BY e.id, e.c")
def codec_vectors(spark, sf_dir):
    """What the decoder makes of these messages."""
    m = decode(encode(load(spark, sf_dir, "embeddings", "vec_id", "embedding"), float(_LAM), 7))
    return m.select("id", F.posexplode("v").alias("coord", "v")).withColumn("v", F.round("v", 9))


# One round of every method on the planted problem.
_N, _STEP, _ALPHA = 8, 0.5, 2.6
_BASE = RunConfig(d=64, n_workers=_N, m_prime=1, k=7, rounds=1, delta=_STEP, alpha=_ALPHA, alpha_s=_ALPHA, loss="logistic", keep=4)
_ROUND = {m: method(m, _BASE) for m in ("plain", "onebit", "up_only", "down_only", "vote", "sign_mean", "no_flatten", "no_dither", "shared_sign", "random_k", "ternary", "observed")}
_ROUND["seed_wire"] = replace(_BASE, eps_wire="seed")
_ROUND["no_dither"] = replace(_ROUND["no_dither"], down="none")  # without dither the server's sums tie with zero, where rounding decides
_L1, _LS = (repr(a) for a in _BASE.amplitudes())
_ONE = "CASE WHEN {} >= 0 THEN 1 ELSE -1 END"
_GRAD = f"""hidden AS (SELECT unnest(range(64)) AS c, unnest({planted().tolist()}::DOUBLE[]) AS h),
x AS (SELECT vec_id, unnest(range(64)) AS c, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings),
y AS (SELECT vec_id, CASE WHEN sum(x * h) >= 0 THEN 1 ELSE -1 END * CASE WHEN {sql_hash60('0', repr('flip'), 'vec_id')} % 20 = 0 THEN -1 ELSE 1 END AS y FROM x JOIN hidden ON hidden.c = x.c GROUP BY vec_id),
d AS ({_draw_sql(1, _N, 1, 'embeddings')}),
g AS (SELECT worker, x.c, -y / 2.0 * x AS g FROM d JOIN x ON x.vec_id = d.row_id JOIN y ON y.vec_id = d.row_id),
ks AS (SELECT unnest(range(64)) AS k),
e AS (SELECT 'own' AS v, worker, c, g, {_sign(1, 'worker', 'c')} AS e FROM g UNION ALL SELECT 'round', worker, c, g, {_sign(1, '0', 'c')} FROM g),
z AS (SELECT v, worker, k, sum(g * e * {_MINUS}) / 8 AS z FROM e, ks GROUP BY v, worker, k UNION ALL SELECT 'none', worker, c, g FROM g),
q AS (SELECT v, worker, k, {_ONE.format(f"z + {_L1} * {_uniform('0', '3', '0', 'worker', 'k', '0')}")} AS q FROM z UNION ALL SELECT 'sure', worker, k, {_ONE.format('z')} FROM z WHERE v = 'own')"""
_BYTES = "(SELECT {0} AS method, worker, {1} // 8 AS pos, sum((({2} + 1) // 2) << ({1} % 8)) AS byte FROM {3} GROUP BY ALL)"
_CODEC = [("onebit", "own", "own"), ("up_only", "own", "own"), ("observed", "own", "own"), ("seed_wire", "own", ""), ("shared_sign", "round", "round"), ("no_dither", "sure", "own"), ("no_flatten", "none", "")]


def _messages_sql() -> str:
    parts = [_BYTES.format(f"'{m}'", "k", "q", f"q WHERE v = '{v}'") for m, v, _ in _CODEC]
    parts += [_BYTES.format(f"'{m}'", "c", "(" + _ONE.format("g") + ")", "g") for m in ("vote", "sign_mean")]
    eps = [_BYTES.format(f"'{m}'", "c", "e", f"e WHERE v = '{v}'") for m, _, v in _CODEC if v]
    seeds = " UNION ALL ".join(f"SELECT 'seed_wire' AS method, worker, {4 * j} + i AS pos, ({sql_counter_hash('0', '1', '0', 'worker', str(j))} >> (8 * i)) & 255 AS byte FROM (SELECT unnest(range({_N})) AS worker), (SELECT unnest(range(4)) AS i)" for j in (0, 1))
    return f"""WITH {_GRAD}, b AS ({' UNION ALL SELECT * FROM '.join(['SELECT * FROM ' + parts[0], *parts[1:]])}),
s AS ({' UNION ALL SELECT * FROM '.join(['SELECT * FROM ' + eps[0], *eps[1:]])} UNION ALL {seeds}),
m AS (SELECT method, worker, {_HEX} AS packed, count(*) AS n FROM b GROUP BY ALL), t AS (SELECT method, worker, {_HEX} AS eps, count(*) AS n FROM s GROUP BY ALL)
SELECT m.method, CAST(m.worker AS INTEGER) AS worker, packed, coalesce(eps, '') AS eps, CAST(8 * (m.n + coalesce(t.n, 0)) AS BIGINT) AS bits FROM m LEFT JOIN t ON t.method = m.method AND t.worker = m.worker"""


@query(_messages_sql())
def round_messages(spark, sf_dir):
    """The bytes that workers send in one round, by method: codec messages with their sign strings or seeds, and signs."""
    o = GradientOracle(planted_rows(spark, sf_dir), "logistic")
    out = None
    for name, cfg in _ROUND.items():
        if cfg.up in ("codec", "sign"):
            m = worker_messages(o.worker_gradients(np.zeros(64), 0, cfg), cfg, 0, 0)
            bits = (8 * (F.octet_length("packed") + F.octet_length("eps"))).cast("long").alias("bits")
            m = m.select(F.lit(name).alias("method"), "worker", F.lower(F.hex("packed")).alias("packed"), F.lower(F.hex("eps")).alias("eps"), bits)
            out = m if out is None else out.union(m)
    return out


def _down(name: str, how: str) -> str:
    """What workers decode from ``w`` of the method ``name``."""
    if how == "float":
        return f"SELECT '{name}' AS method, c, w, CAST(CAST(w AS FLOAT) AS DOUBLE) AS v FROM w WHERE method = '{name}'"
    if how == "sign":
        return f"SELECT '{name}' AS method, c, w, {_ONE.format('w')} AS v FROM w WHERE method = '{name}'"
    tau = _uniform("0", "4", "0", "0", "k", "j")
    flat = how != "identity"
    z = f"SELECT k, sum(w * {_sign(2, '0', 'c')} * {_MINUS}) / 8 AS z FROM (SELECT * FROM w WHERE method = '{name}'), ks GROUP BY k" if flat else f"SELECT c AS k, w AS z FROM w WHERE method = '{name}'"
    lam = "(SELECT max(abs(z)) FROM zs)" if how == "observed" else _LS
    level = f"SELECT k, sum({_ONE.format(f'z + {lam} * {tau}')}) AS q FROM zs, (SELECT unnest(range(7)) AS j) GROUP BY k"
    back = f"SELECT c, any_value({_sign(2, '0', 'c')}) * {lam} / 56 * sum(q * {_MINUS}) AS v FROM qs, (SELECT k AS c FROM ks) GROUP BY c" if flat else f"SELECT k AS c, q * {lam} / 7 AS v FROM qs"
    return f"SELECT '{name}' AS method, b.c, ww.w, b.v FROM (WITH zs AS ({z}), qs AS ({level}) {back}) b JOIN w ww ON ww.c = b.c AND ww.method = '{name}'"


def _iterates_sql() -> str:
    dec = f"SELECT v, worker, c, {_L1} / 8 * any_value(e) * sum(q * {_MINUS}) AS g FROM (SELECT q.v, q.worker, e.c, q.k, q.q, e.e FROM q JOIN e ON e.worker = q.worker AND e.v = CASE q.v WHEN 'sure' THEN 'own' ELSE q.v END) GROUP BY v, worker, c UNION ALL SELECT v, worker, k, {_L1} * q FROM q WHERE v = 'none'"
    keep = f"SELECT worker, c, g, row_number() OVER (PARTITION BY worker ORDER BY {sql_counter_hash('0', '5', '0', 'worker', 'c')}, c) AS place FROM g"
    norm = "SELECT worker, sqrt(sum(g * g)) AS norm FROM g GROUP BY worker"
    u = f"((2 * {sql_counter_hash('0', '6', '0', 'g.worker', 'c')} + 1) / 8589934592.0)"
    mean = lambda name, rows: f"SELECT '{name}' AS method, c, sum(g) / {_N} AS w FROM ({rows}) GROUP BY c"
    real = "SELECT c, CAST(CAST(g AS FLOAT) AS DOUBLE) AS g FROM g"
    signs = f"SELECT c, {_ONE.format('g')} AS g FROM g"
    up = [mean(m, f"SELECT c, g FROM dec WHERE v = '{v}'") for m, v, _ in _CODEC] + [mean(m, real) for m in ("plain", "down_only")] + [mean(m, signs) for m in ("vote", "sign_mean")]
    up += [mean("random_k", f"SELECT c, CASE WHEN place <= 4 THEN CAST(CAST(g * 64 / 4 AS FLOAT) AS DOUBLE) ELSE 0 END AS g FROM ({keep})")]
    up += [mean("ternary", f"SELECT c, CASE WHEN {u} * norm < abs(g) THEN sign(g) * CAST(CAST(norm AS FLOAT) AS DOUBLE) ELSE 0 END AS g FROM g JOIN ({norm}) n ON n.worker = g.worker")]
    how = {"plain": "float", "up_only": "float", "sign_mean": "float", "random_k": "float", "ternary": "float", "vote": "sign", "no_flatten": "identity", "no_dither": "float", "observed": "observed"}
    down = " UNION ALL ".join(_down(m, how.get(m, "codec")) for m in _ROUND)
    return f"WITH {_GRAD}, dec AS ({dec}), w AS ({' UNION ALL '.join(up)}) SELECT method, CAST(c AS INTEGER) AS coord, round(w, 9) AS w, round(v, 9) AS v, round(-{_STEP} * v, 9) AS x FROM ({down})"


@query(_iterates_sql())
def round_iterates(spark, sf_dir):
    """A whole distributed round of every method: the server's mean ``w``, the direction ``v`` that all workers decode and
    the next iterate, through packed messages and exchanges."""
    o = GradientOracle(planted_rows(spark, sf_dir), "logistic")
    out = []
    for name, cfg in _ROUND.items():
        r = descend(o, cfg)
        t = r.trace[0]
        out += [(name, i, float(t["w"][i]), float(t["v"][i]), float(r.x_last[i])) for i in range(64)]
    rows = spark.createDataFrame(out, "method string, coord int, w double, v double, x double")
    return rows.select("method", "coord", *[(F.round(c, 9) + 0.0).alias(c) for c in ("w", "v", "x")])


# Replays of whole runs on 1-sparse gradients.
_T, _EN, _ED = 30, 64, 0.05


def _replay_sql() -> str:
    """Runs as recursion over rounds; a state is the iterate, ``r`` the round's draws as a list of (c, y)."""
    draws = f"SELECT t, list({{'w': worker, 'c': c, 'y': y}} ORDER BY worker) AS r FROM ({_draw_sql(_T, _EN, 1, 'events')}) d JOIN ev ON ev.event_id = d.row_id GROUP BY t"
    own = "list_transform(range(1, 17), lambda i: {})"
    grad = "CAST(2 * (s.x[i] - dd.y) AS FLOAT)"
    runs = {
        "plain": own.format(f"CAST(coalesce(list_sum(list_transform(list_filter(r, lambda dd: dd.c + 1 = i), lambda dd: CAST({grad} AS DOUBLE))), 0) / {_EN} AS FLOAT)"),
        "local": own.format(f"CAST(coalesce(list_sum(list_transform(list_filter(r, lambda dd: dd.w = 0 AND dd.c + 1 = i), lambda dd: CAST({grad} AS DOUBLE))), 0) AS FLOAT)"),
        "sign_mean": own.format(f"CAST(({_EN} - 2 * len(list_filter(r, lambda dd: dd.c + 1 = i AND s.x[i] < dd.y))) / {_EN} AS FLOAT)"),
        "vote": own.format(f"CASE WHEN {_EN} - 2 * len(list_filter(r, lambda dd: dd.c + 1 = i AND s.x[i] < dd.y)) >= 0 THEN 1 ELSE -1 END"),
    }
    step = "CASE s.run " + " ".join(f"WHEN '{k}' THEN list_transform({v}, lambda a: CAST(a AS DOUBLE))" for k, v in runs.items()) + " END"
    return f"""WITH RECURSIVE ev AS (SELECT event_id, CAST(user_id % {EVENT_D} AS INTEGER) AS c, value / 100 AS y FROM events),
st AS (SELECT c, count(*) / (SELECT count(*) FROM ev) AS p, avg(y) AS mu FROM ev GROUP BY c),
lists AS (SELECT list(coalesce(p, 0) ORDER BY k) AS p, list(coalesce(mu, 0) ORDER BY k) AS mu FROM (SELECT unnest(range(16)) AS k) LEFT JOIN st ON st.c = k),
dr AS ({draws}),
walk AS (SELECT run, 0 AS t, list_transform(range(16), lambda i: CAST(0 AS DOUBLE)) AS x, CAST(NULL AS DOUBLE[]) AS v FROM (SELECT unnest({list(runs)}) AS run)
  UNION ALL SELECT run, t + 1, list_transform(range(1, 17), lambda i: x[i] - {_ED} * v[i]), v FROM (SELECT s.run, s.t, s.x, {step} AS v FROM walk s JOIN dr ON dr.t = s.t)),
rounds AS (SELECT a.run, a.t, a.x, b.v FROM walk a JOIN walk b ON b.run = a.run AND b.t = a.t + 1),
means AS (SELECT run, {_T} AS t, list_transform(range(1, 17), lambda i: list_sum(list_transform(xs, lambda x: x[i])) / {_T}) AS x FROM (SELECT run, list(x ORDER BY t) AS xs FROM rounds GROUP BY run)),
every AS (SELECT run, t, x, v FROM rounds UNION ALL SELECT run, t, x, list_transform(range(16), lambda i: CAST(0 AS DOUBLE)) FROM means),
m AS (SELECT run, t, list_sum(list_transform(range(1, 17), lambda i: p[i] * (x[i] - mu[i]) * (x[i] - mu[i]))) AS gap, sqrt(list_sum(list_transform(range(1, 17), lambda i: (x[i] - mu[i]) * (x[i] - mu[i])))) AS distance,
  list_sum(v) AS half_space, list_sum(list_transform(v, lambda a: a * a)) AS v_sq, list_sum(list_transform(range(1, 17), lambda i: (x[i] - mu[i]) * v[i])) AS inner_v, list_sum(list_transform(mu, lambda a: a * a)) AS mu_sq FROM every, lists)
SELECT run, CAST(t AS INTEGER) AS t, round(gap, 6) AS gap, round(distance, 6) AS distance, round(half_space, 6) AS half_space,
  round(mu_sq / 2 + sum({_ED * _ED / 2!r} * v_sq - {_ED} * inner_v) OVER (PARTITION BY run ORDER BY t), 6) AS slack FROM m"""


@query(_replay_sql())
def descent_replay(spark, sf_dir):
    """Every round of plain, single-node and sign descent: gap, distance from the minimiser, <v, 1>, and the slack of the
    telescoping inequality so far; the last row of a run is its average iterate."""
    from pyspark.sql import Window

    o = OneSparseOracle(event_rows(spark, sf_dir))
    n, mu, _ = o.statistics(EVENT_D)
    p = n / n.sum()
    base = RunConfig(d=EVENT_D, n_workers=_EN, rounds=_T, delta=_ED)
    t = trajectories(o, {m: method(m, base) for m in ("plain", "sign_mean", "vote")}, x_star=mu)
    t = t.union(trajectories(o, {"local": method("local", base)}, x_star=mu))
    arr = lambda v: F.array(*[F.lit(float(x)) for x in v])
    sq = F.zip_with("x", arr(mu), lambda a, b: (a - b) * (a - b))
    total = lambda a: F.aggregate(a, F.lit(0.0), lambda s, v: s + v)
    so_far = F.sum(F.lit(_ED * _ED / 2) * F.col("v_sq") - F.lit(_ED) * F.col("inner")).over(Window.partitionBy("run").orderBy("t"))
    rows = t.select("run", "t", total(F.zip_with(sq, arr(p), lambda a, b: a * b)).alias("gap"), F.sqrt(total(sq)).alias("distance"), "half_space", (F.lit(float(mu @ mu) / 2) + so_far).alias("slack"))
    return rows.select("run", "t", *[(F.round(c, 6) + 0.0).alias(c) for c in ("gap", "distance", "half_space", "slack")])


@query(_replay_sql().rsplit("SELECT run, CAST(t AS INTEGER)", 1)[0].rsplit(",\nm AS", 1)[0] + f"""
SELECT run, round(sum(list_sum(list_transform(range(1, 17), lambda i: (x[i] - mu[i]) * v[i])) * {_ED}), 6) AS progress,
  round(any_value(list_sum(list_transform(mu, lambda a: a * a))) / 2 + sum(list_sum(list_transform(v, lambda a: a * a))) * {_ED * _ED / 2!r}, 6) AS allowed FROM rounds, lists WHERE run <> 'local' GROUP BY run""")
def telescoping_replay(spark, sf_dir):
    """Both sides of the telescoping inequality over whole runs."""
    o = OneSparseOracle(event_rows(spark, sf_dir))
    _, mu, _ = o.statistics(EVENT_D)
    base = RunConfig(d=EVENT_D, n_workers=_EN, rounds=_T, delta=_ED)
    t = telescoping(trajectories(o, {m: method(m, base) for m in ("plain", "sign_mean", "vote")}, x_star=mu), mu)
    return t.select("run", F.round("progress", 6).alias("progress"), F.round("allowed", 6).alias("allowed"))


# Roundtrip errors.
_BASIS = {
    "butterfly": "SELECT k, c, (1 - 2 * (bit_count(k & c) % 2)) / sqrt({d}) AS m FROM ks, cs",
    "identity": "SELECT k, c, CASE WHEN k = c THEN 1.0 ELSE 0.0 END AS m FROM ks, cs",
    "cosine": "SELECT k, c, sqrt(2.0 / {d}) * CASE WHEN k = 0 THEN sqrt(0.5) ELSE 1 END * cos(pi() * (2 * c + 1) * k / (2 * {d})) AS m FROM ks, cs",
    "fourier": "SELECT k, c, CASE WHEN k < {d} THEN cos(2 * pi() * k * c / {d}) ELSE -sin(2 * pi() * (k - {d}) * c / {d}) END / sqrt({d}) AS m FROM (SELECT unnest(range(2 * {d})) AS k), cs",
}


def _roundtrip_sql(rows: str, d: int, seeds: int, configs: list[tuple[str, float, int]]) -> str:
    eps = {b: "1" if b == "identity" else _sign(1, "id", "c", "seed") for b in _BASIS}
    bases = sorted({b for b, _, _ in configs})
    flat = " UNION ALL ".join(f"SELECT '{b}' AS basis, id, seed, k, sum(x * e * m) AS z FROM (SELECT id, seed, c, x, {eps[b]} AS e FROM x, sd) a JOIN ({_BASIS[b].format(d=d)}) b ON b.c = a.c GROUP BY id, seed, k" for b in bases)
    cfg = ", ".join(f"('{b}', {a!r}::DOUBLE, {k}, {C.amplitudes(a, 1.0, 1.0, d)[0]!r}::DOUBLE)" for b, a, k in configs)
    tau = _uniform("seed", "3", "0", "id", "k", "j")
    back = " UNION ALL ".join(f"SELECT '{b}' AS basis, alpha, dithers, id, seed, b.c, any_value(lam) / dithers * sum(q * m) AS y FROM q JOIN ({_BASIS[b].format(d=d)}) b ON b.k = q.k WHERE basis = '{b}' GROUP BY alpha, dithers, id, seed, b.c" for b in bases)
    sign = "CASE basis " + " ".join(f"WHEN '{b}' THEN {eps[b].replace('id', 'y.id').replace('seed', 'y.seed')}" for b in bases if b != "identity") + " ELSE 1 END" if bases != ["identity"] else "1"
    sign = "CASE WHEN basis = 'identity' THEN 1 ELSE " + _sign(1, "y.id", "y.c", "y.seed") + " END"
    return f"""WITH x AS ({rows}), sd AS (SELECT unnest(range({seeds})) AS seed), ks AS (SELECT unnest(range({d})) AS k), cs AS (SELECT unnest(range({d})) AS c),
cfg(basis, alpha, dithers, lam) AS (VALUES {cfg}), z AS ({flat}),
q AS (SELECT z.basis, alpha, dithers, any_value(lam) AS lam, id, seed, k, sum(CASE WHEN z + lam * {tau} >= 0 THEN 1 ELSE -1 END) AS q FROM z JOIN cfg ON cfg.basis = z.basis, (SELECT unnest(range(7)) AS j) WHERE j < dithers GROUP BY z.basis, alpha, dithers, id, seed, k),
y AS ({back}),
err AS (SELECT basis, alpha, dithers, y.id, y.seed, sum(power(y * {sign} - x, 2)) AS err_sq, sum(y * y) AS out_sq, sum(x * x) AS norm_sq FROM y JOIN x ON x.id = y.id AND x.c = y.c GROUP BY ALL),
top AS (SELECT basis, id, seed, max(abs(z)) AS top FROM z GROUP BY ALL)
SELECT e.basis, e.alpha, CAST(e.dithers AS INTEGER) AS k, count(*) AS n, round(avg(err_sq), 6) AS mse, round(stddev(err_sq) / sqrt(count(*)), 6) AS std_error,
  round((any_value(lam) * any_value(lam) * {d} - avg(norm_sq) / CASE WHEN e.basis = 'fourier' THEN 2 ELSE 1 END) / e.dithers, 6) AS exact,
  round(e.alpha * e.alpha * ln({d}) / e.dithers + 8 * exp(-e.alpha * e.alpha * ln({d}) / 8), 6) AS bound, round(avg(CASE WHEN top > lam THEN 1.0 ELSE 0.0 END), 6) AS clip_share, round(2 * exp(-e.alpha * e.alpha * ln({d}) / 4), 6) AS clip_bound,
  round(avg(top / sqrt(norm_sq)), 6) AS top_entry, CAST(sum(CASE WHEN sqrt(out_sq) > lam * sqrt({d} * CASE WHEN e.basis = 'fourier' THEN 2 ELSE 1 END) * (1 + 1e-9) THEN 1 ELSE 0 END) AS BIGINT) AS over_cap
FROM err e JOIN top t ON t.basis = e.basis AND t.id = e.id AND t.seed = e.seed JOIN cfg ON cfg.basis = e.basis AND cfg.alpha = e.alpha AND cfg.dithers = e.dithers GROUP BY e.basis, e.alpha, e.dithers"""


def _rounded(df: DataFrame) -> DataFrame:
    return df.select(*[F.round(f.name, 6).alias(f.name) if f.dataType.typeName() == "double" and f.name != "alpha" else F.col(f.name) for f in df.schema])


_RT = [("butterfly", a, k) for a in (2.0, 3.0, 4.0) for k in (1, 7)]
_RB = [(b, 3.0, 1) for b in ("butterfly", "cosine", "fourier", "identity")]
_RS = [(b, 2.0, 1) for b in ("butterfly", "cosine", "identity")]
_VECS = "SELECT vec_id AS id, unnest(range(64)) AS c, CAST(unnest(embedding) AS DOUBLE) AS x FROM embeddings"


@query(_roundtrip_sql(_VECS, 64, 2, _RT))
def roundtrip_mse_table(spark, sf_dir):
    """Roundtrip error over alpha and K beside its exact value and bound, clips, and outputs over the norm cap."""
    return _rounded(measures.roundtrip_table(load(spark, sf_dir, "embeddings", "vec_id", "embedding"), _RT, 64, 2))


@query(_roundtrip_sql(_VECS, 64, 1, _RB))
def basis_comparison(spark, sf_dir):
    """Roundtrip error and largest entry by basis, on dense vectors."""
    return _rounded(measures.roundtrip_table(load(spark, sf_dir, "embeddings", "vec_id", "embedding"), _RB, 64, 1))


@query(_roundtrip_sql(f"SELECT event_id AS id, c, CASE WHEN user_id % {EVENT_D} = c THEN 1.0 ELSE 0.0 END AS x FROM events, (SELECT unnest(range({EVENT_D})) AS c)", EVENT_D, 1, _RS))
def flatness_sparse(spark, sf_dir):
    """The same on one-hot vectors: without a flat basis the largest entry stays 1."""
    hot = F.transform(F.sequence(F.lit(0), F.lit(EVENT_D - 1)), lambda i: F.when(i == F.col("coord"), 1.0).otherwise(0.0))
    rows = event_rows(spark, sf_dir).select(F.col("row_id").alias("vec_id"), hot.alias("embedding"))
    return _rounded(measures.roundtrip_table(rows, _RS, EVENT_D, 1))


# Ledgers and closed forms.
_LEDGER = {
    "plain": ("32 * 48 * n", "32 * 48"), "onebit": ("2 * 64 * n", "9 * 64"), "seed_wire": ("(64 + 64) * n", "8 * 64 + 64"), "vote": ("48 * n", "48"), "sign_mean": ("48 * n", "32 * 48"),
    "no_flatten": ("64 * n", "8 * 64"), "observed": ("2 * 64 * n", "9 * 64 + 64"), "fourier": ("3 * 64 * n", "9 * 64 + 8 * 64"), "random_k": ("n * 4 * (32 + log2(48))", "32 * 48"), "ternary": ("n * (48 * log2(3) + 32)", "32 * 48"),
}


@query("WITH r AS (SELECT n, count(*) AS rounds FROM (SELECT count(DISTINCT user_id % 16) AS n FROM events GROUP BY floor(epoch(ts) / 3600)) GROUP BY n) "
       "SELECT coalesce(method, 'all') AS method, coalesce(party, 'all') AS party, round(sum(bits * rounds), 3) AS bits FROM ("
       + " UNION ALL ".join(f"SELECT '{m}' AS method, '{p}' AS party, rounds, CAST({e} AS DOUBLE) AS bits FROM r" for m, both in _LEDGER.items() for p, e in zip(("up", "down"), both, strict=True))
       + ") GROUP BY ROLLUP (method, party)")
def bits_ledger(spark, sf_dir):
    """Bits of a run over ``events`` by method and party with subtotals: each hour is a round of those of 16 workers (by
    user) that have rows in it; d = 48 (64 on the wire), K = 255."""
    rows = []
    for n in range(1, 17):
        base = RunConfig(d=48, n_workers=n)
        for name in _LEDGER:
            cfg = replace(base, eps_wire="seed") if name == "seed_wire" else method(name, base)
            rows += [(n, name, p, b) for p, b in zip(("up", "down"), traffic(cfg), strict=True)]
    hour = F.floor(F.expr("unix_micros(cast(ts as timestamp))") / 3_600_000_000)
    hours = load(spark, sf_dir, "events", "user_id", "ts").groupBy(hour.alias("t")).agg(F.count_distinct(F.col("user_id") % 16).alias("n"))
    each = spark.createDataFrame(rows, "n long, method string, party string, bits double")
    out = hours.groupBy("n").agg(F.count("*").alias("rounds")).join(F.broadcast(each), "n").rollup("method", "party").agg(F.round(F.sum(F.col("bits") * F.col("rounds")), 3).alias("bits"))
    return out.select(F.coalesce("method", F.lit("all")).alias("method"), F.coalesce("party", F.lit("all")).alias("party"), "bits")


_LN = "ln(d)"
_DECAY = f"exp(-alpha * alpha * {_LN} / 8)"
_FORMS = {
    "lam": f"b * alpha * sqrt({_LN} / d)",
    "lam_s": f"b * alpha * alpha * {_LN} / sqrt(d)",
    "min_alpha": f"greatest(2, sqrt(26.1 / {_LN}))",
    "ops": "d * log2(d)",
    "flatness_failure": f"2 * power({_DECAY}, 2)",
    "tail": "2 * d * exp(-0.5 * 0.5 * d / 2)",
    "roundtrip_mse": f"b * b * (alpha * alpha * {_LN} / k + 8 * {_DECAY})",
    "mean_roundtrip": f"b * b * ((alpha * alpha * {_LN} + 8 * {_DECAY}) / n + 8 * n * {_DECAY})",
    "worker_deviation": f"b * b * (2 * alpha * alpha * {_LN} / n + 8 * n * {_DECAY})",
    "server_deviation": f"b * b * (power(alpha, 4) * {_LN} * {_LN} / k + 8 * alpha * alpha * {_LN} * {_DECAY})",
    "variance_of_mean": "2.5 / n",
    "plain": "4 / (2 * 100 * 0.01) + 0.01 * 1 + 2 * 2.5 / n * 0.01",
    "general": "4 / (2 * 100 * 0.01) + 0.01 * 1 + 2 * 2.5 / n * 0.01 + 2 * 0.01 * 0.7 + 0.3",
    "worker_share": f"b * b * 8 * alpha * alpha * {_LN} * 0.01 / n",
    "server_share": f"b * b * 4 * power(alpha, 4) * {_LN} * {_LN} * 0.01 / k",
    "clip_sq": f"b * b * 32 * 0.01 * {_DECAY} * (n + alpha * alpha * {_LN})",
    "clip_distance": f"b * 4 * 3 * {_DECAY} * (n + alpha * sqrt({_LN}))",
    "rho_tight": f"b * 2 * (1 + alpha * sqrt({_LN})) * power({_DECAY}, 2)",
    "rho_printed": f"b * 2 * n * (1 + alpha * sqrt({_LN})) * power({_DECAY}, 2)",
    "rho_server": f"b * 2 * sqrt(d) * (alpha * sqrt({_LN} / d) + alpha * alpha * {_LN} / sqrt(d)) * power({_DECAY}, 2)",
    "nonconvex": f"0.25 / 10 + (0.1 + 0.2) * b + 0.318 * power(b * alpha * alpha * {_LN} / sqrt(d), 2) * d / 2 / 10",
}


@query("SELECT CAST(d AS INTEGER) AS d, CAST(n AS INTEGER) AS n, CAST(k AS INTEGER) AS k, alpha, round(b, 6) AS b, " + ", ".join(f"round({e}, 6) AS {a}" for a, e in _FORMS.items())
       + " FROM (SELECT unnest([16, 64, 1024]) AS d), (SELECT unnest([16, 1024]) AS n), (SELECT unnest([1, 255]) AS k), (SELECT unnest([2.0, 3.0, 4.0]::DOUBLE[]) AS alpha),"
       " (SELECT coalesce(CAST(max(abs(x)) AS DOUBLE), 0) AS b FROM (SELECT unnest(embedding) AS x FROM embeddings))")
def bound_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Amplitudes, probabilities, moments and every term of the bounds over a grid, by the functions that runs use. B bounds the
    gradients with one entry out of ``embeddings``: it is the largest entry there."""
    b = load(spark, sf_dir, "embeddings", "embedding").agg(F.max(F.array_max(F.transform("embedding", F.abs))).cast("double")).first()[0] or 0.0
    rows = []
    for d in (16, 64, 1024):
        for n in (16, 1024):
            for k in (1, 255):
                for a in (2.0, 3.0, 4.0):
                    plain = C.bound_plain(4.0, [0.01] * 100, [1.0] * 100, 2.5, n)
                    terms, rho, (lam, lam_s) = C.bound_compressed(plain, a, a, b, d, n, k, 0.01, 3.0), C.rho_terms(a, a, b, d, n), C.amplitudes(a, a, b, d)
                    general = C.bound_general(plain, [0.01] * 100, [0.7] * 100, [0.3] * 100)
                    first, second = C.round_deviation_bounds(a, a, b, d, n, k)
                    found = {
                        "lam": lam, "lam_s": lam_s, "min_alpha": C.min_alpha(d), "ops": C.butterfly_ops(d), "flatness_failure": C.flatness_failure(a, d), "tail": C.tail_bound(0.5, d**-0.5, d),
                        "roundtrip_mse": C.roundtrip_mse_bound(a, b, d, k), "mean_roundtrip": C.mean_roundtrip_mse_bound(a, b, d, n), "worker_deviation": first, "server_deviation": second,
                        "variance_of_mean": C.variance_of_mean([2.5] * n), "plain": sum(plain.values()), "general": sum(general.values()), **{x: terms[x] for x in ("worker_share", "server_share", "clip_sq", "clip_distance")},
                        **rho, "nonconvex": C.bound_nonconvex(0.25, 0.1, 0.2, b, 0.318, lam_s, d, [0.1] * 100),
                    }
                    rows.append((d, n, k, a, b, *[float(found[x]) for x in _FORMS]))
    out = spark.createDataFrame(rows, "d int, n int, k int, alpha double, b double, " + ", ".join(f"{x} double" for x in _FORMS))
    return out.select("d", "n", "k", "alpha", F.round("b", 6).alias("b"), *[F.round(x, 6).alias(x) for x in _FORMS])
