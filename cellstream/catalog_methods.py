"""Queries of the methods: smoothing, robust cleaning, start-up solver, online steps, compared methods, measures."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Window
from pyspark.sql import functions as F

from .baselines import methods
from .catalog import _cube, _factor, _factors, _given, _given_sql, _hat_sql, _vec_sql, _with, query, r6
from .functions import lts, robust
from .model import HyperParams, SeasonState, Snapshot, TensorSpec
from .operators import algebra, corrupt, metrics
from .plans import smooth_als, startup
from .sources import cubes
from .sources.tables import load, staged
from .streaming import fold, kernel, step

# ---- smoothing of daily event sums by type, period 7

_SERIES = "series AS (SELECT list_position(['click','error','purchase','signup','view'], event_type) - 1 AS key, date_diff('day', DATE '2024-01-01', CAST(ts AS DATE)) AS t, sum(round(value * 100)::BIGINT) / 100 AS y FROM events GROUP BY ALL)"


def _series(s, d):
    e = load(s, d, "events").select(cubes.code("event_type", cubes.EVENT_TYPES).cast("long").alias("key"), cubes.day("ts", cubes.EVENTS_FROM).alias("t"), "value")
    return e.groupBy("key", "t").agg((F.sum(cubes.cents("value")) / 100).alias("y"))


def _fold_sql(kind="additive", rob="", a="0.3", b="0.1", g="0.2", phi="0.1", sigma2="1e4", grid=""):
    old = "season[1]"
    yhat = f"level + trend + {old}" if kind == "additive" else f"(level + trend) * {old}"
    level = "{a} * (v - old) + (1 - {a}) * base" if kind == "additive" else "{a} * (v / old) + (1 - {a}) * base"
    season = "{g} * (v - base) + (1 - {g}) * old" if kind == "additive" else "{g} * (v / base) + (1 - {g}) * old"
    level, season = level.format(a=a), season.format(g=g)
    rho = "CASE WHEN abs(e / sqrt(sigma2)) <= 2 THEN 2.52 * (1 - (1 - (e / sqrt(sigma2) / 2) ** 2) ** 3) ELSE 2.52 END"
    moved = f"sigma2 * (1 - {phi} + {phi} * ({rho}))" if rob else "sigma2"
    used = {"": "1", "scale_first": "sqrt(moved)", "reject_first": "sqrt(sigma2)"}[rob]
    v = f"greatest(least(e / {used}, 2), -2) * {used} + yhat" if rob else "ys[k + 1]"
    first = "x - m1" if kind == "additive" else "x / m1"
    keep = "p1, p2, p3, " if grid else ""
    return f"""WITH RECURSIVE {_SERIES}, l AS (SELECT key, list(y ORDER BY t) AS ys FROM series GROUP BY key),
i0 AS (SELECT key, {keep}ys, list_sum(ys[1:7]) / 7 AS m1, list_sum(ys[8:14]) / 7 AS m2 FROM l {grid}),
st AS (SELECT key, {keep}ys, 0::BIGINT AS k, m1::DOUBLE AS level, ((m2 - m1) / 7)::DOUBLE AS trend, list_transform(ys[1:7], lambda x: {first})::DOUBLE[] AS season, {sigma2}::DOUBLE AS sigma2, 0::DOUBLE AS sse, 0::DOUBLE AS yhat, 0::DOUBLE AS clean, 0::DOUBLE AS ns FROM i0
UNION ALL SELECT key, {keep}ys, k + 1, nl, {b} * (nl - level) + (1 - {b}) * trend, season[2:] || [ns2], moved, sse + e * e, yhat2, v, ns2 FROM (
 SELECT *, {level} AS nl, {season} AS ns2 FROM (SELECT *, {v} AS v, yhat AS yhat2 FROM (SELECT *, {moved} AS moved FROM (SELECT *, ys[k + 1] - yhat AS e FROM (
  SELECT key, {keep}ys, k, level, trend, season, sigma2, sse, {old} AS old, level + trend AS base, {yhat} AS yhat FROM st WHERE k < len(ys)))))))"""


def _ys(s, d):
    return lts.ordered(_series(s, d))


def _start(kind="additive"):
    one, change, season = lts.initial(F.col("ys"), 7)
    return one, change, season if kind == "additive" else F.transform(F.slice("ys", 1, 7), lambda x: x / one)


def _state(s, d, kind="additive", rob="", **more):
    level, trend, season = _start(kind)
    return _ys(s, d).select("key", "ys", lts.fold(F.col("ys"), level, trend, season, *more.pop("p", (0.3, 0.1, 0.2)), kind=kind, robust=rob, sigma2=F.lit(1e4), **more).alias("st"))


def _path(df):
    return df.select("key", F.posexplode("st.path").alias("t", "p")).select("key", F.col("t").cast("long").alias("t"), *[r6(F.col(f"p.{c}")).alias(c) for c in ("level", "trend", "season", "yhat", "clean")])


_PATH = " SELECT key, k - 1 AS t, round(level, 6) + 0.0 AS level, round(trend, 6) + 0.0 AS trend, round(ns, 6) + 0.0 AS season, round(yhat, 6) + 0.0 AS yhat, round(clean, 6) + 0.0 AS clean FROM st WHERE k > 0"

for _name, _kind, _rob in (("lts_additive_states", "additive", ""), ("lts_multiplicative_states", "multiplicative", ""), ("robust_lts_scale_first", "additive", "scale_first"), ("robust_lts_reject_first", "additive", "reject_first")):
    query(_name, _fold_sql(_kind, _rob) + _PATH)(lambda s, d, k=_kind, r=_rob: _path(_state(s, d, k, r)))


@query("lts_forecast", _fold_sql() + " SELECT key, h, round(level + h * trend + season[(h - 1) % 7 + 1], 6) + 0.0 AS yhat FROM st, range(1, 18) r(h) WHERE k = len(ys)")
def lts_forecast(s, d):
    rows = _state(s, d).select("key", "st", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(17).cast("long"))).alias("h"))
    return rows.select("key", "h", r6(lts.forecast(F.col("st"), F.col("h"), 7)).alias("yhat"))


@query("lts_residuals_sse", _fold_sql() + " SELECT key, round(sse, 4) AS sse FROM st WHERE k = len(ys)")
def lts_residuals_sse(s, d):
    return _state(s, d).select("key", F.round("st.sse", 4).alias("sse"))


@query("lts_initial_state", f"WITH {_SERIES}, l AS (SELECT key, list(y ORDER BY t) AS ys FROM series GROUP BY key) SELECT key, round(list_sum(ys[1:7]) / 7, 6) AS level, round((list_sum(ys[8:14]) - list_sum(ys[1:7])) / 49, 6) + 0.0 AS trend, round(ys[1] - list_sum(ys[1:7]) / 7, 6) + 0.0 AS first_season FROM l")
def lts_initial_state(s, d):
    level, trend, season = _start()
    return _ys(s, d).select("key", F.round(level, 6).alias("level"), r6(trend).alias("trend"), r6(season[0]).alias("first_season"))


_GRID = "CROSS JOIN (VALUES (0.1), (0.3), (0.5), (0.7)) a(p1) CROSS JOIN (VALUES (0.1), (0.3)) b(p2) CROSS JOIN (VALUES (0.1), (0.4)) c(p3)"


@query("lts_grid_fit", _fold_sql(a="p1", b="p2", g="p3", grid=_GRID) + " SELECT key, round(min(sse), 4) AS sse, arg_min(p1, sse)::DOUBLE AS alpha, arg_min(p2, sse)::DOUBLE AS beta, arg_min(p3, sse)::DOUBLE AS gamma FROM st WHERE k = len(ys) GROUP BY key")
def lts_grid_fit(s, d):
    grid = s.createDataFrame([(a, b, g) for a in (0.1, 0.3, 0.5, 0.7) for b in (0.1, 0.3) for g in (0.1, 0.4)], "a double, b double, g double")
    level, trend, season = _start()
    tried = _ys(s, d).crossJoin(F.broadcast(grid)).select("key", "a", "b", "g", lts.fold(F.col("ys"), level, trend, season, F.col("a"), F.col("b"), F.col("g"))["sse"].alias("sse"))
    return tried.groupBy("key").agg(F.round(F.min("sse"), 4).alias("sse"), F.min_by("a", "sse").alias("alpha"), F.min_by("b", "sse").alias("beta"), F.min_by("g", "sse").alias("gamma"))


@query("lts_quasi_newton_fit")
def lts_quasi_newton_fit(s, d):
    """Bounded quasi-Newton fit of every series, one group each."""
    def go(pdf):
        import pandas as pd

        from .functions import lts_fit

        y = pdf.sort_values("t")["y"].to_numpy(float)
        p, sse, _ = lts_fit.fit(y, 7)
        return pd.DataFrame([(int(pdf["key"].iloc[0]), *map(float, p), float(sse))], columns=["key", "alpha", "beta", "gamma", "sse"])

    return _series(s, d).groupBy("key").applyInPandas(go, "key long, alpha double, beta double, gamma double, sse double")


@query("lts_estimated_states")
def lts_estimated_states(s, d):
    """Squared error of every series with first states taken from season means, and with estimated ones."""
    def go(pdf):
        import pandas as pd

        from .functions import lts_fit

        y = pdf.sort_values("t")["y"].to_numpy(float)
        return pd.DataFrame([(int(pdf["key"].iloc[0]), float(lts_fit.fit(y, 7)[1]), float(lts_fit.fit_states(y, 7)[1]))], columns=["key", "sse_usual", "sse_estimated"])

    return _series(s, d).groupBy("key").applyInPandas(go, "key long, sse_usual double, sse_estimated double")


@query("lts_exponential_weights", f"WITH {_SERIES}, n AS (SELECT key, max(t) AS last, count(*) AS n FROM series GROUP BY key), r AS (SELECT key, y, row_number() OVER (PARTITION BY key ORDER BY t) AS k FROM series), w AS (SELECT key, y, 0.3 * pow(0.7, n - k) AS w, n FROM r JOIN n USING (key)) SELECT key, round(sum(w * y), 6) + 0.0 AS level, round(sum(w) + pow(0.7, any_value(n)), 9) AS weights FROM w GROUP BY key")
def lts_exponential_weights(s, d):
    """Without trend and season the level is the past's values with weights that fall by 1 - alpha a step and sum to one
    with the first state's: the smoothing fold against the closed sum in the twin."""
    zero = F.array(*[F.lit(0.0)] * 7)
    fold = lambda ys, level: lts.fold(ys, F.lit(level), F.lit(0.0), zero, 0.3, 0.0, 0.0)["level"]
    rows = lts.ordered(_series(s, d))
    ones = F.transform("ys", lambda y: F.lit(1.0))
    return rows.select("key", r6(fold(F.col("ys"), 0.0)).alias("level"), F.round(fold(ones, 1.0), 9).alias("weights"))


# ---- bounded influence, on hourly sensor cells with forecast 50 and scale 20

_S = _with("sensor_hour")


@query("huber_clip", f"{_S} SELECT i1, i2, t, round(greatest(least((y - 50) / 20, 2), -2), 6) + 0.0 AS psi FROM cells")
def huber_clip(s, d):
    return _cube(s, d, "sensor_hour").select("i1", "i2", "t", r6(robust.huber_psi((F.col("y") - 50) / 20)).alias("psi"))


@query("biweight_rho", f"{_S} SELECT i1, i2, t, round(CASE WHEN abs((y - 50) / 20) <= 2 THEN 2.52 * (1 - (1 - ((y - 50) / 40) ** 2) ** 3) ELSE 2.52 END, 6) AS rho FROM cells")
def biweight_rho(s, d):
    return _cube(s, d, "sensor_hour").select("i1", "i2", "t", F.round(robust.biweight_rho((F.col("y") - 50) / 20), 6).alias("rho"))


@query("soft_threshold", f"{_S} SELECT i1, i2, t, round(sign(y - 50) * greatest(abs(y - 50) - 30, 0), 6) + 0.0 AS o FROM cells")
def soft_threshold(s, d):
    return _cube(s, d, "sensor_hour").select("i1", "i2", "t", r6(robust.soft_threshold(F.col("y") - 50, 30.0)).alias("o"))


@query("preclean_once", f"{_S} SELECT i1, i2, t, round(50 + greatest(least((y - 50) / 20, 2), -2) * 20, 6) AS clean, round(y - 50 - greatest(least((y - 50) / 20, 2), -2) * 20, 6) + 0.0 AS outlier FROM cells")
def preclean_once(s, d):
    y, f, g = F.col("y"), F.lit(50.0), F.lit(20.0)
    return _cube(s, d, "sensor_hour").select("i1", "i2", "t", F.round(robust.clean(y, f, g), 6).alias("clean"), r6(robust.outlier(y, f, g)).alias("outlier"))


@query("scale_update_once", f"{_S} SELECT i1, i2, t, round(400 * (0.99 + 0.01 * CASE WHEN abs((y - 50) / 20) <= 2 THEN 2.52 * (1 - (1 - ((y - 50) / 40) ** 2) ** 3) ELSE 2.52 END), 6) AS sigma2 FROM cells")
def scale_update_once(s, d):
    return _cube(s, d, "sensor_hour").select("i1", "i2", "t", F.round(robust.scale_update(F.lit(400.0), F.col("y") - 50, 0.01), 6).alias("sigma2"))


@query("threshold_decay", "WITH RECURSIVE d AS (SELECT 0 AS k, 10.0::DOUBLE AS threshold UNION ALL SELECT k + 1, greatest(0.85 * threshold, 0.1) FROM d WHERE k < 40) SELECT k::BIGINT AS k, round(threshold, 6) AS threshold FROM d")
def threshold_decay(s, d):
    return s.range(41).select(F.col("id").alias("k"), F.round(F.greatest(10.0 * F.pow(F.lit(0.85), F.col("id")), F.lit(0.1)), 6).alias("threshold"))


# ---- batch solver, on flow_month with y / 100


def _scaled(s, d):
    return _cube(s, d).withColumn("y", F.col("y") / 100)


def _h_sql(skip, rank=2, modes=("i1", "i2", "t")):
    return [" * ".join(_vec_sql(m, n, rank)[r] for n, m in enumerate(modes) if m != skip) for r in range(rank)]


def _system_sql(mode, rank):
    h = _h_sql(mode, rank)
    grams = [f"sum(({h[a]}) * ({h[b]})) AS g{a}{b}" for a in range(rank) for b in range(a, rank)]
    return f"{_with()}, sys AS (SELECT {mode} AS row, {', '.join(grams)}, {', '.join(f'sum(y / 100 * ({h[a]})) AS c{a}' for a in range(rank))} FROM cells GROUP BY {mode})"


def _closed(rank=2, sizes=(25, 25, 83)):
    return [np.cos((np.arange(n)[:, None] + 1) * (0.3 + 0.2 * k + 0.1 * np.arange(rank))) for k, n in enumerate(sizes)]


_NAMES = ["i1", "i2", "t"]


@query("row_system_r2", _system_sql("i1", 2) + " SELECT row::BIGINT AS row, round(g00, 4) + 0.0 AS g00, round(g01, 4) + 0.0 AS g01, round(g11, 4) + 0.0 AS g11, round(c0, 4) + 0.0 AS c0, round(c1, 4) + 0.0 AS c1 FROM sys")
def row_system_r2(s, d):
    rows = algebra.with_rows(_scaled(s, d), {m: f for m, f in _factors(s).items() if m != "i1"})
    h = [F.col("u_i2")[r] * F.col("u_t")[r] for r in range(2)]
    r4 = lambda c: F.round(F.sum(c), 4) + 0.0
    out = rows.groupBy(F.col("i1").cast("long").alias("row")).agg(r4(h[0] * h[0]).alias("g00"), r4(h[0] * h[1]).alias("g01"), r4(h[1] * h[1]).alias("g11"), r4(F.col("y") * h[0]).alias("c0"), r4(F.col("y") * h[1]).alias("c1"))
    return out


@query("row_solve_r2", _system_sql("i1", 2) + " SELECT row::BIGINT AS row, round((c0 * g11 - c1 * g01) / (g00 * g11 - g01 * g01), 4) + 0.0 AS u0, round((c1 * g00 - c0 * g01) / (g00 * g11 - g01 * g01), 4) + 0.0 AS u1 FROM sys")
def row_solve_r2(s, d):
    f = _closed()
    u = smooth_als.solve_rows(*smooth_als.row_systems(_scaled(s, d), f, _NAMES, 0), np.full((25, 2), np.nan))
    return s.createDataFrame([(i, round(float(a), 4) + 0.0, round(float(b), 4) + 0.0) for i, (a, b) in enumerate(u) if a == a], "row long, u0 double, u1 double")


_DET = "g00 * (g11 * g22 - g12 * g12) - g01 * (g01 * g22 - g12 * g02) + g02 * (g01 * g12 - g11 * g02)"


@query("row_solve_r3", _system_sql("i2", 3) + f""" SELECT row::BIGINT AS row,
 round((c0 * (g11 * g22 - g12 * g12) - g01 * (c1 * g22 - g12 * c2) + g02 * (c1 * g12 - g11 * c2)) / ({_DET}), 3) + 0.0 AS u0,
 round((g00 * (c1 * g22 - g12 * c2) - c0 * (g01 * g22 - g12 * g02) + g02 * (g01 * c2 - c1 * g02)) / ({_DET}), 3) + 0.0 AS u1,
 round((g00 * (g11 * c2 - c1 * g12) - g01 * (g01 * c2 - c1 * g02) + c0 * (g01 * g12 - g11 * g02)) / ({_DET}), 3) + 0.0 AS u2 FROM sys""")
def row_solve_r3(s, d):
    u = smooth_als.solve_rows(*smooth_als.row_systems(_scaled(s, d), _closed(3), _NAMES, 1), np.full((25, 3), np.nan))
    return s.createDataFrame([(i, *(round(float(x), 3) + 0.0 for x in row)) for i, row in enumerate(u) if row[0] == row[0]], "row long, u0 double, u1 double, u2 double")


_TIME1 = _system_sql("t", 1) + ", w AS (SELECT i::INT AS t, cos((i + 1) * 0.7) AS w FROM range(83) r(i)), sys2 AS (SELECT w.t, coalesce(g00, 0) AS g, coalesce(c0, 0) AS c, w FROM w LEFT JOIN sys ON w.t = row)"


@query("time_row_solve_jacobi_r1", _TIME1 + """ SELECT a.t::BIGINT AS t, round((a.c + 0.5 * (coalesce(b1.w, 0) + coalesce(b2.w, 0)) + 0.25 * (coalesce(m1.w, 0) + coalesce(m2.w, 0))) /
 (a.g + 0.5 * ((b1.w IS NOT NULL)::INT + (b2.w IS NOT NULL)::INT) + 0.25 * ((m1.w IS NOT NULL)::INT + (m2.w IS NOT NULL)::INT)), 6) + 0.0 AS w
 FROM sys2 a LEFT JOIN w b1 ON b1.t = a.t - 1 LEFT JOIN w b2 ON b2.t = a.t + 1 LEFT JOIN w m1 ON m1.t = a.t - 12 LEFT JOIN w m2 ON m2.t = a.t + 12""")
def time_row_solve_jacobi_r1(s, d):
    return _time_rows(s, d, "jacobi")


def _time_rows(s, d, order):
    f = _closed(1)
    w = smooth_als.time_rows(*smooth_als.row_systems(_scaled(s, d), f, _NAMES, 2), f[2], 12, 0.5, 0.25, order)
    return s.createDataFrame([(t, round(float(x), 6) + 0.0) for t, x in enumerate(w[:, 0])], "t long, w double")


_SWEEP = """, l AS (SELECT list(g ORDER BY t) AS g, list(c ORDER BY t) AS c, list(w ORDER BY t) AS w FROM sys2),
gs AS (SELECT 0 AS k, g, c, w FROM l UNION ALL SELECT k + 1, g, c, w[:k] || [(c[k + 1] + {l1} * (CASE WHEN k > 0 THEN w[k] ELSE 0 END + CASE WHEN k < len(w) - 1 THEN w[k + 2] ELSE 0 END) + {l2} * (CASE WHEN k >= 12 THEN w[k - 11] ELSE 0 END + CASE WHEN k < len(w) - 12 THEN w[k + 13] ELSE 0 END))
 / (g[k + 1] + {l1} * ((k > 0)::INT + (k < len(w) - 1)::INT) + {l2} * ((k >= 12)::INT + (k < len(w) - 12)::INT))] || w[k + 2:] FROM gs WHERE k < len(w))"""


@query("time_row_sweep_gs_r1", _TIME1.replace("WITH cells", "WITH RECURSIVE cells", 1) + _SWEEP.format(l1=0.5, l2=0.25) + " SELECT i::BIGINT AS t, round(w[i + 1], 6) + 0.0 AS w FROM gs, range(83) r(i) WHERE k = len(w)")
def time_row_sweep_gs_r1(s, d):
    return _time_rows(s, d, "gauss_seidel")


@query("normalize_columns", f"WITH {_given_sql('nation')} SELECT i AS idx, " + ", ".join(f"round(v{r} / sqrt(sum(v{r} * v{r}) OVER ()), 6) + 0.0 AS v{r}" for r in range(2)) + " FROM nation")
def normalize_columns(s, d):
    """The factor of customers' nations as the solver normalizes it: a row a nation comes to the driver."""
    rows = sorted(_given(s, d, "nation").collect())
    f = [np.array([r["vec"] for r in rows]).reshape(-1, 2), np.ones((1, 2))]
    smooth_als.normalize(f, 0)
    return s.createDataFrame([(r["idx"], *(round(float(x), 6) + 0.0 for x in row)) for r, row in zip(rows, f[0])], "idx long, v0 double, v1 double")


@query("fitness_once", f"{_with()} SELECT round(1 - sqrt(sum((y / 100 - ({_hat_sql()})) ** 2)) / sqrt(sum((y / 100) ** 2)), 6) + 0.0 AS fitness FROM cells")
def fitness_once(s, d):
    x = algebra.reconstruct(_scaled(s, d), _factors(s))
    r = F.col("y") - F.col("x_hat")
    return x.agg(r6(1 - F.sqrt(F.sum(r * r)) / F.sqrt(F.sum(F.col("y") * F.col("y")))).alias("fitness"))


_ALS1 = f"""{_with().replace('WITH ', 'WITH RECURSIVE ', 1)}, c AS (SELECT i1, i2, t, y / 100 AS y FROM cells),
u0 AS (SELECT i1, sum(y * cos((i2 + 1) * 0.5) * cos((t + 1) * 0.7)) / sum((cos((i2 + 1) * 0.5) * cos((t + 1) * 0.7)) ** 2) AS u FROM c GROUP BY i1),
ua AS (SELECT i::INT AS i1, coalesce(u, cos((i + 1) * 0.3)) AS u FROM range(25) r(i) LEFT JOIN u0 ON i = i1),
na AS (SELECT sqrt(sum(u * u)) AS n FROM ua), u AS (SELECT i1, u / n AS u FROM ua, na), w1 AS (SELECT i::INT AS t, cos((i + 1) * 0.7) * n AS w FROM range(83) r(i), na),
v0 AS (SELECT i2, sum(y * u * w) / sum((u * w) ** 2) AS v FROM c JOIN u USING (i1) JOIN w1 USING (t) GROUP BY i2),
va AS (SELECT i::INT AS i2, coalesce(v, cos((i + 1) * 0.5)) AS v FROM range(25) r(i) LEFT JOIN v0 ON i = i2),
nb AS (SELECT sqrt(sum(v * v)) AS n FROM va), v AS (SELECT i2, v / n AS v FROM va, nb), w2 AS (SELECT t, w * n AS w FROM w1, nb),
sy AS (SELECT t, sum((u * v) ** 2) AS g, sum(y * u * v) AS c FROM c JOIN u USING (i1) JOIN v USING (i2) GROUP BY t),
sys2 AS (SELECT t, coalesce(g, 0) AS g, coalesce(c, 0) AS c, w FROM w2 LEFT JOIN sy USING (t))""" + _SWEEP.format(l1=0.5, l2=0.25)


@query("als_one_sweep_r1", _ALS1 + " SELECT 0 AS mode, i1::BIGINT AS idx, round(u, 6) + 0.0 AS v FROM u UNION ALL SELECT 1, i2, round(v, 6) + 0.0 FROM v UNION ALL SELECT 2, i, round(w[i + 1], 6) + 0.0 FROM gs, range(83) r(i) WHERE k = len(w)")
def als_one_sweep_r1(s, d):
    f = _closed(1)
    smooth_als.sweep_distributed(_scaled(s, d), f, TensorSpec((25, 25), 12, 1), HyperParams(lambda1=0.5, lambda2=0.25))
    return s.createDataFrame([(n, i, round(float(x), 6) + 0.0) for n, u in enumerate(f) for i, x in enumerate(u[:, 0])], "mode int, idx long, v double")


_HP = HyperParams(lambda1=0.01, lambda2=0.01, max_iter=12)
_SPEC = TensorSpec((25, 25), 12, 3)


def _log_flow(s, d):
    return _cube(s, d).select("i1", "i2", "t", F.log2(1 + F.col("y")).alias("y"))


def _factor_rows(s, factors):
    return s.createDataFrame([(n, i, [float(x) for x in row]) for n, u in enumerate(factors) for i, row in enumerate(u)], "mode int, idx int, vec array<double>")


for _solver in ("smooth", "plain"):
    query(f"init_{_solver}_als")(lambda s, d, k=_solver: _factor_rows(s, startup.run(_log_flow(s, d), _SPEC, _HP, k)))


@query("als_inner_loop")
def als_inner_loop(s, d):
    """Fitness after each sweep over the cluster until it settles: the solver's inner loop on the start-up cells."""
    cells = _log_flow(s, d).where(F.col("t") < _SPEC.startup).persist()
    factors, trace = smooth_als.initial_factors((*_SPEC.sizes, _SPEC.startup), _SPEC.rank, _HP.seed), []
    smooth_als.fit_distributed(cells, factors, _SPEC, _HP.with_(inner_max_iter=30), None, trace)
    cells.unpersist()
    return s.createDataFrame([(k + 1, float(x)) for k, x in enumerate(trace)], "sweep int, fitness double")


@query("init_impute")
def init_impute(s, d):
    """Start-up cells that were not observed, with their low-rank values."""
    f = startup.run(_log_flow(s, d), _SPEC, _HP)
    full = algebra.grid(s, {"i1": 25, "i2": 25, "t": _SPEC.startup})
    return smooth_als.residuals(algebra.missing(full, _cube(s, d), _NAMES), f, _NAMES)


# ---- one online step, in closed form: step 40 of flow_month / 100, rank 2, season 12

_LEVEL, _TREND, _SEASON = [0.5, 0.6], [0.01, 0.02], [0.2 * float(np.cos(r + 1)) for r in range(2)]
_HP1 = HyperParams(lambda1=0.3, lambda2=0.2, lambda3=10.0, mu=0.05, phi=0.1, step_rule="fixed")


def _state40():
    m = 12
    season = np.array([[0.2 * np.cos(r + 1) for r in range(2)]] * m)
    ring = np.array([[0.4 + 0.01 * k, 0.5 - 0.01 * k] for k in range(m)])
    p = np.array([0.3, 0.4])
    return Snapshot(_closed()[:2], SeasonState(np.array(_LEVEL), np.array(_TREND), season, p, p / 2, p / 4), ring, 39)


_W = [f"({l!r} + {b!r} + 0.2 * cos({r} + 1))" for r, (l, b) in enumerate(zip(_LEVEL, _TREND))]
_P = [" * ".join(_vec_sql(m, n)[r] for n, m in enumerate(("i1", "i2"))) for r in range(2)]
_STEP = f"""{_with()}, c AS (SELECT i1, i2, y / 100 AS y, CASE WHEN (i1 + i2) % 3 = 0 THEN 0.04 ELSE 0.01 END AS s2, {_P[0]} AS p0, {_P[1]} AS p1 FROM cells WHERE t = 40),
f AS (SELECT *, p0 * {_W[0]} + p1 * {_W[1]} AS y_hat FROM c), z AS (SELECT *, (y - y_hat) / sqrt(s2) AS z FROM f),
j AS (SELECT *, greatest(least(z, 2), -2) * sqrt(s2) AS r, s2 * (0.9 + 0.1 * CASE WHEN abs(z) <= 2 THEN 2.52 * (1 - (1 - (z / 2) ** 2) ** 3) ELSE 2.52 END) AS sigma2 FROM z)"""


def _slice40(s, d):
    return _scaled(s, d).where("t = 40").select("i1", "i2", "y")


def _scales40(s):
    g = algebra.grid(s, {"i1": 25, "i2": 25})
    return g.where("(i1 + i2) % 3 = 0").withColumn("sigma2", F.lit(0.04))


def _step40(s, d):
    return step.advance(_state40(), _slice40(s, d), _scales40(s), TensorSpec((25, 25), 12, 2), _HP1)


@query("predict_time", _fold_sql() + " SELECT key::INT AS r, round(level + trend + season[1], 6) + 0.0 AS w FROM st WHERE k = len(ys)")
def predict_time(s, d):
    """The next time vector of the daily event sums: a component a type of event, from its state at the table's end."""
    rows = sorted(_state(s, d).select("key", "st.level", "st.trend", "st.season").collect())  # a row a type
    level, trend = (np.array([r[c] for r in rows]) for c in ("level", "trend"))
    season = np.array([r["season"] for r in rows]).T
    p = np.full(len(rows), 0.3)
    w = kernel.predict_time(Snapshot([], SeasonState(level, trend, season, p, p / 3, p / 1.5), season, -1))
    return s.createDataFrame([(r["key"], round(float(x), 6) + 0.0) for r, x in zip(rows, w)], "r int, w double")


for _name, _cols in {"predict_cells_r2": ["y_hat"], "outliers_once": ["outlier"], "scales_once": ["sigma2"], "residual_once": ["r"]}.items():
    _sql = ", ".join(f"round({'y - y_hat - r' if c == 'outlier' else c}, 6) + 0.0 AS {c}" for c in _cols)
    query(_name, f"{_STEP} SELECT i1, i2, {_sql} FROM j")(lambda s, d, cols=_cols: _step40(s, d)[1].select("i1", "i2", *[r6(F.col(c)).alias(c) for c in cols]))


@query("factor_grad_r2", f"""{_STEP} SELECT 0 AS mode, i::BIGINT AS idx, {', '.join(f"round({_vec_sql('i', 0)[r]} + 2 * 0.05 * coalesce(sum(j.r * {_W[r]} * {_vec_sql('i2', 1)[r]}), 0), 6) + 0.0 AS u{r}" for r in range(2))} FROM range(25) g(i) LEFT JOIN j ON i1 = i GROUP BY i
UNION ALL SELECT 1, i, {', '.join(f"round({_vec_sql('i', 1)[r]} + 2 * 0.05 * coalesce(sum(j.r * {_W[r]} * {_vec_sql('i1', 0)[r]}), 0), 6) + 0.0" for r in range(2))} FROM range(25) g(i) LEFT JOIN j ON i2 = i GROUP BY i""")
def factor_grad_r2(s, d):
    new, _ = _step40(s, d)
    return s.createDataFrame([(n, i, *(round(float(x), 6) + 0.0 for x in row)) for n, u in enumerate(new.factors) for i, row in enumerate(u)], "mode int, idx long, u0 double, u1 double")


_W40 = [f"({_W[r]} + 2 * 0.05 * (coalesce(sum(r * p{r}), 0) + 0.3 * ({b} - {_W[r]}) + 0.2 * ({a} - {_W[r]})))" for r, (b, a) in enumerate([("(0.4 + 0.01 * 3)", "(0.4 + 0.01 * 4)"), ("(0.5 - 0.01 * 3)", "(0.5 - 0.01 * 4)")])]


@query("time_grad_r2", f"{_STEP} SELECT round({_W40[0]}, 6) AS w0, round({_W40[1]}, 6) AS w1 FROM j")
def time_grad_r2(s, d):
    new, _ = _step40(s, d)
    return s.createDataFrame([tuple(round(float(x), 6) for x in new.ring[4])], "w0 double, w1 double")


@query("season_update_once", f"{_STEP}, w AS (SELECT {_W40[0]} AS w0, {_W40[1]} AS w1 FROM j) " + " UNION ALL ".join(f"SELECT {r} AS r, round({a} * (w{r} - {s_}) + {1 - a} * {l + b}, 6) AS level, round({a / 2} * ({a} * (w{r} - {s_}) + {1 - a} * {l + b} - {l}) + {1 - a / 2} * {b}, 6) + 0.0 AS trend, round({a / 4} * (w{r} - {l + b}) + {1 - a / 4} * {s_}, 6) + 0.0 AS season FROM w" for r, (a, l, b, s_) in enumerate(zip((0.3, 0.4), _LEVEL, _TREND, ("(0.2 * cos(1))", "(0.2 * cos(2))")))))
def season_update_once(s, d):
    new, _ = _step40(s, d)
    n = new.season
    return s.createDataFrame([(r, round(float(n.level[r]), 6), round(float(n.trend[r]), 6) + 0.0, round(float(n.season[4][r]), 6) + 0.0) for r in range(2)], "r int, level double, trend double, season double")


@query("impute_slice_r2", f"""{_STEP}, w AS (SELECT {_W40[0]} AS w0, {_W40[1]} AS w1 FROM j),
a AS (SELECT i, {', '.join(f"{_vec_sql('i', 0)[r]} + 0.1 * coalesce(sum(j.r * {_W[r]} * {_vec_sql('i2', 1)[r]}), 0) AS a{r}" for r in range(2))} FROM range(25) g(i) LEFT JOIN j ON i1 = i GROUP BY i),
b AS (SELECT i, {', '.join(f"{_vec_sql('i', 1)[r]} + 0.1 * coalesce(sum(j.r * {_W[r]} * {_vec_sql('i1', 0)[r]}), 0) AS b{r}" for r in range(2))} FROM range(25) g(i) LEFT JOIN j ON i2 = i GROUP BY i)
SELECT a.i::INT AS i1, b.i::INT AS i2, round(a0 * b0 * w0 + a1 * b1 * w1, 6) + 0.0 AS x_hat FROM a, b, w WHERE (a.i, b.i) NOT IN (SELECT (i1, i2) FROM j)""")
def impute_slice_r2(s, d):
    from .plans import planner

    new, judged = _step40(s, d)
    spec = TensorSpec((25, 25), 12, 2)
    absent = algebra.missing(algebra.grid(s, {"i1": 25, "i2": 25}), judged, ["i1", "i2"])
    return planner.impute_at(absent, new, spec).select("i1", "i2", r6(F.col("x_hat")).alias("x_hat"))


# ---- full online runs


def _tensors(s, d):
    return _log_flow(s, d).select(F.lit("flow").alias("tensor_id"), "i1", "i2", "t", "y")


def _fold(s, d, **more):
    return fold.run(_tensors(s, d), _SPEC, HyperParams(lambda1=0.01, lambda2=0.01, max_iter=40), **more)


query("online_fold")(lambda s, d: _fold(s, d, impute=False))
query("impute_stream")(lambda s, d: _fold(s, d).where("kind = 'imputed'"))
query("forecast_cells")(lambda s, d: _fold(s, d, impute=False, horizon=12).where("kind = 'forecast'"))


@query("online_step")
def online_step(s, d):
    """Every step after the start-up over the cluster, to the stream's end."""
    return step.run(_log_flow(s, d), _SPEC, HyperParams(lambda1=0.01, lambda2=0.01, max_iter=8)).select("t", "i1", "i2", "y_hat", "outlier")


@query("online_many_tensors")
def online_many_tensors(s, d):
    """One stream for each event type's user groups: several tensors folded side by side."""
    cells = _cube(s, d, "sensor_hour")
    c = cells.select(F.concat(F.lit("type "), F.col("i2")).alias("tensor_id"), "i1", "t", F.log2(1 + F.col("y")).alias("y"))
    return fold.run(c, TensorSpec((16,), 24, 2), HyperParams(lambda1=0.01, lambda2=0.01, max_iter=30), horizon=24, impute=False, starts=1)


# ---- compared methods, single steps


@query("b1_step", f"{_with()}, c AS (SELECT i1, i2, y / 100 AS y, cos((i1 + 1) * 0.3) AS u, cos((i2 + 1) * 0.5) AS v FROM cells WHERE t = 40), w AS (SELECT sum(u * v * y) / (sum((u * v) ** 2) + 0.001) AS w FROM c) SELECT i1::BIGINT AS idx, round(any_value(u) + 0.1 * (2 * sum((y - u * v * w) * v * w) / sum((v * w) ** 2) - 0.001 * any_value(u)), 6) + 0.0 AS u FROM c, w GROUP BY i1")
def b1_step(s, d):
    m, idx, y = _one_step(s, d, methods.SgdStreamCp(TensorSpec((25, 25), 12, 1)))
    m.feed(idx, y)
    return _touched(s, m, idx)


def _one_step(s, d, m):
    rows = _slice40(s, d).toPandas()  # one slice
    m.factors = [f.copy() for f in _closed(1)[:2]]
    return m, rows[["i1", "i2"]].to_numpy(np.int64), rows["y"].to_numpy()


def _touched(s, m, idx):
    return s.createDataFrame([(int(i), round(float(m.factors[0][i, 0]), 6) + 0.0) for i in np.unique(idx[:, 0])], "idx long, u double")


@query("b2_step", f"{_with()}, c AS (SELECT i1, i2, y / 100 AS y, cos((i1 + 1) * 0.3) AS u, cos((i2 + 1) * 0.5) AS v FROM cells WHERE t = 40), w AS (SELECT sum(u * v * y) / (sum((u * v) ** 2) + 0.01) AS w FROM c) SELECT i1::BIGINT AS idx, round((sum(y * v * w) + 0.01 * any_value(u)) / (sum((v * w) ** 2) + 0.01), 6) + 0.0 AS u FROM c, w GROUP BY i1")
def b2_step(s, d):
    m, idx, y = _one_step(s, d, methods.RlsStreamCp(TensorSpec((25, 25), 12, 1)))
    m.feed(idx, y)
    return _touched(s, m, idx)


@query("b5_group_shrink", f"{_with()}, c AS (SELECT i1, i2, y / 100 - 3 AS r FROM cells WHERE t = 40), n AS (SELECT i1, sqrt(sum(r * r)) AS n FROM c GROUP BY i1) SELECT i1::BIGINT AS i1, i2::BIGINT AS i2, round(r * greatest(0, 1 - 2 / n), 6) + 0.0 AS e FROM c JOIN n USING (i1)")
def b5_group_shrink(s, d):
    c = _slice40(s, d).select("i1", "i2", (F.col("y") - 3).alias("r"))
    n = c.groupBy("i1").agg(F.sqrt(F.sum(F.col("r") * F.col("r"))).alias("n"))
    return c.join(n, "i1").select(F.col("i1").cast("long").alias("i1"), F.col("i2").cast("long").alias("i2"), r6(F.col("r") * F.greatest(F.lit(0.0), 1 - 2 / F.col("n"))).alias("e"))


@query("b8_gradient", f"{_with()} SELECT i1::BIGINT AS idx, {', '.join(f'round(-sum((y / 100 - ({_hat_sql()})) * ({_h_sql('i1')[r]})), 4) + 0.0 AS g{r}' for r in range(2))} FROM cells GROUP BY i1")
def b8_gradient(s, d):
    rows = algebra.with_rows(_scaled(s, d), _factors(s))
    x = algebra.dot(*[F.col(f"u_{m}") for m in _NAMES])
    g = [F.round(-F.sum((F.col("y") - x) * F.col("u_i2")[r] * F.col("u_t")[r]), 4) + 0.0 for r in range(2)]
    return rows.groupBy(F.col("i1").cast("long").alias("idx")).agg(*[c.alias(f"g{r}") for r, c in enumerate(g)])


@query("b10_cell_lts", _fold_sql(rob="reject_first", phi="0.2") + " SELECT key, h, round(level + h * trend + season[(h - 1) % 7 + 1], 6) + 0.0 AS yhat FROM st, range(1, 8) r(h) WHERE k = len(ys)")
def b10_cell_lts(s, d):
    rows = _state(s, d, rob="reject_first", phi=0.2).select("key", "st", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(7).cast("long"))).alias("h"))
    return rows.select("key", "h", r6(lts.forecast(F.col("st"), F.col("h"), 7)).alias("yhat"))


@query("b11_floors", f"{_with()} SELECT i1, i2, (t % 12)::INT AS phase, round(avg(y), 6) AS season_mean, arg_max(y, t) AS last_value FROM cells GROUP BY ALL")
def b11_floors(s, d):
    return _cube(s, d).groupBy("i1", "i2", F.pmod("t", F.lit(12)).cast("int").alias("phase")).agg(F.round(F.avg("y"), 6).alias("season_mean"), F.max_by("y", "t").alias("last_value"))


def _run_method(name):
    """All runs of a method on the four streams: running error and time a step (forecasters: forecasting error)."""
    def go(s, d):
        from . import experiments

        runs = experiments.forecasting_runs(s, d) if name in experiments.FORECASTERS else experiments.imputation_runs(s, d)
        return experiments.mean_error(runs.where(F.col("method") == name), "seed", "settings")

    return go


for _b, _name in (("b1", "sgd_stream_cp"), ("b2", "rls_stream_cp"), ("b3", "multi_aspect_stream"), ("b5", "slab_robust_stream"), ("b6", "seasonal_stream_mf"), ("b7", "static_cp_forecast")):
    query(f"{_b}_run")(_run_method(_name))


def _fed(s, d, make, read, schema):
    """A method fed the monthly flows, all months that the table has, in one task: 25 x 25 cells a month."""
    def go(pdf):
        import pandas as pd

        m, by = make(), dict(list(pdf.groupby("t")))
        for t in range(int(pdf["t"].max()) + 1):
            p = by.get(t, pdf.iloc[:0])
            m.feed(p[["i1", "i2"]].to_numpy(np.int64), p["y"].to_numpy())
        return pd.DataFrame([(read(m),)], columns=[schema.split()[0]])

    return _log_flow(s, d).withColumn("stream", F.lit(0)).groupBy("stream").applyInPandas(go, schema)


@query("b8_run")
def b8_run(s, d):
    """Loss of the masked gradient factorization of all monthly flows."""
    return _fed(s, d, lambda: methods.MaskedGradientCp(TensorSpec((25, 25), 12, 2), 60), lambda m: float(m.run()), "loss double")


@query("b4_effective_rank")
def b4_effective_rank(s, d):
    return _fed(s, d, lambda: methods.BayesRobustStream(TensorSpec((25, 25), 12, 6)), lambda m: m.effective_rank, "rank int")


# ---- measures; truth y / 100, estimate a closed formula

_EST = f"x AS (SELECT i1, i2, t, y / 100 AS x, y / 100 + 0.1 * cos(i1 + 2 * i2 + t) AS x_hat FROM cells)"
_NRE = f"{_with()}, {_EST}, n AS (SELECT t, sqrt(sum((x_hat - x) ** 2)) / sqrt(sum(x * x)) AS nre FROM x GROUP BY t)"


def _estimated(s, d):
    x = F.col("y") / 100
    return _cube(s, d).select("i1", "i2", "t", x.alias("x"), (x + 0.1 * F.cos(F.col("i1") + 2 * F.col("i2") + F.col("t"))).alias("x_hat"))


@query("nre_per_step", _NRE + " SELECT t, round(nre, 6) AS nre FROM n")
def nre_per_step(s, d):
    return metrics.nre(_estimated(s, d)).select("t", F.round("nre", 6).alias("nre"))


@query("rae", _NRE + " SELECT round(avg(nre), 6) AS rae FROM n")
def rae(s, d):
    return metrics.rae(metrics.nre(_estimated(s, d))).select(F.round("rae", 6).alias("rae"))


@query("rae_running", _NRE + " SELECT t, round(avg(nre) OVER (ORDER BY t), 6) AS rae FROM n")
def rae_running(s, d):
    n = metrics.nre(_estimated(s, d))
    return n.select("t", F.round(F.avg("nre").over(Window.orderBy("t").rowsBetween(Window.unboundedPreceding, 0)), 6).alias("rae"))


@query("afe", _NRE + " SELECT round(avg(nre), 6) AS afe FROM n WHERE t >= 71")
def afe(s, d):
    return metrics.afe(_estimated(s, d).where("t >= 71")).select(F.round("afe", 6).alias("afe"))


@query("art_paper_divisor", "SELECT l_orderkey, round(sum(l_quantity) / (count(*) - 1), 6) AS paper, round(avg(l_quantity), 6) AS mean FROM lineitem GROUP BY l_orderkey HAVING count(*) > 1")
def art_paper_divisor(s, d):
    """Both divisors of the mean time, on every order's quantities in place of times."""
    return metrics.art_rows(load(s, d, "lineitem").select("l_orderkey", "l_quantity"), "l_orderkey", "l_quantity")


@query("rel_change", f"{_with()} SELECT round(sqrt(sum((0.1 * cos(t)) ** 2)) / sqrt(sum((y / 100) ** 2)), 6) AS change FROM cells")
def rel_change(s, d):
    c = _cube(s, d).select((F.col("y") / 100).alias("x_old"), (F.col("y") / 100 + 0.1 * F.cos("t")).alias("x_new"))
    return metrics.relative_change(c).select(F.round("change", 6).alias("change"))


@query("outlier_precision_recall", f"{_with()}, f AS (SELECT i1, i2, t FROM cells WHERE y >= 100), j AS (SELECT i1, i2, t FROM cells WHERE (i1 + i2 + t) % 10 = 0), h AS (SELECT count(*) AS hits FROM f WHERE (i1, i2, t) IN (SELECT (i1, i2, t) FROM j)) SELECT hits, a AS flagged, b AS injected, (hits / greatest(a, 1))::DOUBLE AS precision, (hits / greatest(b, 1))::DOUBLE AS recall FROM h, (SELECT count(*) AS a FROM f), (SELECT count(*) AS b FROM j)")
def outlier_precision_recall(s, d):
    c = _cube(s, d)
    return metrics.outlier_pr(c.where("y >= 100"), c.where("(i1 + i2 + t) % 10 = 0"), _NAMES)


@query("factor_nre")
def factor_nre(s, d):
    """The factor of months by the first three priorities, of counted orders: how far that of summed prices is from it, with its
    columns in another order and of another sign."""
    code = cubes.code("o_orderpriority", cubes.PRIORITIES)
    month = (F.year("o_orderdate") - 1995) * 12 + F.month("o_orderdate") - 1
    sums = load(s, d, "orders").groupBy(month.alias("t")).agg(*[F.sum(F.when(code == r, 1.0).otherwise(0.0)).alias(f"n{r}") for r in range(3)], *[(F.sum(F.when(code == r, cubes.cents("o_totalprice")).otherwise(F.lit(0))) / 100).alias(f"x{r}") for r in range(3)])
    rows = sorted(sums.collect())  # a row a month
    counted, priced = (np.array([[float(r[f"{c}{k}"]) for k in range(3)] for r in rows]) for c in "nx")
    return s.createDataFrame([(metrics.factor_nre(-2 * priced[:, [2, 0, 1]], counted),)], "nre double")


@query("corruption_levels")
def corruption_levels(s, d):
    """Shares of missing and outlying cells that each level makes of the monthly flows."""
    truth = staged(_cube(s, d).select(*_NAMES, F.col("y").alias("x")), "flows")  # read once for every level
    out = None
    for x, y, z in ((20, 10, 2), (30, 15, 3), (50, 20, 4), (70, 20, 5)):
        c = corrupt.apply(truth, _NAMES, x, y, z).agg(F.lit(x).alias("missing"), F.lit(y).alias("outliers"), F.count(F.lit(1)).alias("cells"), F.sum((F.col("o") != 0).cast("long")).alias("hit"))
        out = c if out is None else out.unionByName(c)
    return out


@query("q1_start_up")
def q1_start_up(s, d):
    """Errors of the time factor and the tensor after every outer iteration, with and without smoothness, five seeds,
    of planted values at the coordinates of the monthly flows."""
    from . import experiments

    return experiments.start_up_runs(s, d)


@query("q2_imputation")
def q2_imputation(s, d):
    """Error of every step and its running mean: five methods, four streams, four corruptions, five seeds."""
    from . import experiments

    return experiments.running(experiments.imputation_runs(s, d))


@query("q2_comparison")
def q2_comparison(s, d):
    """Means of five repetitions: the proposed method against the most accurate other, by stream and corruption."""
    from . import experiments

    return experiments.compared(experiments.imputation_runs(s, d), ["workload", "missing", "outliers", "times"])


@query("q3_speed")
def q3_speed(s, d):
    """Mean seconds a step of every method on every stream; a method that is rerun at each step costs a rerun."""
    from . import experiments

    runs = experiments.imputation_runs(s, d).unionByName(experiments.forecasting_runs(s, d).where(F.col("method") != experiments.OWN))
    one = experiments.mean_error(runs, "seed")
    return one.groupBy("workload", "method").agg(F.avg("art").alias("art"))


@query("q4_forecasting")
def q4_forecasting(s, d):
    """Error of every forecast step: four streams, five seeds, three rates of missing cells for the proposed method."""
    from . import experiments

    return experiments.forecasting_runs(s, d)


@query("q4_comparison")
def q4_comparison(s, d):
    """Means of five repetitions by stream and missing rate: the proposed method against the better rival, which sees every cell."""
    from . import experiments

    runs = experiments.forecasting_runs(s, d)
    rates = s.createDataFrame([(m,) for m in experiments.MISSING], "rate int")
    rivals = runs.where(F.col("method") != experiments.OWN).crossJoin(F.broadcast(rates))
    own = runs.where(F.col("method") == experiments.OWN).withColumn("rate", F.col("missing"))
    return experiments.compared(own.unionByName(rivals), ["workload", "rate"])


@query("q5_scalability")
def q5_scalability(s, d):
    """Seconds by cells of a slice (first mode 50 to 500 of 500) and by steps, on slices of line items."""
    from . import experiments

    return experiments.kept("scalability", s, d, lambda: experiments.scalability_runs(s, d))


@query("q5_linearity")
def q5_linearity(s, d):
    from . import experiments

    """Straight lines through the same times: slope and R squared, by cells and by steps."""
    return experiments.linear(q5_scalability(s, d))


@query("b3_step", f"""{_with()}, c AS (SELECT i1, i2, y / 100 AS y, cos((i1 + 1) * 0.3) AS u, cos((i2 + 1) * 0.5) AS v FROM cells WHERE t = 40), w AS (SELECT sum(u * v * y) / (sum((u * v) ** 2) + 0.001) AS w FROM c),
n AS (SELECT sqrt(sum(cos((j + 1) * 0.3) ** 2)) AS n FROM range(25) r(j)), s AS (SELECT i1, sum((v * w) ** 2) AS g, sum(y * v * w) AS c FROM c, w GROUP BY i1)
SELECT i AS idx, round((coalesce(c, 0) + 0.001 * cos((i + 1) * 0.3) * greatest(n - 0.01, 0) / n) / (coalesce(g, 0) + 0.001 + 1e-9), 6) + 0.0 AS u FROM range(25) r(i) LEFT JOIN s ON i1 = i, n""")
def b3_step(s, d):
    m, idx, y = _one_step(s, d, methods.MultiAspectStream(TensorSpec((25, 25), 12, 1), inner=1))
    m.feed(idx, y)
    return s.createDataFrame([(i, round(float(x), 6) + 0.0) for i, x in enumerate(m.factors[0][:, 0])], "idx long, u double")


@query("b6_step", f"""{_with('orders_day')}, x AS (SELECT (a.i * 5 + b.i) AS idx, coalesce(y, 0) AS x, cos((a.i * 5 + b.i + 1) * 0.2) AS u, cos(3 * 0.4) AS c FROM range(5) a(i) CROSS JOIN range(5) b(i) LEFT JOIN cells ON i1 = a.i AND i2 = b.i AND t = 100)
SELECT idx, round(u + 0.3 * (x - u * c) * c / (c * c) / 2, 6) + 0.0 AS u, round(c + 0.3 * (SELECT sum(u * (x - u * c)) / sum(u * u) FROM x), 6) + 0.0 AS c FROM x""")
def b6_step(s, d):
    m = methods.SeasonalStreamMf(TensorSpec((5, 5), 7, 1), zero_fill=True)
    m.history, m.t = None, 99
    m.u = np.cos((np.arange(25)[:, None] + 1) * 0.2)
    m.c = np.cos((np.arange(7)[:, None] + 1) * 0.4)
    rows = _cube(s, d, "orders_day").where("t = 100").toPandas()  # one slice
    m.feed(rows[["i1", "i2"]].to_numpy(np.int64), rows["y"].to_numpy())
    return s.createDataFrame([(i, round(float(u), 6) + 0.0, round(float(m.c[2, 0]), 6) + 0.0) for i, u in enumerate(m.u[:, 0])], "idx long, u double, c double")


@query("b7_forecast", _fold_sql() + " SELECT key, i AS i1, h, round(cos((i + 1) * 0.3) * (level + h * trend + season[(h - 1) % 7 + 1]), 6) + 0.0 AS x_hat FROM st, range(1, 8) r(h), range(5) q(i) WHERE k = len(ys)")
def b7_forecast(s, d):
    """Forecast of a time column times a static factor's rows."""
    rows = _state(s, d).select("key", "st", F.explode(F.sequence(F.lit(1).cast("long"), F.lit(7).cast("long"))).alias("h"))
    u = s.range(5).select(F.col("id").alias("i1"), F.cos((F.col("id") + 1) * 0.3).alias("u"))
    return rows.crossJoin(F.broadcast(u)).select("key", "i1", "h", r6(F.col("u") * lts.forecast(F.col("st"), F.col("h"), 7)).alias("x_hat"))


# ---- many online steps of a rank-one stream of orders by priority and month, from a given state

_R1 = """WITH RECURSIVE cells AS (SELECT list_position(['1-URGENT','2-HIGH','3-MEDIUM','4-NOT SPECIFIED','5-LOW'], o_orderpriority) AS i, (year(o_orderdate) - 1995) * 12 + month(o_orderdate) - 1 AS t, count(*) / 100 AS y FROM orders GROUP BY ALL),
g AS (SELECT t, list(y ORDER BY i) AS ys FROM (SELECT a.t, b.i, y FROM (SELECT unnest(range((SELECT max(t) + 1 FROM cells))) AS t) a CROSS JOIN range(1, 6) b(i) LEFT JOIN cells ON cells.t = a.t AND cells.i = b.i) GROUP BY t),
st AS (SELECT -1::BIGINT AS t, [1.0, 0.9, 0.8, 0.7, 0.6]::DOUBLE[] AS u, 0.4::DOUBLE AS level, 0.01::DOUBLE AS trend, list_transform(range(12), lambda k: 0.02 * cos(k + 1))::DOUBLE[] AS season, list_transform(range(12), lambda k: 0.4 + 0.01 * k)::DOUBLE[] AS ring, list_transform(range(5), lambda k: 0.01)::DOUBLE[] AS s2, 0::DOUBLE AS w
UNION ALL SELECT t + 1, un, ln, 0.1 * (ln - level) + 0.9 * trend, season[2:] || [0.2 * (wn - base) + 0.8 * season[1]], ring[2:] || [wn], sn, wn FROM (
 SELECT *, 0.3 * (wn - season[1]) + 0.7 * base AS ln FROM (SELECT *, wh + 0.2 * (list_sum(list_transform(range(1, 6), lambda i: coalesce(r[i] * u[i], 0))) + 0.1 * (ring[12] - wh) + 0.2 * (ring[1] - wh)) / (list_sum(list_transform(range(1, 6), lambda i: CASE WHEN ys[i] IS NULL THEN 0 ELSE u[i] ** 2 END)) + 0.1 + 0.2) AS wn,
  list_transform(range(1, 6), lambda i: u[i] + CASE WHEN ys[i] IS NULL THEN 0 ELSE 0.2 * r[i] * wh / (wh * wh) END) AS un,
  list_transform(range(1, 6), lambda i: CASE WHEN ys[i] IS NULL THEN s2[i] ELSE s2[i] * (0.95 + 0.05 * CASE WHEN abs(z[i]) <= 2 THEN 2.52 * (1 - (1 - (z[i] / 2) ** 2) ** 3) ELSE 2.52 END) END) AS sn
  FROM (SELECT *, list_transform(range(1, 6), lambda i: CASE WHEN ys[i] IS NULL THEN 0 ELSE greatest(least(z[i], 2), -2) * sqrt(s2[i]) END) AS r FROM (SELECT *, list_transform(range(1, 6), lambda i: (ys[i] - u[i] * wh) / sqrt(s2[i])) AS z FROM (
   SELECT st.*, ys, level + trend AS base, level + trend + season[1] AS wh FROM st JOIN g ON g.t = st.t + 1))))))
SELECT t, round(w, 6) AS w, round(level, 6) AS level, round(u[1], 6) AS u1, round(u[5], 6) AS u5, round(s2[3], 6) AS s3 FROM st WHERE t >= 0"""


@query("online_r1_recursive", _R1)
def online_r1_recursive(s, d):
    o = load(s, d, "orders").select(cubes.code("o_orderpriority", cubes.PRIORITIES).alias("i1"), ((F.year("o_orderdate") - 1995) * 12 + F.month("o_orderdate") - 1).alias("t"))
    cells = o.groupBy("i1", "t").agg((F.count(F.lit(1)) / 100).alias("y"))
    hp = HyperParams(lambda1=0.1, lambda2=0.2, lambda3=10.0, mu=0.1, phi=0.05)
    one = lambda x: np.array([x])
    season = 0.02 * np.cos(np.arange(12) + 1)[:, None]
    state = Snapshot([np.array([[1.0], [0.9], [0.8], [0.7], [0.6]])], SeasonState(one(0.4), one(0.01), season, one(0.3), one(0.1), one(0.2)), (0.4 + 0.01 * np.arange(12))[:, None], -1)

    def go(pdf):
        import pandas as pd

        now, out = state.copy(), []
        by = {t: g for t, g in pdf.groupby("t")}
        for t in range(int(pdf["t"].max()) + 1):
            g = by.get(t)
            idx, y = (g[["i1"]].to_numpy(np.int64), g["y"].to_numpy()) if g is not None else (np.empty((0, 1), np.int64), np.empty(0))
            now, _ = kernel.advance(now, idx, y, hp)
            out.append((t, now.ring[t % 12][0], now.season.level[0], now.factors[0][0, 0], now.factors[0][4, 0], now.scales.get(np.array([[2]]), 0.01)[0]))
        return pd.DataFrame(out, columns=["t", "w", "level", "u1", "u5", "s3"])

    run = cells.withColumn("stream", F.lit(0)).groupBy("stream").applyInPandas(go, "t long, w double, level double, u1 double, u5 double, s3 double")  # one short stream
    return run.select("t", *[F.round(c, 6).alias(c) for c in ("w", "level", "u1", "u5", "s3")])


@query("rank_choice")
def rank_choice(s, d):
    """Running error by rank on the planted monthly flow shape, five seeds, each run in a task of its own."""
    from . import experiments

    def go(pdf):
        import pandas as pd

        rank, seed = int(pdf["rank"].iloc[0]), int(pdf["seed"].iloc[0])
        return pd.DataFrame([(rank, seed, experiments.rank_choice("flow_month", seed, [rank])[rank])], columns=["rank", "seed", "rae"])

    plan = s.createDataFrame([(r, k) for r in experiments.RANKS for k in experiments.SEEDS], "rank int, seed int")
    return plan.repartition(experiments.TASKS, "rank", "seed").groupBy("rank", "seed").applyInPandas(go, "rank int, seed int, rae double")


for _name in ("impute", "outliers"):

    @query(f"op_udtf_{_name}")
    def _table_function(s, d, name=_name):
        from . import sql

        sql.register(s)
        _cube(s, d, "sensor_hour").select(F.lit("sensor").alias("tensor_id"), "i1", "i2", "t", F.log2(1 + F.col("y")).alias("y")).createOrReplaceTempView("sensor_cells")
        return s.sql(f"SELECT * FROM tensor_{name}(TABLE(SELECT i1, i2, t, y, tensor_id FROM sensor_cells) PARTITION BY tensor_id ORDER BY (t), '16,5', 24, 2, 0)")
