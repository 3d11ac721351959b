"""The engine's registered queries and their DuckDB twins.

Factors of exact checks are closed formulas of the index, so that both engines make the same numbers; results
are rounded to six digits where sums of doubles are involved.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .functions import lts, robust
from .model import HyperParams, TensorSpec
from .operators import algebra, cost, metrics
from .sources import cubes
from .sources.tables import load, staged

_queries: dict[str, Callable] = {}
_oracle: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def register(f):
        _queries[name] = f
        if sql:
            _oracle[name] = sql
        return f

    return register


def r6(c) -> Column:
    return F.round(c, 6) + F.lit(0.0)  # no negative zero


# ---- cubes

_DAYS = "date_diff('day', DATE '{0}', CAST({1} AS DATE))"
_EV = """SELECT user_id % 16 AS i1, list_position(['click','error','purchase','signup','view'], event_type) - 1 AS i2, {t} AS t, value, user_id, ts, event_id FROM events"""
_T10 = f"({_DAYS.format('2024-01-01', 'ts')} * 144 + (hour(ts) * 60 + minute(ts)) // 10)"
_TH = f"({_DAYS.format('2024-01-01', 'ts')} * 24 + hour(ts))"
_SHIP = "lineitem JOIN supplier ON l_suppkey = s_suppkey JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey"
_MONTH = "((year(l_shipdate) - 1995) * 12 + month(l_shipdate) - 1)"


def _sensor_sql(t):
    return f"SELECT i1::INT AS i1, i2::INT AS i2, t::INT AS t, round(sum(round(value * 100)::BIGINT) / (count(*) * 100), 6) AS y FROM ({_EV.format(t=t)}) GROUP BY ALL"


def _flow_sql(t, y="sum(round(l_quantity * 100)::BIGINT) / 100"):
    return f"SELECT s_nationkey::INT AS i1, c_nationkey::INT AS i2, ({t})::INT AS t, {y} AS y FROM {_SHIP} GROUP BY ALL"


CUBE_SQL = {
    "sensor_10min": _sensor_sql(_T10),
    "sensor_hour": _sensor_sql(_TH),
    "flow_week": _flow_sql(f"{_DAYS.format('1995-01-01', 'l_shipdate')} // 7"),
    "flow_month": _flow_sql(_MONTH),
    "flow_day": _flow_sql(_DAYS.format("1995-01-01", "l_shipdate"), "round(log2(count(*) + 1.0), 6)"),
    "transition_hour": f"SELECT i2::INT AS i1, j::INT AS i2, t::INT AS t, count(*)::DOUBLE AS y FROM (SELECT i2, t, lead(i2) OVER (ORDER BY ts, event_id) AS j FROM ({_EV.format(t=_TH)})) WHERE j IS NOT NULL GROUP BY ALL",
    "transition_user_hour": f"SELECT i2::INT AS i1, j::INT AS i2, t::INT AS t, count(*)::DOUBLE AS y FROM (SELECT i2, t, lead(i2) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS j FROM ({_EV.format(t=_TH)})) WHERE j IS NOT NULL GROUP BY ALL",
    "orders_day": f"SELECT (list_position({cubes.PRIORITIES}, o_orderpriority) - 1)::INT AS i1, (list_position({cubes.SEGMENTS}, c_mktsegment) - 1)::INT AS i2, ({_DAYS.format('1995-01-01', 'o_orderdate')})::INT AS t, count(*)::DOUBLE AS y FROM orders JOIN customer ON o_custkey = c_custkey GROUP BY ALL",
    "brand_region_month": f"SELECT b.i1::INT AS i1, ns.n_regionkey::INT AS i2, nc.n_regionkey::INT AS i3, ({_MONTH})::INT AS t, sum(round(l_quantity * 100)::BIGINT) / 100 AS y FROM {_SHIP} JOIN part ON l_partkey = p_partkey JOIN (SELECT p_brand, dense_rank() OVER (ORDER BY p_brand) - 1 AS i1 FROM (SELECT DISTINCT p_brand FROM part)) b USING (p_brand) JOIN nation ns ON s_nationkey = ns.n_nationkey JOIN nation nc ON c_nationkey = nc.n_nationkey GROUP BY ALL",
}

for _name in cubes.CUBES:
    query(f"cube_{_name}", CUBE_SQL[_name])(lambda s, d, n=_name: cubes.cells(s, d, n))


def _cube(s, d, name="flow_month"):
    return cubes.cells(s, d, name)


def _with(name="flow_month"):
    return f"WITH cells AS ({CUBE_SQL[name]})"


@query("standardize_by_mode", f"{_with('sensor_hour')}, m AS (SELECT i2, avg(y) AS mean, stddev_pop(y) AS dev FROM cells GROUP BY i2) SELECT i1, i2, t, round((y - mean) / dev, 4) + 0.0 AS y FROM cells JOIN m USING (i2)")
def standardize_by_mode(s, d):
    c = _cube(s, d, "sensor_hour")
    m = c.groupBy("i2").agg(F.avg("y").alias("mean"), F.stddev_pop("y").alias("dev"))
    return c.join(m, "i2").select("i1", "i2", "t", (F.round((F.col("y") - F.col("mean")) / F.col("dev"), 4) + 0.0).alias("y"))


@query("log2_scaled", f"{_with()} SELECT i1, i2, t, round(log2(1 + y), 6) AS y FROM cells")
def log2_scaled(s, d):
    return _cube(s, d).select("i1", "i2", "t", F.round(F.log2(1 + F.col("y")), 6).alias("y"))


@query("mode_dictionary", "SELECT 'brand' AS mode, p_brand AS label, (dense_rank() OVER (ORDER BY p_brand) - 1)::INT AS idx FROM (SELECT DISTINCT p_brand FROM part) UNION ALL SELECT 'event_type', event_type, (dense_rank() OVER (ORDER BY event_type) - 1)::INT FROM (SELECT DISTINCT event_type FROM events)")
def mode_dictionary(s, d):
    def labels(table, column, mode):
        return cubes.numbered(load(s, d, table).select(F.col(column).alias("label")).distinct()).select(F.lit(mode).alias("mode"), "label", "idx")

    return labels("part", "p_brand", "brand").unionByName(labels("events", "event_type", "event_type"))


_density_sql = " UNION ALL ".join(f"SELECT '{n}' AS cube, count(*) AS cells, (count(*) / {int(np.prod(c.sizes)) * c.steps}.0)::DOUBLE AS density FROM ({CUBE_SQL[n]})" for n, c in cubes.CUBES.items())


@query("density_report", f"SELECT cube, cells, round(density, 9) AS density FROM ({_density_sql})")
def density_report(s, d):
    ship = staged(cubes.shipped(s, d), "shipped")  # one star join for the four cubes of line items
    made = {"flow_week": lambda: cubes.flow(s, d, "week", ship), "flow_month": lambda: cubes.flow(s, d, "month", ship), "flow_day": lambda: cubes.flow(s, d, "day", ship), "brand_region_month": lambda: cubes.brand_month(s, d, ship)}
    parts = [made.get(n, lambda n=n: cubes.cells(s, d, n))().agg(F.lit(n).alias("cube"), F.count(F.lit(1)).alias("cells"), F.round(F.count(F.lit(1)) / float(np.prod(c.sizes) * c.steps), 9).alias("density")) for n, c in cubes.CUBES.items()]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


# ---- algebra; flow_month, with closed factors of rank 2

_M, _SIZES = ["i1", "i2", "t"], [25, 25, 83]


def _vec(idx: Column, mode: int, rank: int = 2) -> Column:
    return F.array(*[F.cos((idx + 1) * (0.3 + 0.2 * mode + 0.1 * r)) for r in range(rank)])


def _vec_sql(idx: str, mode: int, rank: int = 2) -> list[str]:
    return [f"cos(({idx} + 1) * {0.3 + 0.2 * mode + 0.1 * r!r})" for r in range(rank)]


def _hat_sql(rank=2, modes=_M):
    return " + ".join(" * ".join(_vec_sql(m, n, rank)[r] for n, m in enumerate(modes)) for r in range(rank))


def _factor(s, n, size, rank=2):
    return s.range(size).select(F.col("id").cast("int").alias("idx")).select("idx", _vec(F.col("idx"), n, rank).alias("vec"))


def _factors(s, rank=2, modes=_M, sizes=_SIZES):
    return {m: _factor(s, n, size, rank) for n, (m, size) in enumerate(zip(modes, sizes))}


for _k, (_mode, _col) in enumerate({"i1": "i2::BIGINT + t * 25", "i2": "i1::BIGINT + t * 25", "t": "i1::BIGINT + i2 * 25"}.items()):
    query(f"unfold_mode{_k + 1}", f"{_with()} SELECT {_mode} AS row, {_col} AS col, y FROM cells")(lambda s, d, m=_mode: algebra.unfold(_cube(s, d), _M, _SIZES, m))


@query("fold_roundtrip", f"{_with()} SELECT i1, i2, t, y FROM cells")
def fold_roundtrip(s, d):
    return algebra.fold(algebra.unfold(_cube(s, d), _M, _SIZES, "i2"), _M, _SIZES, "i2")


@query("hadamard_pair", f"{_with()} SELECT a.i1, a.i2, a.t, a.y * b.y AS y FROM cells a JOIN (SELECT i1, i2, (t + 12)::INT AS t, y FROM cells) b USING (i1, i2, t)")
def hadamard_pair(s, d):
    c = _cube(s, d)
    return algebra.hadamard(c, c.withColumn("t", F.col("t") + 12), on=_M)


@query("hadamard_chain", f"{_with()} SELECT a.i1, a.i2, a.t, a.y * b.y * c.y AS y FROM cells a JOIN (SELECT i1, i2, (t + 12)::INT AS t, y FROM cells) b USING (i1, i2, t) JOIN (SELECT i1, i2, (t + 24)::INT AS t, y FROM cells) c USING (i1, i2, t)")
def hadamard_chain(s, d):
    c = _cube(s, d)
    return algebra.hadamard(c, c.withColumn("t", F.col("t") + 12), c.withColumn("t", F.col("t") + 24), on=_M)


def _flat(df):
    return df.select("idx", r6(F.col("vec")[0]).alias("v0"), r6(F.col("vec")[1]).alias("v1"))


#: Small factors of two columns made of given tables: how many rows an index has, and how much they sum up to.
_GIVEN = {
    "nation": ("customer", "c_nationkey", lambda: F.col("c_nationkey"), "c_acctbal"),
    "priority": ("orders", f"list_position({cubes.PRIORITIES}, o_orderpriority) - 1", lambda: cubes.code("o_orderpriority", cubes.PRIORITIES), "o_totalprice"),
    "event": ("events", "list_position(['click','error','purchase','signup','view'], event_type) - 1", lambda: cubes.code("event_type", cubes.EVENT_TYPES), "value"),
}


def _given(s, d, name):
    table, _, idx, x = _GIVEN[name]
    sums = load(s, d, table).groupBy(idx().cast("int").alias("idx")).agg(F.count(F.lit(1)).alias("n"), (F.sum(F.abs(cubes.cents(x))) / 100).alias("x"))
    return sums.select("idx", F.array(F.log2(1 + F.col("n")), F.log2(1 + F.col("x"))).alias("vec"))


def _given_sql(name):
    table, idx, _, x = _GIVEN[name]
    return f"{name} AS (SELECT ({idx})::BIGINT AS i, log2(1 + count(*)) AS v0, log2(1 + sum(abs(round({x} * 100)::BIGINT)) / 100) AS v1 FROM {table} GROUP BY ALL)"


@query("khatri_rao_pair", f"WITH {_given_sql('nation')}, {_given_sql('priority')} SELECT a.i * 5 + b.i AS idx, " + ", ".join(f"round(a.v{r} * b.v{r}, 6) + 0.0 AS v{r}" for r in range(2)) + " FROM nation a, priority b")
def khatri_rao_pair(s, d):
    """Customers' nations by orders' priorities."""
    return _flat(algebra.khatri_rao(_given(s, d, "nation"), _given(s, d, "priority"), 5)).withColumn("idx", F.col("idx").cast("long"))


@query("khatri_rao_chain", f"WITH {_given_sql('nation')}, {_given_sql('priority')}, {_given_sql('event')} SELECT (a.i * 5 + b.i) * 5 + c.i AS idx, " + ", ".join(f"round(a.v{r} * b.v{r} * c.v{r}, 6) + 0.0 AS v{r}" for r in range(2)) + " FROM nation a, priority b, event c")
def khatri_rao_chain(s, d):
    """Customers' nations by orders' priorities by types of events."""
    two = algebra.khatri_rao(_given(s, d, "nation"), _given(s, d, "priority"), 5)
    return _flat(algebra.khatri_rao(two, _given(s, d, "event"), 5)).withColumn("idx", F.col("idx").cast("long"))


@query("outer_rank1", "SELECT n_nationkey::INT AS i1, r_regionkey::INT AS i2, (k)::INT AS i3, ((n_nationkey + 1) * (r_regionkey + 2) * (k + 3))::DOUBLE AS y FROM nation, region, range(4) t(k)")
def outer_rank1(s, d):
    n = load(s, d, "nation").select(F.col("n_nationkey").cast("int").alias("idx"), (F.col("n_nationkey") + 1.0).alias("x"))
    r = load(s, d, "region").select(F.col("r_regionkey").cast("int").alias("idx"), (F.col("r_regionkey") + 2.0).alias("x"))
    k = s.range(4).select(F.col("id").cast("int").alias("idx"), (F.col("id") + 3.0).alias("x"))
    return algebra.outer([n, r, k])


@query("kruskal_reconstruct", f"{_with()} SELECT i1, i2, t, round({_hat_sql()}, 6) + 0.0 AS x_hat FROM cells")
def kruskal_reconstruct(s, d):
    return algebra.reconstruct(_cube(s, d).select(*_M), _factors(s)).select(*_M, r6(F.col("x_hat")).alias("x_hat"))


@query("missing_cells", f"{_with()} SELECT a.i::INT AS i1, b.i::INT AS i2, c.i::INT AS t FROM range(25) a(i), range(25) b(i), range(83) c(i) WHERE (a.i, b.i, c.i) NOT IN (SELECT (i1, i2, t) FROM cells)")
def missing_cells(s, d):
    return algebra.missing(algebra.grid(s, dict(zip(_M, _SIZES))), _cube(s, d), _M)


@query("frobenius_norm", f"{_with()} SELECT round(sqrt(sum(y * y)), 6) AS frobenius, sum(abs(y)) AS l1, max(abs(y)) AS largest FROM cells")
def frobenius_norm(s, d):
    y = F.col("y")
    return _cube(s, d).agg(F.round(F.sqrt(F.sum(y * y)), 6).alias("frobenius"), F.sum(F.abs(y)).alias("l1"), F.max(F.abs(y)).alias("largest"))


@query("column_norms", "SELECT round(sqrt(sum(n * n)), 6) AS n0, round(sqrt(sum(x * x)), 6) AS n1 FROM (SELECT count(*)::DOUBLE AS n, sum(round(l_quantity * 100)::BIGINT) / 100 AS x FROM lineitem GROUP BY l_partkey)")
def column_norms(s, d):
    """Of a factor with a row a part: its line items and their quantity."""
    rows = load(s, d, "lineitem").groupBy(F.col("l_partkey").alias("idx")).agg(F.array(F.count(F.lit(1)).cast("double"), F.sum(cubes.cents("l_quantity")) / 100).alias("vec"))
    return rows.agg(*[F.round(F.sqrt(F.sum(F.col("vec")[r] * F.col("vec")[r])), 6).alias(f"n{r}") for r in range(2)])


@query("masked_loss", f"{_with()} SELECT round(sum(0.5 * (y / 100 - ({_hat_sql()})) ** 2), 4) AS loss FROM cells")
def masked_loss(s, d):
    x = algebra.reconstruct(_cube(s, d).withColumn("y", F.col("y") / 100), _factors(s))
    return cost.masked_loss(x).select(F.round("loss", 4).alias("loss"))


# ---- objectives; y is scaled by 1/100, outliers are what lies beyond 3

_OBJ = f"""{_with()}, x AS (SELECT i1, i2, t, y / 100 AS y, {_hat_sql()} AS x, greatest(y / 100 - 3, 0) AS o FROM cells),
fit AS (SELECT t, sum((y - o - x) ** 2) AS fit, 0.5 * sum(abs(o)) AS sparse FROM x GROUP BY t),
w AS (SELECT i::INT AS t, {', '.join(f'{v} AS w{r}' for r, v in enumerate(_vec_sql('i', 2)))} FROM range(83) r(i)),
sm AS (SELECT t, 0.1 * coalesce((w0 - lag(w0) OVER (ORDER BY t)) ** 2 + (w1 - lag(w1) OVER (ORDER BY t)) ** 2, 0) AS smooth,
  0.2 * coalesce((w0 - lag(w0, 12) OVER (ORDER BY t)) ** 2 + (w1 - lag(w1, 12) OVER (ORDER BY t)) ** 2, 0) AS seasonal FROM w),
terms AS (SELECT t, coalesce(fit, 0) AS fit, smooth, seasonal, coalesce(sparse, 0) AS sparse FROM sm LEFT JOIN fit USING (t))"""


def _terms(s, d):
    c = algebra.reconstruct(_cube(s, d).withColumn("y", F.col("y") / 100), _factors(s)).withColumn("o", F.greatest(F.col("y") - 3, F.lit(0.0)))
    w = _factor(s, 2, 83).withColumnRenamed("idx", "t")
    return cost.step_terms(c, w, 12, 0.1, 0.2, 0.5)


@query("objective_batch_terms", _OBJ + " SELECT round(sum(fit), 4) AS fit, round(sum(smooth), 6) AS smooth, round(sum(seasonal), 6) AS seasonal, round(sum(sparse), 4) AS sparse, round(sum(fit + smooth + seasonal + sparse), 4) AS total FROM terms")
def objective_batch_terms(s, d):
    b = cost.batch(_terms(s, d))
    return b.select(*[F.round(c, 6 if c in ("smooth", "seasonal") else 4).alias(c) for c in b.columns])


@query("objective_stream_running", _OBJ + " SELECT t, round(fit + smooth + seasonal + sparse, 4) AS step, round(sum(fit + smooth + seasonal + sparse) OVER (ORDER BY t), 4) AS running FROM terms")
def objective_stream_running(s, d):
    return cost.stream(_terms(s, d)).select("t", F.round("step", 4).alias("step"), F.round("running", 4).alias("running"))


@query("objective_step", _OBJ + " SELECT t, round(fit, 4) AS fit, round(smooth, 6) AS smooth, round(seasonal, 6) AS seasonal, round(sparse, 4) AS sparse FROM terms")
def objective_step(s, d):
    return _terms(s, d).select("t", F.round("fit", 4).alias("fit"), F.round("smooth", 6).alias("smooth"), F.round("seasonal", 6).alias("seasonal"), F.round("sparse", 4).alias("sparse"))


for _name, _lag in (("smoothness_lag1", 1), ("smoothness_lagm", 12)):
    query(_name, f"WITH w AS (SELECT i::INT AS t, {', '.join(f'{v} AS w{r}' for r, v in enumerate(_vec_sql('i', 2)))} FROM range(83) r(i)) SELECT t, round(coalesce((w0 - lag(w0, {_lag}) OVER (ORDER BY t)) ** 2 + (w1 - lag(w1, {_lag}) OVER (ORDER BY t)) ** 2, 0), 6) AS d2 FROM w")(
        lambda s, d, lag=_lag: cost.smoothness(_factor(s, 2, 83).withColumnRenamed("idx", "t"), lag).select("t", F.round("d2", 6).alias("d2"))
    )


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    from . import catalog_methods, catalog_operators  # noqa: F401  they register theirs

    return dict(_queries)


def oracle_sql() -> dict[str, str]:
    from . import catalog_methods, catalog_operators  # noqa: F401

    return dict(_oracle)


def flagship(spark: SparkSession, d: str) -> DataFrame:
    """Monthly flows between nations: start-up, online steps, imputed cells and a forecast of twelve months."""
    from .streaming import fold

    rows = cubes.cells(spark, d, "flow_month").select(F.lit("flow").alias("tensor_id"), "i1", "i2", "t", F.log2(1 + F.col("y")).alias("y"))
    spec = TensorSpec((25, 25), 12, 3)
    return fold.run(rows, spec, HyperParams(lambda1=0.01, lambda2=0.01, max_iter=60), horizon=12)
