"""The drivers agree with each other, plans stay as wanted, and the registry's exact queries match DuckDB."""

import os

import duckdb
import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

import __spark_entry__
from cellstream import catalog
from cellstream.model import HyperParams, TensorSpec
from cellstream.plans import planner, smooth_als, startup
from cellstream.sources import cubes, planted
from cellstream.operators import corrupt, algebra
from cellstream.streaming import fold, kernel, live, step
from cellstream.streaming.fold import Stream
from tests.conftest import SMALL

SPEC, HP = TensorSpec((6, 5), 4, 2), HyperParams(lambda1=0.01, lambda2=0.01, max_iter=8)


@pytest.fixture(scope="module")
def cells(spark):
    full = algebra.grid(spark, {"i1": 6, "i2": 5, "t": 24})
    return corrupt.apply(planted.truth(full, ["i1", "i2"], 2, 4), ["i1", "i2", "t"], 20, 5, 2, seed=3).select("i1", "i2", "t", "y").cache()


def local(cells):
    p = cells.orderBy("t", "i1", "i2").toPandas()
    return {t: (g[["i1", "i2"]].to_numpy(np.int64), g["y"].to_numpy()) for t, g in p.groupby("t")}


def test_distributed_start_up_equals_local(cells):
    by = local(cells)
    idx = np.concatenate([np.c_[i, np.full(len(i), t)] for t, (i, _) in by.items() if t < 12])
    y = np.concatenate([v for t, (_, v) in by.items() if t < 12])
    a, _ = startup.run_local(idx, y, SPEC, HP, 12)
    b = startup.run(cells, SPEC, HP)
    assert all(np.allclose(u, v, atol=1e-8) for u, v in zip(a, b))


def test_step_equals_kernel(spark, cells):
    by = local(cells)
    state = startup.snapshot(startup.run(cells, SPEC, HP), SPEC)
    mine, theirs, scales = state.copy(), state.copy(), None
    for t in range(12, 15):
        mine, out = kernel.advance(mine, *by[t], HP)
        theirs, judged = step.advance(theirs, cells.where(F.col("t") == t), scales, SPEC, HP)
        scales = step.overlay(scales, judged, SPEC)
        got = judged.orderBy("i1", "i2").toPandas()
        assert np.allclose(got["outlier"], out["outlier"], atol=1e-9)
    assert np.allclose(mine.ring, theirs.ring) and all(np.allclose(a, b) for a, b in zip(mine.factors, theirs.factors))
    assert {(r["i1"], r["i2"]): round(r["sigma2"], 9) for r in scales.collect()} == {k: round(v, 9) for k, v in mine.scales.items()}


def test_fold_equals_stream_whatever_the_partitions(spark, cells):
    stream, want = Stream(SPEC, HP, 1), {}
    for t, (i, y) in local(cells).items():
        for kind, at, idx, x, o in stream.feed(t, idx=i, y=y):
            want.update({(at, a, b): v for (a, b), v in zip(idx.tolist(), x)})
    for parts in (1, 5):
        rows = cells.repartition(parts, "y").select(F.lit("a").alias("tensor_id"), "*").unionByName(cells.select(F.lit("b").alias("tensor_id"), "*"))
        got = fold.run(rows, SPEC, HP, horizon=2, starts=1).toPandas()
        for tensor in "ab":
            seen = got[(got["tensor_id"] == tensor) & got["kind"].isin(["startup", "update"])]
            assert {(r.t, r.i1, r.i2): round(r.x_hat, 9) for r in seen.itertuples()} == {k: round(v, 9) for k, v in want.items()}
        assert (got["kind"] == "forecast").sum() == 2 * 2 * 30
        assert (got[got["kind"] == "imputed"].groupby(["tensor_id", "t"]).size() < 30).all()


def test_short_tensor_is_an_error(cells):
    with pytest.raises(Exception, match="start-up"):
        fold.run(cells.where("t < 5").select(F.lit("a").alias("tensor_id"), "*"), SPEC, HP, starts=1).collect()


def test_short_tensor_can_be_marked(cells):
    """One tensor that ends too early leaves the others alone."""
    rows = cells.select(F.lit("whole").alias("tensor_id"), "*").unionByName(cells.where("t < 5").select(F.lit("short").alias("tensor_id"), "*"))
    got = fold.run(rows, SPEC, HP, starts=1, short="mark").groupBy("tensor_id", "kind").count().collect()
    kinds = {(r["tensor_id"], r["kind"]): r["count"] for r in got}
    assert kinds["short", "too_short"] == cells.where("t < 5").count() and kinds["whole", "update"] > 0 and ("short", "update") not in kinds


def test_live_replay_restarts_and_skips_late_rows(spark, tmp_path):
    """Micro-batches, a restart in between and a late row give what the fold gives."""
    rng = np.random.default_rng(0)
    origin = pd.Timestamp("2024-01-01")
    rows = [(origin + pd.Timedelta(hours=t, minutes=5 + k), int(i), int(j), float(1 + np.sin(t * np.pi / 2) + i + 0.1 * j)) for t in range(20) for k, (i, j) in enumerate(rng.permutation([(a, b) for a in range(3) for b in range(2)])[:5])]
    frame = pd.DataFrame(rows, columns=["ts", "i1", "i2", "value"])
    frame["ts"] = frame["ts"].dt.tz_localize("UTC").astype("datetime64[us, UTC]")
    spec, hp = TensorSpec((3, 2), 4, 1), HyperParams(lambda1=0.01, lambda2=0.01, max_iter=5)
    source, out, check = tmp_path / "in", tmp_path / "out", tmp_path / "check"
    source.mkdir(), out.mkdir()
    schema = "ts timestamp, i1 int, i2 int, value double"
    read = lambda: live.open_stream(spark, str(source), schema)
    sink = live.Sink(spec, hp, str(out), "2024-01-01", 3600, 1)
    spark.createDataFrame(frame[:60], schema).coalesce(1).write.mode("append").parquet(str(source))
    live.replay(read(), sink, "1 hour", "0 seconds", str(check))
    late = frame[:1].assign(value=1e6)
    spark.createDataFrame(pd.concat([frame[60:], late]), schema).coalesce(1).write.mode("append").parquet(str(source))
    live.replay(read(), sink, "1 hour", "0 seconds", str(check))
    got = sink.outputs(spark).toPandas()
    assert len(sink.commits(spark)) <= 2
    closed = frame[frame["ts"] < frame["ts"].max().floor("h")]
    c = closed.assign(t=((closed["ts"].dt.tz_localize(None) - origin).dt.total_seconds() // 3600).astype(int))
    stream, want = Stream(spec, hp, 1), {}
    for t, g in c.groupby("t"):
        g = g.sort_values(["i1", "i2"])
        for kind, at, idx, x, o in stream.feed(int(t), g[["i1", "i2"]].to_numpy(np.int64), g["value"].to_numpy()):
            want.update({(at, a, b): round(v, 9) for (a, b), v in zip(idx.tolist(), x)})
    assert {(r.t, r.i1, r.i2): round(r.x_hat, 9) for r in got.itertuples()} == want


def test_planner(spark):
    assert planner.choose(SPEC, 30) == "fold" and planner.choose(SPEC, 10**9) == "step"
    with pytest.raises(ValueError):
        planner.choose(TensorSpec((10**9, 5), 4, 2), 30)
    with pytest.raises(ValueError):
        smooth_als.row_systems(spark.range(1), [np.zeros((smooth_als.MOST_NUMBERS // 100 + 1, 10))], ["id"], 0)
    with pytest.raises(ValueError):
        smooth_als.solved_rows(spark.range(1), [np.zeros((smooth_als.MOST_NUMBERS // 10 + 1, 10))], ["id"], 0)


def test_driver_follows_the_slices(spark, monkeypatch):
    """The planner's two drivers give the same updates of the same stream."""
    rng = np.random.default_rng(2)
    spec, hp = TensorSpec((3, 4), 3, 1), HyperParams(lambda1=0.01, lambda2=0.01, max_iter=4)
    rows = [("a", int(i), int(j), t, float(2 + np.sin(2 * np.pi * t / 3) + 0.1 * i * j + 0.01 * rng.random())) for t in range(12) for i in range(3) for j in range(4) if rng.random() < 0.9]
    cells = spark.createDataFrame(rows, "tensor_id string, i1 int, i2 int, t int, y double")
    read = lambda: {(r["t"], r["i1"], r["i2"]): (r["x_hat"], r["outlier"]) for r in planner.drive(cells, spec, hp).where("kind = 'update'").collect()}
    one = read()
    monkeypatch.setattr(planner, "FOLD_CELLS", 5)
    two = read()
    assert one.keys() == two.keys() and len(one) > 20
    assert all(np.allclose(one[k], two[k], atol=1e-6) for k in one)


def test_long_mode_sums_leave_batch_by_batch(spark, monkeypatch):
    """Rows of a mode that is too long for one array a task are summed by the exchange: the same factors."""
    from cellstream.plans import startup

    rng = np.random.default_rng(3)
    spec, hp = TensorSpec((6, 5), 3, 2), HyperParams(lambda1=0.01, lambda2=0.01, max_iter=3, inner_max_iter=3)
    rows = [(i, j, t, float(rng.random() + i + j * np.cos(t))) for i in range(6) for j in range(5) for t in range(9) if rng.random() < 0.8]
    cells = spark.createDataFrame(rows, "i1 int, i2 int, t int, y double").repartition(3)
    want = startup.run(cells, spec, hp)
    monkeypatch.setattr(smooth_als, "TASK_NUMBERS", 1)
    assert all(np.allclose(a, b, atol=1e-8) for a, b in zip(startup.run(cells, spec, hp), want))


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_plans(spark):
    """Pruned scans, no product over cells, one exchange by coordinates after the star join."""
    text = plan(cubes.cells(spark, SMALL, "flow_month"))
    assert "CartesianProduct" not in text and "BroadcastNestedLoopJoin" not in text
    assert "l_extendedprice" not in text and "o_totalprice" not in text
    text = plan(cubes.cells(spark, SMALL, "sensor_hour").where("i2 = 1"))
    assert "Window" not in text
    rows = cubes.cells(spark, SMALL, "flow_month").select(F.concat(F.lit("f"), F.col("i1") % 2).alias("tensor_id"), "i1", "i2", "t", "y")
    assert plan(fold.run(rows, TensorSpec((25, 25), 12, 2), HP)).count("hashpartitioning(tensor_id") == 1
    assert "CartesianProduct" not in plan(catalog.queries()["op_join_range"](spark, SMALL))
    assert "PushedFilters: [" in plan(cubes.load(spark, SMALL, "lineitem").where("l_quantity > 45").select("l_orderkey"))


def canon(rows, columns):
    order = sorted(range(len(columns)), key=lambda i: columns[i])
    show = lambda v: f"{float(v):.8g}" if isinstance(v, float) else str(v)
    return sorted(tuple(show(r[i]) for i in order) for r in rows)


SLOW = {"density_report"}


@pytest.mark.parametrize("name", sorted(set(catalog.oracle_sql()) - SLOW))
def test_against_duckdb(spark, name):
    db = duckdb.connect()
    for f in os.listdir(SMALL):
        db.sql(f"CREATE VIEW {f.removesuffix('.parquet')} AS SELECT * FROM '{SMALL}/{f}'")
    want = db.sql(catalog.oracle_sql()[name])
    got = catalog.queries()[name](spark, SMALL)
    assert sorted(got.columns) == sorted(want.columns)
    assert canon(got.collect(), got.columns) == canon(want.fetchall(), want.columns)


def test_entry(spark):
    assert __spark_entry__.entry(spark).count() > 0
    assert set(__spark_entry__.oracle_sql()) <= set(__spark_entry__.queries())
