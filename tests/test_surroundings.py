"""Files, sinks, snapshots, table functions and the keyed live driver."""

import numpy as np
import pandas as pd
from pyspark.sql import functions as F

from cellstream import experiments, sinks
from cellstream.model import HyperParams, TensorSpec
from cellstream.sources import files
from cellstream.streaming import fold, keyed, kernel
from cellstream.streaming.fold import Stream

SPEC, HP = TensorSpec((3, 2), 4, 1), HyperParams(lambda1=0.01, lambda2=0.01, max_iter=5)


def rows(tensors="ab", steps=16):
    return [(k, i, j, t, float(1 + np.sin(t * np.pi / 2) + i + 0.1 * j + ord(k) / 100)) for k in tensors for t in range(steps) for i in range(3) for j in range(2) if (i + j + t) % 7]


def test_files_and_sinks(spark, tmp_path):
    cells = spark.createDataFrame(rows(), files.schema(SPEC))
    for kind in ("parquet", "orc", "json", "csv"):
        path = str(tmp_path / kind)
        cells.write.format(kind).option("header", True).save(path)
        got = files.read_cells(spark, path, SPEC, kind)
        assert got.dtypes == cells.dtypes and got.exceptAll(cells).count() == 0 == cells.exceptAll(got).count()
    out = str(tmp_path / "out")
    sinks.write(cells, out)
    sinks.write(cells.where("tensor_id = 'a'").withColumn("y", F.col("y") + 1), out, "overwrite")
    back = sinks.read(spark, out, 3, 9)
    assert back.where("tensor_id = 'b'").count() == cells.where("tensor_id = 'b' and t between 3 and 9").count()
    assert back.where("tensor_id = 'a'").agg(F.min("y")).first()[0] > 1.5
    assert "PartitionFilters: [isnotnull(t_bucket" in sinks.read(spark, out, 3, 9)._jdf.queryExecution().executedPlan().toString()


def test_snapshot_round_trip():
    s = Stream(SPEC, HP, 1)
    for t in range(14):
        part = [r for r in rows("a") if r[3] == t]
        s.feed(t, np.array([r[1:3] for r in part]), np.array([r[4] for r in part]))
    again = sinks.snapshot_from(sinks.snapshot_text(s.state))
    assert np.allclose(kernel.forecast_time(again, 3), kernel.forecast_time(s.state, 3)) and again.scales == s.state.scales


def test_keyed_stream_equals_fold(spark, tmp_path):
    """Slices in three files, one a micro-batch; state passes between them."""
    data = pd.DataFrame(rows(), columns=["tensor_id", "i1", "i2", "t", "y"])
    source, out = tmp_path / "in", tmp_path / "out"
    source.mkdir()
    for k, (lo, hi) in enumerate(((0, 9), (9, 13), (13, 16))):
        spark.createDataFrame(data[(data["t"] >= lo) & (data["t"] < hi)], files.schema(SPEC)).coalesce(1).write.mode("append").parquet(str(source))
        stream = spark.readStream.schema(files.schema(SPEC)).parquet(str(source))
        q = keyed.run(stream, SPEC, HP).writeStream.outputMode("append").format("parquet").option("path", str(out)).option("checkpointLocation", str(tmp_path / "check")).trigger(availableNow=True).start()
        q.awaitTermination()
    got = {(r["tensor_id"], r["t"], r["i1"], r["i2"]): round(r["x_hat"], 9) for r in spark.read.parquet(str(out)).collect()}
    want = fold.run(spark.createDataFrame(data, files.schema(SPEC)), SPEC, HP, impute=False, starts=1).collect()
    assert got == {(r["tensor_id"], r["t"], r["i1"], r["i2"]): round(r["x_hat"], 9) for r in want}


def test_comparison_with_the_second(spark):
    """Means over seeds and steps; the most accurate other method is the one compared with."""
    rows = [("w", 20, 10, 2, seed, m, "{}", t, e + 0.1 * (seed == 2), s) for seed in (1, 2) for t in (5, 6, 7) for m, e, s in (("robust_seasonal", 0.05, 1.0), ("b", 0.35, 10.0), ("c", 0.5, 0.1))]
    got = experiments.compared(spark.createDataFrame(rows, experiments.STEP_SCHEMA), ["workload", "missing", "outliers", "times"]).first()
    assert got["second"] == "b" and np.isclose(got["percent_less_error"], 75) and np.isclose(got["times_faster"], 10) and np.isclose(got["own_art"], 1.5)


def test_planted_values_agree(spark):
    """The column formula and the array hold the same numbers, seed by seed."""
    from cellstream.sources import planted

    at = spark.createDataFrame([(i, j, t) for i in range(3) for j in range(4) for t in range(10)], "i1 int, i2 int, t int")
    for seed in (0, 3):
        x = planted.values((3, 4), 10, 2, 5, seed)
        assert all(np.isclose(x[r["i1"], r["i2"], r["t"]], r["x"]) for r in planted.truth(at, ["i1", "i2"], 2, 5, seed).collect())


def test_runs_see_the_cubes_gaps_and_every_method(spark):
    """A small grid of runs on the coordinates of the given tables' monthly flows."""
    cells = experiments.observed(spark, "/root/testdata/sf0.01", "flow_month", [(20, 10, 2)], [1, 2])
    got = experiments.runs(cells, ["robust_seasonal", "sgd_stream_cp"], experiments.imputed, {}).toPandas()
    assert set(got["method"]) == {"robust_seasonal", "sgd_stream_cp"} and set(got["seed"]) == {1, 2} and set(got["t"]) == set(range(36, 83))
    mean = got.groupby("method")["nre"].mean()
    assert mean["robust_seasonal"] < mean["sgd_stream_cp"]


def test_dense_numbers_over_ranges(spark):
    from cellstream.sources import cubes

    labels = [f"l{(7919 * k) % 5000:05d}" for k in range(500)]
    got = {r["label"]: r["idx"] for r in cubes.numbered(spark.createDataFrame([(x,) for x in labels], "label string").repartition(7)).collect()}
    assert got == {x: i for i, x in enumerate(sorted(labels))}
