"""Results in files, laid out so that later steps and late repairs touch what they must."""

from __future__ import annotations

import json

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .model import Scales, SeasonState, Snapshot

#: Steps in one folder.
BUCKET = 1000


def write(df: DataFrame, path: str, mode: str = "append") -> None:
    """Rows with tensor_id and t, partitioned by tensor and bucket of steps; overwriting replaces only the buckets that df has."""
    out = df.withColumn("t_bucket", F.floor(F.col("t") / BUCKET).cast("int")).repartition("tensor_id", "t_bucket")
    out.write.partitionBy("tensor_id", "t_bucket").mode(mode).option("partitionOverwriteMode", "dynamic").parquet(path)


def read(spark: SparkSession, path: str, first: int | None = None, last: int | None = None) -> DataFrame:
    """Rows of steps first..last; the bounds prune folders."""
    df = spark.read.parquet(path)
    if first is not None:
        df = df.where((F.col("t_bucket") >= first // BUCKET) & (F.col("t") >= first))
    if last is not None:
        df = df.where((F.col("t_bucket") <= last // BUCKET) & (F.col("t") <= last))
    return df.drop("t_bucket")


def snapshot_text(state: Snapshot) -> str:
    """A snapshot as JSON: a model row of a table."""
    s = state.season
    lists = lambda a: a.tolist()
    return json.dumps({"t": state.t, "factors": [lists(u) for u in state.factors], "ring": lists(state.ring), "season": {k: lists(getattr(s, k)) for k in ("level", "trend", "season", "alpha", "beta", "gamma")}, "scales": [[list(k), v] for k, v in state.scales.items()]})


def snapshot_from(text: str) -> Snapshot:
    d = json.loads(text)
    return Snapshot([np.array(u) for u in d["factors"]], SeasonState(**{k: np.array(v) for k, v in d["season"].items()}), np.array(d["ring"]), d["t"], Scales([len(u) for u in d["factors"]], d["scales"]))
