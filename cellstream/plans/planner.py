"""Choices that Catalyst cannot make: which driver runs a step, and how coordinates are imputed."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import HyperParams, Snapshot, TensorSpec
from ..streaming import fold, kernel, step

#: Cells of a slice that one task folds over; above, a step runs over the cluster.
FOLD_CELLS = 10_000_000
#: Numbers in all non-temporal factors that may be broadcast.
BROADCAST_NUMBERS = 50_000_000


def choose(spec: TensorSpec, cells_per_slice: int) -> str:
    numbers = sum(spec.sizes) * spec.rank
    if numbers > BROADCAST_NUMBERS:
        raise ValueError(f"factors of {numbers} numbers are not broadcast; bucket them by idx and use algebra.reconstruct")
    return "fold" if cells_per_slice <= FOLD_CELLS else "step"


def drive(cells: DataFrame, spec: TensorSpec, hp: HyperParams) -> DataFrame:
    """Updates of every tensor's stream (tensor_id, modes.., t, kind, x_hat, outlier), by the driver that its largest slice asks for."""
    largest = cells.groupBy("tensor_id", "t").count().agg(F.max("count")).first()[0] or 0
    if choose(spec, largest) == "fold":
        return fold.run(cells, spec, hp, impute=False)
    out = None
    for tensor in [r["tensor_id"] for r in cells.select("tensor_id").distinct().orderBy("tensor_id").collect()]:  # tensors with huge slices are few
        part = step.run(cells.where(F.col("tensor_id") == tensor).drop("tensor_id"), spec, hp, 3).select(F.lit(tensor).alias("tensor_id"), *spec.modes, "t", F.lit("update").alias("kind"), F.col("x_hat"), "outlier")
        out = part if out is None else out.unionByName(part)
    return out if out is not None else fold.run(cells, spec, hp, impute=False)


def impute_at(coords: DataFrame, state: Snapshot, spec: TensorSpec, h: int = 0) -> DataFrame:
    """coords (modes..) with x_hat: values of the last step (h = 0) or h steps past it, for asked coordinates only."""
    w = kernel.forecast_time(state, h) if h else state.ring[state.t % len(state.ring)]
    choose(spec, 0)
    shared = coords.sparkSession.sparkContext.broadcast((state.factors, w))
    modes = spec.modes

    def run(batches):
        import pyarrow as pa

        factors, vector = shared.value
        for batch in batches:
            idx = np.stack([batch.column(k).to_numpy(zero_copy_only=False) for k in modes], 1).astype(np.int64)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(kernel.rows(factors, idx) @ vector)], [*batch.schema.names, "x_hat"])

    from pyspark.sql.types import DoubleType, StructType

    return coords.mapInArrow(run, StructType([*coords.schema.fields]).add("x_hat", DoubleType()))
