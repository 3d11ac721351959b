"""Cells from files of several formats, with a fixed schema."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..model import TensorSpec


def schema(spec: TensorSpec) -> str:
    return "tensor_id string, " + ", ".join(f"{m} int" for m in spec.modes) + ", t int, y double"


def read_cells(spark: SparkSession, path: str, spec: TensorSpec, kind: str = "parquet") -> DataFrame:
    """kind: parquet, orc, json or csv (with a header). A null value is a missing cell and has no row."""
    reader = spark.read.schema(schema(spec))
    if kind == "csv":
        reader = reader.option("header", True)
    return reader.format(kind).load(path).where("y is not null")
