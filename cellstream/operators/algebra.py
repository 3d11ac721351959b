"""Tensor algebra on coordinate-form cells and factor tables (mode, idx, vec)."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def unfold(cells: DataFrame, modes: list[str], sizes: list[int], mode: str) -> DataFrame:
    """(row, col, y): the other modes become one mixed-radix column number, the first varying fastest."""
    stride, col = 1, F.lit(0).cast("long")
    for m, size in zip(modes, sizes):
        if m != mode:
            col = col + F.col(m).cast("long") * stride
            stride *= size
    return cells.select(F.col(mode).alias("row"), col.alias("col"), "y")


def fold(matrix: DataFrame, modes: list[str], sizes: list[int], mode: str) -> DataFrame:
    """Inverse of unfold."""
    out, stride = {}, 1
    for m, size in zip(modes, sizes):
        if m == mode:
            out[m] = F.col("row").cast("int")
        else:
            out[m] = F.pmod(F.floor(F.col("col") / stride), F.lit(size)).cast("int")
            stride *= size
    return matrix.select(*[out[m].alias(m) for m in modes], "y")


def hadamard(*tensors: DataFrame, on: list[str]) -> DataFrame:
    """Element-wise product of tensors; a cell that any of them lacks is absent."""
    named = [t.select(*on, F.col("y").alias(f"y{i}")) for i, t in enumerate(tensors)]
    joined = reduce(lambda a, b: a.join(b, on), named)
    return joined.select(*on, reduce(lambda a, b: a * b, [F.col(f"y{i}") for i in range(len(tensors))]).alias("y"))


def khatri_rao(left: DataFrame, right: DataFrame, right_size: int) -> DataFrame:
    """Column-wise Kronecker product of two factors (idx, vec): I * J rows. For small factors and checks only;
    the methods take the product of factor rows cell by cell."""
    r = right.select(F.col("idx").alias("j"), F.col("vec").alias("w"))
    return left.crossJoin(r).select((F.col("idx") * right_size + F.col("j")).alias("idx"), F.zip_with("vec", "w", lambda a, b: a * b).alias("vec"))


def outer(vectors: list[DataFrame]) -> DataFrame:
    """Cells of a rank-one tensor from vectors (idx, x)."""
    named = [v.select(F.col("idx").alias(f"i{n + 1}"), F.col("x").alias(f"x{n + 1}")) for n, v in enumerate(vectors)]
    joined = reduce(lambda a, b: a.crossJoin(b), named)
    return joined.select(*[f"i{n + 1}" for n in range(len(vectors))], reduce(lambda a, b: a * b, [F.col(f"x{n + 1}") for n in range(len(vectors))]).alias("y"))


def dot(*vectors: Column) -> Column:
    """Sum over components of the product of vectors."""
    product = reduce(lambda a, b: F.zip_with(a, b, lambda x, y: x * y), vectors)
    return F.aggregate(product, F.lit(0.0), lambda s, x: s + x)


def with_rows(cells: DataFrame, factors: dict[str, DataFrame]) -> DataFrame:
    """cells with the factor row of each mode as column u_<mode>; Spark picks broadcast or shuffle by size."""
    for mode, factor in factors.items():
        cells = cells.join(factor.select(F.col("idx").alias(mode), F.col("vec").alias(f"u_{mode}")), mode)
    return cells


def reconstruct(coords: DataFrame, factors: dict[str, DataFrame], name: str = "x_hat") -> DataFrame:
    """Low-rank value at the given coordinates."""
    joined = with_rows(coords, factors)
    return joined.select(*coords.columns, dot(*[F.col(f"u_{m}") for m in factors]).alias(name))


def grid(spark, sizes: dict[str, int]) -> DataFrame:
    """All coordinates, from one range; mode names by size, the last varying fastest."""
    total = 1
    for s in sizes.values():
        total *= s
    out, stride = [], total
    for m, s in sizes.items():
        stride //= s
        out.append(F.pmod(F.floor(F.col("id") / stride), F.lit(s)).cast("int").alias(m))
    return spark.range(total).select(*out)


def missing(full: DataFrame, cells: DataFrame, on: list[str]) -> DataFrame:
    return full.join(cells.select(*on), on, "left_anti")


def norm(df: DataFrame, kind: str = "frobenius", column: str = "y") -> DataFrame:
    y = F.col(column)
    value = {"frobenius": F.sqrt(F.sum(y * y)), "l1": F.sum(F.abs(y)), "max": F.max(F.abs(y))}[kind]
    return df.agg(value.alias("norm"))
