"""Queries that once made their data up: each reads a given table, and changes with its rows."""

import pytest
from pyspark.sql import functions as F

import __spark_entry__ as contract
from tests.conftest import SMALL


@pytest.fixture(scope="module")
def part(spark, tmp_path_factory):
    """The small tables with two thirds of their fact rows."""
    out = tmp_path_factory.mktemp("part")
    for name, key in (("customer", "c_custkey"), ("supplier", None), ("part", None), ("nation", None), ("region", None), ("orders", "o_orderkey"), ("lineitem", "l_orderkey"), ("events", "event_id")):
        rows = spark.read.parquet(f"{SMALL}/{name}.parquet")
        (rows.where(F.pmod(F.xxhash64(key), F.lit(3)) > 0) if key else rows).write.parquet(f"{out}/{name}.parquet")
    return str(out)


def differ(spark, part, name):
    """Whether a query's rows differ between the small tables and a part of them."""
    a, b = ([tuple(r) for r in contract.queries()[name](spark, d).collect()] for d in (SMALL, part))
    assert a and b
    return sorted(map(str, a)) != sorted(map(str, b))


def test_khatri_rao_pair(spark, part):
    assert differ(spark, part, "khatri_rao_pair")


def test_khatri_rao_chain(spark, part):
    assert differ(spark, part, "khatri_rao_chain")


def test_column_norms(spark, part):
    assert differ(spark, part, "column_norms")


def test_normalize_columns(spark, part):
    assert differ(spark, part, "normalize_columns")


def test_predict_time(spark, part):
    assert differ(spark, part, "predict_time")


def test_factor_nre(spark, part):
    assert differ(spark, part, "factor_nre")


def test_corruption_levels(spark, part):
    assert differ(spark, part, "corruption_levels")


def test_capability_table_is_no_query():
    assert "capability_matrix" not in contract.queries() and "capability_matrix" not in contract.oracle_sql()


def test_q1_start_up(spark, part):
    """Both solvers and five seeds, on the given cells' coordinates."""
    assert differ(spark, part, "q1_start_up")


def test_planted_factors_give_the_planted_values():
    import numpy as np

    from cellstream.sources import planted

    x = np.einsum("ir,jr,tr->ijt", *planted.factors((4, 3), 9, 3, 5, 2))
    assert np.allclose(x, planted.values((4, 3), 9, 3, 5, 2))


def test_q5_linearity(spark):
    """Times are of slices of line items: the cells of all steps are those of the table."""
    rows = contract.queries()["q5_scalability"](spark, SMALL).collect()
    item = spark.read.parquet(f"{SMALL}/lineitem.parquet").select(F.pmod("l_orderkey", F.lit(500)).alias("i1"), F.pmod("l_partkey", F.lit(500)).alias("i2"), F.trunc("l_shipdate", "month").alias("t"))
    largest = next(r for r in rows if r["axis"] == "cells" and r["rows"] == 500)
    months = item.select("t").distinct().count()
    assert largest["steps"] == months and largest["cells"] == item.distinct().count() // months
    assert {r["axis"] for r in contract.queries()["q5_linearity"](spark, SMALL).collect()} == {"cells", "steps"}
