"""Tensor streams in coordinate form, made from the given tables: (i1..iK, t, y), a missing cell has no row.

Dimension tables are joined before the one exchange by coordinates; AQE broadcasts them while they are small.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from .tables import load, staged

EVENT_TYPES = ["click", "error", "purchase", "signup", "view"]
PRIORITIES = ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]
SEGMENTS = ["AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY"]
EVENTS_FROM, ORDERS_FROM = "2024-01-01", "1995-01-01"


def code(column: Column | str, labels: list[str]) -> Column:
    """Index of a label in a fixed dictionary, from 0; null for others."""
    return (F.array_position(F.array(*map(F.lit, labels)), F.col(column) if isinstance(column, str) else column) - 1).cast("int")


def day(column: str, start: str) -> Column:
    return F.datediff(F.to_date(column), F.lit(start).cast("date"))


def cents(column: str) -> Column:
    """Hundredths as integers, so that sums do not depend on their order."""
    return F.round(F.col(column) * 100).cast("bigint")


def event_cells(spark: SparkSession, d: str, per_day: int) -> DataFrame:
    minutes = 1440 // per_day
    t = (day("ts", EVENTS_FROM) * per_day + F.floor((F.hour("ts") * 60 + F.minute("ts")) / minutes)).cast("int")
    return load(spark, d, "events").select((F.col("user_id") % 16).cast("int").alias("i1"), code("event_type", EVENT_TYPES).alias("i2"), t.alias("t"), "value", "user_id", "ts", "event_id", "event_type")


def sensor(spark: SparkSession, d: str, per_day: int) -> DataFrame:
    """Mean event value of user group x event type x time bucket."""
    cells = event_cells(spark, d, per_day).groupBy("i1", "i2", "t").agg(F.sum(cents("value")).alias("s"), F.count(F.lit(1)).alias("n"))
    return cells.select("i1", "i2", "t", F.round(F.col("s") / (F.col("n") * 100), 6).alias("y"))


def transition(spark: SparkSession, d: str, per_user: bool) -> DataFrame:
    """Hourly number of steps from an event type to the next one, over all events or each user's.

    The chain over all events is cut by minutes for the order, each minute's last event being followed by the next
    minute's first, so that no task sorts the whole table.
    """
    e = event_cells(spark, d, 24).withColumn("part", day("ts", EVENTS_FROM) * 1440 + F.hour("ts") * 60 + F.minute("ts"))
    if per_user:
        follow = F.lead("i2").over(Window.partitionBy("user_id").orderBy("ts", "event_id"))
        pairs = e.select("i2", "t", follow.alias("j")).where("j is not null")
    else:
        inside = e.select("i2", "t", "part", F.lead("i2").over(Window.partitionBy("part").orderBy("ts", "event_id")).alias("j"))
        first = e.groupBy("part").agg(F.min_by("i2", F.struct("ts", "event_id")).alias("first"))
        after = first.select("part", F.lead("first").over(Window.orderBy("part")).alias("next"))  # a row a minute of the calendar
        pairs = inside.join(after, "part").select("i2", "t", F.coalesce("j", "next").alias("j")).where("j is not null")
    return pairs.groupBy(F.col("i2").alias("i1"), F.col("j").alias("i2"), "t").agg(F.count(F.lit(1)).cast("double").alias("y"))


def shipped(spark: SparkSession, d: str) -> DataFrame:
    """Line items with the nations of supplier and customer; brand stays a key."""
    items = load(spark, d, "lineitem").select("l_orderkey", "l_partkey", "l_suppkey", "l_quantity", "l_shipdate")
    orders = load(spark, d, "orders").select("o_orderkey", "o_custkey")
    customers = load(spark, d, "customer").select("c_custkey", F.col("c_nationkey").cast("int").alias("c_nation"))
    suppliers = load(spark, d, "supplier").select("s_suppkey", F.col("s_nationkey").cast("int").alias("s_nation"))
    buyers = orders.join(customers, F.col("o_custkey") == F.col("c_custkey"))
    return items.join(suppliers, F.col("l_suppkey") == F.col("s_suppkey")).join(buyers, F.col("l_orderkey") == F.col("o_orderkey"))


def month(column: str) -> Column:
    return ((F.year(column) - 1995) * 12 + F.month(column) - 1).cast("int")


def flow(spark: SparkSession, d: str, grain: str, rows: DataFrame | None = None) -> DataFrame:
    """Supplier nation x customer nation x week, month or day; quantity, for days log2(1 + count). rows: a `shipped` made before."""
    t = {"week": F.floor(day("l_shipdate", ORDERS_FROM) / 7).cast("int"), "month": month("l_shipdate"), "day": day("l_shipdate", ORDERS_FROM)}[grain]
    y = F.round(F.log2(F.count(F.lit(1)) + F.lit(1.0)), 6) if grain == "day" else F.sum(cents("l_quantity")) / 100
    return (rows or shipped(spark, d)).groupBy(F.col("s_nation").alias("i1"), F.col("c_nation").alias("i2"), t.alias("t")).agg(y.alias("y"))


def orders_day(spark: SparkSession, d: str) -> DataFrame:
    orders = load(spark, d, "orders").select("o_custkey", "o_orderpriority", "o_orderdate")
    customers = load(spark, d, "customer").select("c_custkey", "c_mktsegment")
    joined = orders.join(customers, F.col("o_custkey") == F.col("c_custkey"))
    return joined.groupBy(code("o_orderpriority", PRIORITIES).alias("i1"), code("c_mktsegment", SEGMENTS).alias("i2"), day("o_orderdate", ORDERS_FROM).alias("t")).agg(F.count(F.lit(1)).cast("double").alias("y"))


def brand_month(spark: SparkSession, d: str, rows: DataFrame | None = None) -> DataFrame:
    """Order 4: brand x supplier region x customer region x month, quantity."""
    nation = load(spark, d, "nation").select(F.col("n_nationkey").cast("int").alias("n"), F.col("n_regionkey").cast("int").alias("r"))
    part = load(spark, d, "part").select("p_partkey", "p_brand")
    brands = part.select("p_brand").distinct().select("p_brand", (F.dense_rank().over(Window.orderBy("p_brand")) - 1).cast("int").alias("i1"))  # a row a brand
    rows = (rows or shipped(spark, d)).join(part, F.col("l_partkey") == F.col("p_partkey")).join(brands, "p_brand")
    rows = rows.join(nation.select(F.col("n").alias("s_nation"), F.col("r").alias("i2")), "s_nation").join(nation.select(F.col("n").alias("c_nation"), F.col("r").alias("i3")), "c_nation")
    return rows.groupBy("i1", "i2", "i3", month("l_shipdate").alias("t")).agg((F.sum(cents("l_quantity")) / 100).alias("y"))


def numbered(labels: DataFrame) -> DataFrame:
    """(label, idx): a dense number from 0 in the order of the labels, for a dictionary of any size.

    Labels are dealt by ranges; a task numbers its range, and the ranges' counts, one row each, are summed up before.
    """
    ranges = staged(labels.select("label").repartitionByRange("label").withColumn("part", F.spark_partition_id()), "labels")
    sizes = ranges.groupBy("part").agg(F.count(F.lit(1)).alias("n"))  # a row a range
    before = F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    own = F.row_number().over(Window.partitionBy("part").orderBy("label"))
    return ranges.withColumn("own", own).join(F.broadcast(sizes.select("part", before.alias("before"))), "part").select("label", (F.col("own") + F.col("before") - 1).cast("int").alias("idx"))


@dataclass(frozen=True)
class Cube:
    name: str
    build: object
    sizes: tuple[int, ...]
    steps: int
    period: int


CUBES = {
    c.name: c
    for c in (
        Cube("sensor_10min", lambda s, d: sensor(s, d, 144), (16, 5), 4320, 144),
        Cube("sensor_hour", lambda s, d: sensor(s, d, 24), (16, 5), 720, 24),
        Cube("flow_week", lambda s, d: flow(s, d, "week"), (25, 25), 357, 52),
        Cube("flow_month", lambda s, d: flow(s, d, "month"), (25, 25), 83, 12),
        Cube("transition_hour", lambda s, d: transition(s, d, False), (5, 5), 720, 24),
        Cube("transition_user_hour", lambda s, d: transition(s, d, True), (5, 5), 720, 24),
        Cube("flow_day", lambda s, d: flow(s, d, "day"), (25, 25), 2499, 7),
        Cube("orders_day", orders_day, (5, 5), 2405, 7),
        Cube("brand_region_month", brand_month, (25, 5, 5), 83, 12),
    )
}


def cells(spark: SparkSession, d: str, name: str) -> DataFrame:
    return CUBES[name].build(spark, d)
