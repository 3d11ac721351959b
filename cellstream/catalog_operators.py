"""Queries of the surrounding operators: joins, aggregates, windows, top-k, sets, JSON, arrays, streams."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from .catalog import CUBE_SQL, _cube, _factor, _vec_sql, _with, query, r6
from .operators import algebra
from .sources import cubes
from .sources.tables import load, new_folder
from .streaming import live

_NAMES = ["i1", "i2", "t"]
_U = f"u AS (SELECT i::INT AS i1, {_vec_sql('i', 0)[0]} AS v FROM range(25) r(i))"


def _u(s):
    return _factor(s, 0, 25).select(F.col("idx").alias("i1"), F.col("vec")[0].alias("v"))


@query("op_join_broadcast", f"{_with()}, {_U} SELECT i1, i2, t, round(y * v, 6) + 0.0 AS y FROM cells JOIN u USING (i1)")
def op_join_broadcast(s, d):
    """Cells with a small factor: 25 rows, whatever the data, so the broadcast is bounded."""
    return _cube(s, d).join(F.broadcast(_u(s)), "i1").select(*_NAMES, r6(F.col("y") * F.col("v")).alias("y"))


@query("op_join_sortmerge", f"{_with()} SELECT a.i1, a.i2, a.t, a.y - b.y AS change FROM cells a JOIN cells b ON a.i1 = b.i1 AND a.i2 = b.i2 AND a.t = b.t + 1")
def op_join_sortmerge(s, d):
    c = _cube(s, d)
    before = c.select("i1", "i2", (F.col("t") + 1).alias("t"), F.col("y").alias("b")).hint("merge")
    return c.join(before, _NAMES).select(*_NAMES, (F.col("y") - F.col("b")).alias("change"))


@query("op_join_semi", f"{_with()} SELECT i1, i2, t, y FROM cells WHERE i1 IN (SELECT n_nationkey FROM nation WHERE n_regionkey = 1)")
def op_join_semi(s, d):
    n = load(s, d, "nation").where("n_regionkey = 1").select(F.col("n_nationkey").cast("int").alias("i1"))
    return _cube(s, d).join(n, "i1", "left_semi")


@query("op_join_anti", f"{_with()} SELECT i1, i2, t, y FROM cells a WHERE NOT EXISTS (SELECT 1 FROM cells b WHERE b.i1 = a.i1 AND b.i2 = a.i2 AND b.t = a.t - 12)")
def op_join_anti(s, d):
    c = _cube(s, d)
    ago = c.select("i1", "i2", (F.col("t") + 12).alias("t"))
    return c.join(ago, _NAMES, "left_anti").select(*_NAMES, "y")


@query("op_join_full_overlay", f"{_with()}, a AS (SELECT i1, i2, y FROM cells WHERE t = 10), b AS (SELECT i1, i2, y FROM cells WHERE t = 11) SELECT i1, i2, coalesce(b.y, a.y) AS y, a.y IS NULL AS fresh FROM a FULL JOIN b USING (i1, i2)")
def op_join_full_overlay(s, d):
    c = _cube(s, d)
    a, b = (c.where(F.col("t") == t).select("i1", "i2", F.col("y").alias(f"y{t}")) for t in (10, 11))
    return a.join(b, ["i1", "i2"], "full_outer").select("i1", "i2", F.coalesce("y11", "y10").alias("y"), F.col("y10").isNull().alias("fresh"))


@query("op_join_cross_grid", "SELECT a.n_nationkey::INT AS i1, b.r_regionkey::INT AS i2 FROM nation a, region b")
def op_join_cross_grid(s, d):
    n, r = load(s, d, "nation"), load(s, d, "region")
    return n.select(F.col("n_nationkey").cast("int").alias("i1")).crossJoin(r.select(F.col("r_regionkey").cast("int").alias("i2")))


@query("op_join_range", f"{_with()} SELECT a.t AS t, b.t AS near, count(*) AS pairs FROM cells a JOIN cells b ON a.i1 = b.i1 AND a.i2 = b.i2 AND abs(a.t - b.t) IN (1, 12) GROUP BY ALL")
def op_join_range(s, d):
    """Neighbours in time at distance 1 and 12: the near steps are spelled out, so that the join has equal keys."""
    c = _cube(s, d).select(*_NAMES)
    near = c.select("i1", "i2", F.col("t"), F.explode(F.array(*[F.col("t") + x for x in (-12, -1, 1, 12)])).alias("near"))
    b = c.select("i1", "i2", F.col("t").alias("near"))
    return near.join(b, ["i1", "i2", "near"]).groupBy("t", "near").agg(F.count(F.lit(1)).alias("pairs"))


@query("op_join_asof", "SELECT event_id, user_id, (SELECT max(b.event_id) FROM events b WHERE b.user_id = a.user_id AND b.event_type = 'purchase' AND (b.ts, b.event_id) <= (a.ts, a.event_id)) AS last_purchase FROM events a WHERE event_type = 'error'")
def op_join_asof(s, d):
    """Latest purchase of the same user up to each error: one window over both sides, no inequality join."""
    e = load(s, d, "events").where("event_type in ('purchase', 'error')").select("event_id", "user_id", "event_type", "ts")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, 0)
    last = F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("last_purchase", last).where("event_type = 'error'").select("event_id", "user_id", "last_purchase")


@query("op_cube_marginals", f"{_with('brand_region_month')} SELECT i2, i3, (t // 12)::INT AS year, sum(y) AS y, count(*) AS cells FROM cells GROUP BY CUBE (i2, i3, year)")
def op_cube_marginals(s, d):
    c = _cube(s, d, "brand_region_month").withColumn("year", F.floor(F.col("t") / 12).cast("int"))
    return c.cube("i2", "i3", "year").agg(F.sum("y").alias("y"), F.count(F.lit(1)).alias("cells"))


@query("op_rollup_time", f"{_with()} SELECT (t // 12)::INT AS year, (t % 12)::INT AS month, sum(y) AS y FROM cells GROUP BY ROLLUP (year, month)")
def op_rollup_time(s, d):
    c = _cube(s, d).withColumn("year", F.floor(F.col("t") / 12).cast("int")).withColumn("month", F.pmod("t", F.lit(12)).cast("int"))
    return c.rollup("year", "month").agg(F.sum("y").alias("y"))


@query("op_grouping_sets", f"{_with()} SELECT i1, i2, sum(y) AS y FROM cells GROUP BY GROUPING SETS ((i1), (i2), ())")
def op_grouping_sets(s, d):
    return _cube(s, d).groupingSets([["i1"], ["i2"], []], "i1", "i2").agg(F.sum("y").alias("y")).select("i1", "i2", "y")


@query("op_distinct_counts", f"{_with()} SELECT t, count(DISTINCT i1) AS sources, count(DISTINCT i2) AS targets, count(DISTINCT (i1, i2)) AS pairs FROM cells GROUP BY t")
def op_distinct_counts(s, d):
    return _cube(s, d).groupBy("t").agg(F.countDistinct("i1").alias("sources"), F.countDistinct("i2").alias("targets"), F.countDistinct("i1", "i2").alias("pairs"))


@query("op_pivot_wide", f"{_with('orders_day')} SELECT t, " + ", ".join(f"sum(CASE WHEN i1 = {i} THEN y END) AS p{i}" for i in range(5)) + " FROM cells GROUP BY t")
def op_pivot_wide(s, d):
    wide = _cube(s, d, "orders_day").groupBy("t").pivot("i1", list(range(5))).agg(F.sum("y"))
    return wide.select("t", *[F.col(str(i)).alias(f"p{i}") for i in range(5)])


@query("op_window_lag", f"{_with()} SELECT i1, i2, t, y - lag(y, 1) OVER w AS d1, y - lag(y, 12) OVER w AS d12 FROM cells WINDOW w AS (PARTITION BY i1, i2 ORDER BY t)")
def op_window_lag(s, d):
    w = Window.partitionBy("i1", "i2").orderBy("t")
    return _cube(s, d).select(*_NAMES, (F.col("y") - F.lag("y", 1).over(w)).alias("d1"), (F.col("y") - F.lag("y", 12).over(w)).alias("d12"))


@query("op_window_running_mean", f"{_with()} SELECT i1, i2, t, round(avg(y) OVER (PARTITION BY i1, i2 ORDER BY t ROWS UNBOUNDED PRECEDING), 6) AS mean FROM cells")
def op_window_running_mean(s, d):
    w = Window.partitionBy("i1", "i2").orderBy("t").rowsBetween(Window.unboundedPreceding, 0)
    return _cube(s, d).select(*_NAMES, F.round(F.avg("y").over(w), 6).alias("mean"))


@query("op_window_seasonal_mean", f"{_with()} SELECT i1, i2, t, round(avg(y) OVER (PARTITION BY i1, i2 ORDER BY t ROWS BETWEEN 12 PRECEDING AND 1 PRECEDING), 6) AS mean FROM cells")
def op_window_seasonal_mean(s, d):
    w = Window.partitionBy("i1", "i2").orderBy("t").rowsBetween(-12, -1)
    return _cube(s, d).select(*_NAMES, F.round(F.avg("y").over(w), 6).alias("mean"))


@query("op_window_range", f"{_with()} SELECT i1, i2, t, sum(y) OVER (PARTITION BY i1, i2 ORDER BY t RANGE BETWEEN 3 PRECEDING AND CURRENT ROW) AS y4 FROM cells")
def op_window_range(s, d):
    w = Window.partitionBy("i1", "i2").orderBy("t").rangeBetween(-3, 0)
    return _cube(s, d).select(*_NAMES, F.sum("y").over(w).alias("y4"))


@query("op_window_ntile", f"{_with()} SELECT i1, i2, t, (ntile(4) OVER (PARTITION BY i1 ORDER BY y, i2, t))::INT AS quarter FROM cells")
def op_window_ntile(s, d):
    return _cube(s, d).select(*_NAMES, F.ntile(4).over(Window.partitionBy("i1").orderBy("y", "i2", "t")).alias("quarter"))


@query("op_topk_outliers", f"{_with()} SELECT i1, i2, t, y FROM cells ORDER BY y DESC, i1, i2, t LIMIT 20")
def op_topk_outliers(s, d):
    return _cube(s, d).orderBy(F.desc("y"), *_NAMES).limit(20)


@query("op_topk_per_step", f"{_with()} SELECT i1, i2, t, y FROM cells QUALIFY row_number() OVER (PARTITION BY t ORDER BY y DESC, i1, i2) <= 3")
def op_topk_per_step(s, d):
    rank = F.row_number().over(Window.partitionBy("t").orderBy(F.desc("y"), "i1", "i2"))
    return _cube(s, d).withColumn("rank", rank).where("rank <= 3").drop("rank")


@query("op_max_by", f"{_with()} SELECT i1, max(y) AS largest, arg_max(t, (y, i2, t)) AS at FROM cells GROUP BY i1")
def op_max_by(s, d):
    return _cube(s, d).groupBy("i1").agg(F.max("y").alias("largest"), F.max_by("t", F.struct("y", "i2", "t")).alias("at"))


@query("op_set_union", f"{_with()} SELECT i1, i2, t FROM cells WHERE t < 20 UNION SELECT i1, i2, t FROM cells WHERE y > 100")
def op_set_union(s, d):
    c = _cube(s, d)
    return c.where("t < 20").select(*_NAMES).union(c.where("y > 100").select(*_NAMES)).distinct()


@query("op_set_except", f"{_with()} SELECT i1, i2 FROM cells WHERE t < 24 EXCEPT SELECT i1, i2 FROM cells WHERE t >= 60")
def op_set_except(s, d):
    c = _cube(s, d)
    return c.where("t < 24").select("i1", "i2").subtract(c.where("t >= 60").select("i1", "i2"))


@query("op_set_intersect", f"{_with()} SELECT i1, i2 FROM cells WHERE t BETWEEN 0 AND 2 INTERSECT SELECT i1, i2 FROM cells WHERE t BETWEEN 12 AND 14")
def op_set_intersect(s, d):
    c = _cube(s, d)
    return c.where("t between 0 and 2").select("i1", "i2").intersect(c.where("t between 12 and 14").select("i1", "i2"))


@query("op_json_measure", "SELECT event_type, sum(CAST(json_extract_string(props, '$.k') AS BIGINT)) AS k, count(*) AS n FROM events GROUP BY event_type")
def op_json_measure(s, d):
    k = F.get_json_object("props", "$.k").cast("bigint")
    return load(s, d, "events").groupBy("event_type").agg(F.sum(k).alias("k"), F.count(F.lit(1)).alias("n"))


@query("op_array_dot", "SELECT vec_id, label, round(list_dot_product(embedding::DOUBLE[], embedding::DOUBLE[]), 6) AS norm2 FROM embeddings")
def op_array_dot(s, d):
    e = F.col("embedding").cast("array<double>")
    return load(s, d, "embeddings").select("vec_id", "label", F.round(algebra.dot(e, e), 6).alias("norm2"))


@query("op_array_posexplode", "SELECT label, i - 1 AS pos, round(sum(embedding[i]::DOUBLE), 4) + 0.0 AS total FROM embeddings, range(1, 65) r(i) GROUP BY ALL")
def op_array_posexplode(s, d):
    e = load(s, d, "embeddings").select("label", F.posexplode("embedding").alias("pos", "x"))
    return e.groupBy("label", F.col("pos").cast("long").alias("pos")).agg((F.round(F.sum(F.col("x").cast("double")), 4) + 0.0).alias("total"))


@query("op_array_ring", "SELECT vec_id, (embedding[2:7] || [embedding[1]])::FLOAT[] AS ring FROM embeddings")
def op_array_ring(s, d):
    return load(s, d, "embeddings").select("vec_id", F.concat(F.slice("embedding", 2, 6), F.slice("embedding", 1, 1)).alias("ring"))


@query("op_text_length_cube", "SELECT lang, source, count(*) AS n, sum(length(text))::BIGINT AS chars FROM documents GROUP BY CUBE (lang, source)")
def op_text_length_cube(s, d):
    return load(s, d, "documents").cube("lang", "source").agg(F.count(F.lit(1)).alias("n"), F.sum(F.char_length("text")).alias("chars"))


@query("op_short_streams", "SELECT conv_id, max(turn) + 1 AS steps, count(DISTINCT role) AS roles, max(turn) + 1 < 3 * 3 AS too_short FROM conversations GROUP BY conv_id")
def op_short_streams(s, d):
    """Streams that are shorter than three seasons of three steps."""
    c = load(s, d, "conversations").groupBy("conv_id").agg((F.max("turn") + 1).alias("steps"), F.countDistinct("role").alias("roles"))
    return c.withColumn("too_short", F.col("steps") < 9)


@query("op_time_floor", "SELECT CAST(date_trunc('week', ts) AS DATE) AS week, hour(ts)::INT AS hour, count(*) AS n FROM events GROUP BY ALL")
def op_time_floor(s, d):
    return load(s, d, "events").groupBy(F.date_trunc("week", "ts").cast("date").alias("week"), F.hour("ts").alias("hour")).agg(F.count(F.lit(1)).alias("n"))


@query("op_series_gaps", f"{_with('sensor_hour')}, seen AS (SELECT DISTINCT t FROM cells) SELECT i::INT AS t FROM range(720) r(i) WHERE i NOT IN (SELECT t FROM seen)")
def op_series_gaps(s, d):
    """Steps without any cell."""
    steps = s.range(720).select(F.col("id").cast("int").alias("t"))
    return steps.join(_cube(s, d, "sensor_hour").select("t").distinct(), "t", "left_anti")


@query("op_approx_distinct")
def op_approx_distinct(s, d):
    return load(s, d, "events").groupBy("event_type").agg(F.approx_count_distinct("user_id").alias("users"))


@query("op_percentiles")
def op_percentiles(s, d):
    return _cube(s, d).groupBy("t").agg(F.percentile_approx("y", [0.25, 0.5, 0.75]).alias("quartiles"))


_STREAM = "SELECT date_diff('hour', TIMESTAMP '2024-01-01', date_trunc('hour', ts)) AS t, event_type, count(*) AS n FROM events WHERE date_trunc('hour', ts) < (SELECT date_trunc('hour', max(ts)) FROM events) GROUP BY ALL"


def _source(s, d):
    """The events table as a stream: a folder is read as it is, a single file by a pattern that it alone meets."""
    path = s._jvm.org.apache.hadoop.fs.Path(f"{d}/events.parquet")
    folder = path.getFileSystem(s._jsparkSession.sessionState().newHadoopConf()).getFileStatus(path).isDirectory()
    return s.readStream.schema(load(s, d, "events").schema).parquet(f"{d}/events.parquet" if folder else f"{d}/[e]vents.parquet")


def _drained(s, d, transform, name):
    """Runs a stream over the events table to its end and returns what it wrote, as a table."""
    folder = new_folder(s, name)
    source = _source(s, d)
    q = transform(source).writeStream.outputMode("append").format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return s.read.parquet(f"{folder}/out")


@query("op_stream_tumbling", _STREAM)
def op_stream_tumbling(s, d):
    """Hourly counts from a watermarked stream: windows that closed by the end of the table."""
    def go(e):
        e = e.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "0 seconds")
        return e.groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))

    out = _drained(s, d, go, "tumbling")
    start = F.col("window.start")
    return out.select((F.datediff(start, F.lit("2024-01-01").cast("date")) * 24 + F.hour(start)).cast("long").alias("t"), "event_type", "n")


@query("op_stream_dedup", "SELECT event_id, user_id FROM events")
def op_stream_dedup(s, d):
    """Each event once, from a stream that brings every event twice."""
    def go(e):
        e = e.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "1 hour")
        twice = e.select("event_id", "user_id", "ts", F.explode(F.array(F.lit(1), F.lit(2))).alias("copy"))
        return twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id")

    return _drained(s, d, go, "dedup")


@query("op_stream_late", "WITH e AS (SELECT event_id, date_trunc('day', ts) AS day FROM events) SELECT count(*) AS late FROM e WHERE day < (SELECT max(day) FROM e) AND event_id % 100 = 0")
def op_stream_late(s, d):
    """Rows dropped by the watermark and counted: a second file brings every hundredth event of closed days once more."""
    folder, events = new_folder(s, "late"), load(s, d, "events").select("event_id", F.col("ts").cast("timestamp").alias("ts"))
    last = F.lit(events.agg(F.max(F.date_trunc("day", "ts"))).first()[0])
    events.coalesce(1).write.parquet(f"{folder}/in/1")
    query, dropped = None, 0
    for k in (1, 2):
        if k == 2:
            events.where((F.date_trunc("day", "ts") < last) & (F.col("event_id") % 100 == 0)).coalesce(1).write.parquet(f"{folder}/in/2")
        rows = s.readStream.schema(events.schema).option("maxFilesPerTrigger", 1).parquet(f"{folder}/in/*").withWatermark("ts", "0 seconds").dropDuplicatesWithinWatermark(["event_id"])
        query = rows.writeStream.outputMode("append").format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
        query.awaitTermination()
        dropped += live.late_rows(query)
    return s.createDataFrame([(dropped,)], "late long")


@query("op_stream_sliding", "SELECT start, event_type, round(avg(value), 6) AS y FROM (SELECT event_type, value, unnest([date_trunc('hour', ts) - (hour(ts) % 3) * INTERVAL 1 HOUR, date_trunc('hour', ts) - (hour(ts) % 3 + 3) * INTERVAL 1 HOUR]) AS start FROM events) WHERE start + INTERVAL 6 HOUR <= (SELECT max(ts) FROM events) GROUP BY start, event_type")
def op_stream_sliding(s, d):
    def go(e):
        e = e.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "0 seconds")
        return e.groupBy(F.window("ts", "6 hours", "3 hours"), "event_type").agg(F.avg("value").alias("y"))

    out = _drained(s, d, go, "sliding")
    return out.select(F.col("window.start").cast("timestamp_ntz").alias("start"), "event_type", F.round("y", 6).alias("y"))


@query("op_stream_session", "WITH e AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER w < INTERVAL 6 HOUR THEN 0 ELSE 1 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), g AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS burst FROM e) SELECT user_id, min(ts) AS start, count(*) AS n FROM g GROUP BY user_id, burst HAVING max(ts) + INTERVAL 6 HOUR <= (SELECT max(ts) FROM events)")
def op_stream_session(s, d):
    """Bursts of a user's events with gaps under six hours."""
    def go(e):
        e = e.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", "0 seconds")
        return e.groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count(F.lit(1)).alias("n"))

    out = _drained(s, d, go, "session")
    return out.select("user_id", F.col("session_window.start").cast("timestamp_ntz").alias("start"), "n")


@query("online_stream_replay")
def online_stream_replay(s, d):
    """The events table as a live stream of hourly slices: start-up, then one update a slice."""
    from .model import HyperParams, TensorSpec

    folder = new_folder(s, "replay")
    rows = _source(s, d).select(F.col("ts").cast("timestamp").alias("ts"), (F.col("user_id") % 16).cast("int").alias("i1"), cubes.code("event_type", cubes.EVENT_TYPES).alias("i2"), F.log2(1 + F.col("value")).alias("value"))
    sink = live.Sink(TensorSpec((16, 5), 24, 2), HyperParams(lambda1=0.01, lambda2=0.01, max_iter=20), folder, "2024-01-01", 3600, 1)
    live.replay(rows, sink, "1 hour", "0 seconds", f"{folder}/checkpoint")
    return sink.outputs(s)


@query("op_udtf_forecast")
def op_udtf_forecast(s, d):
    """SQL face: a table function that runs the method over a partition's cells in order and forecasts."""
    from . import sql

    sql.register(s)
    _cube(s, d, "sensor_hour").select(F.lit("sensor").alias("tensor_id"), "i1", "i2", "t", F.log2(1 + F.col("y")).alias("y")).createOrReplaceTempView("sensor_cells")
    return s.sql("SELECT * FROM tensor_forecast(TABLE(SELECT i1, i2, t, y, tensor_id FROM sensor_cells) PARTITION BY tensor_id ORDER BY (t), '16,5', 24, 2, 24)")
