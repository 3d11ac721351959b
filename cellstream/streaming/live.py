"""The online method on a live stream: windows of event time become slices, each processed once.

A window leaves the watermarked aggregate when it closes. foreachBatch takes closed windows in order of their steps, a
bounded number at a time, fills steps without events, feeds them to the stream, writes outputs in folders by step and then the
snapshot, which is the commit point: after a crash, steps up to the snapshot's are skipped and later ones replace their
folders. All files go through Spark, to a folder that driver and executors share.
"""

from __future__ import annotations

import pickle

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import HyperParams, TensorSpec
from .fold import Stream

#: Slices that are brought to the driver at once.
SLICES = 64


def open_stream(spark, path: str, schema, per_trigger: int = 1) -> DataFrame:
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", per_trigger).parquet(path)


def open_rate(spark, rows_per_second: int = 10) -> DataFrame:
    """A stream of (ts, value) from Spark's own rate source, for trials of a pipeline without data."""
    rows = spark.readStream.format("rate").option("rowsPerSecond", rows_per_second).load()
    return rows.select(F.col("timestamp").alias("ts"), F.col("value").cast("double").alias("value"))


def open_topic(spark, servers: str, topic: str, schema) -> DataFrame:
    """JSON events of a Kafka topic; Spark's connector for it must be on the class path."""
    rows = spark.readStream.format("kafka").option("kafka.bootstrap.servers", servers).option("subscribe", topic).load()
    return rows.select(F.from_json(F.col("value").cast("string"), schema).alias("e")).select("e.*")


def windowed(events: DataFrame, modes: list[str], width: str, delay: str, measure=None, dedup: str | None = None) -> DataFrame:
    """(window, modes.., y): tumbling windows of events (ts, modes.., value), late rows dropped by the watermark."""
    rows = events.withWatermark("ts", delay)
    if dedup:
        rows = rows.dropDuplicatesWithinWatermark([dedup])
    return rows.groupBy(F.window("ts", width), *modes).agg((measure if measure is not None else F.avg("value")).alias("y"))


class Sink:
    """A foreachBatch function; outputs are in folder/steps, by step, and the snapshots of the last two commits in folder/state."""

    def __init__(self, spec: TensorSpec, hp: HyperParams, folder: str, origin: str, seconds: int, starts: int = 3):
        self.spec, self.hp, self.folder, self.starts = spec, hp, folder.rstrip("/"), starts
        self.origin, self.seconds = pd.Timestamp(origin), seconds

    def _files(self, spark: SparkSession):
        path = spark._jvm.org.apache.hadoop.fs.Path(f"{self.folder}/state")
        return path, path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf())

    def commits(self, spark: SparkSession) -> list[int]:
        """Numbers of the whole snapshots, ascending."""
        path, files = self._files(spark)
        if not files.exists(path):
            return []
        whole = [x.getPath().getName() for x in files.listStatus(path) if files.exists(spark._jvm.org.apache.hadoop.fs.Path(x.getPath(), "_SUCCESS"))]
        return sorted(int(n.split("-")[1]) for n in whole)

    def load(self, spark: SparkSession) -> Stream:
        if known := self.commits(spark):
            return pickle.loads(spark.read.parquet(f"{self.folder}/state/commit-{known[-1]}").first()["stream"])
        return Stream(self.spec, self.hp, self.starts)

    def save(self, spark: SparkSession, stream: Stream) -> None:
        known = self.commits(spark)
        number = known[-1] + 1 if known else 0
        spark.createDataFrame([(bytearray(pickle.dumps(stream)),)], "stream binary").coalesce(1).write.mode("overwrite").parquet(f"{self.folder}/state/commit-{number}")
        path, files = self._files(spark)
        for old in known[:-1]:
            files.delete(spark._jvm.org.apache.hadoop.fs.Path(path, f"commit-{old}"), True)

    def outputs(self, spark: SparkSession) -> DataFrame:
        return spark.read.parquet(f"{self.folder}/steps")

    def __call__(self, batch: DataFrame, batch_id: int) -> None:
        spark, modes = batch.sparkSession, self.spec.modes
        start = F.col("window.start").cast("timestamp").cast("long") - int(self.origin.tz_localize(self.origin.tz or "UTC").timestamp())
        rows = batch.select(F.floor(start / self.seconds).cast("int").alias("t"), *modes, "y").persist()
        steps = [r["t"] for r in rows.select("t").distinct().orderBy("t").collect()]  # the slices that closed
        for k in range(0, len(steps), SLICES):
            some = steps[k : k + SLICES]
            stream, found = self.load(spark), []
            part = rows.where((F.col("t") >= some[0]) & (F.col("t") <= some[-1])).toPandas()  # SLICES slices at most
            for t, own in part.sort_values(["t", *modes]).groupby("t"):
                if stream.state is not None and t <= stream.state.t:
                    continue
                for kind, step, idx, x, o in stream.feed(int(t), own[modes].to_numpy(np.int64), own["y"].to_numpy(float)):
                    found.append(pd.DataFrame(idx, columns=modes).assign(t=step, kind=kind, x_hat=x, outlier=o))
            if found:
                schema = ", ".join(f"{m} long" for m in modes) + ", t int, kind string, x_hat double, outlier double"
                out = spark.createDataFrame(pd.concat(found), schema)
                out.repartition("t").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("t").parquet(f"{self.folder}/steps")
            self.save(spark, stream)
        rows.unpersist()


def late_rows(query) -> int:
    """How many rows a query has dropped as too late for its watermark, over the progress that Spark still holds."""
    return sum(int(o.get("numRowsDroppedByWatermark", 0)) for p in query.recentProgress for o in p["stateOperators"])


def replay(events: DataFrame, sink: Sink, width: str, delay: str, checkpoint: str, measure=None):
    """Runs the stream over what is there and stops."""
    modes = sink.spec.modes
    query = windowed(events, modes, width, delay, measure).writeStream.outputMode("append").foreachBatch(sink).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()
    query.awaitTermination()
    return query
