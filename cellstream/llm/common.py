"""Helpers that the corpus operators share."""

from __future__ import annotations

import atexit
import shutil
import tempfile
import uuid

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"

_own_dir: list[str] = []
#: Folders of staged tables that are still there, in the order of their writing.
_held: list[str] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def lower_ascii(text: Column) -> Column:
    """A-Z to a-z and nothing else; null as empty."""
    return F.translate(F.coalesce(text, F.lit("")), UPPER, LOWER)


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share; a temporary one only where a local session names none."""
    if named := spark.conf.get("spark.checkpoint.dir", None):
        return named
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    if not _own_dir:
        _own_dir.append(tempfile.mkdtemp(prefix="cellstream-"))
        atexit.register(shutil.rmtree, _own_dir[0], ignore_errors=True)
    return f"file://{_own_dir[0]}"


def staged(df: DataFrame, what: str) -> DataFrame:
    """df written to the shared folder as Parquet and read again: cuts lineage and survives lost executors.

    The exchanges of the write are let go once it is done; the files stay for later reads.
    """
    spark = df.sparkSession
    path = f"{shared_dir(spark).rstrip('/')}/{what}-{uuid.uuid4().hex}"
    cleanup = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(cleanup, None)
    if before is not None:
        spark.conf.set(cleanup, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        if before is not None:
            spark.conf.set(cleanup, before)
    out = spark.read.schema(df.schema).parquet(path)
    out._staged_path = path
    _held.append(path)
    return out


def removed(spark: SparkSession, paths: list[str]) -> None:
    for name in paths:
        path = spark._jvm.org.apache.hadoop.fs.Path(name)
        path.getFileSystem(spark._jsparkSession.sessionState().newHadoopConf()).delete(path, True)
        _held.remove(name)


def dropped(*tables: DataFrame) -> None:
    """Deletes the files of staged tables that nothing will read again."""
    for df in tables:
        removed(df.sparkSession, [df._staged_path])


def mark() -> int:
    """A place in the order of staged tables, for `release`."""
    return len(_held)


def release(since: int, keep: DataFrame) -> None:
    """Deletes all tables staged after `since` but `keep`: what they led to is written, and nothing reads them again."""
    removed(keep.sparkSession, [p for p in _held[since:] if p != keep._staged_path])


def free_name(df: DataFrame, name: str) -> str:
    """name, or one like it that df has no column of."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name = f"_{name}"
    return name


def numbered(docs: DataFrame, name: str = "row_id") -> DataFrame:
    """docs with a number for each row, different in each.

    The numbers follow the partitions of the scan, and these follow the cores that are there: another read may
    number the rows anew. So only one read may use them, or the result is `staged` first.
    """
    return docs.withColumn(name, F.monotonically_increasing_id())


def matched(rows: DataFrame, keys: DataFrame, on: list[str], heavy) -> DataFrame:
    """rows joined with keys (staged), which hold `on` once. heavy: a condition that a thousand keys meet at most.

    Heavy keys are met by a broadcast, so that none of them sends its rows to one task; the others by an exchange. The
    hashes of the heavy ones part both sides, so that no join sees all rows only to part them; a light key with the same
    hash as a heavy one goes with it on both sides.
    """
    mark = f"xxhash64({', '.join(f'`{c}`' for c in on)})"
    hashes = [str(r[0]) for r in keys.where(heavy).select(F.expr(mark)).distinct().collect()]  # a thousand at most
    out = [*rows.columns, *[c for c in keys.columns if c not in on]]
    if not hashes:
        return rows.join(keys, on).select(out)
    hot = F.expr(f"{mark} IN ({', '.join(f'{h}L' for h in hashes)})")
    return rows.where(hot).join(F.broadcast(keys.where(hot)), on).select(out).unionByName(rows.where(~hot).join(keys.where(~hot), on).select(out))


def components(edges: DataFrame, rounds: int = 40) -> DataFrame:
    """Connected components of edges (a, b): one row (node, root) for every node, root its component's smallest.

    Each round hangs every neighbour larger than a node under the node's smallest neighbour, then does the
    same with the smaller ones; both steps keep the components and shrink them towards stars. Groups never
    come together in one row: only minima are aggregated.
    """
    def hung(pairs: DataFrame, larger: bool) -> DataFrame:
        near = pairs.select("a", "b").unionByName(pairs.select(F.col("b").alias("a"), F.col("a").alias("b"))) if larger else pairs.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
        low = near.groupBy("a").agg(F.min("b").alias("low")).select("a", F.least("a", "low").alias("low"))
        kept = near.where("b > a") if larger else near
        out = kept.join(low, "a").select(F.col("b").alias("a"), F.col("low").alias("b"))
        if not larger:
            out = out.unionByName(low.select("a", F.col("low").alias("b")))
        return out.where("a <> b").distinct()

    now = staged(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), "links")
    sign = None
    for _ in range(rounds):
        before, now = now, staged(hung(hung(now, True), False), "links")
        dropped(before)
        new = now.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if tuple(new) == sign:
            break
        sign = tuple(new)
    else:
        raise RuntimeError(f"components did not settle in {rounds} rounds")
    stars = now.select(F.col("a").alias("node"), F.col("b").alias("root"))
    return stars.unionByName(stars.select(F.col("root").alias("node"), "root").distinct())


# 64-bit mixing in numpy; all arithmetic is modulo 2**64.
_M1, _M2 = np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB)
_S30, _S27, _S31 = np.uint64(30), np.uint64(27), np.uint64(31)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective scramble of uint64 values."""
    x = (x ^ (x >> _S30)) * _M1
    x = (x ^ (x >> _S27)) * _M2
    return x ^ (x >> _S31)


class WordHash(dict):
    """64-bit hashes of words (bytes), kept for words seen lately; at most `most` of them."""

    def __init__(self, most: int = 300_000):
        import xxhash

        super().__init__()
        self.most, self.digest = most, xxhash.xxh3_64_intdigest

    def __missing__(self, word: bytes) -> int:
        if len(self) >= self.most:
            self.clear()
        self[word] = h = self.digest(word)
        return h

    def of(self, words: list[bytes]) -> np.ndarray:
        return np.fromiter(map(self.__getitem__, words), np.uint64, len(words))


def windows(hashes: np.ndarray, k: int, base: int = 0x9E3779B97F4A7C15) -> np.ndarray:
    """Polynomial hashes of every k consecutive word hashes, scrambled."""
    n = len(hashes) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    total = np.zeros(n, np.uint64)
    b = np.uint64(base | 1)
    for i in range(k):
        total = total * b + hashes[i : i + n]
    return mix(total)
