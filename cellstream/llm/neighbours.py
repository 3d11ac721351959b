"""Approximate nearest neighbours by inner product, with collision-counting hashing.

Vectors are brought to one sphere: x / U with one further component that fills its norm up to 1 (U: the largest
norm), and queries scaled to norm 1, so that the largest inner product is the smallest distance. PROJECTIONS
random directions give one sorted array of values each. For a query, a window centred on its own value opens
in every array; by virtual rehashing it widens with the search radius R, half-width R, and only the newly
covered ends are counted. A vector at distance R or less falls into a window with probability 0.683, so one
that collides in at least `THRESHOLD` arrays is verified on its original components. Once it has
k vectors, the k-th's distance is the last radius that a query needs; at the largest radius all are in reach.

The query set is stated (a fixed share of rows), and runs against all rows block by block: a task gets one block
of queries and one of vectors, both of bounded size, and returns k rows a query, which are merged by rank.
Every vector is indexed. Measured recall is in the README; tests hold it against brute force.

Defined results: vectors that are null, zero, of another length than most, or hold null or non-finite components
take no part, nor do rows without vec_id. Rows that repeat a query's vec_id are not its neighbours. Ties go to the smaller
vec_id. An empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

K, EVERY = 20, 20
PROJECTIONS = 64
#: Collisions that a vector needs: 0.683 * 64 less some two standard deviations.
THRESHOLD = 37
RADII = (0.2, 0.6, 1.0, 1.24, 1.5, 2.0)
VECTORS, QUERIES = 65_536, 1024


def valid(rows: DataFrame) -> DataFrame:
    """vec_id, v (doubles) of the vectors that take part."""
    v = F.col("embedding").cast("array<double>")
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf")))
    rows = rows.select("vec_id", v.alias("v")).where("vec_id is not null and v is not null").where(finite)
    return rows.where(F.exists("v", lambda x: x != 0))


def search_block(ids, x, query_ids, q, top: float, k: int):
    """(query row, vector row, score) arrays: the k best of the block for every query, found by collisions; and how many
    vectors were verified."""
    import numpy as np

    dims, n = x.shape[1], len(ids)
    axes = np.random.default_rng(20).standard_normal((dims + 1, PROJECTIONS))
    norms2 = np.minimum((x * x).sum(1) / top**2, 1.0)
    px = np.ascontiguousarray((np.c_[x / top, np.sqrt(1 - norms2)] @ axes).T)
    order = np.argsort(px, axis=1, kind="stable").astype(np.int32)
    values = np.take_along_axis(px, order, 1)
    del px
    pq = (q / np.linalg.norm(q, axis=1, keepdims=True)) @ axes[:dims]
    scale = np.linalg.norm(q, axis=1) * top
    lows = [np.stack([np.searchsorted(values[j], pq[:, j] - r, "left") for j in range(PROJECTIONS)], 1) for r in RADII]
    highs = [np.stack([np.searchsorted(values[j], pq[:, j] + r, "right") for j in range(PROJECTIONS)], 1) for r in RADII]
    room = np.empty(PROJECTIONS * n, np.intp)  # what the windows of a query cover
    out, verified = ([], [], []), 0
    for i in range(len(q)):
        own = ids == query_ids[i]
        count, tried = np.zeros(n, np.uint8), own.copy()
        found, score = np.empty(0, np.int64), np.empty(0)
        wanted = min(k, n - int(own.sum()))
        l0 = h0 = None
        level, r = 0, RADII[0]
        l, h = lows[0][i].tolist(), highs[0][i].tolist()
        while wanted:
            # Only what a wider window newly covers is counted, at both ends of each sorted array.
            if l0 is None:
                pieces = [o[a:b] for o, a, b in zip(order, l, h)]
            else:
                pieces = [p for o, a, b, c, d in zip(order, l, l0, h0, h) for p in (o[a:b], o[c:d])]
            count += np.bincount(np.concatenate(pieces, out=room[: sum(map(len, pieces))]), minlength=n).astype(np.uint8)
            l0, h0 = l, h
            last = r == RADII[-1]
            fresh = np.flatnonzero((count >= THRESHOLD) & ~tried)
            if last and len(found) + len(fresh) < wanted:
                fresh = np.flatnonzero(~tried)
            if len(fresh):
                verified += len(fresh)
                tried[fresh] = True
                found, score = np.r_[found, fresh], np.r_[score, np.take(x, fresh, 0) @ q[i]]
                if len(found) > 4 * k:
                    low = np.partition(score, -k)[-k]
                    found, score = found[score >= low], score[score >= low]
            if last:
                break
            if len(found) >= wanted:
                # The k nearest are no farther than the k-th found: a window of that radius is the last one needed.
                need = float(np.sqrt(max(0.0, 2 - 2 * np.partition(score, -wanted)[-wanted] / scale[i])))
                if need <= r:
                    break
                r = min(need, RADII[-1])
                l = [int(np.searchsorted(values[j], pq[i, j] - r, "left")) for j in range(PROJECTIONS)]
                h = [int(np.searchsorted(values[j], pq[i, j] + r, "right")) for j in range(PROJECTIONS)]
            else:
                level = next(m for m in range(level, len(RADII)) if RADII[m] > r)
                r, l, h = RADII[level], lows[level][i].tolist(), highs[level][i].tolist()
        best = np.lexsort((ids[found], -score))[:k]
        out[0].append(np.full(len(best), i))
        out[1].append(found[best])
        out[2].append(score[best])
    return [np.concatenate(o) if o else np.empty(0) for o in out], verified


def search(rows: DataFrame, queries: DataFrame, k: int = K) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest of `rows` for each of `queries`, both (vec_id, embedding)."""
    rows, queries = valid(rows), valid(queries)
    sizes = rows.groupBy(F.size("v").alias("d")).agg(F.count(F.lit(1)).alias("n"), F.max(F.aggregate("v", F.lit(0.0), lambda a, x: a + x * x)).alias("top")).collect()  # one row a length
    spark = rows.sparkSession
    schema = "query_id long, vec_id long, score double"
    if not sizes:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    most = max(sizes, key=lambda r: (r["n"], r["d"]))
    d, n, top = most["d"], most["n"], most["top"] ** 0.5
    m = queries.where(F.size("v") == d).count()
    blocks, groups = max(1, -(-n // VECTORS)), max(1, -(-m // QUERIES))
    x = rows.where(F.size("v") == d).select("vec_id", "v", F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).alias("block"), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(groups - 1).cast("long"))).alias("group"))
    q = queries.where(F.size("v") == d).select("vec_id", "v", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))).alias("block"), F.pmod(F.xxhash64(F.lit(1), F.col("vec_id")), F.lit(groups)).alias("group"))

    def run(key, left, right):
        import numpy as np
        import pandas as pd

        if not len(left) or not len(right):
            return pd.DataFrame({"query_id": pd.Series(dtype="int64"), "vec_id": pd.Series(dtype="int64"), "score": pd.Series(dtype="float64")})
        ids, query_ids = left["vec_id"].to_numpy(), right["vec_id"].to_numpy()
        (a, b, s), _ = search_block(ids, np.stack(left["v"].to_numpy()).astype(float), query_ids, np.stack(right["v"].to_numpy()).astype(float), top, k)
        return pd.DataFrame({"query_id": query_ids[a.astype(int)], "vec_id": ids[b.astype(int)], "score": s.astype(float)})

    near = x.groupBy("block", "group").cogroup(q.groupBy("block", "group")).applyInPandas(run, schema)
    rank = F.row_number().over(Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id"))
    return near.withColumn("rank", rank).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")


def query(rows: DataFrame) -> DataFrame:
    rows = rows.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding")
    return search(rows, rows.where(F.col("vec_id") % EVERY == 0))
