"""MinHash near-dedup by tensored banding, with links confirmed on full shingle sets.

A document's set holds its distinct runs of `width` words (fewer words: the whole sequence as one). Sets of
64-bit hashes stand for the sets of shingles.

1. Documents with equal sets form one class; its smallest doc_id represents it (partial minima before the
   exchange, so a group of copies of any size costs one row per task).
2. Two small collections of HALVES half-keys, each of ROWS minhashes, are computed for a representative;
   every pair of a half-key of the first and one of the second is a table key. That is HALVES**2 tables from
   2 * HALVES * ROWS minhashes. A pair of Jaccard similarity s meets in a table with probability
   (1 - (1 - s**ROWS)**HALVES)**2, 0.9998 at s = 0.85 and 0.9985 at s = 0.8.
3. A bucket's members are classes. In each bucket every member is paired with the bucket's smallest one, never with all others: one
   row per member. Those pairs are verified on full sets, and the verified links joined to components.
4. Buckets whose members are not yet of one component are looked at again: their members' sets are joined
   by an exact prefix filter (rarest shingles first) within the whole of such members, and each pair of
   different components is verified. This finds what the star of step 3 skips, whatever the bucket's size,
   without a product of the bucket with itself.

Defined results: null, empty and blank texts have an empty set, link with nothing and stay; rows that repeat
a doc_id are one document each but share the id's component; other columns are not read (`query`) or are
passed through (`keep_one`).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

WIDTH, HALVES, ROWS = 5, 10, 3
SHARE = (85, 100)
#: The general contract of near copies, which the pipeline stage keeps; SHARE is that of the query alone.
STAGE_SHARE = (80, 100)
#: Members of one shingle's list that one task pairs, about.
PART = 2000


def shingle_hashes(text: str | None, words: common.WordHash, width: int):
    """Sorted distinct hashes of a text's shingles."""
    import numpy as np

    w = text.encode("utf-8", "surrogatepass").lower().split() if text else []
    if not w:
        return np.empty(0, np.uint64)
    h = words.of(w)
    if len(h) < width:
        return common.windows(h, len(h), 0xD6E8FEB86659FD93)[:1]
    return np.unique(common.windows(h, width))


def digest(s) -> bytes | None:
    """128 bits that name a set; null for the empty one."""
    import hashlib

    return hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None


def profiles(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """doc_id, n_shingles, set_id (128 bits as two longs, null for an empty set) and the 2 * HALVES half-keys."""
    def run(batches):
        import numpy as np
        import pyarrow as pa

        words = common.WordHash()
        # Shingle hashes are well mixed, so an odd factor each makes 60 orders of them.
        factors = common.mix(np.arange(1, 2 * HALVES * ROWS + 1, dtype=np.uint64) * np.uint64(0x9E3779B97F4A7C15)) | np.uint64(1)
        for batch in batches:
            n, ids, halves = [], [], []
            for text in batch.column("text"):
                s = shingle_hashes(text.as_py(), words, width)
                n.append(len(s))
                ids.append(digest(s))
                if not len(s):
                    halves.append(None)
                    continue
                buffer = np.empty_like(s)
                low = np.array([np.multiply(s, f, out=buffer).min() for f in factors])
                halves.append(common.mix((low.reshape(-1, ROWS) * np.array([1, 3, 5], np.uint64)[:ROWS]).sum(1)).view(np.int64))
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids, pa.binary()), pa.array(halves, pa.list_(pa.int64()))], ["doc_id", "n_shingles", "set_id", "halves"])

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, n_shingles long, set_id binary, halves array<long>")


def sets_of(docs: DataFrame, classes: DataFrame, width: int = WIDTH) -> DataFrame:
    """cid and its full set, for each of classes (cid, set_id, rep), read from the representative's text."""
    def run(batches):
        import pyarrow as pa

        words = common.WordHash()
        for batch in batches:
            rows = [shingle_hashes(t.as_py(), words, width) for t in batch.column("text")]
            yield pa.RecordBatch.from_arrays([pa.array([digest(s) for s in rows], pa.binary()), pa.array([s.view("int64") for s in rows], pa.list_(pa.int64()))], ["set_id", "shingles"])

    texts = docs.select("doc_id", "text").join(classes.select(F.col("rep").alias("doc_id")).distinct(), "doc_id", "left_semi")
    # A doc_id that stands on several texts gives the sets of them all; only those asked for stay, once.
    sets = texts.mapInArrow(run, "set_id binary, shingles array<long>").where("set_id is not null")
    return sets.join(classes.select("set_id", "cid"), "set_id").select("cid", "shingles").dropDuplicates(["cid"])


def verified(pairs: DataFrame, sets: DataFrame, share=SHARE) -> DataFrame:
    """The pairs (a, b) whose full sets share at least share[0] / share[1] of their union."""
    both = pairs.join(sets.select(F.col("cid").alias("a"), F.col("shingles").alias("sa")), "a").join(sets.select(F.col("cid").alias("b"), F.col("shingles").alias("sb")), "b")
    shared = F.size(F.array_intersect("sa", "sb"))
    return both.where(share[1] * shared >= share[0] * (F.size("sa") + F.size("sb") - shared)).select("a", "b")


def table_keys(halves: DataFrame) -> DataFrame:
    """One row (key, cid, n) per table: a key joins one half-key of each collection."""
    keys = F.array(*[F.xxhash64(F.lit(i * HALVES + j), F.col("halves")[i], F.col("halves")[HALVES + j]) for i in range(HALVES) for j in range(HALVES)])
    return halves.select("cid", "n_shingles", F.explode(keys).alias("key"))


def prefix_pairs(members: DataFrame, sets: DataFrame, share=SHARE) -> DataFrame:
    """Pairs of members of different components that share a shingle of both prefixes: exact for the threshold.

    In the order rarest first, two sets that meet the threshold share one of the first n - ceil(n * share) + 1
    shingles of each, and so early that enough are left (positional filter). Within a shingle, a component's members
    stand one by one only against other components; a shingle of over PART members is dealt over several tasks, one
    side by salt, the other to each.
    """
    rows = sets.join(members.select("cid", "root").distinct(), "cid").select("cid", "root", F.size("shingles").alias("n"), F.explode("shingles").alias("s"))
    frequency = rows.groupBy("s").agg(F.count(F.lit(1)).alias("f"), F.min("root").alias("lo"), F.max("root").alias("hi"))
    open_ones = frequency.select("s", "f", (F.col("lo") < F.col("hi")).alias("between"))
    ordered = rows.join(open_ones, "s").groupBy("cid", "root", "n").agg(F.array_sort(F.collect_list(F.struct("f", "s", "between"))).alias("o"))
    prefix = F.slice("o", F.lit(1), (F.col("n") - F.ceil(F.col("n") * share[0] / share[1]) + 1).cast("int"))
    first = ordered.select("cid", "root", "n", F.posexplode(prefix).alias("at", "x")).where("x.between")
    salts = F.ceil(F.col("x.f") / PART)
    first = first.select("cid", "root", "n", "at", F.col("x.s").alias("s"), salts.alias("salts"))
    left = first.withColumn("salt", F.pmod(F.xxhash64("cid"), "salts"))
    right = first.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.col("salts") - 1)))
    l, r = left.alias("l"), right.alias("r")
    # What two sets can share if this is the first shingle that they share; for a later one the first has spoken.
    most = F.least(F.col("l.n") - F.col("l.at"), F.col("r.n") - F.col("r.at"))
    fits = (F.col("l.root") < F.col("r.root")) & ((share[0] + share[1]) * most >= share[0] * (F.col("l.n") + F.col("r.n")))
    return l.join(r, (F.col("l.s") == F.col("r.s")) & (F.col("l.salt") == F.col("r.salt")) & fits).select(F.col("l.cid").alias("a"), F.col("r.cid").alias("b")).distinct()


def grouped(docs: DataFrame, width: int = WIDTH, share=SHARE) -> DataFrame:
    """doc_id, n_shingles, component_id, kept: one row per row of docs."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    # Rows without an id are documents of their own; nothing can name them, so they link with nothing.
    seen = common.staged(profiles(docs, width), "profiles")
    named = seen.where("set_id is not null and doc_id is not null")
    classes = named.groupBy("set_id").agg(F.min("doc_id").alias("rep"), F.max("doc_id").alias("last"), F.count(F.lit(1)).alias("copies"), F.first("n_shingles").alias("n_shingles"), F.first("halves").alias("halves"))
    # Classes go by numbers from here on; they are staged, so each keeps its own.
    reps = common.staged(common.numbered(classes, "cid"), "classes")
    keys = table_keys(reps)
    low = keys.groupBy("key").agg(F.min("cid").alias("a"), F.max("cid").alias("z")).where("a < z").select("key", "a")
    met = common.staged(keys.join(low, "key").select("key", "a", F.col("cid").alias("b"), "n_shingles"), "met")
    stars = met.where("a <> b").groupBy("a", "b").agg(F.first("n_shingles").alias("n"))
    stars = stars.join(reps.select(F.col("cid").alias("a"), F.col("n_shingles").alias("na")), "a").where(F.least("n", "na") * share[1] >= F.greatest("n", "na") * share[0]).select("a", "b")
    stars = common.staged(stars, "stars")
    ends = met.select(F.col("b").alias("cid")).distinct()
    sets = common.staged(sets_of(docs, reps.select("cid", "set_id", "rep").join(ends, "cid", "left_semi"), width), "sets")
    links = common.staged(verified(stars, sets, share), "confirmed")
    first = common.components(links)
    rooted = met.select("key", F.col("b").alias("cid")).join(first.withColumnRenamed("node", "cid"), "cid", "left").select("key", "cid", F.coalesce("root", "cid").alias("root"))
    open_keys = rooted.groupBy("key").agg(F.min("root").alias("lo"), F.max("root").alias("hi")).where("lo < hi").select("key")
    members = common.staged(rooted.join(open_keys, "key").select("cid", "root").distinct(), "open")
    common.dropped(met, stars)
    more = verified(prefix_pairs(members, sets, share), sets, share)
    # A doc_id that stands on several texts ties their classes together: to the smallest of them, one row a class.
    several = named.groupBy("doc_id").agg(F.min(F.xxhash64("set_id")).alias("lo"), F.max(F.xxhash64("set_id")).alias("hi")).where("lo < hi").select("doc_id")
    several = common.staged(named.select("doc_id", "set_id").join(several, "doc_id").join(reps.select("set_id", "cid"), "set_id").select("doc_id", "cid"), "several")
    ties = several.join(several.groupBy("doc_id").agg(F.min("cid").alias("a")), "doc_id").where("cid <> a").select("a", F.col("cid").alias("b")).distinct()
    roots = common.staged(common.components(links.unionByName(more).unionByName(ties)), "roots")
    common.dropped(sets, links, members, several)
    # The smallest doc_id of a component, and of each class in one; classes outside keep their own.
    whole = roots.join(reps.select(F.col("cid").alias("node"), "rep"), "node")
    lowest = whole.groupBy("root").agg(F.min("rep").alias("component"))
    linked = roots.join(lowest, "root").select(F.col("node").alias("cid"), "component")
    # One row for each doc_id that is not its own component; ids of several texts agree, since these are tied.
    other = reps.select("cid", "set_id", "rep", "last", "copies").join(linked, "cid", "left").select("set_id", F.coalesce("component", "rep").alias("component"), "last", "copies").where("last <> component")
    other = common.staged(other.drop("last"), "other")
    moved = common.matched(named.select("set_id", "doc_id"), other, ["set_id"], F.col("copies") * 1000 > seen.count())
    moved = common.staged(moved.where("doc_id <> component").select("doc_id", "component").distinct(), "moved")
    common.dropped(reps, roots, other)
    out = seen.select("doc_id", "n_shingles").join(moved, "doc_id", "left")
    component = F.coalesce("component", "doc_id")
    return out.select("doc_id", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))


def keep_one(docs: DataFrame) -> DataFrame:
    """docs with one document of each group of near copies (0.8 or more), the one with the smallest doc_id."""
    gone = grouped(docs, share=STAGE_SHARE).where("not kept").select("doc_id").distinct()
    return docs.join(gone, "doc_id", "left_anti").select(docs.columns)


def oracle(width: int = WIDTH, share=SHARE) -> str:
    """The same rows in DuckDB, by joining the sets on every shingle."""
    return rf"""
WITH RECURSIVE w AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS (SELECT doc_id, CASE WHEN len(w) >= {width} THEN list_distinct(list_transform(range(1, len(w) - {width - 2}), lambda i: array_to_string(w[i:i + {width - 1}], ' '))) WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END AS s FROM w),
c AS (SELECT *, CASE WHEN len(s) > 0 THEN md5(array_to_string(list_sort(s), chr(10))) END AS id FROM s),
rep AS (SELECT id, min(doc_id) AS rep, any_value(s) AS s FROM c WHERE id IS NOT NULL GROUP BY id),
x AS (SELECT id, len(s) AS n, unnest(s) AS k FROM rep),
link AS (SELECT a.id AS a, b.id AS b FROM x a JOIN x b ON a.k = b.k AND a.id < b.id GROUP BY a.id, b.id, a.n, b.n HAVING {share[1]} * count(*) >= {share[0]} * (a.n + b.n - count(*))),
tie AS (SELECT DISTINCT a.id AS a, b.id AS b FROM c a JOIN c b ON a.doc_id = b.doc_id AND a.id < b.id),
edge AS (SELECT a, b FROM link UNION SELECT b, a FROM link UNION SELECT a, b FROM tie UNION SELECT b, a FROM tie),
reach AS (SELECT DISTINCT a, a AS b FROM edge UNION SELECT reach.a, edge.b FROM reach JOIN edge ON reach.b = edge.a),
root AS (SELECT a AS id, min(rep) AS root FROM reach JOIN rep ON reach.b = rep.id GROUP BY a),
own AS (SELECT doc_id, min(coalesce(root, rep)) AS component FROM c JOIN rep USING (id) LEFT JOIN root USING (id) GROUP BY doc_id)
SELECT doc_id, len(c.s)::BIGINT AS n_shingles, coalesce(component, doc_id) AS component_id, doc_id = coalesce(component, doc_id) AS kept FROM c LEFT JOIN own USING (doc_id)
"""
