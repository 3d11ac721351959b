"""Substring dedup: Rabin-Karp hashes of every `width`-word window, counted in Spark.

A window is repeated when its word sequence also starts anywhere else, in the same document or another. Every
word that a repeated window covers goes; overlapping windows merge into maximal intervals.

Rolling hashes of all windows are made by numpy in one pass over each text. To count them without shuffling a
row per window:

1. Each window has an anchor, the smallest hash among its runs of ANCHOR words, the last of equals. Equal
   windows have equal anchors at equal places, and neighbouring windows mostly share theirs, so there are about
   13 times fewer anchors than windows. A window whose anchor occurs at no second place is not repeated: this is
   exact, not a sample. Anchors are counted; repeated ones go back to their documents.
2. Only windows with a repeated anchor are written out, the hashes of neighbouring windows with one anchor as
   one array. Equal arrays are counted; where an anchor has one array only, all its windows are repeated.
3. Where an anchor has several arrays (passages that end at different places), the windows are counted each.

Counts are partial before every exchange, so that a passage in a third of all documents costs a row per task.
Defined results: null, empty and blank texts have no words;
a text shorter than a window keeps all; repeated rows are copies of each other and lose all their windows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

WIDTH, ANCHOR = 35, 10


def rolling(h, k: int):
    """Rabin-Karp hashes of every k consecutive word hashes, modulo 2**64, by one running sum."""
    import numpy as np

    n = len(h) - k + 1
    if n <= 0:
        return np.empty(0, np.uint64)
    base = 0x9E3779B97F4A7C15
    down = np.full(len(h), pow(base, -1, 2**64), np.uint64)
    down[0] = 1
    up = np.full(n, base, np.uint64)
    up[0] = 1
    total = np.concatenate([np.zeros(1, np.uint64), np.cumsum(h * np.cumprod(down))])
    return common.mix((total[k:] - total[:-k]) * np.cumprod(up) + np.uint64(k))


def anchors(h, width: int, anchor: int):
    """For each window, the start of its anchor: the smallest run hash, the last of equals."""
    import numpy as np

    runs = rolling(h, anchor)
    span = width - anchor + 1
    if len(runs) < span:
        return runs, np.empty(0, np.int64)
    view = np.lib.stride_tricks.sliding_window_view(runs[::-1], span)
    last = len(runs) - 1
    return runs, (last - (np.argmin(view, axis=1) + np.arange(len(view))))[::-1]


def word_list(text: str | None) -> list[bytes]:
    return text.encode("utf-8", "surrogatepass").split() if text else []


def anchor_lists(docs: DataFrame, width: int, anchor: int) -> DataFrame:
    """row_id and the distinct anchors of each document; one that occurs at two of its places comes twice."""
    def run(batches):
        import numpy as np
        import pyarrow as pa

        words = common.WordHash()
        for batch in batches:
            rows = []
            for text in batch.column("text"):
                runs, at = anchors(words.of(word_list(text.as_py())), width, anchor)
                found, times = np.unique(runs[np.unique(at)], return_counts=True)
                rows.append(np.concatenate([found, found[times > 1]]).view(np.int64))
            yield pa.RecordBatch.from_arrays([batch.column("row_id"), pa.array(rows, pa.list_(pa.int64()))], ["row_id", "anchors"])

    return docs.select("row_id", "text").mapInArrow(run, "row_id long, anchors array<long>").where("size(anchors) > 0")


def candidate_windows(docs: DataFrame, width: int, anchor: int) -> DataFrame:
    """row_id, start, anchor, hashes: a row for each place of an anchor among the document's repeated ones.

    docs: row_id, text, repeated (array of anchors). hashes are of the windows from `start` on, one by one.
    """
    def run(batches):
        import numpy as np
        import pyarrow as pa

        words = common.WordHash()
        for batch in batches:
            ids, repeated_of = batch.column("row_id").to_pylist(), batch.column("repeated")
            rows, starts, keys, sizes, hashes = [], [], [], [], []
            for i, text in enumerate(batch.column("text")):
                h = words.of(word_list(text.as_py()))
                runs, at = anchors(h, width, anchor)
                if not len(at):
                    continue
                first = np.flatnonzero(np.r_[True, at[1:] != at[:-1]])
                size = np.diff(np.r_[first, len(at)])
                key = runs[at[first]]
                keep = np.isin(key, repeated_of[i].values.to_numpy(zero_copy_only=False).view(np.uint64))
                full = rolling(h, width)
                rows.append(np.full(int(keep.sum()), ids[i], np.int64))
                starts.append(first[keep])
                keys.append(key[keep].view(np.int64))
                sizes.append(size[keep])
                hashes.append(full[np.repeat(keep, size)].view(np.int64))
            if rows:
                offsets = np.r_[0, np.cumsum(np.concatenate(sizes))].astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(offsets), pa.array(np.concatenate(hashes)))
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(rows)), pa.array(np.concatenate(starts)), pa.array(np.concatenate(keys)), lists], ["row_id", "start", "anchor", "hashes"])

    return docs.mapInArrow(run, "row_id long, start long, anchor long, hashes array<long>")


def repeated_windows(docs: DataFrame, width: int = WIDTH, anchor: int = ANCHOR) -> DataFrame:
    """Of docs (row_id, text): row_id and `runs`, an array of (start, size, offsets). The windows at start +
    offsets are repeated; null offsets mean all `size` of them. Documents without one have no row."""
    seen = common.staged(anchor_lists(docs, width, anchor), "anchors")
    places = seen.select("row_id", F.explode("anchors").alias("anchor"))
    total = seen.agg(F.coalesce(F.sum(F.size("anchors")), F.lit(0))).first()[0]
    counts = common.staged(places.groupBy("anchor").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "counts")
    wanted = common.matched(places, counts, ["anchor"], F.col("n") * 1000 > total)
    wanted = common.staged(wanted.groupBy("row_id").agg(F.collect_set("anchor").alias("repeated")), "repeated")
    found = common.staged(candidate_windows(docs.select("row_id", "text").join(wanted, "row_id"), width, anchor).withColumn("kind", F.xxhash64("hashes")), "windows")
    common.dropped(seen, counts, wanted)
    everywhere = found.count()
    kinds = found.groupBy("anchor", "kind").agg(F.count(F.lit(1)).alias("times"), F.first("hashes").alias("hashes"))
    several = found.groupBy("anchor").agg(F.min("kind").alias("lo"), F.max("kind").alias("hi"), F.count(F.lit(1)).alias("n")).where("lo <> hi")
    several = common.staged(several.select("anchor", "n"), "several")
    mixed = common.staged(common.matched(kinds, several, ["anchor"], F.col("n") * 1000 > everywhere), "mixed")
    each = mixed.select("anchor", "kind", "times", F.posexplode("hashes").alias("i", "hash"))
    windows = mixed.agg(F.coalesce(F.sum(F.size("hashes")), F.lit(0))).first()[0]
    twice = common.staged(each.groupBy("anchor", "hash").agg(F.sum("times").alias("times"), F.count(F.lit(1)).alias("n")).where("times > 1").drop("times"), "twice")
    offsets = common.matched(each, twice, ["anchor", "hash"], F.col("n") * 1000 > windows).groupBy("anchor", "kind").agg(F.collect_set("i").alias("offsets"))
    judged = mixed.select("anchor", "kind", "times").join(offsets, ["anchor", "kind"], "left").select("anchor", "kind", "times", F.coalesce("offsets", F.array().cast("array<int>")).alias("offsets"))
    judged = common.staged(judged, "judged")
    # An array that holds more than a thousandth of all rows is one of a thousand at most; these few are broadcast,
    # so that a passage in a third of all documents does not send its rows to one task.
    common_one = F.col("times") * 1000 > everywhere
    hot = judged.where(common_one).select("anchor", "kind", F.col("offsets").alias("hot"))
    runs = found.select("row_id", "start", F.size("hashes").alias("size"), "anchor", "kind").join(F.broadcast(hot), ["anchor", "kind"], "left")
    rest = runs.where("hot is null").join(judged.where(~common_one).select("anchor", "kind", "offsets"), ["anchor", "kind"], "left")
    columns = ["row_id", "start", "size", "offsets"]
    runs = runs.where("hot is not null").withColumnRenamed("hot", "offsets").select(columns).unionByName(rest.select(columns))
    runs = runs.where("offsets is null or size(offsets) > 0")
    out = common.staged(runs.groupBy("row_id").agg(F.collect_list(F.struct("start", "size", "offsets")).alias("runs")), "runs")
    common.dropped(found, several, mixed, twice, judged)
    return out


def removed(runs: list | None, width: int, n: int):
    """Which of n words are covered by repeated windows; the True stretches are the maximal removal intervals."""
    import numpy as np

    edge = np.zeros(n + 1, np.int64)
    for r in runs or ():
        at = r["start"] + (np.arange(r["size"]) if r["offsets"] is None else np.array(r["offsets"], np.int64))
        np.add.at(edge, at, 1)
        np.add.at(edge, at + width, -1)
    return np.cumsum(edge[:n]) > 0


def marked(docs: DataFrame, width: int = WIDTH, anchor: int = ANCHOR) -> tuple[DataFrame, str]:
    """docs with one more column of repeated runs (null: nothing repeated), and that column's name."""
    row, runs = common.free_name(docs, "row_id"), common.free_name(docs, "repeated_runs")
    rows = common.staged(common.numbered(docs, row), "rows")  # read three times, with one number a row
    found = repeated_windows(rows.select(F.col(row).alias("row_id"), "text"), width, anchor)
    found = found.select(F.col("row_id").alias(row), F.col("runs").alias(runs))
    return rows.join(found, row, "left").select(*docs.columns, runs), runs


def digest(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """doc_id, n_words, n_removed, kept_sha256 of every document."""
    def run(batches):
        import hashlib
        from itertools import compress

        import pyarrow as pa

        for batch in batches:
            out = ([], [], [])
            runs = batch.column("repeated_runs")
            for i, text in enumerate(batch.column("text")):
                kept = w = word_list(text.as_py())
                if runs[i].is_valid:
                    kept = list(compress(w, (~removed(runs[i].as_py(), width, len(w))).tolist()))
                out[0].append(len(w))
                out[1].append(len(w) - len(kept))
                out[2].append(hashlib.sha256(b" ".join(kept)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out[0], pa.int64()), pa.array(out[1], pa.int64()), pa.array(out[2], pa.string())], ["doc_id", "n_words", "n_removed", "kept_sha256"])

    rows, _ = marked(docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), width)
    return rows.mapInArrow(run, "doc_id long, n_words long, n_removed long, kept_sha256 string")


def cut(docs: DataFrame, width: int = WIDTH) -> DataFrame:
    """docs with the words of repeated passages cut out of `text`, its other white space as it was.

    The first place of a passage is cut as well: windows are judged by the input alone, so the result does not
    depend on an order of documents. A document left without words stays, with what white space it had.
    """
    names, schema = docs.columns, docs.schema
    rows, column = marked(docs, width)

    def run(batches):
        import re

        import pyarrow as pa

        word = re.compile(rb"[^\x20\x09-\x0D]+")
        for batch in batches:
            runs, texts = batch.column(column), []
            for i, text in enumerate(batch.column("text")):
                t = text.as_py()
                if t is None or not runs[i].is_valid:
                    texts.append(t)
                    continue
                raw = t.encode("utf-8", "surrogatepass")
                spans = [m.span() for m in word.finditer(raw)]
                gone = removed(runs[i].as_py(), width, len(spans)).tolist()
                parts, at, k = [], 0, 0
                while k < len(spans):
                    if not gone[k]:
                        k += 1
                        continue
                    parts.append(raw[at : spans[k][0]])
                    while k < len(spans) and gone[k]:
                        k += 1
                    at = spans[k][0] if k < len(spans) else spans[-1][1]
                parts.append(raw[at:])
                texts.append(b"".join(parts).decode("utf-8", "surrogatepass"))
            yield pa.RecordBatch.from_arrays([pa.array(texts, pa.string()) if c == "text" else batch.column(c) for c in names], names)

    return rows.mapInArrow(run, schema)


def oracle(width: int = WIDTH) -> str:
    """The same rows in DuckDB, window by window."""
    return rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
win AS (SELECT r, i, array_to_string(w[i:i + {width - 1}], ' ') AS k FROM (SELECT r, w, unnest(range(1, len(w) - {width - 2})) AS i FROM d WHERE len(w) >= {width})),
again AS (SELECT r, i FROM (SELECT r, i, count(*) OVER (PARTITION BY k) AS n FROM win) WHERE n > 1),
gone AS (SELECT DISTINCT r, j FROM (SELECT r, unnest(range(i, i + {width})) AS j FROM again)),
kept AS (SELECT r, count(*) AS n, string_agg(x, ' ' ORDER BY j) AS s FROM (SELECT r, unnest(w) AS x, generate_subscripts(w, 1) AS j FROM d) p ANTI JOIN gone USING (r, j) GROUP BY r)
SELECT doc_id, len(w)::BIGINT AS n_words, (len(w) - coalesce(n, 0))::BIGINT AS n_removed, sha256(coalesce(s, '')) AS kept_sha256 FROM d LEFT JOIN kept USING (r)
"""
