"""Packing by the length histogram, shortest pack first.

Every text is encoded by the public byte-level tokenizer and ended by id 0, then cut into pieces of the
sequence length and a rest. The histogram of piece lengths (at most 1024 rows) is packed on the driver:
lengths go longest first, each time onto the packs that are shortest so far, if they have room; packs of equal
composition are one pattern with a count, so the work depends on the number of lengths, not of documents.
A pattern's slots then name, for each length, ranges of ranks; pieces are ranked within their length and
joined to the slots. Ranks are dealt over salted parts of each length, whose counts are added up, so that one
length that holds a third of all pieces is not one task's work.

Defined results: a null text is empty and has the closing id only; repeated rows are packed each; a text of any
length is cut into as many pieces as needed. Other columns are not read.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from . import common

SEQUENCE, CLOSE, SPECIAL = 1024, 0, "<|endoftext|>"
#: Places of patterns that are broadcast at most; more are met by an exchange.
MOST_PLACES = 1_000_000
#: Rows of one length that one task ranks, about.
PART = 100_000


def byte_ranks(path: str) -> dict[bytes, int]:
    """The vocabulary of a byte-level tokenizer file as bytes and ids; its ids are in the order of its merges."""
    import json

    from tokenizers.pre_tokenizers import ByteLevel

    with open(path, encoding="utf-8") as f:
        vocabulary = json.load(f)["model"]["vocab"]
    # The file writes bytes as printable characters: printable Latin-1 as themselves, the rest from 256 on, in order.
    shown = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in shown]
    back = {chr(b): b for b in shown} | {chr(256 + k): b for k, b in enumerate(rest)}
    assert set(back) == set(ByteLevel.alphabet())
    return {bytes(back[c] for c in token): i for token, i in vocabulary.items() if token != SPECIAL}


def encoder(path: str):
    """A function from a list of texts to each one's ids, little-endian unsigned 32-bit; ids of slices seen lately are kept.

    Slices that are new are encoded with the tokenizer's vocabulary by the faster of the installed libraries;
    texts that hold the special token go through the tokenizer itself.
    """
    from array import array

    import public_tokenizers
    import tiktoken
    from tokenizers import Tokenizer

    from .byte_bpe import slices_of

    own = Tokenizer.from_file(path)
    fast = tiktoken.Encoding("packing", pat_str=public_tokenizers.PATTERN, mergeable_ranks=byte_ranks(path), special_tokens={}).encode_ordinary
    packed = lambda ids: array("I", ids).tobytes()

    class Kept(dict):
        def __missing__(self, piece: str) -> bytes:
            if len(self) >= 300_000:
                self.clear()
            found = packed(fast(piece))
            if len(piece) <= 256:
                self[piece] = found
            return found

    kept = Kept()

    def encode(texts: list):
        special = [bool(t) and SPECIAL in t for t in texts]  # these by the tokenizer's own rule for its special token
        for text, odd, found in zip(texts, special, slices_of([None if odd else t for t, odd in zip(texts, special)])):
            yield packed(own.encode(text, add_special_tokens=False).ids) if odd else b"".join(map(kept.__getitem__, found))

    return encode


def pieces(docs: DataFrame, path: str, sequence: int = SEQUENCE) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens: texts cut into pieces of at most `sequence` ids."""
    def run(batches):
        import zlib

        import pyarrow as pa

        encode = encoder(path)
        close = CLOSE.to_bytes(4, "little")
        for batch in batches:
            out = ([], [], [], [], [])
            for doc_id, ids in zip(batch.column("doc_id").to_pylist(), encode(batch.column("text").to_pylist())):
                ids += close
                n = len(ids) // 4
                for at in range(0, n, sequence):
                    part = ids[4 * at : 4 * (at + sequence)]
                    for column, value in zip(out, (doc_id, at, len(part) // 4, zlib.crc32(part), n)):
                        column.append(value)
            yield pa.RecordBatch.from_arrays([pa.array(x, pa.int64()) for x in out], ["doc_id", "start", "length", "ids_crc32", "doc_tokens"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(run, "doc_id long, start long, length long, ids_crc32 long, doc_tokens long")


def patterns(histogram: dict[int, int], sequence: int = SEQUENCE) -> list[tuple[tuple[int, ...], int]]:
    """Packs as (lengths, count): each length, longest first, goes onto the packs that are shortest so far."""
    open_packs: dict[int, dict[tuple[int, ...], int]] = {}  # by room left
    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        # Shortest first means most room first; packs that get a piece now are not looked at again for this length
        # before all others of more room are.
        while left:
            room = max(open_packs, default=0)
            if room < length:
                break
            group = open_packs[room]
            while group and left:
                pack, count = group.popitem()
                took = min(count, left)
                if took < count:
                    group[pack] = count - took
                left -= took
                into = open_packs.setdefault(room - length, {})
                grown = (*pack, length)
                into[grown] = into.get(grown, 0) + took
            if not open_packs[room]:
                del open_packs[room]
        if left:
            open_packs.setdefault(sequence - length, {})[(length,)] = left
    return [(pack, n) for room in sorted(open_packs) for pack, n in sorted(open_packs[room].items())]


def slots(packs: list[tuple[tuple[int, ...], int]]) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, rank after the last, first sequence, offset): one row per place in a pattern."""
    used: dict[int, int] = {}
    out, base = [], 0
    for pack, n in packs:
        offset = 0
        for length in pack:
            lo = used.get(length, 0)
            out.append((length, lo, lo + n, base, offset))
            used[length] = lo + n
            offset += length
        base += n
    return out


def ranked(rows: DataFrame, counts: dict[int, int]) -> DataFrame:
    """rows with `rank` within their length, from 0."""
    parts = max(1, -(-max(counts.values(), default=1) // PART))
    salted = rows.withColumn("part", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.lit(parts)))
    sizes = salted.groupBy("length", "part").count()
    before = F.coalesce(F.sum("count").over(Window.partitionBy("length").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    shift = sizes.select("length", "part", before.alias("before"))
    own = F.row_number().over(Window.partitionBy("length", "part").orderBy("doc_id", "start", "ids_crc32")) - 1
    return salted.withColumn("own", own).join(shift, ["length", "part"]).withColumn("rank", F.col("own") + F.col("before")).drop("own", "before", "part")


def pack(docs: DataFrame, path: str, sequence: int = SEQUENCE) -> DataFrame:
    """doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset of every piece."""
    spark = docs.sparkSession
    rows = common.staged(pieces(docs, path, sequence), "pieces")
    counts = {r["length"]: r["count"] for r in rows.groupBy("length").count().collect()}  # at most `sequence` rows
    found = slots(patterns(counts, sequence))
    places = spark.createDataFrame(found, "length long, lo long, hi long, base long, offset long")
    # As many rows as patterns have places, whatever the number of documents.
    r, s = ranked(rows, counts).alias("r"), (F.broadcast(places) if len(found) <= MOST_PLACES else places).alias("s")
    met = (F.col("r.length") == F.col("s.length")) & (F.col("rank") >= F.col("lo")) & (F.col("rank") < F.col("hi"))
    return r.join(s, met).select("doc_id", "start", F.col("r.length").alias("length"), "ids_crc32", "doc_tokens", (F.col("base") + F.col("rank") - F.col("lo")).alias("sequence_id"), "offset")
