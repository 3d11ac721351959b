"""Byte-level BPE encoding and decoding with vectorised pre-tokenisation.

The split pattern is a finite automaton. Its symbols are classes of code points: letters, numbers, other signs,
white space by what follows it, apostrophes by the contraction that they open; they come from arrays, with a look at the
next two code points. Each symbol is a transition function on the automaton's states, and composing functions is
associative. So a chunk of texts is cut into blocks: the functions of a block's symbols are composed, all blocks at a
time; the blocks' functions are scanned by doubling, which gives each block its first state; and a second pass over the
blocks gives every place its state, hence whether a slice begins there. Texts in a chunk are parted by a symbol whose
function leads to the first state from all others. No regular expression is run over a text.

Slices between boundaries feed a merge table with a cache: merged ids, their decimal digits and the bytes that
the ids decode to are kept for slices seen lately. Offsets of the slices are kept, so a text can be decoded
slice by slice.

Defined results: null and empty texts have no ids and decode to no bytes; texts of any length are encoded whole;
slices beyond `LONG` bytes are merged with a heap, in n log n.
"""

from __future__ import annotations

import heapq

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

LETTER, NUMBER, OTHER, SPACE, BLANK = 0, 1, 2, 3, 4
#: Symbols past the classes of single code points: white space before white space or an end, a blank before a word, other
#: white space before a word, apostrophes that open a contraction of one or two letters, and the end of a text.
WHITE, OPENS, STANDS, SHORT, LONGER, END = 3, 4, 5, 6, 7, 8
#: States, by the slice that the last code point is in: the first state is that before a text and after a closed slice.
FIRST, IN_LETTERS, IN_NUMBERS, IN_OTHERS, IN_WHITE, OPENED, ONE_LEFT, TWO_LEFT = range(8)
BLOCK = 64
#: Code points that are split at once, about.
CHUNK = 400_000
LONG = 64
#: Slices kept in a worker at most.
KEPT = 300_000

_classes: list[np.ndarray] = []


def class_table() -> np.ndarray:
    """The class of every code point, by the Unicode tables of the tiktoken library, asked once a worker."""
    if not _classes:
        import tiktoken

        every = "".join(map(chr, [*range(0xD800), *range(0xE000, 0x110000)]))
        single = {bytes([i]): i for i in range(256)}
        t = np.full(0x110000, OTHER, np.uint8)
        for kind, name in ((LETTER, r"\p{L}+"), (NUMBER, r"\p{N}+"), (SPACE, r"\s+")):
            met = tiktoken.Encoding(f"class{kind}", pat_str=name, mergeable_ranks=single, special_tokens={}).encode_ordinary(every)
            t[np.frombuffer(bytes(met).decode().encode("utf-32-le"), np.uint32)] = kind
        t[0x20] = BLANK
        _classes.append(t)
    return _classes[0]


def automaton() -> tuple[np.ndarray, np.ndarray]:
    """Next state, and whether a slice begins, by symbol and state before."""
    go, begin = np.zeros((9, 8), np.uint8), np.ones((9, 8), bool)
    for symbol, inside in ((LETTER, IN_LETTERS), (NUMBER, IN_NUMBERS), (OTHER, IN_OTHERS), (WHITE, IN_WHITE)):
        go[symbol] = inside
        begin[symbol, inside] = False
        begin[symbol, OPENED] = symbol == WHITE
    go[OPENS], go[STANDS], go[SHORT], go[LONGER], go[END] = OPENED, FIRST, ONE_LEFT, TWO_LEFT, FIRST
    for mark in (SHORT, LONGER):  # an apostrophe in a run of signs, or after the blank that opens one, is a sign
        go[mark, [IN_OTHERS, OPENED]] = IN_OTHERS
        begin[mark, [IN_OTHERS, OPENED]] = False
    go[:, TWO_LEFT], go[:, ONE_LEFT] = ONE_LEFT, FIRST
    begin[:, [TWO_LEFT, ONE_LEFT]] = False
    return go, begin


_GO, _BEGIN = automaton()


def symbols(points: np.ndarray) -> np.ndarray:
    """The automaton's symbol of each code point; END where a text ends (0x110000)."""
    end = points >= 0x110000
    c = class_table()[np.where(end, 0, points)]
    c[end] = END
    white = (c == SPACE) | (c == BLANK)
    after = np.r_[c[1:], np.uint8(END)]
    word = ~((after == SPACE) | (after == BLANK) | (after == END))
    out = np.where(white, np.where(word, np.where(c == BLANK, OPENS, STANDS), WHITE), c).astype(np.uint8)
    out[end] = END
    mark = np.flatnonzero(points == 39)
    if len(mark):
        ahead = np.r_[points, np.full(2, 0x110000, points.dtype)]
        a, b = ahead[mark + 1], ahead[mark + 2]
        out[mark[np.isin(a, [115, 116, 109, 100])]] = SHORT  # s t m d
        out[mark[((a == 114) & (b == 101)) | ((a == 118) & (b == 101)) | ((a == 108) & (b == 108))]] = LONGER  # re ve ll
    return out


def states(symbol: np.ndarray) -> np.ndarray:
    """The automaton's state before each symbol, by a scan over the symbols' transition functions."""
    n, blocks = len(symbol), -(-len(symbol) // BLOCK)
    rows = np.full(blocks * BLOCK, END, np.uint8)
    rows[:n] = symbol
    rows = np.ascontiguousarray(rows.reshape(blocks, BLOCK).T).astype(np.int16) << 3
    flat = _GO.ravel()
    whole = np.tile(np.arange(8, dtype=np.uint8), (blocks, 1))  # each block's function: last state by first state
    for row in rows:
        whole = flat[row[:, None] + whole]
    step = 1
    while step < blocks:  # functions of ever longer stretches of blocks that end at each block
        whole[step:] = np.take_along_axis(whole[step:], whole[:-step], 1)
        step *= 2
    now = np.r_[np.uint8(FIRST), whole[:-1, FIRST]]
    out = np.empty((BLOCK, blocks), np.uint8)
    for t, row in enumerate(rows):
        out[t] = now
        now = flat[row + now]
    return out.T.ravel()[:n]


def boundaries_of(texts: list[str]) -> list[np.ndarray]:
    """For each text, the start of every slice, and its length at the end."""
    parts, end = [], np.array([0x110000], np.uint32)
    for text in texts:
        parts += np.frombuffer(text.encode("utf-32-le", "surrogatepass"), np.uint32), end
    if not parts:
        return []
    points = np.concatenate(parts)
    symbol = symbols(points)
    at = np.flatnonzero(_BEGIN[symbol, states(symbol)] | (symbol == END))
    last = np.flatnonzero(symbol[at] == END)
    ends = at[last]
    starts = np.r_[0, ends[:-1] + 1]
    return [at[a : b + 1] - s for a, b, s in zip(np.r_[0, last[:-1] + 1], last, starts)]


def boundaries(text: str) -> np.ndarray:
    return boundaries_of([text])[0]


def slices_of(texts: list):
    """Each text's slices, in turn; a chunk of texts is split at once (null: none)."""
    chunk, size = [], 0
    for k, text in enumerate(texts):
        chunk.append(text or "")
        size += len(chunk[-1]) + 1
        if size >= CHUNK or k + 1 == len(texts):
            for t, at in zip(chunk, boundaries_of(chunk)):
                at = at.tolist()
                yield [t[a:b] for a, b in zip(at, at[1:])]
            chunk, size = [], 0


def slices(text: str) -> list[str]:
    return next(slices_of([text]))


class Merger:
    """Ids of single slices by a table of ranks, in which a merged token's id is its rank.

    The adjacent pair of the lowest rank is merged first, the leftmost of equals. What a pair of ids merges to
    is kept, at most `most` pairs.
    """

    NONE = 1 << 30

    def __init__(self, ranks: dict[bytes, int], most: int = 500_000):
        self.ranks, self.most = ranks, most
        self.bytes_of = {i: b for b, i in ranks.items()}
        self.single = [ranks[bytes([b])] for b in range(256)]
        self.pairs: dict[int, int] = {}

    def pair(self, a: int, b: int) -> int:
        key = a << 20 | b
        found = self.pairs.get(key)
        if found is None:
            if len(self.pairs) >= self.most:
                self.pairs.clear()
            self.pairs[key] = found = self.ranks.get(self.bytes_of[a] + self.bytes_of[b], self.NONE)
        return found

    def __call__(self, piece: bytes) -> list[int]:
        whole = self.ranks.get(piece)
        if whole is not None:
            return [whole]
        if len(piece) > LONG:
            return merge_long([piece[i : i + 1] for i in range(len(piece))], self.ranks)
        ids = [self.single[b] for b in piece]
        pair, none = self.pair, self.NONE
        ranks = list(map(pair, ids, ids[1:]))
        while ranks:
            low = min(ranks)
            if low == none:
                break
            i = ranks.index(low)
            ids[i] = low
            del ids[i + 1], ranks[i]
            if i:
                ranks[i - 1] = pair(ids[i - 1], low)
            if i < len(ranks):
                ranks[i] = pair(low, ids[i + 1])
        return ids


def merge(piece: bytes, ranks: dict) -> list[int]:
    """Ids of one slice, for a single call."""
    return Merger(ranks)(piece)


def merge_long(parts: list, ranks: dict) -> list[int]:
    right = [*range(1, len(parts)), -1]
    left = [-1, *range(len(parts) - 1)]
    heap = [(r, i, 2) for i in range(len(parts) - 1) if (r := ranks.get(parts[i] + parts[i + 1])) is not None]
    heapq.heapify(heap)
    while heap:
        r, i, size = heapq.heappop(heap)
        j = right[i] if parts[i] is not None else -1
        if parts[i] is None or j < 0 or len(parts[i]) + len(parts[j]) != size or ranks.get(parts[i] + parts[j]) != r:
            continue
        parts[i] += parts[j]
        parts[j] = None
        right[i] = k = right[j]
        if k >= 0:
            left[k] = i
        for a in (left[i], i):
            if a >= 0 and (b := right[a]) >= 0 and (x := ranks.get(both := parts[a] + parts[b])) is not None:
                heapq.heappush(heap, (x, a, len(both)))
    return [ranks[p] for p in parts if p is not None]


def load_ranks(path: str) -> dict[bytes, int]:
    import base64

    with open(path, "rb") as f:
        return {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}


class Coder:
    """Encodes and decodes with one rank file."""

    def __init__(self, path: str):
        self.ranks = load_ranks(path)
        self.merge = Merger(self.ranks)
        self.bytes_of = self.merge.bytes_of
        self.kept: dict[str, tuple] = {}

    def entry(self, piece: str) -> tuple:
        """(number of ids, decimal ids with a comma after each, decoded bytes) of a slice."""
        found = self.kept.get(piece)
        if found is None:
            if len(self.kept) >= KEPT:
                self.kept.clear()
            ids = self.merge(piece.encode("utf-8", "surrogatepass"))
            found = len(ids), "".join(f"{i}," for i in ids), b"".join(map(self.bytes_of.__getitem__, ids))
            if len(piece) <= 256:
                self.kept[piece] = found
        return found

    def encode(self, text: str | None) -> list[int]:
        return [i for p in slices(text or "") for i in self.merge(p.encode("utf-8", "surrogatepass"))]

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))

    def offsets(self, text: str | None) -> list[tuple[int, int, list[int]]]:
        """(start, end, ids) of each slice, in code points of the text."""
        at = boundaries(text or "").tolist()
        return [(a, b, self.merge(text[a:b].encode("utf-8", "surrogatepass"))) for a, b in zip(at, at[1:])]


def digests(docs: DataFrame, path: str) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256 of every text."""
    def run(batches):
        import hashlib

        import pyarrow as pa

        coder = Coder(path)
        for batch in batches:
            n, ids, back = [], [], []
            for found in slices_of(batch.column("text").to_pylist()):
                found = list(map(coder.entry, found))
                n.append(sum(x[0] for x in found))
                ids.append(hashlib.sha256("".join([x[1] for x in found])[:-1].encode()).hexdigest())
                back.append(hashlib.sha256(b"".join([x[2] for x in found])).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(n, pa.int64()), pa.array(ids), pa.array(back)], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return rows.mapInArrow(run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string")
