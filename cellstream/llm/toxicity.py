"""Toxicity: a support vector machine on a gap-weighted subsequence kernel, with Nyström landmarks, trained on sentences.

Sentences are read as strings of lower-cased letters, all kept apart, with blanks around words. Signs inside words
vanish, digits and signs that look like a letter are read as it, and single letters that follow each other
("i d i o t") close up. The kernel of two words sums, over the subsequences of four symbols (letters, and the blanks
at a word's ends) that both hold within SPAN symbols, DECAY to the power of the gaps; it is divided by a norm of each
word's length. So gapped and inserted-character insults, and words of one stem, share most of it.

Training: labels come with documents, and a sentence inherits its document's. The machine is a multiple-instance one:
a sentence's value is that of its highest word, its witness. At most `most` labelled documents of each class are
chosen by hash (MOST_LABELLED), and of these at most `sentences` distinct sentences of each class (MOST_SENTENCES).
How many of the documents hold a word, or a word's beginning, is counted in Spark; what stands out in toxic ones
becomes landmarks, with others from clean ones. In ROUNDS rounds a squared-hinge linear machine is fitted on the
Nyström features of the witnesses of toxic sentences and the hardest words of clean ones, and chooses the next
witnesses; a toxic document's sentence whose witness is on the clean side is left out. The expansion over landmarks
is linear in their subsequences, so it is folded into one table of weights, which gives the same value. A document's
score is a logistic function, fitted on the chosen documents, of its highest sentences and their number.

Scoring sees whole texts only; labels, lang, source and doc_id never enter. Texts never leave their task but for the
training sentences. Defined results: null and empty texts get the score of a text without sentences; where there are
no labels, or only one class, every score is the (smoothed) share of the class; a repeated row is scored each time;
a sentence of any length counts whole, and a word over LONGEST letters as overlapping words of LONGEST.
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

DECAY, SPAN, LONGEST = 0.6, 7, 40
LANDMARKS, MOST_SENTENCES, MOST_LABELLED, ROUNDS = 256, 30_000, 3000, 3
#: Words of clean sentences that a round looks at: the hardest, and some by hash.
HARD, OTHERS = 4000, 2000
#: How much larger a landmark's share of toxic documents must be than its share of clean ones to stand out.
TELLING = 8
#: Distances of the second, third and fourth symbol from the first.
STEPS = [c for c in combinations(range(1, SPAN), 3)]
BLANK, WALL, CUT, MARK = 32, 10, 0x110000, 0x10FFFF
#: Symbols that are worked on at once, about, and words whose values a worker keeps at most.
CHUNK, KEPT = 500_000, 200_000
#: Signs and digits that are read as letters.
LOOKALIKES = dict(zip("013457@$", "oieastas"))

_fold: list[np.ndarray] = []


def fold_table() -> np.ndarray:
    """What each code point is read as: a letter, BLANK, WALL, a full stop, or 0 for nothing."""
    if not _fold:
        every = "".join(map(chr, range(CUT)))
        t = np.zeros(CUT + 1, np.uint32)
        t[:CUT] = np.where(np.fromiter(map(str.isalpha, every), bool, CUT), np.arange(CUT), 0)
        t[:CUT][np.fromiter(map(str.isspace, every), bool, CUT)] = BLANK
        for a, b in LOOKALIKES.items():
            t[ord(a)] = ord(b)
        t[[10, 13]] = WALL
        t[[ord(c) for c in ".!?"]] = ord(".")
        t[CUT] = MARK
        _fold.append(t)
    return _fold[0]


def symbols(texts: list) -> np.ndarray:
    """Code points of the words of all texts in order, with blanks between; MARK starts a text, and WALL ends a sentence."""
    wall, parts = np.array([WALL, CUT, WALL], np.uint32), []
    for text in texts:
        parts += wall, np.frombuffer((text or "").lower().encode("utf-32-le", "surrogatepass"), np.uint32)
    points = np.concatenate([*parts, wall[:1]])
    c = fold_table()[points]
    stop = c == ord(".")
    after = np.r_[c[1:], WALL]
    c[stop] = np.where(after <= BLANK, WALL, 0)[stop] * (after != 0)[stop]
    c = c[c != 0]
    # Single letters that follow each other close up.
    white = c <= BLANK
    lone = np.zeros(len(c), bool)
    lone[1:-1] = white[:-2] & white[2:] & ~white[1:-1] & (c[1:-1] != MARK)
    gone = np.zeros(len(c), bool)
    gone[1:-1] = (c[1:-1] == BLANK) & lone[:-2] & lone[2:]
    c = c[~gone]
    walls = np.where(c == WALL, 3, 1)
    at = np.cumsum(walls) - 2
    out = np.repeat(np.where(c == WALL, BLANK, c), walls)
    out[at[c == WALL]] = WALL
    return out.astype(np.uint32)


def tokens(texts: list) -> list[str]:
    return [t for t in symbols(texts).astype("<u4").tobytes().decode("utf-32-le", "surrogatepass").split(" ") if t]


def places(c: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start, length and a 64-bit hash of each token in an array of `symbols`."""
    word = c != BLANK
    edge = np.flatnonzero(np.diff(np.r_[False, word, False].view(np.int8)))
    starts, sizes = edge[::2], np.diff(edge)[::2]
    if not len(starts):
        return starts, sizes, np.empty(0, np.uint64)
    at = np.flatnonzero(word)
    inside = at - np.repeat(starts, sizes)
    h = common.mix(c[at].astype(np.uint64) + (inside.astype(np.uint64) << np.uint64(21)) + np.uint64(0x9E3779B97F4A7C15))
    return starts, sizes, common.mix(np.add.reduceat(h, np.r_[0, np.cumsum(sizes)[:-1]]))


def sentences(text: str | None) -> list[list[str]]:
    out: list[list[str]] = [[]]
    for t in tokens([text]):
        if t == chr(WALL):
            out.append([])
        elif t != chr(MARK):
            out[-1].append(t)
    return [s for s in out if s]


def pieces(word: str) -> list[str]:
    """The word with its blanks; a longer one as overlapping pieces."""
    if len(word) <= LONGEST:
        return [f" {word} "]
    half = LONGEST // 2
    cuts = range(0, len(word) - half, half)
    return [(" " if i == 0 else "") + word[i : i + LONGEST] + (" " if i + LONGEST >= len(word) else "") for i in cuts]


def norm(m: int) -> float:
    """Of a string of m symbols: the root of the sum of its subsequences' squared weights."""
    return math.sqrt(sum((m - z) * DECAY ** (2 * (z - 3)) for _, _, z in STEPS if z < m)) or 1.0


class Index:
    """Numbers for the subsequences of some landmarks; symbols that no landmark holds are not told apart.

    Landmarks are words with their blanks, or beginnings of words with the blank before.
    """

    def __init__(self, landmarks: list[str]):
        letters = sorted(set("".join(landmarks)))
        self.base = len(letters) + 1
        self.points = np.array([ord(c) for c in letters], np.uint32)
        number = {c: i + 1 for i, c in enumerate(letters)}
        rows = [(k, number[w[i]], number[w[i + x]], number[w[i + y]], number[w[i + z]], DECAY ** (z - 3)) for k, w in enumerate(landmarks) for i in range(len(w)) for x, y, z in STEPS if i + z < len(w)]
        table = np.array(rows, np.float64).reshape(-1, 6)
        owner, four, weight = table[:, 0].astype(int), table[:, 1:5].astype(np.int64), table[:, 5]
        lefts, left = np.unique(four[:, 0] * self.base + four[:, 1], return_inverse=True)
        rights, right = np.unique(four[:, 2] * self.base + four[:, 3], return_inverse=True)
        self.left, self.right = np.zeros(self.base**2, np.int32), np.zeros(self.base**2, np.int32)
        self.width = len(rights) + 1
        self.left[lefts] = (np.arange(len(lefts)) + 1) * self.width  # 0: no landmark has such a first pair
        self.right[rights] = np.arange(len(rights)) + 1
        self.size = (len(lefts) + 1) * self.width
        self.places, f = np.unique((left.astype(np.int64) + 1) * self.width + right + 1, return_inverse=True)
        z = np.zeros((len(landmarks), len(self.places)))
        np.add.at(z, (owner, f), weight)
        self.z = z / np.linalg.norm(z, axis=1, keepdims=True)

    def groups(self, words: list[str]):
        """(owners, codes) of the words' pieces, equally long ones together."""
        by: dict[int, tuple[list, list]] = {}
        for k, word in enumerate(words):
            for p in pieces(word):
                owner, parts = by.setdefault(len(p), ([], []))
                owner.append(k)
                parts.append(p)
        lut = np.zeros(CUT, np.uint16)
        lut[self.points] = np.arange(1, self.base)
        for m, (owner, parts) in by.items():
            step = max(1, 300_000 // m)
            for k in range(0, len(parts), step):
                raw = "".join(parts[k : k + step]).encode("utf-32-le", "surrogatepass")
                yield np.array(owner[k : k + step]), lut[np.frombuffer(raw, np.uint32)].astype(np.int32).reshape(-1, m)

    def hits(self, codes: np.ndarray):
        """For each choice of steps: its gaps and the places in the table of all subsequences with these steps."""
        m = codes.shape[1]
        pair = {d: codes[:, :-d] * self.base + codes[:, d:] for d in range(1, min(SPAN - 2, m))}
        left, right = {d: self.left[x] for d, x in pair.items()}, {d: self.right[x] for d, x in pair.items()}
        for x, y, z in STEPS:
            if z < m:
                yield z - 3, left[x][:, : m - z] + right[z - y][:, y : m - z + y]


def valued(index: Index, table: np.ndarray, bias: float, codes: np.ndarray) -> np.ndarray:
    """The machine's value of equally long strings, as rows of codes."""
    total = np.zeros((SPAN - 3, len(codes)))
    for gaps, at in index.hits(codes):
        total[gaps] += table[at].sum(1)
    return (DECAY ** np.arange(SPAN - 3)) @ total / norm(codes.shape[1]) + bias


def margins(index: Index, table: np.ndarray, bias: float, words: list[str]) -> np.ndarray:
    """The machine's value of each word; of a long one, its highest piece's."""
    out = np.full(len(words), -np.inf)
    for owner, codes in index.groups(words):
        np.maximum.at(out, owner, valued(index, table, bias, codes))
    return out


def margins_at(model: dict, lut: np.ndarray, c: np.ndarray, starts: np.ndarray, sizes: np.ndarray) -> np.ndarray:
    """The same of the words at these places in an array of `symbols`."""
    index, table, bias = model["index"], model["table"], model["bias"]
    out = np.empty(len(starts))
    for size in np.unique(sizes).tolist():
        on = np.flatnonzero(sizes == size)
        if size > LONGEST:
            words = [c[a : a + size].astype("<u4").tobytes().decode("utf-32-le", "surrogatepass") for a in starts[on].tolist()]
            out[on] = margins(index, table, bias, words)
            continue
        for k in range(0, len(on), step := max(1, 200_000 // size)):
            own = on[k : k + step]
            codes = np.full((len(own), size + 2), lut[BLANK], np.int32)
            codes[:, 1:-1] = lut[c[starts[own][:, None] + np.arange(size)]]
            out[own] = valued(index, table, bias, codes)
    return out


def kernel_rows(index: Index, words: list[str]) -> np.ndarray:
    """Kernel of words and normalised landmarks; a long word's is its first piece's."""
    number = np.zeros(index.size, np.int64)
    number[index.places] = np.arange(len(index.places)) + 1
    f = len(index.places) + 1
    z = np.vstack([np.zeros(len(index.z)), index.z.T]).astype(np.float32)
    out = np.zeros((len(words), len(index.z)))
    done = np.zeros(len(words), bool)
    for owner, codes in index.groups(words):
        fresh = np.unique(owner, return_index=True)[1]
        fresh = fresh[~done[owner[fresh]]]
        for k in range(0, len(fresh), 256):
            own, part = owner[fresh[k : k + 256]], codes[fresh[k : k + 256]]
            at, weight = [np.empty(0, np.int64)], [np.empty(0)]
            for gaps, place in index.hits(part):
                row, _ = np.nonzero(place)
                at.append(row * f + number[place[place != 0]])
                weight.append(np.full(len(row), DECAY**gaps))
            held = np.bincount(np.concatenate(at), np.concatenate(weight), minlength=len(own) * f).reshape(-1, f)
            held[:, 0] = 0
            out[own] = held.astype(np.float32) @ z / norm(codes.shape[1])
            done[own] = True
    return out


def spread(ranked: list[str], most: int, alike: float = 0.85) -> list[str]:
    """The first of a ranking that are not alike one taken before, by their kernels over postings of subsequences."""
    taken: list[str] = []
    postings: dict[tuple, list[tuple[int, float]]] = {}
    for word in ranked[: 6 * most]:
        own: dict[tuple, float] = {}
        for i in range(len(word)):
            for x, y, z in STEPS:
                if i + z < len(word):
                    key = word[i], word[i + x], word[i + y], word[i + z]
                    own[key] = own.get(key, 0.0) + DECAY ** (z - 3)
        size = math.sqrt(sum(v * v for v in own.values())) or 1.0
        near = [0.0] * len(taken)
        for key, v in own.items():
            for k, w in postings.get(key, ()):
                near[k] += v * w / size
        if own and max(near, default=0.0) < alike:
            for key, v in own.items():
                postings.setdefault(key, []).append((len(taken), v / size))
            taken.append(word)
            if len(taken) == most:
                break
    return taken


def units(words) -> set[str]:
    """What may be a landmark: words with their blanks, and beginnings of words."""
    words = {w for w in words if 2 <= len(w) <= LONGEST}
    return {f" {w} " for w in words} | {f" {w[:k]}" for w in words for k in range(4, min(9, len(w)))}


def crc(word: str) -> int:
    import zlib

    return zlib.crc32(word.encode("utf-8", "surrogatepass"))


def fit(telling: list[str], plain: list[str], bad: list[str], good: list[str]) -> tuple[Index, np.ndarray, float] | None:
    """Index, folded table and bias from the units that stand out, others, and the sentences (words with blanks between) of both classes."""
    if not (telling and plain and bad and good):
        return None
    index = Index(list(dict.fromkeys(spread(telling, LANDMARKS // 2) + spread(plain, LANDMARKS // 2))))
    lam, vec = np.linalg.eigh(index.z @ index.z.T)
    keep = lam > 1e-6
    root = vec[:, keep] / np.sqrt(lam[keep])
    rank = {u: i for i, u in enumerate(telling)}
    at: dict[str, int] = {}
    numbered = lambda s: np.array([at.setdefault(w, len(at)) for w in s.split(" ")], np.int32)
    bags, held = [numbered(s) for s in bad], [np.unique(numbered(s)) for s in good]
    words = list(at)
    del at
    best = np.array([min((rank[u] for u in units([w]) if u in rank), default=len(rank)) for w in words])
    value = np.where(best < len(rank), 1.0 + 1.0 / (1 + best), -1.0)  # before there is a machine: the order in which units stand out
    clean, often = np.unique(np.concatenate(held), return_counts=True)
    del held
    count = np.zeros(len(words))
    count[clean] = often
    some = np.array(sorted(clean.tolist(), key=lambda i: crc(words[i])), np.int64)[:OTHERS]
    table, bias = None, 0.0
    for _ in range(ROUNDS):
        witness = np.array([b[np.argmax(value[b])] for b in bags], np.int64)
        witness = witness[value[witness] > 0]
        witness = witness[~np.isin(witness, clean)]  # a word of a clean sentence is none
        if not len(witness):
            break
        good_ones, times = np.unique(witness, return_counts=True)
        hard = clean[np.argsort(-value[clean], kind="stable")[:HARD]]
        bad_ones = np.union1d(hard, some)
        x = kernel_rows(index, [words[i] for i in (*good_ones, *bad_ones)]) @ root
        y = np.r_[np.ones(len(good_ones)), -np.ones(len(bad_ones))]
        # A word counts by how many sentences it is in, so that chance witnesses weigh little.
        p, q = np.minimum(times, 50.0), np.sqrt(count[bad_ones])
        weight = np.r_[0.5 * p / p.sum(), 0.5 * q / q.sum()]
        u, bias = hinge(x, y, weight)
        table = np.zeros(index.size, np.float32)
        table[index.places] = index.z.T @ (root @ u)
        value = np.concatenate([margins(index, table, bias, words[k : k + 20_000]) for k in range(0, len(words), 20_000)])
    return (index, table, float(bias)) if table is not None else None


def hinge(x: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float = 1e-4, steps: int = 500) -> tuple[np.ndarray, float]:
    """Squared hinge with a ridge, by accelerated gradient steps; weights sum to 1."""
    xb = np.c_[x, np.ones(len(x))]
    rate = 1.0 / (2 * np.linalg.eigvalsh((xb * weight[:, None]).T @ xb)[-1] + 2 * ridge)
    u = v = np.zeros(xb.shape[1])
    reg = np.r_[np.full(x.shape[1], ridge), 0.0]
    for t in range(steps):
        short = np.maximum(0, 1 - y * (xb @ v))
        new = v - rate * (-2 * xb.T @ (weight * y * short) + 2 * reg * v)
        v, u = new + t / (t + 3) * (new - u), new
    return u[:-1], u[-1]


NONE = [-3.0, -3.0, 0.0, 0.0]


def summaries(value: np.ndarray) -> np.ndarray:
    """Of each text (token values; inf at its start, -inf at a sentence's end): its two highest sentences, how many are
    positive and how many there are, as logarithms."""
    ends = np.flatnonzero(np.isinf(value))
    owner = np.cumsum(value == np.inf) - 1
    n = int(owner[-1]) + 1 if len(owner) else 0
    out = np.tile(NONE, (n, 1))
    held = ends[:-1][np.diff(ends) > 1]  # a mark or wall with words after it
    if len(held):
        finite = np.where(np.isinf(value), -np.inf, value)
        top = np.clip(np.maximum.reduceat(finite, held), -3, 3)
        text = owner[held]
        order = np.lexsort((-top, text))
        t, v = text[order], top[order]
        first = np.flatnonzero(np.r_[True, t[1:] != t[:-1]])
        size = np.diff(np.r_[first, len(t)])
        out[t[first], 0] = v[first]
        more = first[size > 1]
        out[t[more], 1] = v[more + 1]
        out[:, 2] = np.log1p(np.bincount(text, top > 0, minlength=n))
        out[:, 3] = np.log1p(np.bincount(text, minlength=n))
    return out


def logistic(x: np.ndarray, y: np.ndarray, ridge: float = 0.02, steps: int = 60) -> np.ndarray:
    xb = np.c_[x, np.ones(len(x))]
    u = np.zeros(xb.shape[1])
    reg = np.r_[np.full(x.shape[1], ridge), 1e-6]
    for _ in range(steps):
        p = 1 / (1 + np.exp(-np.clip(xb @ u, -30, 30)))
        g = xb.T @ (p - y) + reg * u
        h = (xb * (p * (1 - p))[:, None]).T @ xb + np.diag(reg) + 1e-6 * np.eye(len(u))
        u = u - np.linalg.solve(h, g)
    return u


def chunks(texts: list):
    """Stretches of texts of about CHUNK symbols; a text is never cut."""
    at, size = 0, 0
    for k, t in enumerate(texts):
        size += len(t or "") + 1
        if size >= CHUNK:
            yield texts[at : k + 1]
            at, size = k + 1, 0
    if at < len(texts):
        yield texts[at:]


def featured(model: dict):
    """A function from a list of texts to what their scores look at; values of words seen lately are kept."""
    kept: dict[int, float] = {}
    lut = None
    if model["index"] is not None:
        lut = np.zeros(CUT, np.int32)
        lut[model["index"].points] = np.arange(1, model["index"].base)

    def of(texts: list) -> np.ndarray:
        out = [np.empty((0, len(NONE)))]
        for part in chunks(texts):
            if lut is None:
                out.append(np.tile(NONE, (len(part), 1)))
                continue
            c = symbols(part)
            starts, sizes, h = places(c)
            _, first, back = np.unique(h, return_index=True, return_inverse=True)
            names = h[first].tolist()
            if len(kept) > KEPT:
                kept.clear()
            new = [i for i, x in enumerate(names) if x not in kept]
            at = first[new]
            kept.update(zip([names[i] for i in new], margins_at(model, lut, c, starts[at], sizes[at]).tolist()))
            value = np.fromiter(map(kept.__getitem__, names), float, len(names))[back]
            value[c[starts] == MARK] = np.inf
            value[c[starts] == WALL] = -np.inf
            out.append(summaries(value))
        return np.concatenate(out)

    return of


def counted(rows: DataFrame) -> DataFrame:
    """unit, toxic, clean: how many documents of either class hold a unit. rows: toxic, text."""
    def run(batches):
        import pyarrow as pa

        for batch in batches:
            for k in range(0, batch.num_rows, 64):
                part = batch.slice(k, 64)
                found = [list(units({w for s in sentences(t.as_py()) for w in s})) for t in part.column("text")]
                yield pa.RecordBatch.from_arrays([part.column("toxic"), pa.array(found, pa.list_(pa.string()))], ["toxic", "units"])

    held = rows.select("toxic", "text").mapInArrow(run, "toxic int, units array<string>").select("toxic", F.explode("units").alias("unit"))
    return held.groupBy("unit").agg(F.sum("toxic").alias("toxic"), F.sum(1 - F.col("toxic")).alias("clean"))


def standing(counts: DataFrame, n: dict[int, int]) -> tuple[list[str], list[str]]:
    """Units that stand out in toxic documents, best first, and others: the commonest and some by hash."""
    p0 = n[1] / (n[0] + n[1])
    both = F.col("toxic") + F.col("clean")
    p = F.col("toxic") / both
    surprise = F.col("toxic") * F.log(p / p0) + F.when(F.col("clean") > 0, F.col("clean") * F.log((1 - p) / (1 - p0))).otherwise(0.0)
    rows = counts.select("unit", "toxic", "clean", F.when(p > p0, surprise).otherwise(0.0).alias("value"))
    size, most = rows.agg(F.count(F.lit(1)), F.max("value")).first()
    if not size:
        return [], []
    least = min(math.log(size + 1), 0.5 * most)  # what the best of so many units reach by chance
    ratio = (F.col("toxic") / n[1]) / ((F.col("clean") + 0.5) / n[0])
    telling = rows.where((F.col("value") > max(least, 0.1)) & (ratio >= TELLING)).orderBy(F.desc("value"), "unit").limit(3 * LANDMARKS)
    plain = rows.where((F.col("value") <= 1.0) & (F.col("clean") > 0) & F.col("unit").endswith(" "))
    common = plain.orderBy(F.desc(both), "unit").limit(2 * LANDMARKS)
    rare = plain.orderBy(F.xxhash64("unit"), "unit").limit(2 * LANDMARKS)
    named = lambda df: [r["unit"] for r in df.collect()]  # noqa: E731  bounded by the limits
    return named(telling), [u for pair in zip(*(named(x) for x in (common, rare))) for u in pair]


def train(docs: DataFrame, labels: DataFrame, most: int = MOST_LABELLED, most_sentences: int = MOST_SENTENCES) -> dict:
    """The model, from at most `most` labelled documents of each class and `most_sentences` of their sentences, the smallest by hash."""
    spark = docs.sparkSession
    chosen = labels.select("doc_id", F.col("toxic").cast("int").alias("toxic")).where("toxic in (0, 1) and doc_id is not null").groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    ids = [chosen.where(F.col("toxic") == c).orderBy(F.xxhash64("doc_id"), "doc_id").limit(most) for c in (0, 1)]
    rows = common.staged(docs.select("doc_id", "text").join(F.broadcast(ids[0].unionByName(ids[1])), "doc_id").select("toxic", "text"), "labelled")  # twice `most` ids
    n = {0: 0, 1: 0} | {r["toxic"]: r["count"] for r in rows.groupBy("toxic").count().collect()}
    share = (n[1] + 0.5) / (n[0] + n[1] + 1)
    model = {"index": None, "table": None, "bias": 0.0, "doc": np.r_[np.zeros(len(NONE)), math.log(share / (1 - share))]}
    if not all(n.values()):
        common.dropped(rows)
        return model

    def cut(batches):
        import pandas as pd

        for pdf in batches:
            for k in range(0, len(pdf), 64):
                part = pdf.iloc[k : k + 64]
                # Bounded sentences for the training sample; scoring takes sentences of any length whole.
                found = [(t, " ".join(s[a : a + 64])) for t, text in zip(part["toxic"], part["text"]) for s in sentences(text) for a in range(0, len(s), 64)]
                yield pd.DataFrame(found, columns=["toxic", "string"])

    counts = common.staged(counted(rows), "units")
    telling, plain = standing(counts, n)
    common.dropped(counts)
    found = rows.mapInPandas(cut, "toxic int, string string").groupBy("string").agg(F.min("toxic").alias("toxic"))  # what a clean document holds is clean
    sample = [[r["string"] for r in found.where(F.col("toxic") == c).orderBy(F.xxhash64("string"), "string").limit(most_sentences).collect()] for c in (1, 0)]
    fitted = fit(telling, plain, *sample)
    if fitted is not None:
        model |= dict(zip(("index", "table", "bias"), fitted))
        shared = spark.sparkContext.broadcast(model)
        columns = [f"x{i}" for i in range(len(NONE))]

        def seen(batches):
            of = featured(shared.value)
            for pdf in batches:
                x = of(pdf["text"].tolist())
                yield pdf[["toxic"]].assign(**{c: x[:, i] for i, c in enumerate(columns)})

        got = rows.mapInPandas(seen, "toxic int, " + ", ".join(f"{c} double" for c in columns)).orderBy("toxic", *columns).toPandas()  # a few numbers for each of twice `most` documents
        model["doc"] = logistic(got[columns].to_numpy(), got["toxic"].to_numpy(float))
    common.dropped(rows)
    return model


def score(docs: DataFrame, model: dict, column: str = "toxicity") -> DataFrame:
    """docs with a further column of scores."""
    shared = docs.sparkSession.sparkContext.broadcast(model)  # by the number of landmarks, whatever the data

    def scored(batches):
        model = shared.value
        of = featured(model)
        for pdf in batches:
            x = np.c_[of(pdf["text"].tolist()), np.ones(len(pdf))]
            pdf[column] = 1 / (1 + np.exp(-np.clip(x @ model["doc"], -30, 30)))
            yield pdf

    from pyspark.sql.types import DoubleType, StructType

    return docs.mapInPandas(scored, StructType([*docs.schema.fields]).add(column, DoubleType()))


def fold(doc_id) -> F.Column:
    return F.crc32(F.col(doc_id).cast("string").cast("binary")) % 5


def query(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted for every document; labels of held-out rows are not read."""
    model = train(docs, labels.where(fold("doc_id") != 0))
    out = score(docs.select("doc_id", "text"), model, "score")
    return out.select("doc_id", (fold("doc_id") == 0).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"))
