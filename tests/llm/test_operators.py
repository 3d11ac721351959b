"""Each operator against a plain version of itself, and its defined results in odd cases."""

import base64
import hashlib
import random
import re
import string
import zlib
from collections import Counter, defaultdict
from itertools import combinations

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from tokenizers import Tokenizer

from cellstream.llm import byte_bpe, language_model, licenses, neardup, neighbours, packing, pages, quality, registry, substrings, toxicity
from tests.conftest import SMALL

LOWER = str.maketrans(string.ascii_uppercase, string.ascii_lowercase)
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, n_words string, row_id string, score string, key string"


def words(text):
    return re.findall(r"[^\x20\x09-\x0D]+", text or "")


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty, blank, repeated, long and clashing columns."""
    rng = random.Random(3)
    vocabulary = ["".join(rng.choice("abcdefgh") for _ in range(rng.randint(1, 7))) for _ in range(3000)]
    text = lambda n: " ".join(rng.choice(vocabulary) for _ in range(n))
    base, passage = text(120), text(60)
    near = base.split()
    near[60] = "changed"
    rows = [(0, None, None, None), (1, "", "en", "a"), (2, " \n\t ", "en", None), (3, base, "en", "a"), (3, base, "en", "a"), (4, base, "fr", "a"), (5, " ".join(near), "en", "b"), (6, text(40) + " " + passage + "\n" + text(30), "en", "b"), (7, text(10) + "\t" + passage + "  " + text(50), None, "b"), (None, base, "en", "a"), (8, "one two", "en", "a"), (9, "One\x85two é İ K", "en", "a"), (10, "word " * 500, "en", "a"), (11, "x" * 3000 + " é" * 200, "en", "a"), (12, "Released under the MIT License.\nLicensed under CC BY-NC 4.0.", "en", "a"), (13, passage, "en", "a")]
    rows += [(20 + i, text(rng.randint(0, 300)), "en", "c") for i in range(30)]
    return spark.createDataFrame([(i, t, a, b, len(t or ""), "clash", "clash", "clash", "clash") for i, t, a, b in rows], SCHEMA)


@pytest.fixture(scope="module")
def empty(odd):
    return odd.limit(0)


def small(spark, name):
    return spark.read.parquet(f"{SMALL}/{name}.parquet")


# 1


def test_licenses_odd(odd, empty):
    got = {r["doc_id"]: r for r in licenses.scan(odd).collect()}
    assert got[12]["base_labels"] == "cc-by,mit" and got[12]["labels"] == "cc-by,cc-by-nc-notice,mit,mit-notice" and got[12]["score"] == 1.0
    assert (got[12]["n_base"], got[12]["first_word"], got[12]["last_word"], got[12]["n_words"]) == (2, 3, 7, 12)
    assert (got[0]["n_words"], got[0]["labels"], got[0]["first_word"]) == (0, "", None)
    assert licenses.scan(empty).count() == 0


def test_licenses_filters_are_exact(spark):
    """Random blocks of template words: the filtered join finds what comparing every pair finds."""
    rng = random.Random(1)
    pool = sorted({w for _, t in licenses.TEMPLATES for w in t.split()}) + ["other", "more"]
    texts = []
    for i in range(300):
        lines = [" ".join(rng.choice(pool) for _ in range(rng.randint(1, 12)))]
        t = rng.choice(licenses.TEMPLATES)[1].split()
        lines.append(" ".join(w for w in t if rng.random() < 0.85))
        texts.append((i, "\n".join(lines)))
    got = {r["doc_id"]: set(r["labels"].split(",")) - {""} - set(licenses.PHRASES.values()) for r in licenses.scan(spark.createDataFrame(texts, "doc_id long, text string")).collect()}
    for i, text in texts:
        want = set()
        for line in text.split("\n"):
            b = set(re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", line))
            want |= {label for label, t in licenses.TEMPLATES if len(b & set(t.split())) >= licenses.need(len(set(t.split())))}
        assert got[i] == want


# 2


def subsequences(x):
    """Plain features of a string: four symbols within SPAN, weighted by their gaps."""
    out = Counter()
    for i, j, k, n in combinations(range(len(x)), 4):
        if n - i < toxicity.SPAN:
            out[x[i], x[j], x[k], x[n]] += toxicity.DECAY ** (n - i - 3)
    return out


def test_kernel_table_equals_landmark_expansion():
    """Folded weights give the same value as the sum of plain kernels with the landmarks; letters are kept apart."""
    landmarks = [" idiot ", " clown ", " niño ", " größ", " thing "]
    index = toxicity.Index(landmarks)
    c = np.array([0.5, -0.2, 0.3, 0.1, -0.4])
    table = np.zeros(index.size, np.float32)
    table[index.places] = index.z.T @ c
    words = ["idiot", "idxiot", "idiiot", "clown", "nino", "niño", "größer", "großer", "a", "thing", "字字字字", "moron" * 12]

    def plain(word):
        best = []
        for p in toxicity.pieces(word):
            f, own = subsequences(p), 0.0
            for w, l in zip(c, landmarks):
                z = subsequences(l)
                own += w * sum(v * z[k] for k, v in f.items()) / sum(v * v for v in z.values()) ** 0.5
            best.append(own / toxicity.norm(len(p)))
        return max(best)

    got = toxicity.margins(index, table, 0.0, words)
    assert np.allclose(got, [plain(w) for w in words], atol=1e-5)
    rows = toxicity.kernel_rows(index, words[:-1]) @ c
    assert np.allclose(rows, got[:-1], atol=1e-5)
    near = dict(zip(words, toxicity.kernel_rows(index, words)))
    assert near["idxiot"][0] > 0.3 > near["clown"][0] and near["niño"][2] > 2 * near["nino"][2] and near["größer"][3] > 2 * near["großer"][3]


def test_tokens_of_sentences():
    assert toxicity.sentences("You ***IDI.OT###! i d i o t yes.\nNo 1d1ot here.") == [["you", "idiot"], ["idiot", "yes"], ["no", "idiot", "here"]]
    assert toxicity.sentences(None) == toxicity.sentences(" \n .. ") == []
    assert toxicity.tokens(["", "a.", None]).count(chr(toxicity.MARK)) == 3


def test_score_is_the_highest_sentences(spark):
    """The query's scores equal a plain reading of its model, sentence by sentence and word by word."""
    d = SMALL.replace("sf0.001", "sf0.01")
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    model = toxicity.train(docs, labels)
    few = docs.where("doc_id % 7 = 0")
    got = {r["doc_id"]: r["toxicity"] for r in toxicity.score(few.select("doc_id", "text"), model).collect()}
    for r in few.collect():
        tops = [max(toxicity.margins(model["index"], model["table"], model["bias"], s)) for s in toxicity.sentences(r["text"])]
        tops = sorted((min(max(t, -3), 3) for t in tops), reverse=True)
        x = [*(tops[:2] + [-3.0, -3.0])[:2], np.log1p(sum(t > 0 for t in tops)), np.log1p(len(tops)), 1.0]
        assert abs(got[r["doc_id"]] - 1 / (1 + np.exp(-np.dot(x, model["doc"])))) < 1e-6


def test_toxicity_held_out(spark):
    d = SMALL.replace("sf0.001", "sf0.01")
    docs, labels = spark.read.parquet(f"{d}/documents.parquet"), spark.read.parquet(f"{d}/labels.parquet")
    got = {r["doc_id"]: r for r in toxicity.query(docs, labels).collect()}
    assert len(got) == docs.count()
    pairs = [(got[r["doc_id"]]["score"], r["toxic"]) for r in labels.collect() if got[r["doc_id"]]["held_out"]]
    pos, neg = [s for s, t in pairs if t], [s for s, t in pairs if not t]
    auc = np.mean([(a > b) + 0.5 * (a == b) for a in pos for b in neg])
    assert auc > 0.75
    assert np.mean([t >= 0.5 for t in neg]) < 0.02
    assert all(r["held_out"] == (zlib.crc32(str(i).encode()) % 5 == 0) and 0 <= r["score"] <= 1 for i, r in got.items())


def test_toxicity_odd(spark, odd, empty):
    none = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    assert {round(r["score"], 6) for r in toxicity.query(odd, none).collect()} == {0.5}
    one = spark.createDataFrame([(20, 1, 0), (21, 1, 0), (None, 1, 1)], "doc_id long, quality int, toxic int")
    assert toxicity.query(odd, one).count() == odd.count()
    assert toxicity.query(empty, one).count() == 0


# 3


def near_brute(rows, least=85):
    sets = []
    for i, t in rows:
        w = words((t or "").translate(LOWER))
        sets.append((i, frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])))
    root = {i: i for i, _ in sets if i is not None}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for (a, s), (b, t) in combinations([x for x in sets if x[0] is not None and x[1]], 2):
        if 100 * len(s & t) >= least * len(s | t):
            a, b = sorted((find(a), find(b)))
            root[b] = a
    return sorted((i if i is not None else -1, len(s), find(i) if i is not None else -1) for i, s in sets)


def test_neardup(spark, odd, empty):
    rows = [(r["doc_id"], r["text"]) for r in odd.collect()]
    got = neardup.grouped(odd).collect()
    assert sorted((r["doc_id"] if r["doc_id"] is not None else -1, r["n_shingles"], r["component_id"] if r["component_id"] is not None else -1) for r in got) == near_brute(rows)
    assert all(r["kept"] == (r["doc_id"] is None or r["doc_id"] == r["component_id"]) for r in got)
    assert neardup.grouped(empty).count() == 0
    kept = neardup.keep_one(odd)
    assert kept.columns == odd.columns and 4 not in {r["doc_id"] for r in kept.collect()}


def test_neardup_ids_on_several_texts(spark):
    """An id that stands on two texts ties what is near either; a DuckDB twin agrees."""
    import duckdb

    rng = random.Random(6)
    a, b, c = ([f"{x}{rng.randrange(10**6)}" for _ in range(80)] for x in "abc")
    near = lambda w: " ".join([*w[:79], "changed"])
    rows = [(1, " ".join(a)), (1, " ".join(b)), (2, near(a)), (3, near(b)), (4, " ".join(c)), (4, ""), (5, near(c)), (6, " ".join(c)), (7, ""), (7, None)]
    got = sorted(map(tuple, neardup.grouped(spark.createDataFrame(rows, "doc_id long, text string")).collect()))
    documents = __import__("pandas").DataFrame(rows, columns=["doc_id", "text"])  # noqa: F841
    assert got == sorted(duckdb.sql(neardup.oracle()).fetchall())
    assert {(i, k) for i, _, k, _ in got} == {(1, 1), (2, 1), (3, 1), (4, 4), (5, 4), (6, 4), (7, 7)}


def test_neardup_groups_of_edits(spark):
    """Chains and clouds of edited copies, some linked only through others."""
    rng = random.Random(5)
    rows, i = [], 0
    for g in range(6):
        w = [f"g{g}w{k}" for k in range(150)]
        for _ in range(25):
            v = list(w)
            for _ in range(rng.randint(0, 4)):
                v[rng.randrange(150)] = f"e{rng.random()}"
            if rng.random() < 0.3:
                w = v
            rows.append((i, " ".join(v)))
            i += 1
    rng.shuffle(rows)
    got = neardup.grouped(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted((r["doc_id"], r["n_shingles"], r["component_id"]) for r in got) == near_brute(rows)


# 4


def test_language_model_counts_and_base(spark, odd):
    import math

    got = language_model.query(odd).collect()
    docs = [(r["doc_id"], words((r["text"] or "").translate(LOWER)) + ["\n"]) for r in odd.collect()]
    held = lambda i: i is None or zlib.crc32(str(i).encode()) % 7 == 2
    c = Counter(w for i, ws in docs if not held(i) for w in ws)
    n, v = sum(c.values()), len(c)
    want = sorted((-1 if i is None else i, len(ws), sum(c[w] > 0 for w in ws), n, round(sum(math.log10((c[w] + 1) / (n + v + 1)) for w in ws), 4), held(i)) for i, ws in docs)
    assert sorted((-1 if r["doc_id"] is None else r["doc_id"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 4), r["held_out"]) for r in got) == want
    assert all(r["score"] < 0 for r in got)


def test_language_model_follows_the_documents_alone(spark):
    """One, four and sixteen partitions, in any order, give the same scores."""
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text")
    got = [{r["doc_id"]: (r["base_score"], r["score"]) for r in language_model.query(d).collect()} for d in (docs.coalesce(1), docs.repartition(4), docs.orderBy("text").repartition(16))]
    for other in got[1:]:
        assert max(abs(a - b) / max(1, abs(a)) for i in got[0] for a, b in zip(got[0][i], other[i])) < 1e-5


def test_copies_are_averaged_by_tokens(spark):
    rng = np.random.default_rng(3)
    rows = [(i, int(rng.integers(1, 50)), rng.standard_normal(5).tolist()) for i in range(70)]
    n, flat = language_model.averaged(spark.createDataFrame(rows, "shard long, n long, flat array<double>").repartition(5), 70)
    assert n == sum(r[1] for r in rows) and np.allclose(flat, np.sum([r[2] for r in rows], 0))


def test_lanes_hold_long_texts():
    """One document far longer than the others does not make every lane as long."""
    docs = [np.zeros(50_000, np.int32), *[np.zeros(10, np.int32)] * 300]
    inputs, _, _, owner = language_model.lanes(docs, 256, 0)
    assert inputs.size <= 5 * sum(map(len, docs)) and sorted(set(owner.ravel().tolist()) - {-1}) == list(range(301))


def test_language_model_empty(spark, empty, odd):
    assert language_model.query(empty).count() == 0
    nothing = odd.where("doc_id is null")
    assert nothing.count() == 1 and language_model.query(nothing).first()["train_tokens"] == 0


def test_network_probabilities_sum_to_one_and_gradient():
    net = language_model.Network.initial([5, 4, 3] * 30, 10)
    h = np.random.default_rng(0).standard_normal((4, language_model.STATE)).astype(np.float32)
    total = sum(np.exp(net.output(h, np.full(4, w, np.int32))[0]) for w in range(net.size + 1))
    assert np.allclose(total, 1, atol=1e-4)
    g = language_model.Network(net.size)
    y = np.array([0, 70, 90, 3], np.int32)
    _, back = net.output(h, y, g)
    e = 1e-2
    for name, at in (("wc", (2, 1)), ("wo", (70, 3)), ("bo", (0,))):
        p = getattr(net, name)
        p[at] += e
        up = -net.output(h, y)[0].sum()
        p[at] -= 2 * e
        down = -net.output(h, y)[0].sum()
        p[at] += e
        assert abs((up - down) / (2 * e) - getattr(g, name)[at]) < 2e-2
    h[1, 4] += e
    up = -net.output(h, y)[0].sum()
    h[1, 4] -= 2 * e
    assert abs((up + net.output(h, y)[0].sum()) / (2 * e) - back[1, 4]) < 2e-2


def test_state_is_carried_over_windows_and_lanes():
    """A document's score does not depend on the lanes beside it, nor on windows."""
    net = language_model.Network.initial([9, 8, 7, 6], 5)
    rng = np.random.default_rng(1)
    docs = [np.r_[rng.integers(0, 5, n), 0].astype(np.int32) for n in (3, 200, 70, 0, 131)]
    together = language_model.log_probabilities(net, docs, 0)
    alone = [language_model.log_probabilities(net, [d], 0)[0] for d in docs]
    assert np.allclose(together, alone, rtol=1e-4)


def test_training_helps():
    rng = np.random.default_rng(2)
    docs = []
    for _ in range(60):
        start = rng.integers(0, 8)
        docs.append(np.r_[(start + np.arange(40)) % 8 + 1, 0].astype(np.int32))
    counts = np.bincount(np.concatenate(docs), minlength=9).tolist()
    net = language_model.Network.initial(counts, 0)
    before = language_model.log_probabilities(net, docs, 0).sum()
    for _ in range(6):
        language_model.fit_copy(net, docs, 0)
    assert language_model.log_probabilities(net, docs, 0).sum() > 0.8 * before


# 5 and 10


def test_boundaries_match_the_library():
    ranks = byte_bpe.load_ranks(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    own = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    coder = byte_bpe.Coder(public_tokenizers.path("byte_bpe_multi_50k.tiktoken"))
    rng = random.Random(9)
    parts = list("ab'stredmvl  \n\t12é $!") + ["'s", "'re", "'ll", " '", "字", "👍", " ", " ", "𞤀"]
    texts = ["".join(rng.choice(parts) for _ in range(rng.randint(0, 16))) for _ in range(4000)]
    texts += ["a" * 700, " " * 500, "ab" * 300 + "é" * 40, "", "<|endoftext|>"]
    for t in texts:
        ids = coder.encode(t)
        assert ids == own.encode_ordinary(t), repr(t)
        assert coder.decode(ids) == t.encode()
        assert "".join(t[a:b] for a, b, _ in coder.offsets(t)) == t


def test_bpe_digests(spark, odd, empty):
    path = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    own = tiktoken.Encoding("t", pat_str=public_tokenizers.PATTERN, mergeable_ranks={base64.b64decode(a): int(b) for a, b in map(bytes.split, open(path, "rb"))}, special_tokens={})
    want = []
    for r in odd.collect():
        t = r["text"] or ""
        ids = own.encode_ordinary(t)
        want.append((r["doc_id"] or -1, len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest(), hashlib.sha256(t.encode()).hexdigest()))
    assert sorted((r[0] or -1, *r[1:]) for r in map(tuple, byte_bpe.digests(odd, path).collect())) == sorted(want)
    assert byte_bpe.digests(empty, path).count() == 0


def test_packing(spark, odd, empty):
    path = public_tokenizers.path("byte_bpe_50k.json")
    extra = odd.unionByName(spark.createDataFrame([(99, "a <|endoftext|> b " * 900, *[None] * 7)], SCHEMA))
    rows = packing.pack(extra, path).collect()
    own = Tokenizer.from_file(path)
    want = Counter()
    for r in extra.collect():
        ids = np.array(own.encode(r["text"] or "", add_special_tokens=False).ids + [0], "<u4")
        for at in range(0, len(ids), 1024):
            want[r["doc_id"], at, len(ids[at : at + 1024]), zlib.crc32(ids[at : at + 1024].tobytes()), len(ids)] += 1
    assert Counter((r["doc_id"], r["start"], r["length"], r["ids_crc32"], r["doc_tokens"]) for r in rows) == want
    sequences = defaultdict(list)
    for r in rows:
        sequences[r["sequence_id"]].append((r["offset"], r["length"]))
    for s in sequences.values():
        at = 0
        for offset, length in sorted(s):
            assert offset == at
            at += length
        assert at <= 1024
    assert sorted(sequences) == list(range(len(sequences)))
    assert packing.pack(empty, path).count() == 0


def test_patterns_place_every_length():
    rng = random.Random(2)
    histogram = Counter(rng.randint(1, 1024) for _ in range(5000))
    packs = packing.patterns(histogram)
    placed = Counter()
    for pack, n in packs:
        assert sum(pack) <= 1024
        for x in pack:
            placed[x] += n
    assert placed == histogram
    tokens = sum(k * v for k, v in histogram.items())
    assert tokens / (1024 * sum(n for _, n in packs)) > 0.97


# 6


def test_quality_counts(odd, empty):
    got = Counter((r["doc_id"], r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"], r["base_failed"]) for r in quality.query(odd).collect())
    want = Counter()
    for r in odd.collect():
        t = r["text"] or ""
        w = words(t)
        lines = [x for x in t.split("\n") if words(x)]
        seen = Counter(tuple(w[i : i + 3]) for i in range(len(w) - 2))
        rep = len({i + j for i in range(len(w) - 2) if seen[tuple(w[i : i + 3])] > 1 for j in range(3)})
        want[r["doc_id"], len(w), sum(map(len, w)), sum(t.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), rep, len(w) < 50 or 100 * rep > 50 * len(w)] += 1
    assert got == want
    assert quality.query(empty).count() == 0
    kept = quality.filtered(odd)
    assert kept.columns == odd.columns and kept.count() and {r["n_words"] for r in kept.collect()} == {"clash"}


def test_quality_agrees_with_labels(spark):
    """On labelled rows that pass the base rules the verdict is the label."""
    d = SMALL.replace("sf0.001", "sf0.01")
    got = quality.query(spark.read.parquet(f"{d}/documents.parquet")).join(spark.read.parquet(f"{d}/labels.parquet"), "doc_id").where("not base_failed")
    assert got.where("kept <> (quality = 1)").count() == 0


# 7


def test_neighbours_recall_and_odd(spark):
    rng = np.random.default_rng(0)
    x = rng.standard_normal((600, 16))
    x[:, 0] *= 3
    x[300:400] = x[300] + 0.01 * rng.standard_normal((100, 16))
    rows = [(i, [float(a) for a in v], 0) for i, v in enumerate(x)]
    rows += [(1000, None, 0), (1020, [0.0] * 16, 0), (1040, [float("nan")] * 16, 0), (1060, [None] + [1.0] * 15, 0), (1080, [1.0] * 3, 0), (1100, [], 0), (None, [1.0] * 16, 0)]
    table = spark.createDataFrame(rows, "vec_id long, embedding array<double>, rank int")
    got = defaultdict(list)
    for r in neighbours.query(table).collect():
        got[r["query_id"]].append((r["rank"], r["vec_id"], r["score"]))
    assert set(got) == set(range(0, 600, 20))
    hits = 0
    for i, found in got.items():
        s = x @ x[i]
        s[i] = -np.inf
        want = np.lexsort((np.arange(600), -s))[:20]
        hits += len({v for _, v, _ in found} & set(want.tolist()))
        found.sort()
        assert [r for r, _, _ in found] == list(range(1, 21))
        assert all(abs(sc - x[i] @ x[v]) < 1e-9 for _, v, sc in found)
    assert hits / (20 * len(got)) >= 0.95
    few = neighbours.query(table.where("vec_id < 5"))
    assert few.count() == 4
    assert neighbours.query(table.limit(0)).count() == 0


# 8


def cut_brute(rows, width=35):
    seen = Counter()
    for _, t in rows:
        w = words(t)
        seen.update(tuple(w[k : k + width]) for k in range(len(w) - width + 1))
    out = []
    for i, t in rows:
        w = words(t)
        gone = [False] * len(w)
        for k in range(len(w) - width + 1):
            if seen[tuple(w[k : k + width])] > 1:
                gone[k : k + width] = [True] * width
        kept = [x for x, g in zip(w, gone) if not g]
        out.append((i if i is not None else -1, len(w), len(w) - len(kept), hashlib.sha256(" ".join(kept).encode()).hexdigest()))
    return sorted(out)


def test_substrings(odd, empty):
    got = substrings.digest(odd).collect()
    rows = [(r["doc_id"], r["text"]) for r in odd.collect()]
    assert sorted((r[0] if r[0] is not None else -1, *r[1:]) for r in map(tuple, got)) == cut_brute(rows)
    assert substrings.digest(empty).count() == 0
    cut = substrings.cut(odd)
    assert cut.columns == odd.columns and cut.count() == odd.count()
    kept = {i: n - m for i, n, m, _ in cut_brute(rows)}
    assert all(len(words(r["text"])) == kept[-1 if r["doc_id"] is None else r["doc_id"]] for r in cut.collect())


def test_rolling_hash_equals_direct():
    from cellstream.llm.common import mix

    h = mix(np.arange(1, 60, dtype=np.uint64))
    got = substrings.rolling(h, 7)
    direct = []
    base = 0x9E3779B97F4A7C15
    for i in range(len(h) - 6):
        total = sum(int(h[i + j]) * pow(pow(base, -1, 2**64), j, 2**64) for j in range(7)) % 2**64
        direct.append(total)
    want = mix(np.array(direct, np.uint64) + np.uint64(7))
    assert (got == want).all()


def test_substrings_hold_when_splits_change(spark, tmp_path):
    """Rows keep their numbers when the scan is split otherwise between the operator's reads."""
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text")
    docs.unionAll(docs.selectExpr("doc_id + 1000000 as doc_id", "reverse(text) as text")).coalesce(1).write.parquet(f"{tmp_path}/docs")
    names = ["spark.sql.files.openCostInBytes", "spark.sql.leafNodeDefaultParallelism"]
    before = {n: spark.conf.get(n, None) for n in names}
    read = lambda: substrings.digest(spark.read.parquet(f"{tmp_path}/docs"))
    want = sorted(map(tuple, read().collect()))
    try:
        spark.conf.set(names[0], "1024")
        spark.conf.set(names[1], "2")
        later = read()
        spark.conf.set(names[1], "16")
        assert sorted(map(tuple, later.collect())) == want
    finally:
        for n, v in before.items():
            spark.conf.unset(n) if v is None else spark.conf.set(n, v)
    assert sum(r[2] for r in want) > 0


# 9


PAGE = """<!doctype html><html><head><title>T</title><style>p{}</style><script>var a="</p>";</script></head><body>
<header>Site name</header><nav><ul><li><a href=x>Menu</a></li></ul></nav><div class="cookie-notice">We use cookies</div><!-- c --><div class="ad">Buy</div>
<article><h1>A &amp; B</h1><p><b>First  line<br>same&nbsp;block<p>Second &lt;x&gt;</p><aside>Also</aside><form><p>Mail</p><button>Go</button></form><div id="comments"><p>Bad take</p></div><p>Last</article>
<footer>Foot</footer></body>"""


def test_pages(spark):
    rows = [(1, "http://h.org/1", PAGE), (2, "http://h.org/2", None), (3, None, ""), (None, "http://h.org/1", PAGE), (4, "x", "<p>only"), (4, "x", "<p>only")]
    rows += [(10 + i, f"http://o.org/{i}", f"<body><div>Welcome to the site of o org enjoy reading</div><div>story number {i} with {i * 7} and {i * 13} parts that nobody {i * 17} repeats</div></body>") for i in range(6)]
    got = Counter((r["page_id"], r["text"], r["n_chars"]) for r in pages.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect())
    text = "A & B\nFirst line same block\nSecond <x>\nLast"
    assert got[1, text, len(text)] == 1 and got[None, text, len(text)] == 1
    assert got[2, "", 0] == 1 and got[3, "", 0] == 1 and got[4, "only", 4] == 2
    for i in range(6):
        own = f"story number {i} with {i * 7} and {i * 13} parts that nobody {i * 17} repeats"
        assert got[10 + i, own, len(own)] == 1
    assert pages.extract(small(spark, "pages").limit(0)).count() == 0


def test_pages_in_marked_wrappers():
    kept = lambda page: [t for s, t in pages.blocks(page) if s == pages.KEPT]
    assert kept("<body><div class='with-sidebar'><nav>n</nav><main><p>a</p><div class=share>s</div></main></div>") == ["a"]
    assert kept("<body><div class='with-sidebar'><article>a</article><p>x</div>") == ["a"]
    assert kept("<body><article>a</article><div class=related><article>b</article></div>") == ["a"]
    assert kept("<article>a<p class=notice>n<p>b<section id='comments'><article>c</article></section>d</article>") == ["a", "b", "d"]


def test_suffix_order_brings_equal_stretches_together():
    rng = np.random.default_rng(0)
    t = rng.integers(0, 3, 400)
    rank = pages.suffix_order(t, pages.GRAM)
    depth = 8
    keys = [tuple(t[i : i + depth]) for i in range(len(t))]
    order = np.argsort(rank, kind="stable")
    assert [keys[i] for i in order] == sorted(keys)


# the registry


def test_every_operator_is_registered():
    names = list(registry.queries())
    assert [sum(n.startswith(f"op{k}_") for n in names) for k in range(1, 11)] == [1] * 10 and "pipeline" in names
    assert set(registry.oracle_sql()) <= set(names)
