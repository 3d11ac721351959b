"""Cases in which an operator once did less than its whole job."""

import random
from collections import Counter
import string
from itertools import combinations

from cellstream.llm import common, language_model, neardup, neighbours, pages, quality
from tests.conftest import SMALL

LOWER = str.maketrans(string.ascii_uppercase, string.ascii_lowercase)


def shingles(text):
    w = text.split()
    return {tuple(w[k : k + 5]) for k in range(len(w) - 4)}


def test_stage_groups_near_copies_from_four_fifths_on(spark):
    """Pairs of similarity 0.815 are near copies to the pipeline's stage, pairs of 0.774 are not."""
    rng = random.Random(8)
    rows = []
    for g in range(40):
        w = [f"g{g}w{k}" for k in range(200)]
        v = list(w)
        for at in range(4 if g < 30 else 5):
            v[10 + 35 * at + rng.randrange(10)] = f"g{g}e{at}"
        rows += [(2 * g, " ".join(w)), (2 * g + 1, " ".join(v))]
    sets = {i: shingles(t) for i, t in rows}
    near = [(a, b) for a, b in combinations(sets, 2) if 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b])]
    assert len(near) == 30 and all(100 * len(sets[a] & sets[b]) < 85 * len(sets[a] | sets[b]) for a, b in near)
    kept = {r["doc_id"] for r in neardup.keep_one(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert kept == set(sets) - {b for _, b in near}


def test_stage_equals_brute_force_at_four_fifths(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    sets = {r["doc_id"]: shingles(r["text"].translate(LOWER)) for r in docs.collect() if len((r["text"] or "").split()) >= 5}
    root = {i: i for i in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a, b in combinations(sets, 2):
        if 100 * len(sets[a] & sets[b]) >= 80 * len(sets[a] | sets[b]):
            x, y = sorted((find(a), find(b)))
            root[y] = x
    kept = {r["doc_id"] for r in neardup.keep_one(docs).select("doc_id").collect()}
    assert kept & set(sets) == {i for i in sets if find(i) == i}


def test_quality_judges_an_unusual_group_by_itself(spark):
    """A regular source of many signs and one of long words are kept whole; what is odd within a source is not."""
    rng = random.Random(9)
    word = lambda n: "".join(rng.choice("abcdefghijklmnop") for _ in range(n))

    def text(signs, length):
        w = [word(rng.randint(length - 2, length + 2)) for _ in range(100)]
        for k in range(signs):
            w[k] += "|"
        return " ".join(w)

    made = [("prose", text(0, 5)) for _ in range(4000)] + [("tables", text(rng.randint(40, 60), 5)) for _ in range(1000)] + [("long", text(0, 14)) for _ in range(1000)]
    strange = [("prose", text(12, 5)), ("prose", text(0, 9)), ("long", text(0, 5)), ("tables", text(100, 5).replace("|", "|||"))]
    rows = [(i, t, "en", s) for i, (s, t) in enumerate(made + strange)]
    got = {r["doc_id"]: r["kept"] for r in quality.query(spark.createDataFrame(rows, "doc_id long, text string, lang string, source string")).collect()}
    assert all(got[i] for i in range(len(made)))
    assert not any(got[i] for i in range(len(made), len(rows)))


def test_suffix_array_judges_blocks_beside_an_article(spark):
    """The main text beside a teaser article is kept; a plain notice that the host's pages repeat there is not."""
    page = "<body><article>teaser {0}</article><div>main text {0} of which each of the words {0} stands here only {0}</div><div>this site is made with care by the people of the house</div></body>"
    rows = [(i, f"http://h.org/{i}", page.format(f"n{i}")) for i in range(5)]
    got = {r["page_id"]: r["text"] for r in pages.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == {i: "teaser n{0}\nmain text n{0} of which each of the words n{0} stands here only n{0}".format(i) for i in range(5)}


def test_text_does_not_hang_on_class_names(spark):
    """Without its classes, ids and roles a page of the given table gives the same text: the suffix array finds its adverts."""
    import re

    given = spark.read.parquet(f"{SMALL.replace('sf0.001', 'sf0.01')}/pages.parquet")
    bare = re.compile(r"""\s(?:class|id|role)\s*=\s*("[^"]*"|'[^']*'|[^\s>]+)""")
    rows = [(r["page_id"], r["url"], bare.sub("", r["html"] or "")) for r in given.collect()]
    want = {r["page_id"]: r["text"] for r in pages.extract(given).collect()}
    got = {r["page_id"]: r["text"] for r in pages.extract(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()}
    assert got == want


def test_stretches_equal_brute_force(spark, monkeypatch):
    """Stretches on two distinct pages of a host, over hosts of several parts, as a plain count finds them."""
    monkeypatch.setattr(pages, "PART", 8)
    rng = random.Random(12)
    rows = [(f"h{i % 3}", i // 2, [" ".join(rng.choice("abc") for _ in range(rng.randint(1, 14))) for _ in range(rng.randint(0, 4))]) for i in range(120)]
    seen = {}
    for host, page, texts in rows:
        for t in texts:
            w = t.split()
            for k in range(max(1, len(w) - pages.GRAM + 1)):
                seen.setdefault((host, tuple(w[k : k + pages.GRAM])), set()).add(page)
    words = pages.common.WordHash()
    want = {(h, int(pages.grams(list(g), words).view("int64")[0])) for (h, g), p in seen.items() if len(p) > 1}
    got = pages.stretches(spark.createDataFrame(rows, "host string, page_id long, texts array<string>")).collect()
    assert {(r["host"], r["gram"]) for r in got} == want and len(got) == len(want)


def test_suffix_array_judges_blocks_of_articles(spark):
    """A plain notice in over half of a host's articles goes; copied articles, shared passages and headings stay."""
    rng = random.Random(5)
    text = lambda n: " ".join("".join(rng.choice("abcdefgh") for _ in range(6)) for _ in range(n))
    notice, passage, base = text(9), text(30), [text(40) for _ in range(4)]
    rows, want = [], {}

    def add(host, kept, inside=()):
        rows.append((len(rows), f"http://{host}/{len(rows)}", "<body><nav>Menu</nav><article>" + "".join(f"<p>{t}" for t in [*kept, *inside]) + "</article>"))
        want[rows[-1][0]] = "\n".join(kept)

    for i in range(20):
        add("notice.org", ["In short", text(30), text(20)], [notice] * (i % 5 > 0))
        add("passage.org", [text(30), *[passage] * (i % 5 < 2)])
        add("copies.org", [*base[:3], f"{base[3]} edition {i}"])
        add("same.org", [base[0], notice])
    for i in range(6):
        add("few.org", [text(10), notice])
    made = spark.createDataFrame(rows, "page_id long, url string, html string")
    assert {r["page_id"]: r["text"] for r in pages.extract(made.repartition(5)).collect()} == want


def test_notices_equal_brute_force(spark, monkeypatch):
    """Stretches of over half of a host's distinct articles, over hosts of one and of several parts, as a plain count finds them."""
    monkeypatch.setattr(pages, "PART", 128)
    rng = random.Random(6)
    often = [" ".join(f"w{k}n{i}" for i in range(8)) for k in range(4)]
    rows, held = [], {}
    for i in range(900):
        host = "big" if i < 600 else f"h{i % 9}"
        texts = [f"a{rng.randint(0, 500)} b c d e f g", *[t for k, t in enumerate(often) if rng.random() < (0.35, 0.6, 0.8, 0.95)[k]]]
        for _ in range(1 + (i % 7 == 0)):
            rows.append((i, f"http://{host}/{i}", "<article>" + "".join(f"<p>{t}" for t in texts) + "</article>"))
        held.setdefault(host, set()).add(tuple(texts))
    words, want = pages.common.WordHash(), set()
    for host, articles in held.items():
        n = Counter(g for a in articles for g in {tuple(t.split()[k : k + pages.GRAM]) for t in a for k in range(len(t.split()) - pages.GRAM + 1)})
        want |= {(host, int(pages.common.windows(pages.short_hashes(" ".join(g), words), pages.GRAM).view("int64")[0])) for g, c in n.items() if 2 * c > len(articles) + pages.PRIOR}
    made = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3)
    got = pages.notices(pages.common.staged(pages.parsed(pages.common.numbered(made)), "pages")).collect()
    assert {(r["host"], g) for r in got for g in r["heavy"]} == want and sum(len(r["heavy"]) for r in got) == len(want) > 30


def test_heavy_keys_are_parted_without_an_outer_join(spark):
    """A key with nine tenths of the rows is met by a broadcast; no join gives all rows back only to part them."""
    rows = spark.createDataFrame([(i, 7 if i % 10 else i, "x") for i in range(2000)] + [(-1, None, "x")], "row_id long, key long, word string")
    keys = spark.createDataFrame([(7, "x", 1800), (20, "x", 1), (30, "y", 1), (None, "x", 5)], "key long, word string, n long")
    for on in (["key"], ["key", "word"]):
        got = common.matched(rows, keys if len(on) > 1 else keys.drop("word"), on, "n > 1000")
        want = sorted((i, 7, 1800) for i in range(2000) if i % 10) + [(20, 20, 1)] + ([(30, 30, 1)] if len(on) == 1 else [])
        assert sorted((r["row_id"], r["key"], r["n"]) for r in got.collect()) == sorted(want)
        plan = got._jdf.queryExecution().executedPlan().toString()
        assert "LeftOuter" not in plan and "BroadcastHashJoin" in plan


def test_every_training_document_gives_gradients(spark, monkeypatch):
    """The tokens that the copies were trained on, over all rounds, are those of all training documents."""
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text")
    seen, averaged = [], language_model.averaged

    def kept(copies, shards):
        got = averaged(copies, shards)
        seen.append(got[0] if got else 0)
        return got

    monkeypatch.setattr(language_model, "averaged", kept)
    monkeypatch.setattr(language_model, "SHARD", 100_000)
    language_model.trained(docs, language_model.Network.initial([5, 3], 9), {b"\n": 0, b"the": 1})
    assert sum(seen) == sum(len(language_model.word_list(r["text"])) for r in docs.collect())


def test_training_makes_few_array_calls():
    """A span's cost is bounded in calls, with a whole vocabulary too: most of them once a span, not once a class."""
    import sys

    import numpy as np

    rng = np.random.default_rng(3)
    net = language_model.Network.initial([9] * language_model.VOCABULARY, 9)
    docs = [np.r_[rng.integers(1, language_model.VOCABULARY + 1, 99), 0].astype(np.int32) for _ in range(language_model.TRAIN_LANES)]
    calls = [0]
    sys.setprofile(lambda frame, event, arg: calls.__setitem__(0, calls[0] + (event in ("call", "c_call"))))
    try:
        seen = language_model.fit_copy(net, docs, 0)
    finally:
        sys.setprofile(None)
    assert seen == sum(map(len, docs))
    assert calls[0] * language_model.SPAN / 100 < 800  # 673; 1,085 when each class had its own


def test_step_follows_the_gradient():
    """The first step of Adam moves each weight against the sign of its gradient, as differences of the score give it."""
    import numpy as np

    rng = np.random.default_rng(4)
    docs = [np.r_[rng.integers(1, 6, n), 0].astype(np.int32) for n in (6, 9, 13, 13)]
    before = language_model.Network.initial([9, 8, 7, 6, 5], 3)
    after = language_model.Network(before.size, before.flat.copy())
    language_model.fit_copy(after, docs, 0)
    for name in ("embed", "wx", "wh", "b", "wc", "bc", "wo", "bo"):
        p, tried = getattr(before, name), 0
        for _ in range(25):
            at = tuple(rng.integers(0, k) for k in p.shape)
            kept, e = p[at], np.float32(0.05)
            p[at] = kept + e
            up = language_model.log_probabilities(before, docs, 0).sum()
            p[at] = kept - e
            slope = (up - language_model.log_probabilities(before, docs, 0).sum()) / (2 * e)
            p[at] = kept
            if abs(slope) > 0.02:
                assert np.sign(getattr(after, name)[at] - kept) == np.sign(slope), name
                tried += 1
        assert tried, name


ODD_TEXTS = ["  A b\tc\n", None, "", " ", "x", "\x0b\x0cÀ É\x85z q\xa0  w\x1c\x1dk", "a\rb a", "a\n\na"]


def test_words_in_arrow_are_those_of_word_list():
    """Texts are split, lower-cased and numbered in bulk, as word_list does it one by one; a slice and long offsets too."""
    import pyarrow as pa

    for texts in (pa.array(ODD_TEXTS), pa.array(ODD_TEXTS).slice(1, 6), pa.array(ODD_TEXTS, pa.large_string()), pa.array(["", None], pa.string())):
        want = [language_model.word_list(x.as_py()) for x in texts]
        words, n = language_model.words_of(texts)
        assert words.to_pylist() == [x for w in want for x in w[:-1]] and n.tolist() == [len(w) - 1 for w in want]
        ids, starts = language_model.numbers_of(words, n, pa.array([b"a", b"b", b"\n"], pa.binary()), 9, 2)
        assert ids.tolist() == [{b"a": 0, b"b": 1, b"\n": 2}.get(x, 9) for w in want for x in w]
        assert starts.tolist() == [sum(map(len, want[:i])) for i in range(len(want))]


def test_words_are_counted_before_they_are_rows(spark):
    """A word that a slice of texts repeats leaves it as one row with its count, not as a row for each place."""
    docs = spark.createDataFrame([(i, t) for i, t in enumerate(ODD_TEXTS)], "doc_id long, text string")
    got = language_model.counted(docs)
    want = {}
    for t in ODD_TEXTS:
        for w in language_model.word_list(t):
            want[w] = want.get(w, 0) + 1
    assert {bytes(r["word"]): r["c"] for r in got.collect()} == want
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "MapInArrow" in plan and "Generate" not in plan


def test_a_shard_is_trained_on_without_word_lists(monkeypatch):
    """A shard's network is that of fit_copy on its documents by hash, and no text becomes a list of Python's words."""
    import numpy as np
    import pyarrow as pa

    ids = {b"\n": 0, b"a": 1, b"b": 2}
    net = language_model.Network.initial([5, 3, 2], 4)
    order = sorted(range(len(ODD_TEXTS)), key=lambda i: i * 5 % 8)
    plain = language_model.Network(net.size, net.flat.copy())
    docs = [np.array([ids.get(w, net.size) for w in language_model.word_list(ODD_TEXTS[i])], np.int32) for i in order]
    seen = language_model.fit_copy(plain, docs, 0)

    def never(text):
        raise AssertionError("a text was split by itself")

    monkeypatch.setattr(language_model, "word_list", never)
    shared = type("Shared", (), {"value": (net.size, net.flat.copy(), ids)})
    table = pa.table({"doc_id": range(8), "text": [t or "" for t in ODD_TEXTS], "h": [i * 5 % 8 for i in range(8)], "shard": [7] * 8})
    got = language_model.trainer(shared)(table).to_pylist()
    assert [(r["shard"], r["n"]) for r in got] == [(7, seen)] and seen == sum(map(len, docs))
    assert np.allclose(np.array(got[0]["flat"]) / seen, plain.flat, atol=1e-6)


def test_rare_words_meet_their_counts(spark, monkeypatch):
    """Words beyond the head are counted in each text and joined; known words and the base score stay what they are."""
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text").limit(60)
    want = {r["doc_id"]: (r["n_tokens"], r["n_known"], round(r["base_score"], 6)) for r in language_model.query(docs).collect()}
    monkeypatch.setattr(language_model, "HEAD", 50)
    assert {r["doc_id"]: (r["n_tokens"], r["n_known"], round(r["base_score"], 6)) for r in language_model.query(docs).collect()} == want


def test_verified_vectors_are_those_that_collide_often(monkeypatch):
    """At the one radius left, a vector is verified where it lies in THRESHOLD windows: as a plain count of all values says."""
    import numpy as np

    monkeypatch.setattr(neighbours, "RADII", (1.1, 3.0))
    rng = np.random.default_rng(3)
    x = rng.standard_normal((3000, 16))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    ids = np.arange(3000)
    axes = np.random.default_rng(20).standard_normal((17, neighbours.PROJECTIONS))
    px = np.c_[x, np.sqrt(1 - np.minimum((x * x).sum(1), 1))] @ axes
    for i in range(5):
        near = np.abs(px - x[i] @ axes[:16]) <= 1.1
        often = np.flatnonzero((near.sum(1) >= neighbours.THRESHOLD) & (ids != i))
        score = np.sort(x[often] @ x[i])[::-1]
        assert len(often) > 5 and 2 - 2 * score[4] < 1.1**2  # so that no wider window is opened
        (_, found, s), verified = neighbours.search_block(ids, x, ids[i : i + 1], x[i : i + 1], 1.0, 5)
        assert verified == len(often) and np.allclose(s, score[:5])
