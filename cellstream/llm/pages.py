"""Main text of web pages: markup structure, and a host's suffix array that judges what structure does not drop.

A page is cut into blocks at block-level tags. Structure gives each a state: blocks in menus, headers, footers,
sidebars, notices, adverts, forms, scripts, styles and comments go, the latter also where a class, id or role says
so; blocks in an article (or main part) are kept unless the array speaks against them; all other blocks stay open,
beside an article too, which may be a mere teaser of the main text. For open blocks, the streams of open and dropped blocks of a host's pages are concatenated, with a
separator that occurs once after each block, and a suffix array, sorted to depth GRAM, brings equal stretches together. A
stretch of GRAM tokens or more on two distinct pages of the host covers its tokens (longer repeats are unions of these); an open block
goes if at least half of it is covered, and the rest is kept as the page's unique runs. Where a page has an article, its
open blocks are also held against the open and dropped blocks of all hosts' pages, since adverts and notices are served
to many hosts; a page without one is judged by its own host alone, since its main text may be copied elsewhere.

Every article goes through the suffix array of its host's articles. Copied articles and shared passages are
common, and the extraction must give each page its whole article, so two pages are not enough there: a block of an
article goes, as a notice, if at least half of it is covered by stretches that over half of the host's distinct articles
hold (of n articles, more than (n + PRIOR) / 2, so that few articles prove nothing). Equal articles count as one; an
article that such stretches cover by half is a copy of others, and stays whole; so do blocks under GRAM tokens, which may
be headings.

A host's pages (and the pages of all hosts) are dealt into parts of bounded size. Each part has its own suffix array. For
open blocks it gives one row per distinct stretch, with its first and last page; these are merged over the parts of a
host, so a host with a third of all pages is neither one task's work nor judged by a part of it. For articles, which
are dealt by their hashes, it gives those stretches that over a quarter of its articles hold, with their number; the sums over
the parts are compared with the host's articles. So at most four articles' worth of stretches leaves a part; to the parts,
words travel as hashes of 32 bits. A sum
never exceeds the true number, and falls short of it only if a stretch of over half of all articles is in under a quarter of
some part's 1,000 or more: by Hoeffding's bound with probability e**-125 a part.

Defined results: null and empty html give an empty text and 0; a null url is a host of its own for each page; repeated
rows give a row each, and count as distinct pages only when their page_id differs.
"""

from __future__ import annotations

import html
import re

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

GRAM = 6
#: Pages of a host in one suffix array, about.
PART = 2048
#: Articles without a stretch that each host is taken to have beside its own.
PRIOR = 6
KEPT, OPEN, GONE = 1, 0, -1
#: Stands for all hosts together; no host's name is empty.
EVERYWHERE = ""

# Elements by what they are for.
BREAKS = set("address article aside blockquote body caption center dd details dialog dir div dl dt fieldset figcaption figure footer form h1 h2 h3 h4 h5 h6 head header hgroup hr html legend li main menu nav ol optgroup option p pre section summary table tbody td tfoot th thead title tr ul".split())
HOLDERS = set("article aside blockquote body button center details dialog div dl fieldset figure footer form head header label main menu nav ol section table title ul span p li".split())
DROPPED = set("aside button dialog footer form head label menu nav title".split())
MARKS = set("ad ads advert advertisement adverts adsense banner sponsor sponsored promo promotion cookie cookies consent gdpr notice notices alert popup modal overlay newsletter subscribe subscription signup nav navbar navigation menu breadcrumb breadcrumbs sidebar widget widgets footer header masthead topbar comment comments disqus reply replies respond share sharing social related recommended recommendations pagination pager login search toolbar skip".split())
ROLES = set("navigation banner contentinfo complementary search dialog alert alertdialog menu menubar form".split())
OWN = set("article post entry story content".split())

_token = re.compile(
    r"""<!--.*?(?:-->|\Z)|<(script|style|noscript|template|svg|iframe|textarea|select|math|object|canvas|video|audio)\b[^>]*+>.*?(?:</\1\s*+>|\Z)|<(/?)([a-zA-Z][a-zA-Z0-9:-]*+)((?:[^>"']++|"[^"]*+"|'[^']*+')*+)>|</?[a-zA-Z!?][^>]*+>""",
    re.S | re.I,
)
_named = re.compile(r"""\b(class|id|role|hidden|aria-hidden)\b(?:\s*=\s*("[^"]*"|'[^']*'|[^\s>]+))?""", re.I)


def dropped_by(tag: str, attributes: str, inside: bool) -> bool:
    """Whether an element drops what it holds."""
    if tag in DROPPED or (tag == "header" and not inside):
        return True
    if not attributes or tag in ("body", "html", "article", "main"):
        return False
    for name, value in _named.findall(attributes):
        name, words = name.lower(), set(re.findall(r"[a-z]+", re.sub(r"([a-z])([A-Z])", r"\1 \2", value).lower()))
        if name == "hidden" or (name == "aria-hidden" and "true" in words) or (name == "role" and words & ROLES):
            return True
        if name in ("class", "id") and (met := words & MARKS) and not (met == {"header"} and words & OWN):
            return True
    return False


def blocks(page: str, revive: bool = False) -> list[tuple[int, str]]:
    """(state, text) of the page's blocks in order; markup decoded and white space joined.

    A main part inside a dropped element is kept: then it is a layout's wrapper that bears the mark. So is an
    article, if the page has no other (revive: the second look at such a page).
    """
    out: list[tuple[int, str]] = []
    stack: list[tuple[str, bool, bool, int | None]] = []  # tag, drops, article, count of dropping holders set aside
    buffer: list[str] = []
    gone = inside = 0
    has_article = lost_article = False

    def end() -> None:
        if buffer:
            text = " ".join(html.unescape("".join(buffer)).split())
            buffer.clear()
            if text:
                out.append((GONE if gone else KEPT if inside else OPEN, text))

    at = 0
    for m in _token.finditer(page):
        if m.start() > at:
            buffer.append(page[at : m.start()])
        at = m.end()
        tag = m[3]
        if tag is None:
            if m[1]:
                buffer.append(" ")
            continue
        tag = tag.lower()
        if tag in BREAKS:
            end()
        elif tag == "br":
            buffer.append(" ")
        if m[2]:
            if tag in HOLDERS and any(s[0] == tag for s in stack):
                end()
                while True:
                    name, drops, article, aside = stack.pop()
                    gone = gone - drops if aside is None else aside
                    inside -= article
                    if name == tag:
                        break
        elif tag in HOLDERS and not m[4].endswith("/"):
            if tag in ("p", "li", "span"):
                # These often lack an end; only ones that drop what they hold are followed.
                while tag != "span" and stack and stack[-1][0] == tag:
                    end()
                    gone -= stack.pop()[1]
                if not m[4] or not dropped_by(tag, m[4], inside > 0):
                    continue
            end()
            article = tag in ("article", "main") or bool(m[4] and re.search(r"""role\s*=\s*["']?main\b""", m[4], re.I))
            drops = dropped_by(tag, m[4], inside > 0)
            aside = gone if gone and article and not drops and (revive or tag != "article") else None
            gone = 0 if aside is not None else gone
            has_article |= article and not drops and not gone
            lost_article |= article and gone > 0
            stack.append((tag, drops, article, aside))
            gone += drops
            inside += article
    if at < len(page):
        buffer.append(page[at:])
    end()
    if lost_article and not has_article and not revive:
        return blocks(page, True)
    return out


def host_of(url: str | None, page_id) -> str:
    m = re.match(r"[a-zA-Z][a-zA-Z0-9+.-]*://(?:[^/?#@]*@)?([^/?#:]*)", url or "")
    return m[1].lower() if m and m[1] else f"page {page_id}"


def parsed(rows: DataFrame) -> DataFrame:
    """page_id, url, host, row_id, states, texts, waits, article, first.

    states and texts: all blocks. waits: whether any is open. article: hash of the blocks in an article (null: none);
    first: whether the task has not met this article on this host before.
    """
    def run(batches):
        import pyarrow as pa
        import xxhash

        met = set()
        for batch in batches:
            hosts = [host_of(u.as_py(), p.as_py()) for u, p in zip(batch.column("url"), batch.column("page_id"))]
            states, texts, waits, articles, first = [], [], [], [], []
            for host, h in zip(hosts, batch.column("html")):
                found = blocks(h.as_py() or "")
                states.append([s for s, _ in found])
                texts.append([t for _, t in found])
                waits.append(OPEN in states[-1])
                own = "\n".join(t for s, t in found if s == KEPT).encode("utf-8", "surrogatepass")
                articles.append(xxhash.xxh3_64_intdigest(own) - (1 << 63) if own else None)
                key = (host, articles[-1])
                first.append(bool(own) and key not in met)
                met.add(key)
            made = [(hosts, pa.string()), (states, pa.list_(pa.int32())), (texts, pa.list_(pa.string())), (waits, pa.bool_()), (articles, pa.int64()), (first, pa.bool_())]
            yield pa.RecordBatch.from_arrays(
                [batch.column("row_id"), batch.column("page_id"), batch.column("url"), *(pa.array(x, t) for x, t in made)],
                ["row_id", "page_id", "url", "host", "states", "texts", "waits", "article", "first"],
            )

    return rows.select("row_id", "page_id", "url", "html").mapInArrow(run, "row_id long, page_id long, url string, host string, states array<int>, texts array<string>, waits boolean, article long, first boolean")


def suffix_order(tokens, depth: int):
    """Ranks of all suffixes by their first `depth` tokens at least, by prefix doubling."""
    import numpy as np

    rank = np.unique(tokens, return_inverse=True)[1].astype(np.int64)
    n, step = len(rank), 1
    while step < depth:
        ahead = np.zeros(n, np.int64)
        ahead[: max(0, n - step)] = rank[step:] + 1
        rank = np.unique(rank * (n + 2) + ahead, return_inverse=True)[1].astype(np.int64)
        step *= 2
    return rank


def grams(texts: list[str], words: common.WordHash):
    """Hashes of every GRAM consecutive tokens of a block; a shorter block is one stretch of its own."""
    import numpy as np

    h = words.of([t.encode("utf-8", "surrogatepass") for t in texts])
    if 0 < len(h) < GRAM:
        return common.windows(h, len(h), 0xD6E8FEB86659FD93)
    return common.windows(h, GRAM) if len(h) else np.empty(0, np.uint64)


def stretches(pages: DataFrame) -> DataFrame:
    """host, gram: stretches on two distinct pages of a host. pages: host, page_id, texts."""
    counts = common.staged(pages.groupBy("host").agg(F.count(F.lit(1)).alias("n")), "hosts")
    total = counts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    sized = common.matched(pages, counts, ["host"], F.col("n") * 1000 > total)
    parts = sized.withColumn("part", F.pmod(F.xxhash64("page_id"), F.ceil(F.col("n") / PART)))

    def run(key, pdf):
        import numpy as np
        import pandas as pd

        words = common.WordHash()
        tokens, owner, single = [], [], []
        mark = np.uint64(0)
        for page, texts in zip(pdf["page_id"], pdf["texts"]):
            for text in texts:
                w = text.split()
                h = words.of([x.encode("utf-8", "surrogatepass") for x in w])
                if len(h) < GRAM:
                    single.append((page, int(grams(w, words)[0])))
                    continue
                mark += np.uint64(1)  # a separator that occurs once
                tokens.append(np.r_[h, mark])
                owner.append(np.full(len(h) + 1, page, np.int64))
        out = []
        if tokens:
            t, o = np.concatenate(tokens), np.concatenate(owner)
            rank = suffix_order(t, GRAM)  # to depth 8: stretches equal to 6 tokens are neighbours in this order
            order = np.argsort(rank, kind="stable")
            inner = common.windows(t, GRAM)
            stops = np.cumsum(np.r_[0, (t <= mark).astype(np.int64)])
            whole = (stops[GRAM:] - stops[:-GRAM]) == 0
            at = order[order < len(inner)]
            at = at[whole[at]]
            g, p = inner[at], o[at]
            if len(g):
                new = np.flatnonzero(np.r_[True, g[1:] != g[:-1]])
                out.append(pd.DataFrame({"gram": g[new].view(np.int64), "lo": np.minimum.reduceat(p, new), "hi": np.maximum.reduceat(p, new)}))
        if single:
            s = pd.DataFrame(single, columns=["page", "gram"])
            s["gram"] = np.array([x[1] for x in single], np.uint64).view(np.int64)
            out.append(s.groupby("gram", as_index=False).agg(lo=("page", "min"), hi=("page", "max"))[["gram", "lo", "hi"]])
        found = pd.concat(out) if out else pd.DataFrame({"gram": pd.Series(dtype="int64"), "lo": pd.Series(dtype="int64"), "hi": pd.Series(dtype="int64")})
        found.insert(0, "host", key[0])
        return found

    found = parts.select("host", "part", "page_id", "texts").groupBy("host", "part").applyInPandas(run, "host string, gram long, lo long, hi long")
    return found.groupBy("host", "gram").agg(F.min("lo").alias("lo"), F.max("hi").alias("hi")).where("lo <> hi").select("host", "gram")


def short_hashes(text: str, words: common.WordHash):
    """32-bit hashes of an article's words, none of them 0."""
    import numpy as np

    return np.maximum(words.of(text.encode("utf-8", "surrogatepass").split(b" ")) & np.uint64(0xFFFFFFFF), np.uint64(1))


def article_tokens(articles: DataFrame) -> DataFrame:
    """host, article, tokens: the hashes of the words of an article's blocks of GRAM words or more, 0 after each block."""
    def run(batches):
        import numpy as np
        import pyarrow as pa

        words = common.WordHash()
        for batch in batches:
            tokens = []
            for states, texts in zip(batch.column("states").to_pylist(), batch.column("texts").to_pylist()):
                found = [h for h in (short_hashes(t, words) for s, t in zip(states, texts) if s == KEPT) if len(h) >= GRAM]
                tokens.append(np.concatenate([x for h in found for x in (h, [0])]).astype(np.uint32).view(np.int32) if found else [])
            yield pa.RecordBatch.from_arrays([batch.column("host"), batch.column("article"), pa.array(tokens, pa.list_(pa.int32()))], ["host", "article", "tokens"])

    return articles.select("host", "article", "states", "texts").mapInArrow(run, "host string, article long, tokens array<int>")


def notices(seen: DataFrame) -> DataFrame:
    """host, heavy: the stretches that over half of the host's distinct articles hold. seen: host, article, first, states, texts."""
    articles = seen.where("article is not null")
    hosts = common.staged(articles.select("host", "article").distinct().groupBy("host").agg(F.count(F.lit(1)).alias("n")), "articles")
    total = hosts.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    # Only hosts of several parts are told their number: one in PART articles at most. Small parts share a suffix array.
    many = hosts.where(F.col("n") > PART).select("host", F.ceil(F.col("n") / PART).alias("parts"))
    dealt = article_tokens(articles.where("first")).join(F.broadcast(many), "host", "left").withColumn("parts", F.coalesce("parts", F.lit(1)))
    array = F.pmod(F.xxhash64("host", F.pmod("article", "parts")), F.lit(max(1, -(-total // PART))))

    def run(pdf):
        import numpy as np
        import pandas as pd

        pdf = pdf.drop_duplicates(["host", "article"])
        place, names = pd.factorize(pdf["host"].to_numpy(object))
        parts = pdf.groupby(place)["parts"].first().to_numpy()
        n = np.bincount(place)
        # More than this many articles; a host of one part is judged at once.
        least = np.where(parts > 1, n / 4, (n + PRIOR) / 2)
        on = np.flatnonzero((n > least)[place])
        out = {"host": [], "gram": [], "c": []}
        if sum(len(pdf["tokens"].iloc[k]) for k in on):
            plain = np.concatenate([pdf["tokens"].iloc[k] for k in on]).view(np.uint32).astype(np.uint64)
            o = np.repeat(on, [len(pdf["tokens"].iloc[k]) for k in on])
            mark = np.cumsum(plain == 0, dtype=np.uint64)  # each separator occurs once; a host's stretches are its own
            t = np.where(plain == 0, mark, (place[o] + 1).astype(np.uint64) << np.uint64(32) | plain)
            rank = suffix_order(t, GRAM)
            order = np.argsort(rank, kind="stable")
            inner = common.windows(t, GRAM)
            stops = np.cumsum(np.r_[0, (plain == 0).astype(np.int64)])
            whole = (stops[GRAM:] - stops[:-GRAM]) == 0
            at = order[order < len(inner)]
            at = at[whole[at]]
            new = np.flatnonzero(np.r_[True, inner[at][1:] != inner[at][:-1]])[: len(at)]
            long = np.diff(np.r_[new, len(at)]) > least[place[o[at[new]]]]  # places; articles are counted for these only
            run_of = np.repeat(np.where(long, np.arange(len(new)), -1), np.diff(np.r_[new, len(at)]))
            pairs = np.unique(run_of[run_of >= 0] * len(pdf) + o[at[run_of >= 0]])
            runs, c = np.unique(pairs // len(pdf), return_counts=True)
            first = at[new[runs]]
            good = c > least[place[o[first]]]
            first = first[good]
            out = {"host": names[place[o[first]]], "gram": common.windows(plain, GRAM)[first].view(np.int64), "c": c[good]}
        return pd.DataFrame(out).astype({"host": object, "gram": "int64", "c": "int64"})

    found = dealt.groupBy(array).applyInPandas(run, "host string, gram long, c long")
    found = found.groupBy("host", "gram").agg(F.sum("c").alias("c")).join(hosts, "host").where(2 * F.col("c") > F.col("n") + PRIOR)
    return found.groupBy("host").agg(F.collect_list("gram").alias("heavy"))


def open_grams(pages: DataFrame) -> DataFrame:
    """row_id, host, gram: the distinct stretches of the pages' open blocks; of a page with an article, also under EVERYWHERE."""
    def run(batches):
        import numpy as np
        import pyarrow as pa

        words = common.WordHash()
        for batch in batches:
            lists = []
            for states, texts in zip(batch.column("states").to_pylist(), batch.column("texts").to_pylist()):
                found = [grams(t.split(), words) for s, t in zip(states, texts) if s == OPEN]
                lists.append(np.unique(np.concatenate(found)).view(np.int64) if found else [])
            hosts = [[h, EVERYWHERE] if KEPT in s else [h] for h, s in zip(batch.column("host").to_pylist(), batch.column("states").to_pylist())]
            yield pa.RecordBatch.from_arrays([batch.column("row_id"), pa.array(hosts, pa.list_(pa.string())), pa.array(lists, pa.list_(pa.int64()))], ["row_id", "hosts", "grams"])

    return pages.select("row_id", "host", "states", "texts").mapInArrow(run, "row_id long, hosts array<string>, grams array<long>").select("row_id", F.explode("hosts").alias("host"), "grams").select("row_id", "host", F.explode("grams").alias("gram"))


def covered(g, n: int, known) -> int:
    """How many of a block's n words stand in a stretch of `known`. g: the block's stretches."""
    import numpy as np

    met = np.isin(g, known)
    cover = np.zeros(n + GRAM, bool)
    for i in range(min(GRAM, n)):
        cover[i : i + len(g)] |= met
    return int(cover[:n].sum())


def settled(pages: DataFrame) -> DataFrame:
    """page_id, url, text, given `repeated` for the open blocks and `heavy` for articles (arrays of stretches, null: none)."""
    def run(batches):
        import numpy as np
        import pyarrow as pa

        hashes = common.WordHash()
        known = lambda x: x.values.to_numpy(zero_copy_only=False).view(np.uint64) if x.is_valid else np.empty(0, np.uint64)
        for batch in batches:
            out = []
            for states, texts, repeated, heavy in zip(batch.column("states").to_pylist(), batch.column("texts").to_pylist(), batch.column("repeated"), batch.column("heavy")):
                gone = set()
                if OPEN in states:
                    met = known(repeated)
                    for i, (s, t) in enumerate(zip(states, texts)):
                        if s == OPEN and 2 * covered(grams(w := t.split(), hashes), len(w), met) >= len(w):
                            gone.add(i)
                if heavy.is_valid and KEPT in states:
                    met, total, all_covered, found = known(heavy), 0, 0, []
                    for i, (s, t) in enumerate(zip(states, texts)):
                        if s == KEPT:
                            w = short_hashes(t, hashes)
                            c = covered(common.windows(w, GRAM), len(w), met)
                            total, all_covered = total + len(w), all_covered + c
                            if c and 2 * c >= len(w):
                                found.append(i)
                    if 2 * all_covered < total:  # else a copied article
                        gone.update(found)
                out.append("\n".join(t for i, (s, t) in enumerate(zip(states, texts)) if s != GONE and i not in gone))
            yield pa.RecordBatch.from_arrays([batch.column("page_id"), batch.column("url"), pa.array(out, pa.string())], ["page_id", "url", "text"])

    return pages.select("page_id", "url", "states", "texts", "repeated", "heavy").mapInArrow(run, "page_id long, url string, text string")


def extract(pages: DataFrame) -> DataFrame:
    """page_id, url, text, n_chars of every row of pages (page_id, url, html)."""
    rows = common.numbered(pages.select(F.col("page_id").cast("long").alias("page_id"), "url", "html"))
    seen = common.staged(parsed(rows), "pages")
    judged = seen.join(common.staged(notices(seen), "notices"), "host", "left")
    none = F.lit(None).cast("array<long>").alias("repeated")
    done = settled(judged.where("not waits").select("*", none))
    waiting = seen.where("waits")
    if not waiting.isEmpty():
        # Other pages, of the host or of all hosts, bear witness with what structure did not keep of them.
        asked = common.staged(open_grams(waiting), "asked")
        witness = seen.where("page_id is not null").select(F.explode(F.array("host", F.lit(EVERYWHERE))).alias("host"), "page_id", F.transform(F.filter(F.arrays_zip("states", "texts"), lambda b: b["states"] != KEPT), lambda b: b["texts"]).alias("texts"))
        witness = witness.where("size(texts) > 0").join(asked.select("host").distinct(), "host", "left_semi")
        known = asked.groupBy("host", "gram").agg(F.count(F.lit(1)).alias("n")).join(stretches(witness), ["host", "gram"])
        known = common.staged(known, "known")
        total = asked.count()
        met = common.matched(asked, known, ["host", "gram"], F.col("n") * 1000 > total).groupBy("row_id").agg(F.collect_set("gram").alias("repeated"))
        done = done.unionByName(settled(judged.where("waits").join(met, "row_id", "left")))
    return done.select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))
