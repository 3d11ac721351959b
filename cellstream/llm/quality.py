"""Quality rules with adaptive thresholds from mergeable quantile sketches per language and source.

Each text gives counts in one pass. Four rates are drawn from them: signs a word, repeated lines a line,
words in repeated three-word windows a word, and code points a word. Spark's percentile_approx keeps a
Greenwald-Khanna sketch for each (lang, source), merged from the tasks' partial ones, so a source that holds a third of
all rows costs one sketch a task. Rows that fail the base rules are rejected anyway and left out of the sketches.
The thresholds are joined back to the documents and replace fixed cutoffs: a rate is out when it lies beyond the
median by more than FENCE times the spread, the distance from the median to the rate's quantile of TAILS.

Median and spread are the group's own, so a source of tables or code, or of long words, is judged by what is usual
in it, be that more or less than elsewhere. The median leans towards the corpus's as n / (n + LEAN) for a group of n
rows, and the spread, taken from there, towards that of all rows around their groups' medians. It is never under
TIGHTEST of the latter, since a group that is mostly copies of one document shows hardly any and must not reject
its others; FLOORS only stand where there is no spread at all.

The base rules (too few words, mostly repeated) reject on their own.
Defined results: null and empty texts have no words and fail the base rules; null lang or source is a group like
any other; repeated rows count each.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common

FENCE, ACCURACY, LEAN, TIGHTEST = 4.0, 10_000, 200, 0.25
#: The quantile whose distance from the median is the spread: junk by repeats fails the base rules, so the sketches of
#: these two reach far out; junk by signs and by word length is still among the rows.
TAILS = {"symbol_rate": 0.75, "dup_line_rate": 0.99, "repeat_rate": 0.99, "word_length": 0.9}
LOW = 0.1
#: Least spread by rate, against none at all.
FLOORS = {"symbol_rate": 0.005, "dup_line_rate": 0.005, "repeat_rate": 0.005, "word_length": 0.025}
#: Groups of language and source whose fences are broadcast at most; more are met by an exchange.
BROADCAST = 20_000
COUNTS = ["n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words"]
_SIGNS = b"#*$%&|<>"


def repeated_words(codes) -> int:
    """How many words lie in a three-word window that the text has twice or more."""
    import numpy as np

    n = len(codes) - 2
    if n < 2:
        return 0
    key = common.windows(codes, 3)
    _, inverse, times = np.unique(key, return_inverse=True, return_counts=True)
    twice = times[inverse] > 1
    cover = np.zeros(n + 2, bool)
    for i in range(3):
        cover[i : i + n] |= twice
    return int(cover.sum())


def measured(docs: DataFrame) -> DataFrame:
    """docs with the counts of COUNTS in front (counts whose names docs has already are replaced)."""
    keep = [c for c in docs.columns if c not in COUNTS]

    def run(batches):
        import pyarrow as pa

        words = common.WordHash()
        for batch in batches:
            out = [[] for _ in COUNTS]
            for text in batch.column("text"):
                raw = (text.as_py() or "").encode("utf-8", "surrogatepass")
                w = raw.split()
                lines = [x for x in raw.split(b"\n") if x and not x.isspace()]
                chars = b"".join(w)
                row = (len(w), len(chars.decode("utf-8", "surrogatepass")), sum(map(raw.count, (bytes([c]) for c in _SIGNS))), len(lines), len(lines) - len(set(lines)), repeated_words(words.of(w)))
                for column, value in zip(out, row):
                    column.append(value)
            yield pa.RecordBatch.from_arrays([*(pa.array(x, pa.int64()) for x in out), *(batch.column(c) for c in keep)], [*COUNTS, *keep])

    from pyspark.sql.types import LongType, StructField, StructType

    rows = docs.select(keep)
    return rows.mapInArrow(run, StructType([*(StructField(c, LongType()) for c in COUNTS), *rows.schema.fields]))


def rates() -> list:
    words = F.greatest(F.col("n_words"), F.lit(1))
    return [
        (F.col("n_symbols") / words).alias("symbol_rate"),
        (F.col("n_dup_lines") / F.greatest(F.col("n_lines"), F.lit(1))).alias("dup_line_rate"),
        (F.col("n_repeat_words") / words).alias("repeat_rate"),
        (F.col("word_chars") / words).alias("word_length"),
    ]


def base_failed():
    return (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words"))


def thresholds(rows: DataFrame) -> DataFrame:
    """g_lang, g_source and the fences t_ of every group of lang and source."""
    by = ["lang", "source"]
    lean = lambda own, whole: (F.col("size") * own + LEAN * whole) / (F.col("size") + LEAN)
    at = lambda c, p: F.percentile_approx(c, F.lit(p), F.lit(ACCURACY))
    whole = rows.agg(*[at(c, 0.5).alias(f"all_{c}") for c in TAILS])
    group = rows.groupBy(*by).agg(F.count(F.lit(1)).alias("size"), *[at(c, 0.5).alias(c) for c in TAILS]).crossJoin(F.broadcast(whole))  # one row at the right
    centres = group.select(F.col("lang").alias("g_lang"), F.col("source").alias("g_source"), "size", *[lean(F.col(c), F.col(f"all_{c}")).alias(f"mid_{c}") for c in TAILS])
    met = F.col("lang").eqNullSafe(F.col("g_lang")) & F.col("source").eqNullSafe(F.col("g_source"))
    away = rows.join(centres.drop("size"), met).select(*by, *[(F.col(c) - F.col(f"mid_{c}")).alias(c) for c in TAILS])
    spread = [*[F.greatest(at(c, p), F.lit(0.0)).alias(f"{c}_hi") for c, p in TAILS.items()], F.greatest(-at("word_length", LOW), F.lit(0.0)).alias("word_length_lo")]
    pooled = away.agg(*spread)
    pooled = pooled.select([F.col(c).alias(f"all_{c}") for c in pooled.columns])
    group = centres.join(away.groupBy(*by).agg(*spread), met).crossJoin(F.broadcast(pooled))  # one row at the right
    wide = lambda c, side: FENCE * F.greatest(lean(F.col(f"{c}_{side}"), F.col(f"all_{c}_{side}")), TIGHTEST * F.col(f"all_{c}_{side}"), F.lit(FLOORS[c]))
    high = [(F.col(f"mid_{c}") + wide(c, "hi")).alias(f"t_{c}_hi") for c in TAILS]
    return group.select("g_lang", "g_source", *high, (F.col("mid_word_length") - wide("word_length", "lo")).alias("t_word_length_lo"))


def verdicts(rows: DataFrame) -> DataFrame:
    """rows (lang, source and the counts, staged) with base_failed and kept."""
    names = [c for c in rows.columns if c not in ("base_failed", "kept")]
    fences = common.staged(thresholds(rows.where(~base_failed()).select("lang", "source", *rates())), "fences")
    met = F.col("lang").eqNullSafe(F.col("g_lang")) & F.col("source").eqNullSafe(F.col("g_source"))
    out = rows.join(F.broadcast(fences) if fences.count() <= BROADCAST else fences, met, "left")
    rate = dict(zip(TAILS, rates()))
    odd = F.lit(False)
    for c in TAILS:
        odd = odd | (rate[c] > F.col(f"t_{c}_hi"))
    odd = odd | (rate["word_length"] < F.col("t_word_length_lo"))
    return out.select(*names, base_failed().alias("base_failed"), (~base_failed() & ~F.coalesce(odd, F.lit(False))).alias("kept"))


def query(docs: DataFrame) -> DataFrame:
    """doc_id, the counts, base_failed and kept of every document; each text is read once, its counts are staged."""
    rows = measured(docs.select("doc_id", "text", "lang", "source")).select("doc_id", "lang", "source", *COUNTS)
    out = verdicts(common.staged(rows, "measured"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def filtered(docs: DataFrame) -> DataFrame:
    """The rows of docs that are kept, with the columns of docs; rows are staged with their counts, so texts are read once."""
    aside = {c: c if c in ("text", "lang", "source") else f"own_{i}" for i, c in enumerate(docs.columns)}
    rows = docs.select([F.col(c).alias(a) for c, a in aside.items()])  # so that no name clashes with a count's
    # What fails the base rules is gone whatever the sketches say, and takes no part in them.
    rows = common.staged(measured(rows).where(~base_failed()), "measured")
    return verdicts(rows).where("kept").select([F.col(a).alias(c) for c, a in aside.items()])


def oracle() -> str:
    """The same rows in DuckDB, with exact quantiles in place of sketches (these are exact up to ACCURACY / 2 rows a group)."""
    q = lambda c, p: f"list_sort(list({c}))[greatest(1, ceil({p} * count(*)))::BIGINT]"
    medians = ", ".join(f"{q(c, 0.5)} AS {c}" for c in TAILS)
    lean = lambda own, whole: f"(size * {own} + {LEAN} * {whole}) / (size + {LEAN})"
    mids = ", ".join(f"{lean('g.' + c, 'w.' + c)} AS mid_{c}" for c in TAILS)
    away = ", ".join(f"{c} - mid_{c} AS {c}" for c in TAILS)
    spreads = ", ".join(f"greatest({q(c, p)}, 0) AS {c}_hi" for c, p in TAILS.items()) + f", greatest(-{q('word_length', LOW)}, 0) AS word_length_lo"
    wide = lambda c, side: f"{FENCE} * greatest({lean(f'e.{c}_{side}', f'p.{c}_{side}')}, {TIGHTEST} * p.{c}_{side}, {FLOORS[c]})"
    odd = " OR ".join(f"{c} > mid_{c} + {wide(c, 'hi')}" for c in TAILS) + f" OR word_length < mid_word_length - {wide('word_length', 'lo')}"
    both = lambda a, b: f"{a}.lang IS NOT DISTINCT FROM {b}.lang AND {a}.source IS NOT DISTINCT FROM {b}.source"
    return rf"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, lang, source, coalesce(text, '') AS t FROM documents),
w AS (SELECT *, regexp_extract_all(t, '[^\x20\x09-\x0D]+') AS w, list_filter(string_split(t, chr(10)), lambda l: regexp_matches(l, '[^\x20\x09-\x0D]')) AS lines FROM d),
win AS (SELECT r, i, count(*) OVER (PARTITION BY r, a, b, c) AS times FROM (SELECT r, i, w[i] AS a, w[i + 1] AS b, w[i + 2] AS c FROM (SELECT r, w, unnest(range(1, len(w) - 1)) AS i FROM w WHERE len(w) > 2))),
rep AS (SELECT r, count(DISTINCT j) AS n FROM (SELECT r, unnest([i, i + 1, i + 2]) AS j FROM win WHERE times > 1) GROUP BY r),
m AS (SELECT r, doc_id, lang, source, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars, length(regexp_replace(t, '[^#*$%&|<>]', '', 'g'))::BIGINT AS n_symbols, len(lines) AS n_lines,
  (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, coalesce(n, 0)::BIGINT AS n_repeat_words FROM w LEFT JOIN rep USING (r)),
x AS (SELECT *, n_symbols / greatest(n_words, 1) AS symbol_rate, n_dup_lines / greatest(n_lines, 1) AS dup_line_rate, n_repeat_words / greatest(n_words, 1) AS repeat_rate, word_chars / greatest(n_words, 1) AS word_length,
  n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM m),
ok AS (SELECT * FROM x WHERE NOT base_failed),
g AS (SELECT lang, source, count(*) AS size, {medians} FROM ok GROUP BY lang, source),
w0 AS (SELECT {medians} FROM ok),
mid AS (SELECT g.lang, g.source, size, {mids} FROM g, w0 w),
away AS (SELECT ok.lang, ok.source, {away} FROM ok JOIN mid ON {both('ok', 'mid')}),
e AS (SELECT lang, source, {spreads} FROM away GROUP BY lang, source),
p AS (SELECT {spreads} FROM away)
SELECT x.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND NOT coalesce({odd}, false) AS kept
FROM x LEFT JOIN mid ON {both('x', 'mid')} LEFT JOIN e ON {both('x', 'e')} CROSS JOIN p
"""
