"""Quality rules with thresholds that adapt to each language and source.

DataFrame functions only. Each measure of a document (a share in thousandths) goes to a mergeable quantile sketch of its language and source:
counts of buckets whose width is 1/32 of their value or less, so sketches of any parts of the data add up to the sketch of the whole,
in any order, with the same result. Rows that fail the base rule are not in the sketches.

A measure's limit is the group's median plus a multiple of the spread above it, the distance from the median to a higher quantile; both come from sketches and no constant
takes part. The spread is never less than that of the whole language, and a group of fewer than MIN_GROUP rows has its language's limit. Medians
and third quartiles do not move with junk that is less than a quarter of a group. Documents are joined with their group's limits.

A null text has no words, no symbols, no lines and fails the base rule. Null languages and sources form groups of their own. Repeated rows are judged
each on its own (each counts in the sketch). An empty table gives no rows.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import WORD, cut, pick, table

SYMBOLS = "#*$%&|<>"
WINDOW = 8
MIN_WORDS, MAX_REPEAT_PERCENT = 20, 30
#: Measure: the quantile (percent) whose distance from the median is its spread, and how many spreads above the median its limit lies. Repeated lines and
#: words are 0 in nearly all documents, so that only a quantile near the end shows how far ordinary texts go.
SPREADS = {"symbols": (75, 4), "dup_lines": (99, 5), "repeats": (99, 5), "word_chars": (75, 10)}
MIN_GROUP = 50
SPACES = " \t\n\x0b\x0c\r"


def _repeat_words(words: str) -> list[str]:
    """SQL steps (name, expression) from an array of words to n_repeat_words: a position counts if a window over it occurs twice or more."""
    pair = "transform(slice({a}, 1, greatest(size({a}) - {k}, 0)), (x, i) -> xxhash64(x, get({a}, i + {k})))"
    yield "w1", f"transform({words}, x -> xxhash64(x))"
    for k, (a, b) in {1: ("w1", "w2"), 2: ("w2", "w4"), 4: ("w4", "w8")}.items():
        yield b, pair.format(a=a, k=k)
    # most texts repeat no window; only the others are sorted
    yield "again", "CASE WHEN size(array_distinct(w8)) < size(w8) THEN array_sort(transform(w8, (x, i) -> struct(x AS h, i AS i))) ELSE array() END"
    yield "at", "array_sort(transform(filter(again, (x, i) -> x.h = get(again, i - 1).h OR x.h = get(again, i + 1).h), x -> x.i))"
    yield "n_repeat_words", f"aggregate(transform(at, (x, i) -> least({WINDOW}, coalesce(get(at, i + 1) - x, {WINDOW}))), 0L, (s, x) -> s + x)"


def measures(docs: DataFrame) -> DataFrame:
    """doc_id, lang, source, the base columns, n_lines and base_failed."""
    text = F.coalesce(F.col("text").cast("string"), F.lit(""))
    out = pick(docs, "doc_id", "text", "lang", "source").select("doc_id", "lang", "source", text.alias("text"))
    lines = F.filter(F.split("text", "\n"), lambda x: x.rlike(WORD))
    out = out.select(
        "doc_id",
        "lang",
        "source",
        F.length(F.translate("text", SPACES, "")).cast("long").alias("word_chars"),
        (F.length("text") - F.length(F.translate("text", SYMBOLS, ""))).cast("long").alias("n_symbols"),
        lines.alias("lines"),
        F.filter(F.split("text", r"[\x20\x09-\x0D]+"), lambda x: x != "").alias("words"),
    )
    keep = ["doc_id", "lang", "source", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_words"]
    out = out.select(*keep[:5], F.size("lines").cast("long").alias("n_lines"), (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"), F.size("words").cast("long").alias("n_words"), "words")
    held = "words"
    for name, step in _repeat_words("words"):
        out = out.select(*keep, F.expr(step).alias(name))
        held = name
    n = F.col("n_words")
    return out.select(*keep, held, ((n < MIN_WORDS) | (100 * F.col(held) > MAX_REPEAT_PERCENT * n)).alias("base_failed"))


def shares(m: DataFrame) -> dict[str, Column]:
    """Each measure as an integer."""
    per = lambda a, b: F.expr(f"CASE WHEN {b} > 0 THEN ({a} * 1000) div {b} ELSE 0L END")
    return {"symbols": per("n_symbols", "n_words"), "dup_lines": per("n_dup_lines", "n_lines"), "repeats": per("n_repeat_words", "n_words"), "word_chars": per("word_chars", "n_words")}


def bucket_floor(v: str) -> str:
    """SQL: the least value of the sketch bucket of an integer v >= 0; its width is under 1/32 of it."""
    scale = f"greatest(length(bin({v})) - 6, 0)"
    return f"shiftleft(shiftright({v}, {scale}), {scale})"


def sketch(m: DataFrame) -> DataFrame:
    """lang, source, measure, bucket, n: the quantile sketch of each group."""
    long = m.select("lang", "source", F.explode(F.create_map(*(x for k, c in shares(m).items() for x in (F.lit(k), c)))).alias("measure", "v"))
    return long.groupBy("lang", "source", "measure", F.expr(bucket_floor("v")).alias("bucket")).agg(F.count(F.lit(1)).alias("n"))


def _quantiles(sketches: DataFrame, *keys: str) -> DataFrame:
    """keys, measure, mid, spread, total: of each sketch."""
    group = Window.partitionBy(*keys, "measure")
    at = sketches.select(*keys, "measure", "bucket", F.sum("n").over(group.orderBy("bucket")).alias("upto"), F.sum("n").over(group).alias("total"))
    high = F.expr("CASE measure " + " ".join(f"WHEN '{k}' THEN {q}" for k, (q, _) in SPREADS.items()) + " END")
    least = lambda percent: F.min(F.when(100 * F.col("upto") >= percent * F.col("total"), F.col("bucket")))
    return at.groupBy(*keys, "measure").agg(least(F.lit(50)).alias("mid"), least(high).alias("high"), F.max("total").alias("total")).select(*keys, "measure", "mid", (F.col("high") - F.col("mid")).alias("spread"), "total")


def limits(sketches: DataFrame, min_group: int = MIN_GROUP) -> DataFrame:
    """lang, source and a column limit_<measure> each."""
    own = _quantiles(sketches, "lang", "source").alias("g")
    whole = _quantiles(sketches.groupBy("lang", "measure", "bucket").agg(F.sum("n").alias("n")), "lang").alias("l")
    both = own.join(whole, F.col("g.lang").eqNullSafe(F.col("l.lang")) & (F.col("g.measure") == F.col("l.measure")))
    times = F.expr("CASE g.measure " + " ".join(f"WHEN '{k}' THEN {t}" for k, (_, t) in SPREADS.items()) + " END")
    limit = F.when(F.col("g.total") >= min_group, F.col("g.mid") + times * F.greatest("g.spread", "l.spread")).otherwise(F.col("l.mid") + times * F.col("l.spread"))
    rows = both.select(F.col("g.lang").alias("lang"), F.col("g.source").alias("source"), F.col("g.measure").alias("measure"), limit.alias("most"))
    return rows.groupBy("lang", "source").agg(*(F.min(F.when(F.col("measure") == k, F.col("most"))).alias(f"limit_{k}") for k in SPREADS))


def apply_rules(docs: DataFrame) -> DataFrame:
    m = cut(measures(docs))
    by = limits(sketch(m.where("not base_failed"))).withColumnsRenamed({"lang": "g_lang", "source": "g_source"})
    m = m.select("*", *(c.alias(f"v_{k}") for k, c in shares(m).items()))
    over = F.lit(False)
    for k in SPREADS:  # limits are buckets' least values, so values are compared by their buckets
        over = over | (F.expr(bucket_floor(f"v_{k}")) > F.col(f"limit_{k}"))
    out = m.join(by, m["lang"].eqNullSafe(by["g_lang"]) & m["source"].eqNullSafe(by["g_source"]), "left")
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", (~F.col("base_failed") & ~F.coalesce(over, F.lit(False))).alias("kept"))


def op6_quality_rules(spark, sf_dir) -> DataFrame:
    return apply_rules(table(spark, sf_dir, "documents"))


_SHARES = {"symbols": ("n_symbols", "n_words"), "dup_lines": ("n_dup_lines", "n_lines"), "repeats": ("n_repeat_words", "n_words"), "word_chars": ("word_chars", "n_words")}
ORACLE_SQL = (
    r"""
WITH d AS (
  SELECT doc_id, lang, source, coalesce(text, '') AS text,
         regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w,
         list_filter(string_split(coalesce(text, ''), chr(10)), lambda x: regexp_matches(x, '[^\x20\x09-\x0D]')) AS ls
  FROM documents),
win AS (SELECT doc_id, i, w[i:i+7] AS v FROM (SELECT doc_id, w, unnest(range(1, len(w) - 6)) AS i FROM d)),
hit AS (SELECT doc_id, i FROM (SELECT doc_id, i, count(*) OVER (PARTITION BY doc_id, v) AS c FROM win) WHERE c > 1),
rep AS (SELECT doc_id, count(DISTINCT i + j) AS n FROM hit, range(8) AS r(j) GROUP BY doc_id),
m AS (
  SELECT *, n_words < 20 OR 100 * n_repeat_words > 30 * n_words AS base_failed FROM (
    SELECT d.doc_id, lang, source, len(w) AS n_words, CAST(coalesce(list_sum(list_transform(w, lambda x: length(x))), 0) AS BIGINT) AS word_chars,
           length(text) - length(translate(text, '#*$%&|<>', '')) AS n_symbols,
           len(ls) AS n_lines, len(ls) - len(list_distinct(ls)) AS n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words
    FROM d LEFT JOIN rep ON d.doc_id = rep.doc_id)),
v AS ("""
    + " UNION ALL ".join(f"SELECT doc_id, lang, source, base_failed, '{k}' AS k, CASE WHEN {b} > 0 THEN ({a} * 1000) // {b} ELSE 0 END AS v FROM m" for k, (a, b) in _SHARES.items())
    + "),\np(k, q, times) AS (VALUES "
    + ", ".join(f"('{k}', {q}, {t})" for k, (q, t) in SPREADS.items())
    + rf"""),
s AS (SELECT lang, source, k, (v >> greatest(length(bin(v)) - 6, 0)) << greatest(length(bin(v)) - 6, 0) AS b, count(*) AS n FROM v WHERE NOT base_failed GROUP BY ALL),
sl AS (SELECT lang, k, b, sum(n) AS n FROM s GROUP BY ALL),
c AS (SELECT *, sum(n) OVER (PARTITION BY lang, source, k ORDER BY b) AS upto, sum(n) OVER (PARTITION BY lang, source, k) AS total FROM s),
cl AS (SELECT *, sum(n) OVER (PARTITION BY lang, k ORDER BY b) AS upto, sum(n) OVER (PARTITION BY lang, k) AS total FROM sl),
g AS (SELECT lang, source, k, times, total, min(b) FILTER (WHERE 100 * upto >= 50 * total) AS mid, min(b) FILTER (WHERE 100 * upto >= q * total) AS high FROM c JOIN p USING (k) GROUP BY ALL),
l AS (SELECT lang, k, min(b) FILTER (WHERE 100 * upto >= 50 * total) AS mid, min(b) FILTER (WHERE 100 * upto >= q * total) AS high FROM cl JOIN p USING (k) GROUP BY ALL),
lim AS (SELECT g.lang, g.source, g.k, CASE WHEN total >= {MIN_GROUP} THEN g.mid + times * greatest(g.high - g.mid, l.high - l.mid) ELSE l.mid + times * (l.high - l.mid) END AS most
        FROM g JOIN l ON g.k = l.k AND g.lang IS NOT DISTINCT FROM l.lang),
bad AS (SELECT DISTINCT v.doc_id FROM v JOIN lim ON v.k = lim.k AND v.lang IS NOT DISTINCT FROM lim.lang AND v.source IS NOT DISTINCT FROM lim.source WHERE (v.v >> greatest(length(bin(v.v)) - 6, 0)) << greatest(length(bin(v.v)) - 6, 0) > lim.most)
SELECT m.doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND bad.doc_id IS NULL AS kept
FROM m LEFT JOIN bad ON m.doc_id = bad.doc_id"""
)
