"""URL rules, and a ratio of two character language models for URLs that no rule fits.

URLs that a rule allows or blocks train one variable-order Markov model each: counts of every character after its
last 0 to ORDER characters, smoothed from the longest context down by Witten-Bell weights. Counts are exact and stay a distributed table,
a row for each distinct string of ORDER + 1 bytes, so what the models hold grows with the URLs and no two contexts share counts; lower orders are sums over it.
A byte's log ratio depends on its string alone: it is found once for each string that occurs, by a join for each order, and then summed by URL.
Strings that make up 1/COMMON of all bytes or more (COMMON at most) are sent to all tasks and summed there; only the others are shuffled.
Sums are of whole numbers of 2**-32, the same in any order.

A URL's score is the difference of the two log-likelihoods divided by its length. Every fifth rule-judged URL (by hash)
is left out of the counts and calibrates the threshold: the score at which the shares of wrongly judged URLs of both classes are closest.

Null URLs and URLs without `://` have an empty host and path and fit no rule; like any other they get the method's verdict, null and empty ones with score 0.
If rules judge no URL of a class, or leave none to calibrate on, the threshold is 0; untrained models score 0.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import ascii_lower, cut, pick, table

#: (verdict, rule): fixed values of the contract.
RULES = (("allow", "org/"), ("block", "example.org/es/"), ("block", "example.org/en/1"), ("allow", "com/fr/"), ("block", "com/de/"))
ORDER, ALPHABET, COMMON, UNIT = 4, 256, 10_000, 1 << 32
BINS, REACH = 400, 4.0


def parts(url: Column) -> tuple[Column, Column]:
    """Host and path as the contract has them."""
    rest = F.when(F.instr(url, "://") > 0, F.expr("substring(url, instr(url, '://') + 3)")).otherwise(F.lit(""))
    host = ascii_lower(F.regexp_extract(rest, r"^([^/?#]*)", 1))
    path = F.regexp_extract(rest, r"(?s)^[^/?#]*([^?#]*)", 1)
    return host, path


def rule_of(host: Column, path: Column, rules=RULES) -> Column:
    """struct(rule, verdict) of the longest rule that fits, else null."""
    out = F.lit(None).cast("struct<rule:string,verdict:string>")
    for verdict, rule in sorted(rules, key=lambda r: len(r[1])):  # the longest is tested first
        at = rule.index("/")
        fits = ((host == rule[:at]) | host.endswith("." + rule[:at])) & path.startswith(rule[at:])
        out = F.when(fits, F.struct(F.lit(rule).alias("rule"), F.lit(verdict).alias("verdict"))).otherwise(out)
    return out


def strings(urls: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """For each byte of each URL, the number that it and the ORDER bytes before it make (0 before the start), and its URL."""
    raw = [(u or "").encode("utf-8", "surrogatepass") for u in urls.to_pylist()]
    pad = b"\0" * ORDER
    data = np.frombuffer(b"".join(pad + r for r in raw) + pad, np.uint8).astype(np.int64)
    size = np.asarray([len(r) for r in raw], np.int64)
    owner = np.repeat(np.arange(len(raw)), size)
    at = np.arange(len(owner)) + ORDER * (owner + 1)
    code = np.zeros(len(owner), np.int64)
    for back in range(ORDER, -1, -1):
        code = code << 8 | data[at - back]
    return code, owner


def _counted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """url, class (null: not trained on) -> string, n, accepted, rejected."""
    for b in batches:
        code, owner = strings(b.column(0))
        kind = np.asarray([-1 if c is None else c for c in b.column(1).to_pylist()], np.int64)[owner]
        key, which = np.unique(code, return_inverse=True)
        of = lambda ok: pa.array(np.bincount(which, ok, minlength=len(key)).astype(np.int64))
        yield pa.RecordBatch.from_arrays([pa.array(key), of(np.ones(len(code))), of(kind == 1), of(kind == 0)], names=["string", "n", "accepted", "rejected"])


def log_ratios(counts: DataFrame) -> DataFrame:
    """counts: string, n, accepted, rejected. Returns string, n and ratio, in units of 1/UNIT: the log-likelihood as accepted less that as rejected."""
    pairs = {ORDER: counts.where("accepted + rejected > 0").select("string", "accepted", "rejected")}
    for o in range(ORDER - 1, -1, -1):
        pairs[o] = pairs[o + 1].groupBy(F.expr(f"string & {(1 << 8 * (o + 1)) - 1}L").alias("string")).agg(F.sum("accepted").alias("accepted"), F.sum("rejected").alias("rejected"))
    out = counts.select("string", "n", F.lit(1 / ALPHABET).alias("p"), F.lit(1 / ALPHABET).alias("q"))
    for o in range(ORDER + 1):
        following = F.map_from_entries(F.collect_list(F.struct(F.expr("string & 255").alias("k"), F.struct("accepted", "rejected").alias("v"))))  # ALPHABET entries at most
        table = pairs[o].groupBy(F.expr("string >> 8").alias("context")).agg(
            following.alias("next"),
            F.sum("accepted").alias("na"),
            F.sum("rejected").alias("nr"),
            F.count_if(F.col("accepted") > 0).alias("ka"),
            F.count_if(F.col("rejected") > 0).alias("kr"),
        )
        if o < 2:
            table = F.broadcast(table)  # ALPHABET ** o contexts of ALPHABET entries at most
        joined = out.join(table, F.expr(f"(string & {(1 << 8 * (o + 1)) - 1}L) >> 8") == F.col("context"), "left")
        step = lambda p, own, n, k: f"CASE WHEN {n} > 0 THEN (coalesce(next[string & 255].{own}, 0L) + {k} * {p}) / ({n} + {k}) ELSE {p} END AS {p}"
        out = joined.selectExpr("string", "n", step("p", "accepted", "na", "ka"), step("q", "rejected", "nr", "kr"))
    return out.select("string", "n", F.round((F.log("p") - F.log("q")) * UNIT).cast("long").alias("ratio"))


def scored(urls: DataFrame, ratios: DataFrame) -> DataFrame:
    """urls: id (unique), url. Returns id, score."""
    total = ratios.agg(F.sum("n")).first()[0] or 0
    some = ratios.where(F.col("n") * COMMON >= total).select("string", "ratio").toArrow()  # COMMON rows at most
    key, value = some["string"].to_numpy(), some["ratio"].to_numpy()
    order = np.argsort(key)
    shared = urls.sparkSession.sparkContext.broadcast((key[order], value[order]))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, value = shared.value
        for b in batches:
            code, owner = strings(b.column(1))
            k = np.minimum(np.searchsorted(key, code), max(len(key) - 1, 0))
            known = key[k] == code if len(key) else np.zeros(len(code), bool)
            base = np.zeros(b.num_rows, np.int64)
            np.add.at(base, owner[known], value[k[known]])
            size = np.bincount(owner, minlength=b.num_rows)
            offsets = np.append(0, np.cumsum(np.bincount(owner[~known], minlength=b.num_rows)))
            rest = pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(code[~known], pa.int64()))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(base), pa.array(size, pa.int64()), rest], names=["id", "base", "size", "rest"])

    begun = urls.select("id", "url").mapInArrow(run, "id long, base long, size long, rest array<long>")
    rest = begun.select("id", F.explode("rest").alias("string")).join(ratios.select("string", "ratio"), "string")
    sums = rest.groupBy("id").agg(F.sum("ratio").alias("more"))
    whole = begun.select("id", "base", "size").join(sums, "id", "left")
    return whole.select("id", F.expr(f"CASE WHEN size > 0 THEN (base + coalesce(more, 0L)) / {float(UNIT)}D / size ELSE 0D END").alias("score"))


def _threshold(held: DataFrame) -> float:
    """held: class, score. Where the two classes' shares of errors are closest, from a histogram of BINS bins."""
    place = F.least(F.lit(BINS - 1), F.greatest(F.lit(0), F.floor((F.col("score") + REACH) / (2 * REACH) * BINS))).cast("int")
    h = np.zeros((2, BINS))
    for r in held.groupBy("class", place.alias("bin")).count().collect():  # 2 * BINS rows at most
        h[r["class"], r["bin"]] = r["count"]
    if not h[0].sum() or not h[1].sum():
        return 0.0
    lost = np.concatenate([[0], np.cumsum(h[1] / h[1].sum())])  # accepted URLs under the threshold
    let = 1 - np.concatenate([[0], np.cumsum(h[0] / h[0].sum())])  # rejected URLs over it
    worst = np.maximum(lost, let)
    best = np.flatnonzero(worst <= worst.min() + 1e-12)
    return float(best.mean() / BINS * 2 * REACH - REACH)


def judge(pages: DataFrame, rules=RULES) -> DataFrame:
    """page_id, host, path, rule, verdict, score."""
    p = pick(pages, "page_id", "url").select("page_id", F.col("url").cast("string").alias("url"))
    host, path = parts(F.col("url"))
    p = p.select("page_id", "url", F.coalesce(host, F.lit("")).alias("host"), F.coalesce(path, F.lit("")).alias("path"))
    p = p.withColumn("fit", rule_of(F.col("host"), F.col("path"), rules))
    allowed = F.when(F.col("fit").isNotNull(), (F.col("fit.verdict") == "allow").cast("int"))
    # written once, so that the numbers of rows stay the same
    p = cut(p.select(F.monotonically_increasing_id().alias("id"), "page_id", "url", "host", "path", F.col("fit.rule").alias("rule"), F.col("fit.verdict").alias("verdict"), allowed.alias("class"), (F.pmod(F.xxhash64("url"), F.lit(5)) == 0).alias("held")))
    found = p.select("url", F.when(~F.col("held"), F.col("class")).alias("class")).mapInArrow(_counted, "string long, n long, accepted long, rejected long")
    counts = cut(found.groupBy("string").agg(*(F.sum(c).alias(c) for c in ("n", "accepted", "rejected"))))
    out = cut(p.drop("url").join(scored(p, cut(log_ratios(counts))), "id"))
    limit = _threshold(out.where("held and class is not null").select("class", "score"))
    verdict = F.coalesce("verdict", F.when(F.col("score") >= limit, "allow").otherwise("block"))
    return out.select("page_id", "host", "path", "rule", verdict.alias("verdict"), "score")


def op10_url_filter(spark, sf_dir) -> DataFrame:
    return judge(table(spark, sf_dir, "pages"))
