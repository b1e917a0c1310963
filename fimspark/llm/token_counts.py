"""Exact length histogram of encoded documents.

Documents are encoded in the map tasks, which send on only (length, documents) counts. Suffix sums over the
lengths answer totals, quantiles and truncated totals for every context limit.

A null or empty text has length 0. Repeated rows count as often as they occur. An empty table gives no rows.
"""

from __future__ import annotations

from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import cut, pick, table
from .packing import tokenizer

#: Lengths of one block of the suffix sums; a task sums the lengths of whole blocks.
BLOCK = 1024


def _lengths(path: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tok, seen = tokenizer(path), Counter()
        for b in batches:
            for text in b.column(0):
                seen[len(tok.ids(text.as_py() or "")) // 4] += 1
        yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.int64()), pa.array(list(seen.values()), pa.int64())], names=["n_tokens", "n_docs"])

    return run


def length_histogram(docs: DataFrame, path: str | None = None, text: str = "text") -> DataFrame:
    """(n_tokens, n_docs): the documents of each encoded length."""
    if path is None:
        import public_tokenizers

        path = public_tokenizers.path("word_bpe_49k.json")
    counts = pick(docs, text).select(F.col(f"`{text}`").cast("string").alias("text")).mapInArrow(_lengths(path), "n_tokens long, n_docs long")
    return counts.groupBy("n_tokens").agg(F.sum("n_docs").alias("n_docs"))


def with_suffix_sums(hist: DataFrame) -> DataFrame:
    """For each length as a context limit: documents at least so long, their tokens, all tokens when cut at the limit, and the share of documents that are shorter.

    Suffix sums within blocks of lengths are added to those of the later blocks; there are at most longest / BLOCK blocks.
    """
    h = hist.select("n_tokens", "n_docs", (F.col("n_tokens") * F.col("n_docs")).alias("n_total"), F.floor(F.col("n_tokens") / BLOCK).alias("block"))
    later = Window.orderBy(F.desc("block")).rowsBetween(Window.unboundedPreceding, -1)
    everything = Window.partitionBy(F.lit(0))
    blocks = h.groupBy("block").agg(F.sum("n_docs").alias("d"), F.sum("n_total").alias("t"))
    blocks = blocks.select(
        "block",
        F.coalesce(F.sum("d").over(later), F.lit(0)).alias("later_docs"),
        F.coalesce(F.sum("t").over(later), F.lit(0)).alias("later_total"),
        F.sum("d").over(everything).alias("all_docs"),
        F.sum("t").over(everything).alias("all_total"),
    )
    own = Window.partitionBy("block").orderBy(F.desc("n_tokens")).rowsBetween(Window.unboundedPreceding, 0)
    at_least = (F.sum("n_docs").over(own) + F.col("later_docs")).alias("docs_at_least")
    return (
        h.join(blocks, "block")
        .select("n_tokens", "n_docs", at_least, (F.sum("n_total").over(own) + F.col("later_total")).alias("tokens_at_least"), "all_docs", "all_total")
        .select(
            "n_tokens",
            "n_docs",
            "docs_at_least",
            "tokens_at_least",
            (F.col("all_total") - F.col("tokens_at_least") + F.col("n_tokens") * F.col("docs_at_least")).alias("truncated_total"),
            ((F.col("all_docs") - F.col("docs_at_least")) / F.col("all_docs")).alias("share_shorter"),
        )
    )


def quantile(sums: DataFrame, q: float) -> DataFrame:
    """The smallest length that at least a share q of the documents do not exceed, as one row `n_tokens`."""
    total = sums.agg(F.max("docs_at_least").alias("total"))  # all documents are at least as long as the shortest
    upto = F.col("total") - F.col("docs_at_least") + F.col("n_docs")
    return sums.crossJoin(total).where(upto >= F.ceil(F.col("total") * F.lit(q) - 1e-9)).agg(F.min("n_tokens").alias("n_tokens"))


def truncated_total(sums: DataFrame, limit: int) -> DataFrame:
    """All tokens when documents are cut at any limit, present as a length or not, as one row `truncated_total`."""
    above = sums.where(F.col("n_tokens") >= limit).agg(F.max("docs_at_least").alias("d"))
    below = sums.where(F.col("n_tokens") < limit).agg(F.sum(F.col("n_tokens") * F.col("n_docs")).alias("t"))
    return above.crossJoin(below).select((F.coalesce("t", F.lit(0)) + F.coalesce("d", F.lit(0)) * limit).alias("truncated_total"))


def op5_token_counts(spark, sf_dir) -> DataFrame:
    return with_suffix_sums(cut(length_histogram(table(spark, sf_dir, "documents"))))
