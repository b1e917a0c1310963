"""A corpus pipeline of the training-data operators: each stage works on all that the one before it kept.

1. quality: documents that the ordinal classifier, trained on the labels, rejects go.
2. near_dedup: of each group of documents linked by a similarity of 0.8 or more (Jaccard, five-word shingles, exact) the one of least doc_id stays.
   Candidates meet in vantage-point trees of SimHash fingerprints.
   Texts without words are one group.
   Rows that repeat a doc_id are one document and stay or go together.
3. decontaminate: documents that share a passage with a benchmark item go.
4. pii: personal numbers, dates and e-mail names become pseudonyms.
5. packing: documents become pieces of token sequences.

All but the last return the columns of documents. Null doc_ids: such a row is in no group and stays as it is. Empty tables give no rows.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fimspark.llm import decontamination, near_copies, packing, pii, quality_classifier
from fimspark.llm.common import cut, table

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    model = quality_classifier.train(docs, quality_classifier.graded(table(spark, sf_dir, "labels")))
    return quality_classifier.score(docs.select(*COLUMNS), model).where("selected").select(*COLUMNS)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = near_copies.near_copies(docs.select(*COLUMNS))
    gone = out.where("doc_id <> component_id").select("doc_id").distinct()
    return docs.select(*COLUMNS).join(gone, "doc_id", "left_anti").select(*COLUMNS)


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    leaks = decontamination.leaks(docs, table(spark, sf_dir, "benchmark"))
    return docs.select(*COLUMNS).join(cut(leaks.select("doc_id").distinct()), "doc_id", "left_anti").select(*COLUMNS)


def pseudonyms(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    out = pii.pseudonymise(docs.select(*COLUMNS)).drop("n_found")
    return out.withColumn("n_chars", F.length("text").cast("long")).select(*COLUMNS)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs)


STAGES = [("quality", quality), ("near_dedup", near_dedup), ("decontaminate", decontaminate), ("pii", pseudonyms), ("packing", pack)]
#: No SQL expresses the trained classifier, the shingles or the tokenizer; tests compare each stage with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Each stage's rows are written and read again in the shared checkpoint folder, so no later stage computes an earlier one anew."""
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = cut(docs)
    return docs
