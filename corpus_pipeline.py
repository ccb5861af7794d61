"""The corpus pipeline: five stages, each one of the corpus operators, over all documents.

A stage takes (spark, docs, sf_dir) and returns a DataFrame; what it returns is written as Parquet and
read again as the next stage's docs. All stages but the last return the columns of documents.

Defined results: null text is empty text; further columns, whatever their names, are left out; rows that
repeat an id are rows of their own, so rows of equal id and text are the same document and stay or go
together, and a row whose id survives in another row's group stays; a null id survives a group only
where it is alone; documents without words are never near copies; an empty table gives an empty result.
Folders between stages lie in the shared folder; storage.tidy removes them.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from motifloom.llm import decontaminate, exact_dedup, mixing, near_dedup, toxicity
from motifloom.llm.common import scratch, table

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")


def clean(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that the classifier scores as toxic."""
    return toxicity.keep_clean(docs.select(*COLUMNS), toxicity.train(docs, table(spark, sf_dir, "labels")))


def exact(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts keeps the document with the smallest id."""
    kept = exact_dedup.text_groups(docs, keep="smallest").select(F.col("best").alias("kept_id"))
    return docs.select(*COLUMNS).join(kept, F.col("doc_id").eqNullSafe(F.col("kept_id")), "left_semi")


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of near-duplicate groups keeps the document with the smallest id."""
    return near_dedup.keep_first(docs.select(*COLUMNS))


def decontaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that hold a benchmark item."""
    return decontaminate.keep_clean(docs.select(*COLUMNS), table(spark, sf_dir, "benchmark"))


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """What the mix takes of each document: doc_id, size, source_size, target, taken, first_start."""
    return mixing.taken_words(docs)


STAGES = [("toxicity", clean), ("exact_dedup", exact), ("near_dedup", near), ("decontaminate", decontaminated), ("mixing", mixed)]

#: SQL cannot express the classifier, so tests hold each stage against brute force instead.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over documents; the last stage's rows."""
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        out = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            path = scratch(spark, f"pipeline-{name}")
            out.write.parquet(path)
            out = spark.read.parquet(path)
        docs = out
    return docs
