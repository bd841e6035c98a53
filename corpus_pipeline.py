"""The corpus pipeline: toxicity, line dedup, near-duplicate documents, repeated passages, packing.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; all but the last return the columns of
documents. run() applies them to the documents of a folder, each stage's rows written and read again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from probsum.llm import line_dedup, packing, passage_dedup, simhash_dedup, toxicity
from probsum.llm.common import table, written


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the sentence model calls toxic go; the model learns from the labels of the folder."""
    model = toxicity.trained(docs, table(spark, sf_dir, "labels"))
    return toxicity.without_toxic(docs, model)


def drop_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that repeat an earlier line, exactly or nearly, leave the texts."""
    return line_dedup.without_repeats(docs, **line_dedup.WIDE)


def drop_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates (SimHash and minima of five-word shingles, then Jaccard 0.8) stays."""
    return simhash_dedup.without_similar(docs)


def drop_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Passages that an earlier document has too leave the texts."""
    return passage_dedup.without_passages(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents with their places in bins."""
    return packing.packed(docs).withColumnRenamed("id", "doc_id")


STAGES = [
    ("toxicity", drop_toxic),
    ("line_dedup", drop_lines),
    ("near_copies", drop_near_copies),
    ("passages", drop_passages),
    ("packing", pack),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), f"stage-{name}")
    return STAGES[-1][1](spark, docs, sf_dir)


#: SimHash, learned scores and chained passages have no SQL form.
ORACLE_SQL = None
