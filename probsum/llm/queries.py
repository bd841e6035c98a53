"""Queries opN_<name> over the given tables, one per corpus operator, and their SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from probsum.llm import (
    licenses,
    line_dedup,
    packing,
    passage_dedup,
    piece_bpe,
    quality_rules,
    simhash_dedup,
    site_quality,
    toxicity,
    vector_join,
)
from probsum.llm.common import table


def op1_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of every document, and whether base rules and certified cutoffs keep it."""
    found = quality_rules.judged(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))
    return found.drop("failed_rules")


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What line deduplication leaves of every document."""
    return line_dedup.reported(table(spark, sf_dir, "documents"), **line_dedup.WIDE).withColumnRenamed("id", "doc_id")


def op3_passage_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Passages of every document that an earlier document has too."""
    found = passage_dedup.passages(table(spark, sf_dir, "documents"))
    return found.withColumnsRenamed({"id": "doc_id", "others": "other_doc_ids"})


def op4_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity score of every document by a model of its sentences, learned outside the held-out fifth."""
    docs = table(spark, sf_dir, "documents")
    model = toxicity.trained(docs, table(spark, sf_dir, "labels"))
    return toxicity.scored(docs, model).select(
        F.col("id").alias("doc_id"),
        F.expr("crc32(cast(id as string)) % 5 = 0").alias("held_out"),
        "score",
        "predicted",
        "n_sentences",
        "worst_sentence",
        "worst_score",
    )


def op5_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Licences found in every document."""
    return licenses.scanned(table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")


def op6_piece_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Token ids and decoded text of every document, as digests."""
    import public_tokenizers

    found = piece_bpe.encoded(
        table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"), ids=False
    )
    return found.withColumnRenamed("id", "doc_id")


def op7_simhash_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Fingerprint and group of every document."""
    found = simhash_dedup.near_duplicates(table(spark, sf_dir, "documents"))
    return found.select(
        F.col("id").alias("doc_id"),
        F.lower(F.lpad(F.hex("fp"), 16, "0")).alias("fingerprint"),
        F.col("component").alias("component_id"),
    )


def op8_site_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Quality of every document, its source taken as the host and the language section as the path."""
    found = site_quality.scored(
        table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"), F.col("source"), F.col("lang")
    )
    return found.withColumnRenamed("id", "doc_id")


def op9_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every piece of every document with its place in a bin."""
    return packing.packed(table(spark, sf_dir, "documents")).withColumnRenamed("id", "doc_id")


def op10_vector_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Links and group of every vector."""
    found = vector_join.near_duplicates(table(spark, sf_dir, "embeddings"))
    return found.withColumnsRenamed({"id": "vec_id", "component": "component_id"})


QUERIES = {
    "op1_quality_rules": op1_quality_rules,
    "op2_line_dedup": op2_line_dedup,
    "op3_passage_dedup": op3_passage_dedup,
    "op4_toxicity": op4_toxicity,
    "op5_license_scan": op5_license_scan,
    "op6_piece_bpe": op6_piece_bpe,
    "op7_simhash_dedup": op7_simhash_dedup,
    "op8_site_quality": op8_site_quality,
    "op9_best_fit_packing": op9_best_fit_packing,
    "op10_vector_join": op10_vector_join,
}

ORACLES: dict[str, str] = {
    "op10_vector_join": """
with recursive v as (select vec_id, embedding::double[] as e from embeddings where embedding is not null),
l as (select a.vec_id as a, b.vec_id as b from v a join v b on a.vec_id <> b.vec_id
  and list_cosine_similarity(a.e, b.e) >= 0.9),
r(a, b) as (select vec_id, vec_id from v union select r.a, l.b from r join l on r.b = l.a),
c as (select a, min(b) as component_id from r group by 1),
n as (select a, count(*) as n from l group by 1)
select vec_id, coalesce(n, 0)::bigint as n_links, coalesce(component_id, vec_id) as component_id,
  vec_id = coalesce(component_id, vec_id) as kept
from embeddings left join c on c.a = vec_id left join n on n.a = vec_id""",
    "op1_quality_rules": quality_rules.oracle(),
    "op5_license_scan": licenses.oracle(),
}
