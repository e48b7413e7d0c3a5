"""A training-data pipeline over ``documents``: five stages, each written and read again before the next.

Every stage takes all rows that the one before it kept and, but for the last, returns the columns of
documents. Null ids are ids of their own; rows that repeat an id are merged by the stages that compare
documents (the greatest text stays).
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from markerpanel.llm import decontamination, line_dedup, near_duplicates, piece_codec, quality_rules
from markerpanel.llm.common import NULL_ID, one_row_per_id, public_file, shared_dir, table, unique_rows, with_ids


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rejected documents go."""
    return quality_rules.accepted(docs)


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later copies of similar lines go; n_chars follows the text. A document may end up empty."""
    docs = unique_rows(docs)
    cleaned = line_dedup.deduplicated(one_row_per_id(docs.select("doc_id", "text"))).filter("n_removed > 0").select(F.col("doc_id").alias("_id"), F.col("text").alias("_text"))
    both = docs.join(cleaned, F.coalesce(docs["doc_id"].cast("long"), F.lit(NULL_ID)) == F.col("_id"), "left")
    changed = F.col("_id").isNotNull()
    new = {"text": F.when(changed, F.col("_text")).otherwise(docs["text"])}
    if "n_chars" in docs.columns:
        new["n_chars"] = F.when(changed, F.char_length("_text").cast(docs.schema["n_chars"].dataType)).otherwise(docs["n_chars"])
    return both.select(*[new[c].alias(c) if c in new else docs[c] for c in docs.columns])


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: that of the smallest id."""
    docs = unique_rows(docs)
    dropped = near_duplicates.near_duplicates(docs.select("doc_id", "text")).filter("not kept")
    return with_ids(docs, dropped, "left_anti")


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a window of a benchmark item go."""
    found = decontamination.contaminated(docs.select("doc_id", "text"), table(spark, sf_dir, "benchmark").select("item_id", "text"))
    return with_ids(docs, found.filter("n_hit > 0"), "left_anti")


def encode(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, n_tokens, ids (end id last) and decoded, the text that the ids give back."""
    return piece_codec.encode_documents(docs, public_file("piece_bpe_32k.model"))


STAGES = [("quality_rules", quality), ("line_dedup", lines), ("near_duplicates", near), ("decontamination", decontaminate), ("sentencepiece", encode)]

#: Line matching, near-duplicate search and piece encoding are not SQL; tests hold run() against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        path = shared_dir(spark)
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
