"""The training-data pipeline: quality rules, near duplicates, repeated passages, packing.

Defined cases: a null or empty text fails the quality rules and goes; rows with one id, or none, are documents of their own; of repeated
rows one stays; a very long text is one document throughout; an empty table stays empty in every stage; columns beyond those of
documents pass through the first three stages unchanged, whatever their names."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from keyless.llm import dedup, jaccard, packing, quality
from keyless.llm.workspace import Workspace, table


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules reject go."""
    return quality.keep_clean(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays: shingles of five words, similarity of 0.8."""
    return jaccard.keep_one(docs, width=5, percent=80)


def repeated_passages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Text under strings of 200 bytes that also stand elsewhere goes; a document that is empty after it goes too."""
    kept = dedup.drop_repeats(docs.select(F.struct("*").alias("doc"), "text"), carry=["doc"])
    changed = {"text": F.col("kept_text"), "n_chars": F.length("kept_text").cast("long")}
    return kept.filter("kept_text != '' or n_removed = 0").select(*[changed.get(c, F.col(f"doc.{c}")).alias(c) for c in docs.columns])


def packed_sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of all documents with their sequences and offsets."""
    return packing.pack(docs.select("doc_id", "text"))


STAGES = [("quality_rules", quality_rules), ("near_duplicates", near_duplicates), ("repeated_passages", repeated_passages), ("packed_sequences", packed_sequences)]

#: Suffix arrays, prefix joins and packing have no SQL form; tests compare the stages with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ws = Workspace(spark, "pipeline")
    docs = table(spark, sf_dir, "documents")
    for k, (name, stage) in enumerate(STAGES):
        docs = ws.keep(stage(spark, docs, sf_dir), f"{k}-{name}")
    return docs
