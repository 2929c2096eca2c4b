"""Corpus pipeline: quality rules, SimHash near-duplicates, secret scan, mixing, packing.

Every stage takes (spark, docs, sf_dir) and returns a DataFrame; run() writes each stage's rows as a Parquet table
in the shared folder and gives the reread table to the next one.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from bucketcsr.llm import host_rules, mixing, packing, secrets, simhash
from bucketcsr.llm.shared import fresh, store


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that neither the base rule nor their host's verdict rejects.

    Texts go through untouched; a column of docs that bears a name the rules add is moved aside for the time.
    """
    columns = docs.columns
    moved = docs.select(*[F.col(f"`{c}`").alias(f"c{i}") for i, c in enumerate(columns)])
    at = {c: f"c{i}" for i, c in enumerate(columns)}
    kept = host_rules.judge(moved, at["text"], at["source"]).where("kept")
    return kept.select(*[F.col(at[c]).alias(c) for c in columns])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of texts that the trees of fingerprints link or whose five-word shingles are similar to 0.8 or more."""
    return simhash.one_per_group(docs, similarity=simhash.Similarity())


def secret_scan(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents; values found to be secrets are masked, and n_chars follows the text where it changes."""
    size = fresh(docs.columns, "_size")
    masked = secrets.redact(docs.withColumn(size, F.length("text")))
    if "n_chars" in docs.columns:
        masked = masked.withColumn("n_chars", F.when(F.length("text") != F.col(size), F.length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return masked.select(*[F.col(f"`{c}`") for c in docs.columns])


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The mix: each document as often as its source's target asks, dealt to shards."""
    return mixing.draw(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row per packed piece."""
    return packing.pack(docs)


STAGES = [
    ("quality_rules", quality_rules),
    ("near_duplicates", near_duplicates),
    ("secret_scan", secret_scan),
    ("source_mix", source_mix),
    ("pack", pack),
]

#: SimHash values and byte-level tokens are not in DuckDB's SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents of sf_dir."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES:
        docs = store(stage(spark, docs, sf_dir))
    return docs
