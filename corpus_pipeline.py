"""A training-corpus pipeline over `documents`. Each stage takes (spark, docs, sf_dir) and works on all rows its
predecessor kept; all but the last return the columns of documents.

Rows with a null or repeated doc_id are rows of their own throughout: a stage decides on each by
itself. Null texts count as empty. An empty table passes through every stage."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from shadowpack.llm.common import release, stage, stage_mark, unique_ids
from shadowpack.llm.decontaminate import decontaminate
from shadowpack.llm.minhash import near_duplicates
from shadowpack.llm.packing import pack
from shadowpack.llm.quality import quality_scores
from shadowpack.llm.queries import tokenizer_path
from shadowpack.llm.substring_dedup import substring_dedup


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _kept(docs: DataFrame, decide: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Rows of docs whose decision (doc_id, keep) is to keep them."""
    numbered = unique_ids(docs)
    keep = decide(numbered.select(F.col("_uid").alias("doc_id"), "text")).where("keep").select(F.col("doc_id").alias("_uid"))
    return numbered.join(keep, "_uid", "left_semi").select(docs.columns)


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go."""
    labels = _table(spark, sf_dir, "labels")
    return _kept(docs, lambda d: quality_scores(d, labels).withColumn("keep", F.col("predicted") == 1))


def near_dedup_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near copies stays (five-word shingles, similarity 0.8)."""
    return _kept(docs, lambda d: near_duplicates(d).withColumn("keep", F.col("kept")))


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Words in repeated passages go from the texts; n_chars follows."""
    numbered = unique_ids(docs)
    cut = substring_dedup(numbered.select(F.col("_uid").alias("doc_id"), "text")).select(F.col("doc_id").alias("_uid"), "n_removed", "kept_text")
    changed = cut.where("n_removed > 0")
    text = F.when(F.col("n_removed").isNotNull(), F.col("kept_text")).otherwise(F.col("text"))
    joined = numbered.join(changed.hint("shuffle_hash"), "_uid", "left").withColumn("text", text)
    if "n_chars" in docs.columns:
        joined = joined.withColumn("n_chars", F.when(F.col("n_removed").isNotNull(), F.char_length("text").cast(docs.schema["n_chars"].dataType)).otherwise(F.col("n_chars")))
    return joined.select(docs.columns)


def decontaminate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold benchmark passages go."""
    benchmark = _table(spark, sf_dir, "benchmark")
    return _kept(docs, lambda d: decontaminate(d, benchmark).withColumn("keep", ~F.col("contaminated")))


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces of all documents, placed in sequences."""
    return pack(docs, tokenizer_path())


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality", quality_stage),
    ("near_dedup", near_dedup_stage),
    ("substring_dedup", substring_stage),
    ("decontaminate", decontaminate_stage),
    ("packing", packing_stage),
]

#: Neither shingle similarity over hash bands nor tokenisation can be said in SQL; tests use brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = _table(spark, sf_dir, "documents")
    mark = stage_mark()
    for name, step in STAGES[:-1]:
        docs = stage(step(spark, docs, sf_dir), f"pipeline-{name}")
        release(mark, docs)  # what the step and the one before it have written
    return STAGES[-1][1](spark, docs, sf_dir)


QUERIES = {"pipeline": run}
ORACLE_QUERIES: dict[str, str] = {}
