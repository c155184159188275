"""One query for each corpus operator, over whole tables with production parameters."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import oracles
from .ann import nearest
from .decontaminate import decontaminate
from .html_extract import extract_text
from .license_scan import scan_documents
from .minhash import near_duplicates
from .packing import pack
from .quality import quality_scores
from .sharding import shard_by_size
from .substring_dedup import substring_dedup
from .suffix_dedup import suffix_dedup


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def tokenizer_path() -> str:
    import public_tokenizers

    return str(public_tokenizers.path("word_bpe_49k.json"))


def op1_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_by_size(_read(spark, sf_dir, "documents"), 16)


def op2_license_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return scan_documents(_read(spark, sf_dir, "documents"))


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return substring_dedup(_read(spark, sf_dir, "documents"), with_text=False)


def op4_html_extract(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extract_text(_read(spark, sf_dir, "pages"))


def op5_nearest_vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(_read(spark, sf_dir, "embeddings"))


def op6_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    return decontaminate(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "benchmark")).drop("items")


def op7_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_scores(_read(spark, sf_dir, "documents"), _read(spark, sf_dir, "labels"))


def op8_near_duplicates(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(_read(spark, sf_dir, "documents"), width=2)


def op9_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(_read(spark, sf_dir, "documents"), tokenizer_path())


def op10_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = suffix_dedup(_read(spark, sf_dir, "documents"))
    # a cut may fall inside a character: what is left of it shows as a replacement character
    return out.withColumn("kept_text", F.make_valid_utf8(F.col("kept_bytes").cast("string"))).drop("kept_bytes")


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (op1_sharding, op2_license_scan, op3_substring_dedup, op4_html_extract, op5_nearest_vectors, op6_decontaminate, op7_quality, op8_near_duplicates, op9_packing, op10_suffix_dedup)
}

#: The others are tested against brute force: SQL can't say them, or takes too long on whole tables.
ORACLE_QUERIES: dict[str, str] = {"op3_substring_dedup": oracles.SUBSTRING_DEDUP, "op6_decontaminate": oracles.DECONTAMINATE}
