"""A corpus pipeline of five operators: language, quality, near-duplicates, secrets, packing.

Each stage takes (spark, docs, sf_dir) and works on all that the stage before kept; its result is written as Parquet and
read again. All but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ditherspark.llm import language_id, near_copies, packing, quality, secret_scan
from ditherspark.llm.common import shared_folder
from ditherspark.llm.queries import tokenizer_path


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents of an identified language (operator 8)."""
    return language_id.kept_only(docs)


def rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep (operator 9)."""
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality", "toxic")
    return quality.kept_only(docs, labels)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group whose sets of 5-word shingles are alike by 0.8 or more (operator 2's candidates and
    those of shared shingles, each compared in full)."""
    return near_copies.one_of_each(docs, shingle=5, least=0.8)


def secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts with their secrets replaced (operator 1); ``n_chars`` follows the new text."""
    clean = secret_scan.redact(docs)
    return clean.withColumn("n_chars", F.length("text").cast("long")).select(docs.columns)


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token pieces and their places in sequences (operator 10)."""
    return packing.digest(docs, tokenizer_path("byte_bpe_50k.json"))


STAGES = [("language_id", language), ("quality_rules", rules), ("simhash_near_dedup", near_duplicates), ("secret_scan", secrets), ("best_fit_packing", packed)]

#: SQL can't express the tokenizer or the fitted models; tests/llm checks ``run`` against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        path = f"{shared_folder(spark)}/{name}"
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
