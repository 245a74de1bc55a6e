"""The operators' queries with production parameters, and SQL for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from ditherspark.llm import language_id, lm_trie, multiset_hash, packing, piece_transducer, quality, secret_scan, simhash, token_counts, warc

#: Where the installed public tokenizer files are; a parameter of every operator that needs one.
TOKENIZERS = "/opt/tokenizers"


def tokenizer_path(name: str) -> str:
    """A public tokenizer file, by the installed package's own path function where there is one."""
    try:
        import public_tokenizers
    except ImportError:
        return f"{TOKENIZERS}/{name}"
    return public_tokenizers.path(name)


def _table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*columns)


def op1_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secret_scan.digest(_table(spark, sf_dir, "documents", "doc_id", "text"))


def op2_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simhash.digest(_table(spark, sf_dir, "documents", "doc_id", "text"))


def op3_lm_trie(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_trie.digest(_table(spark, sf_dir, "documents", "doc_id", "text"))


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.digest(_table(spark, sf_dir, "documents", "doc_id", "text"), tokenizer_path("piece_bpe_32k.model"))


def op5_piece_transducer(spark: SparkSession, sf_dir: str) -> DataFrame:
    return piece_transducer.digest(_table(spark, sf_dir, "documents", "doc_id", "text"), tokenizer_path("piece_bpe_32k.model"))


def op6_warc_dictionary(spark: SparkSession, sf_dir: str) -> DataFrame:
    return warc.digest(_table(spark, sf_dir, "pages", "page_id", "url", "html"))


def op7_multiset_hash(spark: SparkSession, sf_dir: str) -> DataFrame:
    return multiset_hash.digest(_table(spark, sf_dir, "documents", "doc_id", "text"))


def op8_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return language_id.digest(_table(spark, sf_dir, "documents", "doc_id", "text", "lang"))


def op9_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = _table(spark, sf_dir, "labels", "doc_id", "quality", "toxic")
    return quality.digest(_table(spark, sf_dir, "documents", "doc_id", "text"), labels)


def op10_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return packing.digest(_table(spark, sf_dir, "documents", "doc_id", "text"), tokenizer_path("byte_bpe_50k.json"))


def packing_under_limits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Operator 10 where all three capacities bind: sequences of 4,096 tokens and pieces of 1,024, at most 8 documents and
    the attention of two whole pieces."""
    pieces = packing.token_pieces(_table(spark, sf_dir, "documents", "doc_id", "text"), tokenizer_path("byte_bpe_50k.json"))
    return packing.pack(pieces, packing.Capacity(4096, 8, 2 << 20, weights=(1.0, 1.0, 1.0)))


QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {
    f.__name__: f
    for f in (
        op1_secret_scan, op2_simhash, op3_lm_trie, op4_token_counts, op5_piece_transducer,
        op6_warc_dictionary, op7_multiset_hash, op8_language_id, op9_quality_rules, op10_best_fit_packing, packing_under_limits,
    )
}

ORACLES: dict[str, str] = {"op6_warc_dictionary": warc.SQL}
