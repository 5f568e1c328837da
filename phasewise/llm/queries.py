"""One query per operator, over whole tables with production settings."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import bpe, compression_quality, host_rules, kneser_ney, license_rules, line_dedup, mixing, near_dedup, one_bit_search, unigram_counts
from .store import read_table


def op1_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = near_dedup.near_duplicates(read_table(spark, sf_dir, "documents"), k=3, percent=85)
    return out.select("doc_id", "n_shingles", "component_id", "kept")


def op2_host_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return host_rules.judge(read_table(spark, sf_dir, "documents"))


def op3_kneser_ney(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kneser_ney.train_and_score(read_table(spark, sf_dir, "documents"))


def op4_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mixing.mixed_words(read_table(spark, sf_dir, "documents"))


def tokenizer_file(spark: SparkSession, name: str) -> str:
    """A public tokenizer file: in the folder ``phasewise.tokenizers.dir`` of the session, if set."""
    folder = spark.conf.get("phasewise.tokenizers.dir", None)
    if folder:
        return f"{folder}/{name}"
    import public_tokenizers

    return public_tokenizers.path(name)


def op5_word_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bpe.digests(read_table(spark, sf_dir, "documents"), tokenizer_file(spark, "word_bpe_49k.json"))


def op7_unigram_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return unigram_counts.token_counts(read_table(spark, sf_dir, "documents"), tokenizer_file(spark, "piece_bpe_32k.model"))


def op8_compression_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    return compression_quality.scored(docs, compression_quality.train(docs, read_table(spark, sf_dir, "labels")))


def op9_one_bit_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return one_bit_search.search(read_table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op10_license_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return license_rules.scan(read_table(spark, sf_dir, "documents"))


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return line_dedup.cleaned(read_table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {name: f for name, f in globals().items() if name.startswith("op") and callable(f) and name[2].isdigit()}


def oracle_sql() -> dict[str, str]:
    return {"op2_host_rules": host_rules.ORACLE, "op4_source_mix": mixing.ORACLE}
