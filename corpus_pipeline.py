"""A corpus pipeline: host-level quality rules, line dedup, MinHash near-dedup, mixing of sources
to target weights, and BPE encoding.  Every stage works on all that its predecessor kept.

A stage's result must be written before the next stage is called with the written table: the tables
that a stage made on its way are deleted then."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession

from phasewise.llm import bpe, host_rules, line_dedup, mixing, near_dedup
from phasewise.llm.queries import tokenizer_file
from phasewise.llm.store import delete, new_path, stage


def quality_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the rules or their host's verdict reject go."""
    with stage(docs):
        return host_rules.keep_good(docs)


def line_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines that an earlier document or line has already go; so does a document left with none."""
    with stage(docs):
        return line_dedup.documents_left(docs)


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays (five-word shingles, similarity 0.8 or more)."""
    with stage(docs):
        return near_dedup.one_of_each(docs, k=5, percent=80)


def source_mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Whole documents, as often as the mix takes them, in the order of its schedule."""
    with stage(docs):
        return mixing.mixed_documents(docs)


def encoding(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """doc_id, source, n_tokens, ids of every document."""
    with stage(docs):
        return bpe.encoded_documents(docs, tokenizer_file(spark, "word_bpe_49k.json"))


STAGES: list[tuple[str, Callable[[SparkSession, DataFrame, str], DataFrame]]] = [
    ("quality rules", quality_rules),
    ("line dedup", line_copies),
    ("near dedup", near_copies),
    ("source mix", source_mix),
    ("encoding", encoding),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``; each one's result is written and read again, and deleted when the
    next one's is written."""
    docs, old = spark.read.parquet(f"{sf_dir}/documents.parquet"), []
    for name, apply in STAGES[:-1]:
        path = new_path(spark, name.replace(" ", "-"))
        out = apply(spark, docs, sf_dir)
        out.write.parquet(path)
        docs = spark.read.schema(out.schema).parquet(path)
        delete(spark, old)
        old = [path]
    return STAGES[-1][1](spark, docs, sf_dir)


#: The shuffled mix takes whole documents by hash order after three stages that SQL expresses only in
#: quadratic time; the pipeline is tested against a brute-force version on a small fixture instead.
ORACLE_SQL: str | None = None
