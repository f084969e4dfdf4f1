"""The corpus pipeline: five operators in a row over the documents table."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, functions as F

from densegrid.llm import decontaminate, langid, line_dedup, near_copies, sentencepiece_codec
from densegrid.plans.lineage import cut


def _same_columns(out: DataFrame, docs: DataFrame) -> DataFrame:
    return out.select(*[F.col(f"`{c}`") for c in docs.columns])


def known_languages(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any letter, and so without a language, go; all others stay."""
    model = langid.train(docs)
    if not model.languages:  # nothing to learn from: no document can be told to have no language
        return docs
    return _same_columns(langid.annotate(docs, model).where(F.col("lang_pred") != langid.UNKNOWN), docs)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later occurrences of three-line passages go; every document stays."""
    return _same_columns(line_dedup.dedup_lines(docs), docs)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """The smallest doc_id of each group of texts whose five-word shingles are alike by 0.8 stays."""
    return _same_columns(near_copies.drop_near_copies(docs), docs)


def without_benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold a benchmark item go."""
    return _same_columns(decontaminate.drop_leaking(docs, spark.read.parquet(f"{sf_dir}/benchmark.parquet")), docs)


def token_ids(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """What remains, as token ids that decode to the text."""
    return sentencepiece_codec.encode(docs)


STAGES = [
    ("language_id", known_languages),
    ("line_dedup", drop_repeated_lines),
    ("simhash_near_dedup", one_of_each_group),
    ("benchmark_decontamination", without_benchmark),
    ("sentencepiece", token_ids),
]

#: Language models, Hamming search and tokenisation are beyond SQL.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Applies the stages in order, each to what is written of the one before."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        docs = stage(spark, docs, sf_dir)
        if k + 1 < len(STAGES):
            docs = cut(docs)
    return docs
