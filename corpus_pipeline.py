"""A corpus pipeline of five stages, each on all that its predecessor kept.

Each stage is (spark, docs, sf_dir) -> DataFrame; its result is written as Parquet and read again as the next one's docs.
All but the last return the columns of documents.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from dpchangelog.llm.common import discard, made, prepare, shared_path, table
from dpchangelog.llm.line_dedup import dedup_lines
from dpchangelog.llm.packing import pack_texts
from dpchangelog.llm.quality_classifier import documents_accepted
from dpchangelog.llm.quality_rules import documents_kept
from dpchangelog.llm.simhash import near_duplicates_removed


def classify(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts (score of 0.7 or more)."""
    return documents_accepted(docs, table(spark, sf_dir, "labels"))


def apply_rules(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality rules keep."""
    return documents_kept(docs)


def cut_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without later occurrences of repeated passages; n_chars follows the text."""
    return dedup_lines(docs).selectExpr(*[f"cast(length(text) as bigint) as {c}" if c == "n_chars" else f"`{c}`" for c in docs.columns])


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near duplicates: sets of five-word shingles with a similarity of 0.8 or more, found by
    wide fingerprints."""
    return near_duplicates_removed(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of at most 1024 tokens, placed in sequences."""
    import public_tokenizers

    return pack_texts(docs, public_tokenizers.path("byte_bpe_50k.json"))


STAGES = [("quality_classifier", classify), ("quality_rules", apply_rules), ("line_dedup", cut_repeated_lines), ("simhash_near_dedup", drop_near_duplicates), ("packing", pack)]

#: SQL can't express the classifier, the fingerprints or the tokenizer; tests hold each stage against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The stages one after the other. What a stage left for its own use, and its input, go once its result is written."""
    prepare(spark)
    docs, before = table(spark, sf_dir, "documents"), None
    for name, stage in STAGES:
        own = len(made())
        out, at = stage(spark, docs, sf_dir), shared_path(spark, f"stage-{name}")
        out.write.parquet(at)
        docs = spark.read.schema(out.schema).parquet(at)
        discard(spark, [p for p in made()[own:] if p != at] + ([before] if before else []))
        before = at
    return docs
