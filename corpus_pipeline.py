"""A training corpus in five steps: each takes the documents that its predecessor kept."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fieldloom.llm import byte_bpe, decontaminate, language_id, line_dedup, ngram_join
from fieldloom.llm.common import read_table, written


def identify_language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents in which a language can be told; nulls and texts without a letter go."""
    out = language_id.identify(docs, docs.select("text", "lang"))
    return out.where(F.col("lang_pred") != language_id.UNKNOWN).select(*docs.columns)


def drop_repeated_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Texts without chunks of lines that an earlier document has; a document of which nothing is left goes."""
    out = line_dedup.deduplicate(docs).where((F.col("n_removed_lines") == 0) | (F.length("kept") > 0))
    n_chars = F.when(F.col("n_removed_lines") == 0, F.col("n_chars")).otherwise(F.length("kept"))
    return out.withColumns({"text": F.col("kept"), "n_chars": n_chars.cast("bigint")}).select(*docs.columns)


def keep_one_of_near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked documents the one with the smallest id."""
    linked = ngram_join.link_components(docs.select("doc_id", "text"))
    return docs.join(linked.where("component_id <> doc_id").select("doc_id"), "doc_id", "left_anti").select(*docs.columns)


def drop_benchmark_leaks(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a window of a benchmark item."""
    return decontaminate.find(docs, read_table(spark, sf_dir, "benchmark")).where("n_hit = 0").select(*docs.columns)


def encode_texts(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each document, with digests of the ids and of the bytes decoded from them."""
    return byte_bpe.encode_documents(docs, byte_bpe.default_ranks(spark), digests=True).drop("token_ends")


STAGES = [
    ("language ID", identify_language),
    ("line dedup", drop_repeated_lines),
    ("n-gram Jaccard join", keep_one_of_near_copies),
    ("benchmark decontamination", drop_benchmark_leaks),
    ("byte-level BPE", encode_texts),
]

#: SQL has no support vector machines and no tokenizer; tests hold the stages against brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return STAGES[-1][1](spark, docs, sf_dir)
