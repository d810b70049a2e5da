"""The registered queries of this subpackage, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import byte_bpe, decontaminate, language_id, learned_partitions, line_dedup, ngram_join, secret_scan, substring_dedup, suffix_dedup, toxicity
from .common import read_table


def folded(n: int, k: int):
    """Whether a row falls in fold ``k`` of ``n``, by crc32 of its doc_id as text."""
    return F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string").cast("binary")), F.lit(n)) == k, F.lit(False))


def op7_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents")
    train = docs.where(~folded(5, 0)).select("text", "lang")
    out = language_id.identify(docs.select("doc_id", "text"), train)
    return out.select("doc_id", folded(5, 0).alias("held_out"), "lang_pred", "score")


def op4_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    out = byte_bpe.encode_documents(docs, byte_bpe.default_ranks(spark), ids=False, digests=True)
    return out.select("doc_id", "n_tokens", "ids_sha256", "decoded_sha256")


def op8_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = secret_scan.scan(read_table(spark, sf_dir, "documents").select("doc_id", "text"))
    shown = lambda spans: F.array_join(F.transform(spans, lambda x: F.concat_ws(":", x["kind"], x["start"].cast("string"), x["end"].cast("string"))), ",")
    base = F.filter("secrets", lambda x: x["kind"] != "named")
    count = lambda kind: F.size(F.filter("secrets", lambda x: x["kind"] == kind)).cast("bigint").alias(f"n_{kind}")
    return out.select("doc_id", count("assign"), count("access"), count("hex"), F.sha2(shown(base), 256).alias("base_sha256"), shown(F.col("secrets")).alias("spans"))


def op1_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = read_table(spark, sf_dir, "documents").select("doc_id", "text")
    labels = read_table(spark, sf_dir, "labels").select("doc_id", "toxic").where(~folded(4, 2))
    out = toxicity.judge(docs, toxicity.fit(docs, labels))
    score = F.col("toxicity")
    return out.select("doc_id", folded(4, 2).alias("held_out"), score.alias("score"), (score >= 0.3).cast("int").alias("predicted"), F.size("segments").alias("n_segments"))


def op10_learned_partitions(spark: SparkSession, sf_dir: str) -> DataFrame:
    vectors = read_table(spark, sf_dir, "embeddings").select("vec_id", "embedding")
    return learned_partitions.search(vectors, vectors.where("vec_id % 100 = 0"))


def op3_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = substring_dedup.deduplicate(read_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2("kept", 256).alias("kept_sha256"))


def op9_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = suffix_dedup.deduplicate(read_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


def op2_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = line_dedup.deduplicate(read_table(spark, sf_dir, "documents").select("doc_id", "text"))
    return out.select("doc_id", "n_lines", "n_removed_lines", F.sha2("kept", 256).alias("kept_sha256"))


def op5_decontaminate(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = decontaminate.find(read_table(spark, sf_dir, "documents").select("doc_id", "text"), read_table(spark, sf_dir, "benchmark").select("item_id", "text"))
    return out.select("doc_id", "n_words", "n_hit", F.size("item_ids").cast("bigint").alias("n_items"), F.sha2(F.array_join("item_ids", ","), 256).alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def op6_ngram_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.link_components(read_table(spark, sf_dir, "documents").select("doc_id", "text"))


QUERIES = {"op6_ngram_join": op6_ngram_join, "op2_line_dedup": op2_line_dedup, "op5_decontaminate": op5_decontaminate, "op3_substring_dedup": op3_substring_dedup, "op9_suffix_dedup": op9_suffix_dedup, "op10_learned_partitions": op10_learned_partitions, "op1_toxicity": op1_toxicity, "op8_secret_scan": op8_secret_scan, "op4_byte_bpe": op4_byte_bpe, "op7_language_id": op7_language_id}
ORACLES: dict[str, str] = {"op2_line_dedup": line_dedup.ORACLE, "op5_decontaminate": decontaminate.ORACLE, "op6_ngram_join": ngram_join.ORACLE, "op3_substring_dedup": substring_dedup.ORACLE}
#: SQL that is too slow on whole tables; tests run it on the smallest ones.
SLOW_ORACLES: dict[str, str] = {"op9_suffix_dedup": suffix_dedup.ORACLE}
