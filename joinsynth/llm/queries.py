"""The thin queries of the training-data operators over whole tables, and their SQL where SQL can express them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import table
from .decontamination import contamination_report
from .embedding_dedup import embedding_near_duplicates
from .line_dedup import dedup_lines
from .minhash_dedup import near_duplicates
from .oracles import ORACLES  # noqa: F401
from .packing import pack
from .quality_classifier import classify
from .sharding import shard_by_bytes
from .substring_dedup import cut_repeats
from .token_counts import count_tokens
from .url_filters import Rule, judge_urls

#: The url rules of the query.
URL_RULES = (
    Rule("allow", "org", "/"), Rule("block", "example.org", "/es/"), Rule("block", "example.org", "/en/1"),
    Rule("allow", "com", "/fr/"), Rule("block", "com", "/de/"),
)


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op1_minhash_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"))


def op2_quality_classifier(spark: SparkSession, sf_dir: str) -> DataFrame:
    return classify(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op3_benchmark_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contamination_report(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"), window=10)


def op4_substring_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return cut_repeats(table(spark, sf_dir, "documents")).drop("kept")


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return count_tokens(table(spark, sf_dir, "documents"), tokenizer_path("word_bpe_49k.json"), limit=2048)


def op6_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    names = {"ld_lines": "n_lines", "ld_chunks": "n_chunks", "ld_removed": "n_removed_chunks", "ld_removed_lines": "n_removed_lines"}
    return dedup_lines(docs).withColumn("kept_md5", F.md5("text")).drop("text").withColumnsRenamed(names)


def op7_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack(table(spark, sf_dir, "documents"), tokenizer_path("byte_bpe_50k.json"), capacity=2048, close=1)


def op8_url_filters(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge_urls(table(spark, sf_dir, "pages"), URL_RULES).select("page_id", "host", "path", "rule", "verdict")


def op9_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return shard_by_bytes(table(spark, sf_dir, "documents"), shards=24)


def op10_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embedding_near_duplicates(table(spark, sf_dir, "embeddings"), cosine=0.9)


QUERIES = {
    f.__name__: f
    for f in (
        op1_minhash_near_dedup, op2_quality_classifier, op3_benchmark_decontamination, op4_substring_dedup, op5_token_counts, op6_line_dedup,
        op7_packing, op8_url_filters, op9_sharding, op10_embedding_near_dedup,
    )
}


