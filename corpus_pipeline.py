"""A training corpus from raw documents in five stages of the operators in ``joinsynth.llm``.

Each stage takes (spark, docs, sf_dir) and returns a DataFrame; ``run`` writes it as Parquet into
the shared folder of ``spark.checkpoint.dir`` and reads it again as the next stage's documents.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from joinsynth.llm.common import cut, ensure_checkpoint_dir, table
from joinsynth.llm.decontamination import clean_only
from joinsynth.llm.line_dedup import dedup_lines
from joinsynth.llm.minhash_dedup import near_duplicates
from joinsynth.llm.packing import pack
from joinsynth.llm.quality_classifier import accepted_only
from joinsynth.llm.queries import tokenizer_path


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the co-trained classifier accepts."""
    return accepted_only(docs, table(spark, sf_dir, "labels"))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Lines of repeated chunks are cut; a document that lost all its text goes, one that had none stays.

    ``n_chars`` follows the text where it was cut.
    """
    cut = dedup_lines(docs).filter("ld_removed_lines = 0 or text != ''")
    chars = F.when(F.col("ld_removed_lines") > 0, F.length("text")).otherwise(F.col("n_chars"))
    return cut.withColumn("n_chars", chars.cast(docs.schema["n_chars"].dataType)).select(docs.columns)


def near(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of near-duplicates: the least id, once; one without an id only if no other holds its text."""
    after_all = F.lit(1 << 62).cast("bigint") + F.shiftrightunsigned(F.xxhash64("text"), 2)
    rows = docs.withColumn("near_id", F.coalesce(F.col("doc_id").cast("bigint"), after_all)).withColumn("near_text", F.xxhash64("text"))
    gone = near_duplicates(rows.select("near_id", "text"), "near_id").groupBy("doc_id").agg(F.max("kept").alias("kept")).filter("not kept").select(F.col("doc_id").alias("near_id"))
    left = rows.join(gone, "near_id", "left_anti")
    key = ["near_id", "near_text"]
    repeated = cut(rows.select(*key).groupBy(*key).count().filter("count > 1").select(*key))
    if repeated.limit(1).count():
        left = left.join(repeated, key, "left_anti").unionByName(left.join(repeated, key, "left_semi").dropDuplicates(key))
    return left.select(docs.columns)


def benchmark(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without a window of the benchmark."""
    return clean_only(docs, table(spark, sf_dir, "benchmark"))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the remaining documents in sequences."""
    return pack(docs, tokenizer_path("byte_bpe_50k.json"))


STAGES = [("quality classifier", quality), ("line dedup", lines), ("minhash near-dedup", near), ("benchmark decontamination", benchmark), ("packing", packing)]

#: The classifier can't be expressed in SQL; tests compare the pipeline with a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    ensure_checkpoint_dir(spark)
    folder = f"{spark.sparkContext.getCheckpointDir()}/pipeline-{uuid.uuid4().hex}"
    docs = table(spark, sf_dir, "documents")
    for k, (_, stage) in enumerate(STAGES):
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{k}")
        docs = spark.read.parquet(f"{folder}/{k}")
        if k:  # what this stage has read is not needed again
            _remove(spark, f"{folder}/{k - 1}")
    return docs


def _remove(spark: SparkSession, path: str) -> None:
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)
