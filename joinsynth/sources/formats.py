"""Sources and sinks: round trips through file formats in the cluster's shared folder."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """A new folder that the driver and all executors share."""
    ensure_shared(spark)
    return f"{spark.sparkContext.getCheckpointDir()}/{uuid.uuid4().hex}"


def ensure_shared(spark: SparkSession) -> None:
    """The session's checkpoint folder; a local one is named only where none is set (tests)."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(spark.conf.get("spark.checkpoint.dir", None) or tempfile.mkdtemp(prefix="joinsynth-"))


def cut(frame: DataFrame) -> DataFrame:
    """Materialises a frame in the shared folder and cuts its lineage: a lost executor recomputes nothing upstream."""
    ensure_shared(frame.sparkSession)
    return frame.checkpoint(eager=True)


def round_trip(frame: DataFrame, kind: str, partition_by: str | None = None) -> DataFrame:
    """Writes and reads again with the same schema (``csv``, ``json``, ``orc``, ``parquet``)."""
    path = shared_folder(frame.sparkSession)
    writer = frame.write.format(kind)
    if kind == "csv":
        writer = writer.option("header", True)
    if partition_by:
        writer = writer.partitionBy(partition_by)
    writer.save(path)
    reader = frame.sparkSession.read.format(kind).schema(frame.schema)
    return (reader.option("header", True) if kind == "csv" else reader).load(path)


def save_bucketed(frame: DataFrame, table: str, keys: tuple[str, ...], buckets: int) -> None:
    """A table bucketed by its join keys: later degree and join plans on them need no exchange."""
    frame.write.mode("overwrite").bucketBy(buckets, *keys).sortBy(*keys).saveAsTable(table)


def read_jdbc(spark: SparkSession, url: str, table: str, column: str, low: int, high: int, partitions: int, **options: str) -> DataFrame:
    """A relation from a database, read in parallel ranges of a numeric column."""
    return spark.read.jdbc(url, table, column=column, lowerBound=low, upperBound=high, numPartitions=partitions, properties=options)
