"""Shared plumbing of the training-data operators: table access and lineage cuts.

Every helper is plan-only except :func:`cut`, which writes to the folder that the
cluster names in ``spark.checkpoint.dir`` (shared by the driver and all executors).
"""

from __future__ import annotations

import tempfile
import time

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


#: Most rows of an Arrow batch that holds texts: with the default 10,000 a batch alone can take a worker's memory.
BATCH_ROWS = 1_000


def small_batches(spark: SparkSession) -> None:
    """Bounds the Arrow batches of the session (a run-time setting), unless they are smaller already."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    now = int(spark.conf.get(name))
    if now > BATCH_ROWS or now <= 0:
        spark.conf.set(name, str(BATCH_ROWS))


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables; only Spark's reader touches the path."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Use the session's checkpoint folder; name a local one only where none is set (tests)."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        named = spark.conf.get("spark.checkpoint.dir", None)
        context.setCheckpointDir(named or tempfile.mkdtemp(prefix="joinsynth-ckpt-"))


def cut(frame: DataFrame) -> DataFrame:
    """Materialise ``frame`` in the shared checkpoint folder and cut its lineage."""
    ensure_checkpoint_dir(frame.sparkSession)
    done = frame.checkpoint(eager=True)
    _forget(frame.sparkSession)
    return done


#: Least seconds between two collections of the driver's garbage.
FORGET_SECONDS = 10.0
_forgot = [0.0]


def _forget(spark: SparkSession) -> None:
    """Spark removes shuffle files once the driver has collected the plans that made them, by itself every half hour.

    An operator of many short steps would leave hundreds of small files a step on every executor's disk until then.
    """
    if time.monotonic() - _forgot[0] >= FORGET_SECONDS:
        spark.sparkContext._jvm.System.gc()
        _forgot[0] = time.monotonic()


def deal(frame: DataFrame, rows_per_task: int, *cols: str) -> DataFrame:
    """Spread rows by ``cols`` over as many tasks as their count asks for, never fewer than the shuffle default."""
    width = int(frame.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return frame.repartition(max(width, -(-frame.count() // rows_per_task)), *cols)


def ascii_lower(column):
    """Lower-case A-Z only; every other character stays."""
    return F.translate(column, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")


#: Keys that may count as hot: one holds at least this share of all rows, so there are no more of them than its inverse.
HOT_SHARE, HOT_LEAST = 1e-3, 1_000


def look_up(rows: DataFrame, names: DataFrame, keys: list[str], copies: str = "copies") -> DataFrame:
    """Inner join of ``rows`` with ``names`` (one row a key, ``copies``: its number of rows), both materialised.

    Rows of hot keys meet a broadcast of at most ``1 / HOT_SHARE`` names in place; the others are dealt by key.
    """
    total = names.agg(F.coalesce(F.sum(copies), F.lit(0))).first()[0]
    hot = F.col(copies) >= max(HOT_LEAST, total * HOT_SHARE)
    few = names.filter(hot).drop(copies)
    if not few.limit(1).count():
        return rows.join(names.drop(copies), keys)
    cold = rows.join(F.broadcast(few.select(*keys)), keys, "left_anti").join(names.filter(~hot).drop(copies), keys)
    return rows.join(F.broadcast(few), keys).unionByName(cold)
