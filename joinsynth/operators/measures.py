"""Accuracy and cost measures of releases and partitions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.elimination import join_size
from .partition import Partition


def error_table(exact: DataFrame, released: DataFrame, numbers: list[str]) -> DataFrame:
    """``q..., exact, released, abs_error, rel_error`` (relative to the larger of one and the exact answer)."""
    both = exact.withColumnRenamed("answer", "exact").join(released, numbers, "full").na.fill(0.0, ["exact", "released"])
    gap = F.abs(F.col("exact") - F.col("released"))
    return both.select(*numbers, "exact", "released", gap.alias("abs_error"), (gap / F.greatest(F.lit(1.0), F.abs("exact"))).alias("rel_error"))


def linf_error(errors: DataFrame) -> DataFrame:
    return errors.agg(F.max("abs_error").alias("linf"))


def error_quantiles(errors: DataFrame) -> DataFrame:
    exact = F.percentile("abs_error", F.array(F.lit(0.5), F.lit(0.9)))
    return errors.agg(F.max("abs_error").alias("linf"), F.avg("abs_error").alias("mean_error"), exact[0].alias("median_error"), exact[1].alias("p90_error"), F.max("rel_error").alias("max_rel_error"))


def join_size_vector(part: Partition) -> DataFrame:
    """(label, keys or tuples labelled, join size) of every sub-instance, empty ones included."""
    label = part.by[0]
    sizes = join_size(part.instance, part.by).select(label, F.col("val").cast("bigint").alias("out_size"))
    counted = part.labels.groupBy(label).agg(F.count("*").alias("n_keys"))
    return counted.join(sizes, label, "left").select(label, "n_keys", F.coalesce("out_size", F.lit(0)).cast("bigint").alias("out_size"))


def conforms(vector: DataFrame, target: DataFrame, label: str, factor: float = 2.0) -> DataFrame:
    """One row: do both vectors agree within a constant factor in every part?"""
    both = vector.select(label, F.col("out_size").alias("a")).join(target.select(label, F.col("out_size").alias("b")), label, "full").na.fill(0, ["a", "b"])
    ok = (F.col("a") <= factor * F.col("b")) & (F.col("b") <= factor * F.col("a"))
    return both.agg(F.coalesce(F.min(ok), F.lit(True)).alias("conforms"))


def gain(part: Partition) -> DataFrame:
    """One row: sqrt(OUT * max degree) of the whole join and the sum over buckets of sqrt(OUT_i * 2**i)."""
    from .sensitivity import max_degree

    vector = join_size_vector(part)
    whole = vector.agg(F.sum("out_size").alias("out"), F.sum(F.sqrt(F.col("out_size") * F.pow(F.lit(2.0), F.col("bucket")))).alias("uniformized"))
    degree = max_degree(part.instance)
    return whole.crossJoin(degree).select(F.sqrt(F.col("out") * F.col("max_degree")).alias("whole_join"), "uniformized")
