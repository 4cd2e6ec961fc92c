"""Relations as frequency tables: DataFrames of attributes and an integer ``freq``."""

from __future__ import annotations

import re
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .hyper import JoinSpec, RelationSpec

#: Counts of joins are decimals: products of frequencies overflow 64 bits at scale.
COUNT = "decimal(38,0)"


@dataclass(frozen=True)
class Instance:
    """A join specification with one frequency table per relation."""

    spec: JoinSpec
    frames: tuple[DataFrame, ...]

    @property
    def spark(self) -> SparkSession:
        return self.frames[0].sparkSession

    def with_frame(self, i: int, frame: DataFrame) -> Instance:
        return replace(self, frames=tuple(frame if j == i else f for j, f in enumerate(self.frames)))


def frequency(rows: DataFrame, attrs: tuple[str, ...], annotation: str | None = None) -> DataFrame:
    """Rows to (attrs, freq): row counts, or sums of an integer annotation.  One shuffle, pre-aggregated."""
    value = F.count(F.lit(1)) if annotation is None else F.sum(F.col(annotation).cast("bigint"))
    return rows.groupBy(*attrs).agg(value.cast("bigint").alias("freq"))


def source_rows(spark: SparkSession, sf_dir: str, relation: RelationSpec) -> DataFrame:
    """The relation's rows; only the columns that its text names are read."""
    names = set(re.findall(r"\{(\w+)\}", relation.source))
    return spark.sql(relation.source, **{n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in names}).select(*relation.attrs)


def load(spark: SparkSession, sf_dir: str, spec: JoinSpec) -> Instance:
    return Instance(spec, tuple(frequency(source_rows(spark, sf_dir, r), r.attrs) for r in spec.relations))


def materialise(inst: Instance) -> Instance:
    """Frequency tables written once to the shared folder: a release reads them several times, its sources only once.

    A table has at most one row per combination of attributes, whatever the number of source rows.
    """
    from .sources.formats import cut

    return Instance(inst.spec, tuple(cut(f) for f in inst.frames))


def input_size(inst: Instance) -> DataFrame:
    """(relation, n) of every relation and the whole (relation 'all')."""
    sizes = None
    for r, f in zip(inst.spec.relations, inst.frames, strict=True):
        one = f.agg(F.coalesce(F.sum("freq"), F.lit(0)).alias("n")).select(F.lit(r.name).alias("relation"), "n")
        sizes = one if sizes is None else sizes.unionByName(one)
    return sizes.unionByName(sizes.agg(F.sum("n").alias("n")).select(F.lit("all").alias("relation"), "n"))


def natural_join(inst: Instance) -> DataFrame:
    """Every joining combination with the product of frequencies.  Output-sized: for tests and small instances."""
    out = inst.frames[0].withColumn("freq", F.col("freq").cast(COUNT))
    for f in inst.frames[1:]:
        shared = [c for c in out.columns if c in f.columns and c != "freq"]
        right = f.withColumnRenamed("freq", "freq_r")
        out = (out.join(right, shared) if shared else out.crossJoin(right)).withColumn("freq", (F.col("freq") * F.col("freq_r")).cast(COUNT)).drop("freq_r")
    return out


def restrict(frame: DataFrame, values: dict[str, object]) -> DataFrame:
    """Rows that agree with a tuple on the attributes they share."""
    for a, v in values.items():
        if a in frame.columns:
            frame = frame.filter(F.col(a).eqNullSafe(F.lit(v)))
    return frame


def restrict_by(frame: DataFrame, keys: DataFrame) -> DataFrame:
    """Semijoin: rows that agree with some tuple of ``keys``."""
    return frame.join(keys, [c for c in keys.columns if c in frame.columns], "left_semi")


def project(frame: DataFrame, attrs: tuple[str, ...], distinct: bool = True) -> DataFrame:
    """Distinct projection, or the projected frequency table."""
    return frame.select(*attrs).distinct() if distinct else frame.groupBy(*attrs).agg(F.sum("freq").alias("freq"))


def neighbor(inst: Instance, i: int, values: tuple, delta: int = 1) -> Instance:
    """The instance with one unit of one tuple added or removed; a removal below zero is an error of the caller and clipped."""
    frame = inst.frames[i]
    attrs = inst.spec.relations[i].attrs
    one = inst.spark.createDataFrame([(*values, delta)], frame.select(*attrs, "freq").schema)
    merged = frame.select(*attrs, "freq").unionByName(one).groupBy(*attrs).agg(F.sum("freq").alias("freq"))
    return inst.with_frame(i, merged.filter("freq > 0"))


def substitute(inst: Instance, i: int, old: tuple, new: tuple) -> Instance:
    """One unit of a tuple replaced by another: two steps of :func:`neighbor`."""
    return neighbor(neighbor(inst, i, old, -1), i, new, 1)
