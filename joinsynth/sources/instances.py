"""Generated instances in closed form (any size), the hard and worked cases of the analysis."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..hyper import AttrDomain, JoinSpec, RelationSpec
from ..relation import Instance

ABC = JoinSpec("ABC", (RelationSpec("R1", ("A", "B"), ""), RelationSpec("R2", ("B", "C"), "")), {a: AttrDomain(values=()) for a in "ABC"})


def _instance(*frames: DataFrame, spec: JoinSpec = ABC) -> Instance:
    return Instance(spec, tuple(f.select(*r.attrs, F.col("freq").cast("bigint").alias("freq")) for r, f in zip(spec.relations, frames, strict=True)))


def gen_collapse(spark: SparkSession, n: int, present: bool = True) -> Instance:
    """n tuples on one join value against one tuple that may be missing: join size n or 0."""
    left = spark.range(1, n + 1).select(F.col("id").alias("A"), F.lit(1).cast("bigint").alias("B"), F.lit(1).alias("freq"))
    right = spark.range(1, 2 if present else 1).select(F.col("id").alias("B"), F.lit(1).cast("bigint").alias("C"), F.lit(1).alias("freq"))
    return _instance(left, right)


def gen_hard_two(table: DataFrame, delta: int) -> Instance:
    """A single table (A, freq) encoded with a fresh join value per unit, against ``delta`` tuples for each: amplifies the single-table problem."""
    spark = table.sparkSession
    units = table.select("A", F.explode(F.sequence(F.lit(1), F.col("freq").cast("int"))).alias("u"))
    left = units.select("A", F.xxhash64(F.col("A").cast("string"), "u").alias("B"), F.lit(1).alias("freq"))
    right = left.select("B").crossJoin(spark.range(1, delta + 1).select(F.col("id").alias("C"))).withColumn("freq", F.lit(1))
    return _instance(left, right)


def gen_hard_multi(spec: JoinSpec, table: DataFrame, delta: int) -> Instance:
    """The first relation holds the table on a diagonal (its attributes all equal to the value); every other relation is full.

    Attributes outside the first relation range over round(delta ** (1/k)) values, k their number: each
    value of the table joins with about ``delta`` combinations.
    """
    spark = table.sparkSession
    first = spec.relations[0]
    outside = [a for a in spec.attrs if a not in first.attrs]
    side = max(1, round(delta ** (1 / max(1, len(outside)))))
    values = table.select(F.col("A").cast("bigint").alias("v"))
    frames = [table.select(*(F.col("A").cast("bigint").alias(a) for a in first.attrs), "freq")]
    for r in spec.relations[1:]:
        inner = [a for a in r.attrs if a in first.attrs]
        rows = None
        for a in r.attrs:
            column = values.select(F.col("v").alias(a)).distinct() if a in inner else spark.range(1, side + 1).select(F.col("id").alias(a))
            rows = column if rows is None else rows.crossJoin(column)
        frames.append(rows.withColumn("freq", F.lit(1)))
    return _instance(*frames, spec=spec)


def gen_staircase(spark: SparkSession, r: int, degrees: DataFrame | None = None) -> Instance:
    """One join value of each degree 1..r on both sides: r(r+1) rows, join size r(r+1)(2r+1)/6; of those of ``degrees`` (B) only, where given."""
    keys = spark.range(1, r + 1).select(F.col("id").alias("B")) if degrees is None else degrees.filter(F.col("B").between(1, r))
    fan = keys.select("B", F.explode(F.sequence(F.lit(1).cast("bigint"), F.col("B"))).alias("x")).withColumn("freq", F.lit(1))
    return _instance(fan.withColumnRenamed("x", "A"), fan.withColumnRenamed("x", "C"))


def gen_geometric(spark: SparkSession, k: int) -> Instance:
    """k*k / 8**i join values of degree 2**i, for i up to two thirds of log2(k)."""
    levels = [(i, k * k // 8**i) for i in range(int(2 * math.log2(k) / 3 + 1e-9) + 1)]
    keys = None
    for i, n in levels:
        one = spark.range(n).select((F.col("id") * 64 + i).alias("B"), F.lit(2**i).alias("d"))
        keys = one if keys is None else keys.unionByName(one)
    fan = keys.select("B", F.explode(F.sequence(F.lit(1).cast("bigint"), F.col("d").cast("bigint"))).alias("x")).withColumn("freq", F.lit(1))
    return _instance(fan.withColumnRenamed("x", "A"), fan.withColumnRenamed("x", "C"))


def gen_hard_vector(spark: SparkSession, vector: dict[int, int], lam: float) -> Instance:
    """Disjoint hard instances, one per bucket: n_i units against floor(lam * 2**i) tuples, so that n_i * degree is near the wanted size."""
    left = right = None
    for i, out in sorted(vector.items()):
        degree = max(1, math.floor(lam * 2.0**i))
        n = max(0, round(out / degree))
        one = spark.range(n).select((F.col("id") * 64 + i).alias("B")).select(F.col("B").alias("A"), "B", F.lit(1).alias("freq"))
        # numbered as a whole: a cross join broadcasts a side, and rows that explode makes are not in the planner's sizes, so that it broadcasts them
        two = spark.range(n * degree).select((F.expr(f"id div {degree}") * 64 + i).alias("B"), (F.col("id") % degree + 1).alias("C"), F.lit(1).alias("freq"))
        left, right = (one, two) if left is None else (left.unionByName(one), right.unionByName(two))
    return _instance(left, right)


def gen_edges(spark: SparkSession) -> dict[str, Instance]:
    """Corner cases: an empty relation, an empty join, one join value, repeated rows, zero frequency, a null attribute."""
    rows = lambda data, attrs: spark.createDataFrame(data, ", ".join(f"{a} bigint" for a in (*attrs, "freq")))
    left, right = ("A", "B"), ("B", "C")
    make = lambda a, b: _instance(rows(a, left), rows(b, right))
    return {
        "empty_relation": make([], [(1, 1, 1)]), "empty_join": make([(1, 1, 1)], [(2, 1, 1)]), "one_value": make([(1, 1, 2), (2, 1, 1)], [(1, 1, 3)]),
        "repeated_rows": make([(1, 1, 1), (1, 1, 1)], [(1, 1, 1)]), "zero_frequency": make([(1, 1, 0)], [(1, 1, 5)]), "null_attribute": make([(None, 1, 1)], [(1, None, 1)]),
    }
