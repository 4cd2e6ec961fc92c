"""Linear query families over a join: per relation a list of weight functions with values in [-1, 1].

A query of a workload is one member of each relation's family, so a workload has as many queries
as the product of the family sizes.  A family is declarative: (name, SQL expression) pairs over
its relation's attributes, so weights are computed inside the aggregate that they weigh.
"""

from __future__ import annotations

import hashlib
import math
import re
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .hyper import JoinSpec
from .plans.elimination import Factor, total
from .relation import Instance, natural_join


@dataclass(frozen=True)
class Family:
    """Weight expressions of one relation, in a dialect that Spark and other engines share."""

    weights: tuple[str, ...]

    def __len__(self) -> int:
        return len(self.weights)

    def __add__(self, other: Family) -> Family:
        return Family(self.weights + other.weights)

    @staticmethod
    def all_ones() -> Family:
        """The counting query."""
        return Family(("1.0",))

    @staticmethod
    def marginal(attr: str, values: tuple) -> Family:
        """An indicator for each value."""
        return Family(tuple(f"case when {attr} = {_literal(v)} then 1.0 else 0.0 end" for v in values))

    @staticmethod
    def joint_marginal(attrs: tuple[str, ...], values: tuple[tuple, ...]) -> Family:
        """An indicator for each combination of values of several attributes."""
        from itertools import product

        return Family(tuple(f"case when {' and '.join(f'{a} = {_literal(v)}' for a, v in zip(attrs, combo, strict=True))} then 1.0 else 0.0 end" for combo in product(*values)))

    @staticmethod
    def prefix(attr: str, edges: tuple) -> Family:
        """An indicator of being at most each edge."""
        return Family(tuple(f"case when {attr} <= {_literal(e)} then 1.0 else 0.0 end" for e in edges))

    @staticmethod
    def intervals(attr: str, edges: tuple) -> Family:
        """An indicator of each closed interval between two edges."""
        return Family(tuple(f"case when {attr} between {_literal(a)} and {_literal(b)} then 1.0 else 0.0 end" for i, a in enumerate(edges) for b in edges[i:]))

    @staticmethod
    def random_sign(attrs: tuple[str, ...], size: int, seed: str) -> Family:
        """+1 or -1 by the first hex digit of an md5 of seed, number and attributes."""
        key = ", ".join(f"cast({a} as string)" for a in attrs)
        return Family(tuple(f"case when substr(md5(concat_ws('|', '{seed}', '{i}', {key})), 1, 1) in ('0', '1', '2', '3', '4', '5', '6', '7') then 1.0 else -1.0 end" for i in range(size)))

    @staticmethod
    def weighted(expression: str) -> Family:
        """A real weight, clamped to [-1, 1]."""
        return Family((f"least(1.0, greatest(-1.0, {expression}))",))

    def columns(self) -> list[Column]:
        return [F.expr(w).cast("double") for w in self.weights]


def _literal(v: object) -> str:
    return "'" + v.replace("'", "''") + "'" if isinstance(v, str) else str(v)


@dataclass(frozen=True)
class QuerySet:
    """One family per relation; a query is a tuple of numbers, one in each family."""

    families: tuple[Family, ...]

    def __len__(self) -> int:
        n = 1
        for f in self.families:
            n *= len(f)
        return n

    def ids(self) -> list[tuple[int, ...]]:
        """All queries, the last family's number moving fastest."""
        return [tuple(map(int, x)) for x in np.stack(np.unravel_index(np.arange(len(self)), [len(f) for f in self.families]), 1)]

    def sample(self, size: int, seed: object) -> list[tuple[int, ...]]:
        """A selection of queries without repetition: those with the least md5 of seed and number."""
        pick = sorted(range(len(self)), key=lambda i: hashlib.md5(f"{seed}|{i}".encode()).hexdigest())[:size]
        every = self.ids()
        return [every[i] for i in sorted(pick)]


def weighted_factor(frame: DataFrame, keep: tuple[str, ...], family: Family, number: str) -> Factor:
    """A relation's weighted frequencies, one row per kept key and query number that is not all zero.

    All weights are sums of one aggregate over the scan; the numbers are unpivoted after it, so the
    rows of the relation are never multiplied by the size of the family.
    """
    sums = [F.sum(F.col("freq") * w).alias(f"w{i}") for i, w in enumerate(family.columns())]
    grouped = frame.groupBy(*keep).agg(*sums)
    rows = grouped.select(*keep, F.posexplode(F.array(*(F.coalesce(F.col(f"w{i}"), F.lit(0.0)) for i in range(len(family))))).alias(number, "val")).filter("val != 0.0")
    return Factor(rows, (*keep, number))


def answers(inst: Instance, queries: QuerySet, by: tuple[str, ...] = ()) -> DataFrame:
    """``[by], q1..qm, answer``: exact answers, factorised; queries whose answer is zero by absence are missing rows."""
    spec = inst.spec
    factors = []
    for i, (frame, family) in enumerate(zip(inst.frames, queries.families, strict=True)):
        columns = [c for c in frame.columns if c != "freq"]
        keep = tuple(c for c in columns if c in by or any(c in f.columns for j, f in enumerate(inst.frames) if j != i))
        factors.append(weighted_factor(frame, keep, family, f"q{i + 1}"))
    numbers = tuple(f"q{i + 1}" for i in range(spec.m))
    return total(factors, (*by, *numbers)).select(*by, *numbers, F.col("val").alias("answer"))


def answers_naive(inst: Instance, queries: QuerySet) -> DataFrame:
    """The same by joining the tables and summing weights over the output: the baseline plan."""
    joined = natural_join(inst)
    numbered = [F.posexplode(F.array(*f.columns())) for f in queries.families]
    for i, n in enumerate(numbered):
        joined = joined.select("*", n.alias(f"q{i + 1}", f"w{i + 1}"))
    weight = F.col("freq").cast("double")
    for i in range(len(numbered)):
        weight = weight * F.col(f"w{i + 1}")
    numbers = [f"q{i + 1}" for i in range(len(numbered))]
    return joined.groupBy(*numbers).agg(F.sum(weight).alias("answer"))


def dense_answers(rows: list, queries: QuerySet) -> np.ndarray:
    """Collected answer rows as an array with one axis per family."""
    out = np.zeros([len(f) for f in queries.families])
    m = len(queries.families)
    for r in rows:
        out[tuple(r[f"q{i + 1}"] for i in range(m))] = r["answer"]
    return out


def group_query(inst: Instance, attr: str) -> DataFrame:
    """Join size per value of one attribute: a family of one query a value."""
    from .plans.elimination import join_size

    return join_size(inst, (attr,)).select(attr, F.col("val").cast("bigint").alias("answer"))


def cells(spec: JoinSpec, attrs: tuple[str, ...], n_keys: dict[str, int]) -> tuple[list[tuple], float, float]:
    """(cells over the listed attributes, volume of each, log of the domain size).

    Points of the join's domain with equal weights in every query hold equal masses, so a key that no
    query looks at is one cell coordinate of its full volume.
    """
    from itertools import product

    points = list(product(*(spec.domains[a].values for a in attrs)))
    hidden = [n_keys[a] if spec.domains[a].is_key else len(spec.domains[a].values) for a in spec.attrs if a not in attrs]
    log_volume = sum(math.log(n) for n in hidden)
    volume = float(math.prod(hidden)) if log_volume < 700 else math.inf
    return points, volume, log_volume + math.log(len(points))


def key_sizes(inst: Instance, sf_dir: str) -> dict[str, int]:
    """Sizes of the public key domains."""
    return {a: domain_frame(inst.spark, sf_dir, inst.spec, a).count() for a in inst.spec.attrs if inst.spec.domains[a].is_key}


def _public_rows(spark, sf_dir: str, text: str) -> DataFrame:
    names = set(re.findall(r"\{(\w+)\}", text))
    return spark.sql(text, **{n: spark.read.parquet(f"{sf_dir}/{n}.parquet") for n in names})


def domain_frame(spark, sf_dir: str, spec: JoinSpec, attr: str) -> DataFrame:
    """The public domain of an attribute as a one-column table."""
    d = spec.domains[attr]
    if not d.is_key:
        return spark.createDataFrame([(v,) for v in d.values], [attr])
    return _public_rows(spark, sf_dir, d.sql).select(attr)


def joint_domain(spark, sf_dir: str, spec: JoinSpec, attrs: tuple[str, ...]) -> DataFrame:
    """The public domain of several attributes: a public table that names them all, else the product of their domains."""
    if not attrs:
        return spark.range(1).select()
    listed = next((text for names, text in sorted(spec.public, key=lambda x: len(x[0])) if set(attrs) <= set(names)), None)
    if listed is not None:
        return _public_rows(spark, sf_dir, listed).select(*attrs).distinct()
    out = None
    for a in attrs:
        one = domain_frame(spark, sf_dir, spec, a)
        out = one if out is None else out.crossJoin(one)
    return out.distinct()
