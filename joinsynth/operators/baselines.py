"""Baselines: separate answers, count-only releases, truncation, trivial releases, and broken designs (guarded)."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.noise import NoiseSource, laplace_col, tau, uniform_col
from ..ledger import per_query, require
from ..plans.elimination import join_size
from ..queries import QuerySet, answers
from ..relation import Instance
from .sensitivity import join_attrs, max_degree, out_size


def complete_answers(inst: Instance, queries: QuerySet) -> DataFrame:
    """All answers, zeros included."""
    numbers = [f"q{i + 1}" for i in range(inst.spec.m)]
    every = inst.spark.createDataFrame(queries.ids(), ", ".join(f"{n} int" for n in numbers))
    found = answers(inst, queries)
    return every.join(found, numbers, "left").select(*numbers, F.coalesce("answer", F.lit(0.0)).alias("answer"))


def answer_independently(inst: Instance, queries: QuerySet, eps: float, delta: float, noise: NoiseSource, sensitivity: float, composition: str = "basic") -> DataFrame:
    """Every query gets a share of the budget and its own Laplace noise: error grows with the number of queries.

    ``sensitivity`` is that of one row; a unit that touches several rows divides the budget.
    """
    eps, delta = eps / inst.spec.group_factor, delta / inst.spec.group_factor
    share, _ = per_query(eps, delta, len(queries), composition)
    numbers = [f"q{i + 1}" for i in range(inst.spec.m)]
    exact = complete_answers(inst, queries)
    if noise.kind == "zero":
        return exact.withColumnRenamed("answer", "released")
    u = uniform_col(noise.secret, "query", *(F.col(n).cast("string") for n in numbers))
    return exact.select(*numbers, (F.col("answer") + laplace_col(sensitivity / share, u)).alias("released"))


def release_count(inst: Instance, eps: float, delta: float, noise: NoiseSource, smooth: float | None = None, law: str = "tlap", truncate_at: int | None = None) -> float:
    """Only the join size: truncated-Laplace on a private bound, Laplace or Cauchy calibrated to a smooth bound, or truncation.

    ``smooth``: value of a smooth bound with the smoothness that the law needs (Laplace: eps / (2 ln(2/delta));
    Cauchy: eps / 6).  ``truncate_at``: tuples of join values of larger degree are dropped by this public threshold.
    A unit that touches several rows divides the budget.
    """
    eps, delta = eps / inst.spec.group_factor, delta / inst.spec.group_factor
    if truncate_at is not None:
        kept = truncate(inst, truncate_at)
        return out_size(kept) + noise.laplace(truncate_at * truncated_stability(truncate_at) / eps, "count")
    exact = out_size(inst)
    if law == "tlap":
        bound = (max_degree(inst).first()[0] if smooth is None else smooth) + noise.tlap(2 / eps, tau(eps / 2, delta / 2, 1), "degree")
        return exact + noise.tlap(2 * bound / eps, tau(eps / 2, delta / 2, bound), "count")
    if smooth is None:
        raise ValueError("Laplace and Cauchy noise need a smooth bound")
    if law == "laplace":
        return exact + noise.laplace(2 * smooth / eps, "count")
    if noise.kind == "zero":
        return float(exact)
    return exact + 6 * smooth / eps * math.tan(math.pi * (noise.uniform("count") - 0.5))


def truncate(inst: Instance, threshold: int) -> Instance:
    """Drops every tuple whose join value has a larger degree in its own relation."""
    on = list(join_attrs(inst.spec))
    frames = tuple(f.join(f.groupBy(*on).agg(F.sum("freq").alias("_d")).filter(F.col("_d") <= threshold).select(*on), on, "left_semi") for f in inst.frames)
    return Instance(inst.spec, frames)


def truncated_stability(threshold: int) -> int:
    """Tuples that one unit can bring in or out of the truncated table: a whole join value at its threshold."""
    return threshold + 1


def flawed_local_noise(inst: Instance, eps: float, noise: NoiseSource, allow_nonprivate: bool = False) -> float:
    """Laplace noise on the exact local sensitivity, which itself depends on the data."""
    require(allow_nonprivate, "noise scaled by the local sensitivity")
    return out_size(inst) + noise.laplace(max_degree(inst).first()[0] / eps, "count")


def flawed_degree_rule(inst: Instance, eps: float, delta: float, noise: NoiseSource, allow_nonprivate: bool = False) -> float:
    """The two-table rule on many tables: the local sensitivity's own sensitivity is not one there."""
    from .sensitivity import local_sensitivity

    require(allow_nonprivate, "the two-table rule for more than two tables")
    return local_sensitivity(inst).first()[0] + noise.tlap(2 / eps, tau(eps / 2, delta / 2, 1), "degree")


def constant_release(inst: Instance, n_cells: int, total: float) -> np.ndarray:
    """A fixed histogram whatever the data: private, and right only for one instance."""
    return np.full(n_cells, total / n_cells)


def size_frame(inst: Instance) -> DataFrame:
    return join_size(inst).select(F.col("val").cast("bigint").alias("out_size"))
