"""Release methods: statistics in a few key-level aggregates, noise on the driver, rounds in tasks.

Exact statistics reach the driver or a task only to be covered by noise; nothing exact is part of
a :class:`Release`.  Control flow depends on public figures and noisy values only.
"""

from __future__ import annotations

import math
from dataclasses import dataclass, replace

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bounds import auto_rounds
from ..functions.bounds import lam as lam_of
from ..functions.noise import NoiseSource, tau
from ..ledger import Ledger, require
from ..plans.elimination import join_size
from ..queries import QuerySet, answers, cells, dense_answers, joint_domain, key_sizes
from ..relation import Instance, materialise
from ..sources.formats import cut
from .kernel import STATS, TASK_BYTES, KernelPlan, KernelSettings, noisy_total, plan_weights, release_groups, run_frame
from .partition import Partition, bucket_count, degree_bound, label_bounds, partition_hierarchical, partition_open_domain, partition_two_table, replication_bound
from .sensitivity import ResidualBound, SmoothBound, join_attrs, max_degree, out_size, residual_sensitivity, subsets


@dataclass(frozen=True)
class Release:
    """Synthetic cells (sub_id, cell attributes, volume, mass), the plan behind them, and the ledger."""

    cells: DataFrame
    plan: KernelPlan | None
    queries: QuerySet
    ledger: Ledger

    def answer(self) -> DataFrame:
        """``q1..qm, released``: all queries on the synthetic cells, summed over sub-instances (post-processing)."""
        m = len(self.queries.families)
        frame = self.cells
        for i, f in enumerate(self.queries.families):
            frame = frame.select("*", F.posexplode(F.array(*f.columns())).alias(f"q{i + 1}", f"w{i + 1}"))
        weight = F.col("mass")
        for i in range(m):
            weight = weight * F.col(f"w{i + 1}")
        return frame.groupBy(*(f"q{i + 1}" for i in range(m))).agg(F.sum(weight).alias("released"))

    def to_rows(self, noise: NoiseSource, method: str = "randomised_round") -> DataFrame:
        """Integer rows: each cell's mass rounded up with the probability of its fraction, then one row a unit.

        ``'nearest'`` rounds to the nearest integer.
        """
        from ..functions.noise import uniform_col

        up = F.lit(0.5) if method == "nearest" else uniform_col(noise.secret, "rows", F.col("sub_id"), F.col("cell").cast("string"))
        whole = F.floor("mass") + F.when(F.col("mass") - F.floor("mass") > up, 1).otherwise(0)
        return self.cells.withColumn("n", whole.cast("int")).filter("n > 0").withColumn("row", F.explode(F.sequence(F.lit(1), F.col("n")))).drop("n", "mass", "volume")

    def view(self, name: str) -> None:
        """A temporary view answerable by ordinary SQL: sum(mass * weight)."""
        self.cells.createOrReplaceTempView(name)

    def save(self, path: str) -> None:
        """Cells by sub-instance, and the ledger; an idempotent overwrite."""
        self.cells.write.mode("overwrite").partitionBy("sub_id").parquet(f"{path}/cells")
        self.ledger.frame(self.cells.sparkSession).write.mode("overwrite").parquet(f"{path}/ledger")


def private_attrs(inst: Instance) -> tuple[str, ...]:
    """Attributes with listed values: the coordinates of cells."""
    return tuple(a for a in inst.spec.attrs if not inst.spec.domains[a].is_key and a not in _join_only(inst))


def _join_only(inst: Instance) -> set[str]:
    return {a for a in inst.spec.attrs if len(inst.spec.atom(a)) > 1}


def kernel_plan(inst: Instance, queries: QuerySet, sf_dir: str, attrs: tuple[str, ...] | None = None) -> tuple[KernelPlan, float]:
    """(plan, volume of a cell): cells over the private attributes, join attributes collapsed into the volume."""
    attrs = private_attrs(inst) if attrs is None else attrs
    points, volume, log_domain = cells(inst.spec, attrs, key_sizes(inst, sf_dir))
    return plan_weights(inst.spark, points, attrs, queries, log_domain), volume


def _finish(stats: DataFrame, plan: KernelPlan, settings: KernelSettings) -> DataFrame:
    found = release_groups(stats, plan, settings)
    spark = stats.sparkSession
    named = spark.createDataFrame([(i, *p) for i, p in enumerate(plan.points)], ["cell", *plan.attrs]).withColumn("cell", F.col("cell").cast("int"))
    return found.join(F.broadcast(named), "cell").select("sub_id", "cell", *plan.attrs, "volume", "mass", "n_hat", "dtilde", "rounds")


def _one(inst: Instance, queries: QuerySet, plan: KernelPlan, volume: float, out: float, dtilde: float) -> DataFrame:
    truth = dense_answers(answers(inst, queries).collect(), queries)
    row = ("all", float(out), float(dtilde), truth.ravel().tolist(), [volume] * len(plan.points))
    return inst.spark.createDataFrame([row], STATS)


def release_single(inst: Instance, queries: QuerySet, sf_dir: str, eps: float, delta: float, noise: NoiseSource | None = None, rounds: int | str = "auto", **kernel: object) -> Release:
    """One table: the kernel with sensitivity one."""
    inst = materialise(inst)
    ledger, e, d = _budget(eps, delta, "add_remove", inst.spec.group_factor)
    release = _release(inst, queries, sf_dir, 1.0, noise or NoiseSource.os(), rounds, _Grouped(ledger, inst.spec.group_factor), (e, d), **kernel)
    return replace(release, ledger=ledger)


def cell_bytes(inst: Instance, queries: QuerySet) -> int:
    """Bytes of the largest family's weights on all cells: what a task of the kernel would hold."""
    n = math.prod(len(inst.spec.domains[a].values) for a in private_attrs(inst))
    return 8 * n * max(len(f) for f in queries.families)


def _frame_release(inst: Instance, queries: QuerySet, sf_dir: str, dtilde: float, settings: KernelSettings) -> DataFrame:
    """The kernel over cells that stay a DataFrame: no list of cells anywhere."""
    attrs = private_attrs(inst)
    sizes = key_sizes(inst, sf_dir)
    hidden = [sizes.get(a) or len(inst.spec.domains[a].values) for a in inst.spec.attrs if a not in attrs]
    log_volume = sum(math.log(n) for n in hidden)
    log_domain = log_volume + sum(math.log(len(inst.spec.domains[a].values)) for a in attrs)
    points = cut(joint_domain(inst.spark, sf_dir, replace(inst.spec, public=()), attrs).withColumn("volume", F.lit(math.exp(log_volume))))
    truth = dense_answers(answers(inst, queries).collect(), queries)
    s = settings
    n_hat = noisy_total(float(out_size(inst)), dtilde, s.eps, s.delta, s.noise, "all")
    k = auto_rounds(n_hat, s.eps, s.delta, dtilde, max(log_domain, 1e-9), len(queries), s.max_rounds) if s.rounds == "auto" else int(s.rounds)
    found = run_frame(points, queries, truth, n_hat, dtilde, s.eps, s.delta, s.noise, k, s.out, s.accounting, ("all",))
    return found.select(F.lit("all").alias("sub_id"), F.xxhash64(*attrs).alias("cell"), *attrs, "volume", "mass", F.lit(n_hat).alias("n_hat"), F.lit(float(dtilde)).alias("dtilde"), F.lit(k).alias("rounds"))


def _release(inst: Instance, queries: QuerySet, sf_dir: str, dtilde: float, noise: NoiseSource, rounds: int | str, ledger: Ledger, share: tuple[float, float], out: str = "average", accounting: str = "advanced", max_rounds: int | None = None, kernel: str = "auto") -> Release:
    """``kernel``: 'task' holds the cells in one task, 'frame' as a DataFrame; 'auto' decides by their size."""
    ledger.spend("kernel", *share, rule="total, then advanced composition over the rounds")
    settings = KernelSettings(*share, noise, rounds, out, accounting, max_rounds)
    if kernel == "frame" or kernel == "auto" and cell_bytes(inst, queries) > TASK_BYTES:
        return Release(_frame_release(inst, queries, sf_dir, dtilde, settings), None, queries, ledger)
    plan, volume = kernel_plan(inst, queries, sf_dir)
    return Release(_finish(_one(inst, queries, plan, volume, out_size(inst), dtilde), plan, settings), plan, queries, ledger)


def _budget(eps: float, delta: float, dp: str, group: int) -> tuple[Ledger, float, float]:
    """The ledger and what add/remove mechanisms may use when a unit touches ``group`` rows."""
    ledger = Ledger(eps, delta, dp)
    e, d = ledger.budget()
    return ledger, e / group, d / group


def release_two_table(inst: Instance, queries: QuerySet, sf_dir: str, eps: float, delta: float, noise: NoiseSource | None = None, rounds: int | str = "auto", dp: str = "add_remove", public_bound: float | None = None, **kernel: object) -> Release:
    """Noisy maximum degree, then the kernel at that sensitivity.  ``public_bound`` replaces the noisy degree by a declared cap."""
    if inst.spec.m != 2:
        raise ValueError("the maximum degree bounds the sensitivity of two-table joins only; use release_multi_table")
    inst, noise = materialise(inst), noise or NoiseSource.os()
    ledger, e, d = _budget(eps, delta, dp, inst.spec.group_factor)
    g = inst.spec.group_factor
    if public_bound is None:
        dtilde = max_degree(inst).first()[0] + noise.tlap(2 / e, tau(e / 2, d / 2, 1), "degree")
        ledger.spend("maximum degree", e / 2, d / 2, times=g)
        share = e / 2, d / 2
    else:
        dtilde, share = public_bound, (e, d)
    release = _release(inst, queries, sf_dir, dtilde, noise, rounds, _Grouped(ledger, g), share, **kernel)
    return replace(release, ledger=ledger)


class _Grouped:
    """A ledger whose steps count once for each row that a unit touches."""

    def __init__(self, ledger: Ledger, times: int) -> None:
        self.ledger, self.times = ledger, times

    def spend(self, step: str, eps: float, delta: float = 0.0, rule: str = "basic") -> None:
        self.ledger.spend(step, eps, delta, rule, self.times)


def release_padded(inst: Instance, queries: QuerySet, sf_dir: str, eps: float, delta: float, noise: NoiseSource | None = None, rounds: int | str = "auto", dp: str = "add_remove", **kernel: object) -> Release:
    """Pad first: uniform domain rows are added to the join before the kernel runs on the padded table with its exact total."""
    inst, noise = materialise(inst), noise or NoiseSource.os()
    g = inst.spec.group_factor
    ledger, eps, delta = _budget(eps, delta, dp, g)
    dtilde = max_degree(inst).first()[0] + noise.tlap(2 / eps, tau(eps / 2, delta / 2, 1), "degree")
    ledger.spend("maximum degree", eps / 2, delta / 2, times=g)
    plan, volume = kernel_plan(inst, queries, sf_dir)
    eta = int(round(noise.tlap(2 * dtilde / (eps / 2), tau(eps / 4, delta / 4, dtilde), "padding")))
    pad = _pad_rows(eta, len(plan.points), noise)
    truth = dense_answers(answers(inst, queries).collect(), queries) + plan.answers(pad)
    ledger.spend("padding and kernel", eps / 2, delta / 2, times=g)
    # the padded total is released as it is: the padding has covered it, so the kernel adds no noise of its own
    stats = inst.spark.createDataFrame([("all", float(out_size(inst) + eta), float(dtilde), truth.ravel().tolist(), [volume] * len(plan.points))], STATS)
    settings = KernelSettings(eps / 4, delta / 4, _NoTotal(noise.kind, noise.secret), rounds, **kernel)
    return Release(_finish(stats, plan, settings), plan, queries, ledger)


def _pad_rows(eta: int, n: int, noise: NoiseSource) -> np.ndarray:
    """How many of ``eta`` uniform rows fall into each of ``n`` cells."""
    if noise.kind == "zero":
        return np.full(n, eta / n)
    if noise.kind == "seeded":  # row by row, so that other engines can draw the same
        return np.bincount((noise.uniforms(eta, "pad") * n).astype(int), minlength=n).astype(float)
    return noise.generator("pad rows").multinomial(eta, np.full(n, 1 / n)).astype(float)


@dataclass(frozen=True)
class _NoTotal(NoiseSource):
    """Noise of the rounds, none on the total."""

    def tlap(self, b: float, radius: float, *key: object) -> float:
        return 0.0 if key and key[0] == "total" else super().tlap(b, radius, *key)


def release_multi_table(inst: Instance, queries: QuerySet, sf_dir: str, eps: float, delta: float, noise: NoiseSource | None = None, rounds: int | str = "auto", smooth: SmoothBound | None = None, beta: float | None = None, dp: str = "add_remove", **kernel: object) -> Release:
    """Residual sensitivity (or another smooth bound) raised by noise in the log domain, then the kernel; any join."""
    inst, noise = materialise(inst), noise or NoiseSource.os()
    ledger, e, d = _budget(eps, delta, dp, inst.spec.group_factor)
    beta = 1 / lam_of(e, d) if beta is None else beta
    bound = (smooth or ResidualBound()).value(inst, beta)
    dtilde = raise_bound(bound, beta, e, d, noise)
    ledger.spend("smooth bound", e / 2, d / 2, times=inst.spec.group_factor)
    release = _release(inst, queries, sf_dir, dtilde, noise, rounds, _Grouped(ledger, inst.spec.group_factor), (e / 2, d / 2), **kernel)
    return replace(release, ledger=ledger)


def raise_bound(bound: float, beta: float, eps: float, delta: float, noise: NoiseSource, *key: object) -> float:
    """A private upper bound on a smooth bound: its logarithm changes by at most beta between neighbours."""
    return float(bound * np.exp(noise.tlap(2 * beta / eps, tau(eps / 2, delta / 2, beta), "smooth", *key)))


def group_stats(part: Partition, queries: QuerySet, plan: KernelPlan, volume: float, eps: float, delta: float, noise: NoiseSource, inner: str, key_share: DataFrame | None) -> DataFrame:
    """Rows of STATS for every sub-instance: degrees or boundary maxima, join sizes and answers with the label as a group key.

    ``eps, delta`` are the whole budget of a sub-instance's release, half of which its sensitivity takes.
    """
    inst, by = part.instance, part.by
    spark = inst.spark
    label = by[0]
    sizes = join_size(inst, by).select(F.col(label).cast("string").alias("sub_id"), F.col("val").cast("double").alias("out_size"))
    m = inst.spec.m
    numbers = [F.col(f"q{i + 1}") for i in range(m)]
    widths = [len(f) for f in queries.families]
    place = numbers[0]
    for n, w in zip(numbers[1:], widths[1:], strict=True):
        place = place * w + n
    found = answers(inst, queries, by).select(F.col(label).cast("string").alias("sub_id"), place.cast("int").alias("place"), "answer")
    sparse = found.groupBy("sub_id").agg(F.map_from_entries(F.collect_list(F.struct("place", "answer"))).alias("by_place"))
    total = int(np.prod(widths))
    dense = F.transform(F.sequence(F.lit(0), F.lit(total - 1)), lambda i: F.coalesce(F.element_at("by_place", i), F.lit(0.0)))
    if inner == "two":
        on = list(join_attrs(inst.spec))
        every = None
        for f in inst.frames:
            one = f.groupBy(label, *on).agg(F.sum("freq").alias("deg"))
            every = one if every is None else every.unionByName(one)
        exact = every.groupBy(F.col(label).cast("string").alias("sub_id")).agg(F.max("deg").cast("double").alias("bound"))
    else:
        exact = label_bounds(part, 1 / lam_of(eps, delta)).select("sub_id", "bound")
    # a part without rows has the bound of empty tables
    empty = 0.0 if inner == "two" else residual_sensitivity({frozenset(e): float(not e) for e in subsets(m)}, m, 1 / lam_of(eps, delta))
    labels = part.labels.select(F.col(label).cast("string").alias("sub_id")).distinct()
    rows = labels.join(sizes, "sub_id", "left").join(sparse, "sub_id", "left").join(exact, "sub_id", "left")
    share = rows.select("sub_id", F.coalesce("out_size", F.lit(0.0)).alias("out_size"), F.coalesce("bound", F.lit(empty)).alias("bound"), dense.alias("truth")) if total else rows
    if key_share is not None:
        share = share.join(key_share, "sub_id", "left")
        volumes = F.array_repeat(F.coalesce("share", F.lit(0.0)) * volume, len(plan.points))
    else:
        volumes = F.array_repeat(F.lit(volume), len(plan.points))
    share = share.withColumn("volumes", volumes)

    import pandas as pd

    def raised(frame: pd.DataFrame) -> pd.DataFrame:
        beta = 1 / lam_of(eps, delta)
        out = []
        for s, b in zip(frame["sub_id"], frame["bound"], strict=True):
            out.append(b + noise.tlap(2 / eps, tau(eps / 2, delta / 2, 1), "degree", s) if inner == "two" else raise_bound(b, beta, eps, delta, noise, s))
        return frame.assign(dtilde=out)[["sub_id", "out_size", "dtilde", "truth", "volumes"]]

    return share.groupBy("sub_id").applyInPandas(raised, STATS)


def release_uniformized(inst: Instance, queries: QuerySet, sf_dir: str, eps: float, delta: float, noise: NoiseSource | None = None, rounds: int | str = "auto", partitioner: str = "two_table", inner: str | None = None, lam: float | None = None, n_max: float = 2.0**40, max_configs: int = 10**6, dp: str = "add_remove", domain_size: int | None = None, **kernel: object) -> Release:
    """Partition privately, release every part, return the union.  One Spark job for all parts.

    The parts of a two-table partition are disjoint, so releasing them counts once.  In a hierarchical
    partition a tuple may be in several parts: the budget is divided by a public bound before any noise.
    Degrees of the whole public domain are noised, with rows or without, and every part that follows from the noisy
    degrees is released, empty ones too, so what is released never tells which values occur.  ``domain_size``: a public
    number of join values that can't be listed (two tables).
    """
    inst, noise = materialise(inst), noise or NoiseSource.os()
    g = inst.spec.group_factor
    ledger, eps, delta = _budget(eps, delta, dp, g)
    lam = lam_of(eps, delta) if lam is None else lam
    inner = inner or ("two" if inst.spec.m == 2 else "multi")
    plan, volume = kernel_plan(inst, queries, sf_dir)
    key_share = None
    if partitioner == "two_table":
        if not join_attrs(inst.spec):
            raise ValueError("the tables share no attribute: there is one join value and nothing to partition")
        ledger.spend("degrees", eps / 2, delta / 2, "parallel over join values", g)
        if domain_size is not None:
            part, key_share = partition_open_domain(inst, domain_size, eps / 2, delta / 2, lam, noise)
        else:
            domain = joint_domain(inst.spark, sf_dir, inst.spec, join_attrs(inst.spec))
            part = partition_two_table(inst, domain, eps / 2, delta / 2, lam, noise)
            whole = domain.count()
            key_share = part.labels.groupBy(F.col("bucket").cast("string").alias("sub_id")).agg((F.count("*") / F.lit(float(whole))).alias("share"))
        share = eps / 2, delta / 2
        ledger.spend("parts", *share, "parallel", g)
    else:
        copies = replication_bound(inst, n_max, lam)
        if copies > max_configs:
            raise ValueError(f"{copies} parts may hold one tuple, above the public cap {max_configs}")
        touched = degree_bound(inst, n_max, lam)
        e, d = eps / 2 / touched, delta / 2 / touched
        part = partition_hierarchical(inst, e, d, lam, noise, lambda attrs: joint_domain(inst.spark, sf_dir, inst.spec, attrs), last=bucket_count(n_max, lam))
        ledger.spend("degrees", e, d, "group privacy over the degrees that a tuple changes", touched * g)
        share = eps / 2 / copies, delta / 2 / copies
        ledger.spend("parts", *share, "group privacy over the parts of a tuple", copies * g)
    stats = group_stats(part, queries, plan, volume, *share, noise, inner, key_share)
    settings = KernelSettings(share[0] / 2, share[1] / 2, noise, rounds, **kernel)
    return Release(_finish(stats, plan, settings), plan, queries, ledger)


def release_exact_total(inst: Instance, queries: QuerySet, sf_dir: str, eps: float, delta: float, noise: NoiseSource, rounds: int, allow_nonprivate: bool = False, out: str = "average") -> Release:
    """First broken idea: the kernel with the exact join size as its total, which the total gives away."""
    require(allow_nonprivate, "a release with the exact join size")
    plan, volume = kernel_plan(inst, queries, sf_dir)
    stats = _one(inst, queries, plan, volume, out_size(inst), 1.0)
    return Release(_finish(stats, plan, KernelSettings(eps, delta, _NoTotal(noise.kind, noise.secret), rounds, out)), plan, queries, Ledger(eps, delta))


def release_pad_after(inst: Instance, queries: QuerySet, sf_dir: str, eps: float, delta: float, noise: NoiseSource, rounds: int, allow_nonprivate: bool = False) -> Release:
    """Second broken idea: padding after an exact-total release leaves regions empty in one neighbour and heavy in the other."""
    require(allow_nonprivate, "padding after an exact release")
    first = release_exact_total(inst, queries, sf_dir, eps, delta, noise, rounds, True)
    dtilde = max_degree(inst).first()[0] + noise.tlap(2 / eps, tau(eps / 2, delta / 2, 1), "degree")
    eta = int(round(noise.tlap(2 * dtilde / eps, tau(eps / 2, delta / 2, dtilde), "padding")))
    n = len(first.plan.points)
    pad = _pad_rows(eta, n, noise)
    extra = inst.spark.createDataFrame(list(enumerate(pad.tolist())), "cell int, pad double")
    return replace(first, cells=first.cells.join(F.broadcast(extra), "cell").withColumn("mass", F.col("mass") + F.col("pad")).drop("pad"))


