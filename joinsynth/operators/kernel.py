"""The multiplicative-weights kernel over signature cells.

A cell stands for all domain points with equal weights in every query; it holds their common mass
times their number.  Query weights are kept per relation (``weights[i]``: queries of family i by
cells), and answers of all product queries on a histogram are a chain of small matrix products,
never a (cells x queries) matrix.

Two executions with the same arithmetic: :func:`run_task` keeps all rounds in one task, one row a
sub-instance, so the sub-instances of a partitioned release run in parallel in one Spark job;
:func:`run_frame` keeps the cells as a DataFrame for cell tables beyond a task's memory, with one
pass a round.  Its durable state is the sum of steps of every query on the driver: log-weights
are rebuilt from it in one matrix product, so the plan doesn't grow with the rounds.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions.bounds import auto_rounds, round_budget
from ..functions.noise import NoiseSource, exp_mech_index, tau
from ..queries import QuerySet

#: Bytes of (cells x queries of one family) up to which rounds run in a task.
TASK_BYTES = 2 * 10**8


@dataclass(frozen=True)
class KernelPlan:
    """What is public: cells, their volumes, weights by family, and the log of the true domain's size."""

    points: list[tuple]
    attrs: tuple[str, ...]
    weights: tuple[np.ndarray, ...]
    log_domain: float

    @property
    def n_queries(self) -> int:
        return int(np.prod([len(w) for w in self.weights]))

    def bytes(self) -> int:
        return max(w.nbytes for w in self.weights)

    def answers(self, mass: np.ndarray) -> np.ndarray:
        """Answers of all product queries, one axis per family."""
        sizes = [len(w) for w in self.weights]
        if len(sizes) == 1:
            return self.weights[0] @ mass
        left = self.weights[0] * mass
        for w in self.weights[1:-1]:
            left = (left[:, None, :] * w[None, :, :]).reshape(-1, left.shape[-1])
        return (left @ self.weights[-1].T).reshape(sizes)

    def weight_of(self, number: int) -> np.ndarray:
        """The product query's weight on every cell."""
        at = np.unravel_index(number, [len(w) for w in self.weights])
        return np.prod([w[i] for w, i in zip(self.weights, at, strict=True)], axis=0)


def plan_weights(spark, points: list[tuple], attrs: tuple[str, ...], queries: QuerySet, log_domain: float) -> KernelPlan:
    """Evaluates the families' SQL expressions on the public cells."""
    rows = spark.createDataFrame([(i, *p) for i, p in enumerate(points)], ["cell", *attrs])
    width = [F.array(*f.columns()).alias(f"f{i}") for i, f in enumerate(queries.families)]
    found = sorted(rows.select("cell", *width).collect(), key=lambda r: r["cell"])
    return KernelPlan(points, attrs, tuple(np.array([r[f"f{i}"] for r in found]).T.copy() for i in range(len(width))), log_domain)


def choose(truth: np.ndarray, error: np.ndarray, dtilde: float, eps_round: float, noise: NoiseSource, r: int, *key: object) -> tuple[int, float]:
    """A round's private choice of a query with a large error, and its noisy measurement."""
    if noise.kind == "zero":
        chosen = exp_mech_index(error, eps_round, None)
        return chosen, float(truth[chosen])
    chosen = exp_mech_index(error / dtilde, eps_round, noise.uniforms(len(error), "choice", r, *key))
    return chosen, float(truth[chosen]) + noise.laplace(dtilde / eps_round, "measure", r, *key)


@dataclass
class Trace:
    """Non-private record of a run: chosen query, measured value, largest error before each round, potential."""

    query: list[int] = field(default_factory=list)
    measured: list[float] = field(default_factory=list)
    error: list[float] = field(default_factory=list)
    potential: list[float] = field(default_factory=list)


def noisy_total(out: float, dtilde: float, eps: float, delta: float, noise: NoiseSource, *key: object) -> float:
    """Join size plus truncated noise of radius tau(eps/2, delta/2, dtilde): never below the join size."""
    return out + noise.tlap(2 * dtilde / eps, tau(eps / 2, delta / 2, dtilde), "total", *key)


def uniform_start(n_hat: float, volumes: np.ndarray) -> np.ndarray:
    return n_hat * volumes / volumes.sum() if volumes.sum() > 0 else volumes * 0.0


def step_size(measured: float, current: float, n_hat: float) -> float:
    """Exponent of the update; the measurement is clamped to what a histogram of this total can answer."""
    return (min(n_hat, max(-n_hat, measured)) - current) / (2 * n_hat)


def _potential(truth: np.ndarray, mass: np.ndarray) -> float:
    """Relative entropy of the true cell totals to the histogram's, both normalised."""
    p, q = truth / truth.sum(), mass / mass.sum()
    some = p > 0
    return float((p[some] * np.log(p[some] / np.maximum(q[some], 1e-300))).sum())


def run_task(plan: KernelPlan, truth: np.ndarray, volumes: np.ndarray, n_hat: float, dtilde: float, eps: float, delta: float, noise: NoiseSource, rounds: int, out: str = "average", accounting: str = "advanced", key: tuple = (), trace: Trace | None = None, true_cells: np.ndarray | None = None) -> np.ndarray:
    """Mass of every cell after all rounds (average of the histograms, or the last)."""
    start = uniform_start(n_hat, volumes)
    if rounds < 1 or n_hat <= 0 or not start.any():
        return start
    eps_round = round_budget(eps, delta, rounds, accounting)
    log_w = np.log(np.maximum(start, 1e-300))
    mass, total = start, np.zeros_like(start)
    flat = truth.ravel()
    for r in range(rounds):
        now = plan.answers(mass).ravel()
        error = np.abs(now - flat)
        chosen, measured = choose(flat, error, dtilde, eps_round, noise, r, *key)
        if trace is not None:
            trace.query.append(chosen)
            trace.measured.append(measured)
            trace.error.append(float(error.max()))
            if true_cells is not None:
                trace.potential.append(_potential(true_cells, mass))
        log_w = log_w + plan.weight_of(chosen) * step_size(measured, float(now[chosen]), n_hat)
        mass = np.exp(log_w - log_w[volumes > 0].max())
        mass[volumes <= 0] = 0.0
        mass = mass * (n_hat / mass.sum())
        total += mass
    if trace is not None and true_cells is not None:
        trace.potential.append(_potential(true_cells, mass))
    return total / rounds if out == "average" else mass


@dataclass(frozen=True)
class KernelSettings:
    eps: float
    delta: float
    noise: NoiseSource
    rounds: int | str = "auto"
    out: str = "average"
    accounting: str = "advanced"
    max_rounds: int | None = None


#: One row per sub-instance: exact statistics that never leave a task but through noise.
STATS = "sub_id string, out_size double, dtilde double, truth array<double>, volumes array<double>"
CELLS = "sub_id string, cell int, volume double, mass double, n_hat double, dtilde double, rounds int"


def release_groups(stats: DataFrame, plan: KernelPlan, settings: KernelSettings) -> DataFrame:
    """Kernel of every sub-instance (rows as in STATS) to its cells (rows as in CELLS), one group a task."""
    shape = [len(w) for w in plan.weights]

    def one(rows: pd.DataFrame) -> pd.DataFrame:
        r = rows.iloc[0]
        volumes, s = np.array(r["volumes"], float), settings
        n_hat = noisy_total(r["out_size"], r["dtilde"], s.eps, s.delta, s.noise, r["sub_id"])
        share = volumes.sum()
        log_domain = plan.log_domain if share <= 0 else float(np.log(share))
        k = auto_rounds(n_hat, s.eps, s.delta, r["dtilde"], max(log_domain, 1e-9), plan.n_queries, s.max_rounds) if s.rounds == "auto" else int(s.rounds)
        mass = run_task(plan, np.array(r["truth"], float).reshape(shape), volumes, n_hat, r["dtilde"], s.eps, s.delta, s.noise, k, s.out, s.accounting, (r["sub_id"],))
        return pd.DataFrame({"sub_id": r["sub_id"], "cell": np.arange(len(mass), dtype=np.int32), "volume": volumes, "mass": mass, "n_hat": n_hat, "dtilde": r["dtilde"], "rounds": np.int32(k)})

    return stats.groupBy("sub_id").applyInPandas(one, CELLS)


def frame_weights(cells: DataFrame, queries: QuerySet) -> DataFrame:
    """``cells`` with an array column of weights for each family, ``f1..fm``."""
    return cells.select("*", *(F.array(*f.columns()).alias(f"f{i + 1}") for i, f in enumerate(queries.families)))


def _weights_of(rows: pd.DataFrame, m: int) -> list[np.ndarray]:
    return [np.array(rows[f"f{i + 1}"].tolist(), float) for i in range(m)]


def _product_answers(weights: list[np.ndarray], mass: np.ndarray) -> np.ndarray:
    """Answers of all product queries on some cells (rows of each weight matrix), flat."""
    left = (weights[0] * mass[:, None]) if len(weights) > 1 else mass[:, None]
    for w in weights[1:-1]:
        left = (left[:, :, None] * w[:, None, :]).reshape(len(mass), -1)
    return (left.T @ weights[-1]).ravel()


def _summed_weights(weights: list[np.ndarray], steps: np.ndarray) -> np.ndarray:
    """For each cell the sum over product queries of step times weight."""
    out = steps[None, ...]
    for w in weights:
        out = (w.reshape(len(w), -1, *([1] * (out.ndim - 2))) * out).sum(axis=1)
    return out


def run_frame(cells: DataFrame, queries: QuerySet, truth: np.ndarray, n_hat: float, dtilde: float, eps: float, delta: float, noise: NoiseSource, rounds: int, out: str = "average", accounting: str = "advanced", key: tuple = ()) -> DataFrame:
    """``cells`` (attributes, volume) to the same with ``mass``; one pass over the cells a round and one at the end.

    The state is the sum of steps of every query, an array of the size of the workload: a round's log-weights follow
    from it in one matrix product a batch, so neither plan nor work grows with the rounds gone.  A batch returns its
    answers with its largest log-weight and their sum; the driver adds up one row a task.
    """
    shape, m = [len(f) for f in queries.families], len(queries.families)
    live = frame_weights(cells.filter("volume > 0"), queries)
    narrow = live.select("volume", *(f"f{i + 1}" for i in range(m)))
    flat, eps_round = truth.ravel(), round_budget(eps, delta, max(1, rounds), accounting)
    steps, taken = np.zeros(shape), []

    def answered(total: np.ndarray):
        def run(batches):
            top, z, sums = -np.inf, 0.0, np.zeros(len(flat))
            for rows in batches:
                if not len(rows):
                    continue
                weights = _weights_of(rows, m)
                lw = np.log(rows["volume"].to_numpy(float)) + _summed_weights(weights, total)
                high = max(top, float(lw.max()))
                mass, fade = np.exp(lw - high), np.exp(top - high)
                top, z, sums = high, z * fade + mass.sum(), sums * fade + _product_answers(weights, mass)
            if z > 0:
                yield pd.DataFrame({"top": [top], "z": [z], "sums": [sums.tolist()]})

        found = narrow.mapInPandas(run, "top double, z double, sums array<double>").collect()
        high = max(r["top"] for r in found)
        parts = [np.exp(r["top"] - high) for r in found]
        z = sum(p * r["z"] for p, r in zip(parts, found, strict=True))
        return high, z, sum(p * np.array(r["sums"]) for p, r in zip(parts, found, strict=True)) * (n_hat / z)

    if not rounds or n_hat <= 0 or not narrow.limit(1).count():
        total = cells.agg(F.sum("volume")).first()[0]
        return cells.withColumn("mass", F.col("volume") * F.lit(float(n_hat / total) if total else 0.0))
    scales = []
    for r in range(rounds):
        high, z, now = answered(steps)
        scales.append((high, z))
        chosen, measured = choose(flat, np.abs(now - flat), dtilde, eps_round, noise, r, *key)
        step = step_size(measured, float(now[chosen]), n_hat)
        taken.append((chosen, step))
        steps[np.unravel_index(chosen, shape)] += step
    scales.append(answered(steps)[:2])

    def massed(batches):
        for rows in batches:
            weights = _weights_of(rows, m)
            lw, total = np.log(rows["volume"].to_numpy(float)), np.zeros(len(rows))
            for (chosen, step), (high, z) in zip(taken, scales[1:], strict=True):
                at = np.unravel_index(chosen, shape)
                lw = lw + step * np.prod([w[:, i] for w, i in zip(weights, at, strict=True)], axis=0)
                now = np.exp(lw - high) * (n_hat / z)
                total = total + now if out == "average" else now
            yield rows.assign(mass=total / rounds if out == "average" else total)[[*kept, "mass"]]

    kept = cells.columns
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in cells.schema)
    return live.mapInPandas(massed, f"{schema}, mass double").unionByName(cells.filter("not (volume > 0)").withColumn("mass", F.lit(0.0)))
