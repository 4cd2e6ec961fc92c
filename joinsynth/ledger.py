"""Privacy accounting: what each step spends, and how steps compose."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession


class BudgetExceeded(ValueError):
    """A step asks for more than is left."""


class NotPrivate(ValueError):
    """A step isn't differentially private and wasn't explicitly allowed."""


@dataclass
class Ledger:
    """Steps of one release under a total (eps, delta).

    Basic composition adds; steps on disjoint parts of the data count once (the largest); a unit
    that may touch ``k`` rows or parts multiplies both figures by ``k`` (the mechanisms are run at
    the divided budget); post-processing is free; substituting a row costs two units.
    """

    eps: float
    delta: float
    dp: str = "add_remove"
    steps: list[tuple[str, float, float, str]] = field(default_factory=list)

    def __post_init__(self) -> None:
        if self.dp not in ("add_remove", "substitute"):
            raise ValueError(self.dp)

    @property
    def units(self) -> int:
        return 2 if self.dp == "substitute" else 1

    def budget(self) -> tuple[float, float]:
        """What the mechanisms of add/remove neighbours may use in all."""
        return self.eps / self.units, self.delta / self.units

    def spend(self, step: str, eps: float, delta: float = 0.0, rule: str = "basic", times: int = 1) -> None:
        eps, delta = eps * times, delta * times
        self.steps.append((step, eps, delta, rule))
        if self.total[0] > self.eps / self.units * (1 + 1e-9) or self.total[1] > self.delta / self.units * (1 + 1e-9):
            self.steps.pop()
            raise BudgetExceeded(step)

    def parallel(self, step: str, parts: list[tuple[float, float]]) -> None:
        """Steps on disjoint parts."""
        self.spend(step, max((p[0] for p in parts), default=0.0), max((p[1] for p in parts), default=0.0), "parallel")

    def note(self, step: str, rule: str = "post-processing") -> None:
        self.steps.append((step, 0.0, 0.0, rule))

    @property
    def total(self) -> tuple[float, float]:
        return sum(s[1] for s in self.steps), sum(s[2] for s in self.steps)

    @property
    def remaining(self) -> tuple[float, float]:
        e, d = self.total
        return self.eps / self.units - e, self.delta / self.units - d

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.steps, "step string, eps double, delta double, rule string")


def per_query(eps: float, delta: float, n: int, composition: str = "basic") -> tuple[float, float]:
    """Budget of each of ``n`` separate answers: an equal share, or advanced composition's."""
    if composition == "basic":
        return eps / n, delta / n
    import math

    return eps / (2 * math.sqrt(2 * n * math.log(2 / delta))), delta / (2 * n)


def require(allowed: bool, what: str) -> None:
    if not allowed:
        raise NotPrivate(f"{what} is not differentially private; pass allow_nonprivate=True to run it as a counter-example")
