"""Noise: truncation radius, inverse distribution functions as columns and as numbers, private choice.

Noise is a keyed function of (secret, purpose, key): a task that runs again draws the same value,
so a retry neither spends budget twice nor mixes outputs.  ``kind='os'`` draws the secret from the
operating system once a release, ``'seeded'`` takes it from the caller (tests), ``'zero'`` is for
tests of exactness and is not private.
"""

from __future__ import annotations

import hashlib
import math
import secrets
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def tau(eps: float, delta: float, sens: float) -> float:
    """Radius of truncation that makes the truncated noise (eps, delta)-private at this sensitivity."""
    return sens / eps * math.log1p(math.expm1(eps) / delta)


@dataclass(frozen=True)
class NoiseSource:
    kind: str = "os"
    secret: str = ""

    @staticmethod
    def os() -> NoiseSource:
        return NoiseSource("os", secrets.token_hex(16))

    @staticmethod
    def seeded(secret: str) -> NoiseSource:
        return NoiseSource("seeded", secret)

    @staticmethod
    def zero() -> NoiseSource:
        return NoiseSource("zero", "")

    def uniform(self, *key: object) -> float:
        """A number in (0, 1) for the key; the same in SQL as the first 13 hex digits of an md5."""
        digest = hashlib.md5("|".join(map(str, (self.secret, *key))).encode()).hexdigest()
        return (int(digest[:13], 16) + 0.5) / 2.0**52

    def generator(self, *key: object) -> np.random.Generator:
        return np.random.default_rng(int.from_bytes(hashlib.sha256("|".join(map(str, (self.secret, *key))).encode()).digest()[:16], "big"))

    def uniforms(self, n: int, *key: object) -> np.ndarray:
        """``n`` numbers in (0, 1): those of :meth:`uniform` for the key and each number below ``n`` if seeded, else of one generator."""
        if self.kind == "seeded":
            return np.array([self.uniform(*key, i) for i in range(n)])
        return np.clip(self.generator(*key).random(n), 1e-300, 1 - 2.0**-53)

    def laplace(self, b: float, *key: object) -> float:
        return 0.0 if self.kind == "zero" else laplace_value(b, self.uniform(*key))

    def tlap(self, b: float, radius: float, *key: object) -> float:
        return 0.0 if self.kind == "zero" else tlap_value(b, radius, self.uniform(*key))


def laplace_value(b: float, u: float) -> float:
    return b * math.log(2 * u) if u < 0.5 else -b * math.log(2 * (1 - u))


def tlap_value(b: float, radius: float, u: float) -> float:
    """Inverse distribution function of the Laplace law centred at ``radius`` and cut to [0, 2 * radius]."""
    edge = math.exp(-radius / b)
    low = min(u, 1 - u)
    half = radius + b * math.log(edge + 2 * low * (1 - edge))
    return half if u < 0.5 else 2 * radius - half


def tlap_below(x: float, b: float, radius: float) -> float:
    """Distribution function of that law."""
    if x <= 0 or x >= 2 * radius:
        return float(x >= 2 * radius)
    edge = math.exp(-radius / b)
    half = (math.exp((min(x, 2 * radius - x) - radius) / b) - edge) / (2 * (1 - edge))
    return half if x <= radius else 1 - half


def uniform_col(secret: str, *key: Column | str) -> Column:
    """The column of :meth:`NoiseSource.uniform`."""
    digest = F.md5(F.concat_ws("|", F.lit(secret), *(k if isinstance(k, Column) else F.lit(k) for k in key)).cast("binary"))
    return (F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") + 0.5) / F.lit(2.0**52)


def laplace_col(b: float | Column, u: Column) -> Column:
    b = F.lit(b) if isinstance(b, (int, float)) else b
    return F.when(u < 0.5, b * F.log(2 * u)).otherwise(-b * F.log(2 * (1 - u)))


def tlap_col(b: float | Column, radius: float | Column, u: Column) -> Column:
    b, radius = (F.lit(float(x)) if isinstance(x, (int, float)) else x for x in (b, radius))
    edge = F.exp(-radius / b)
    half = radius + b * F.log(edge + 2 * F.least(u, 1 - u) * (1 - edge))
    return F.when(u < 0.5, half).otherwise(2 * radius - half)


def gumbel_col(u: Column) -> Column:
    return -F.log(-F.log(u))


def exp_mech(scores: DataFrame, score: str, key: str, eps: float, noise: NoiseSource, purpose: str = "em") -> DataFrame:
    """One row: a candidate drawn with probability proportional to exp(eps/2 * score), by the largest Gumbel-shifted score."""
    shifted = F.lit(eps / 2) * F.col(score)
    if noise.kind != "zero":
        shifted = shifted + gumbel_col(uniform_col(noise.secret, purpose, F.col(key).cast("string")))
    return scores.withColumn("_shifted", shifted).agg(F.max_by(F.struct(*scores.columns), F.struct("_shifted", F.col(key))).alias("c")).select("c.*")


def exp_mech_index(scores: np.ndarray, eps: float, u: np.ndarray | None) -> int:
    """The same choice in a task, by uniform numbers; without them the first largest score."""
    if u is None:
        return int(np.argmax(np.round(scores, 6)))
    return int(np.argmax(eps / 2 * scores - np.log(-np.log(u))))
