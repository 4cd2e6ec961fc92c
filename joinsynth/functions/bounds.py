"""Error bounds with all hidden constants set to one, as plain functions of instance statistics.

Two printed variants of some bounds exist; ``'primary'`` is the one its derivation supports.
"""

from __future__ import annotations

import math
from collections.abc import Iterable


def lam(eps: float, delta: float) -> float:
    return math.log(1 / delta) / eps


def f_low(log_domain: float, eps: float) -> float:
    return math.sqrt(math.sqrt(log_domain) / eps)


def f_up(log_domain: float, eps: float, delta: float, n_queries: float, tight: bool = False) -> float:
    """``tight`` uses the fourth root of ln(1/delta) that the derivation yields in place of the printed square root."""
    extra = math.log(1 / delta) ** 0.25 if tight else math.sqrt(math.log(1 / delta))
    return f_low(log_domain, eps) * math.sqrt(math.log(n_queries)) * extra if n_queries > 1 else f_low(log_domain, eps) * extra


def upper_kernel(out: float, dtilde: float, lam_: float, up: float) -> float:
    return (math.sqrt(out * dtilde) + dtilde * math.sqrt(lam_)) * up


def upper_two_table(out: float, delta_deg: float, lam_: float, up: float) -> float:
    return upper_kernel(out, delta_deg + lam_, lam_, up)


def upper_multi_table(out: float, rs: float, lam_: float, up: float, variant: str = "primary") -> float:
    if variant == "early":
        return (math.sqrt(out * rs * lam_) + rs * lam_) * up
    return upper_kernel(out, rs, lam_, up)


def upper_uniformized(outs: Iterable[tuple[int, float]], delta_deg: float, lam_: float, up: float) -> float:
    """``outs``: (bucket, join size)."""
    return (lam_**1.5 * (delta_deg + lam_) + sum(math.sqrt(o * 2.0**i * lam_) for i, o in outs)) * up


def upper_hierarchical(parts: Iterable[tuple[float, float]], lam_: float, up: float) -> float:
    """``parts``: (join size, residual sensitivity) of each configuration."""
    return sum(math.sqrt(o * rs * lam_) + rs * lam_ for o, rs in parts) * up


def lower_single(n: float, low: float) -> float:
    return min(n, math.sqrt(n) * low)


def lower_sensitivity(ls: float) -> float:
    return ls


def lower_join(out: float, ls: float, low: float, variant: str = "primary") -> float:
    """The early variant has no cap at the join size."""
    return math.sqrt(out * ls) * low if variant == "early" else min(out, math.sqrt(out * ls) * low)


def lower_uniformized(outs: Iterable[tuple[int, float]], lam_: float, low: float) -> float:
    return max((min(o, math.sqrt(o * 2.0**i * lam_) * low) for i, o in outs), default=0.0)


def lower_hierarchical(parts: Iterable[tuple[float, float]], low: float) -> float:
    """``parts``: (join size, local sensitivity) of each configuration."""
    return max((min(o, math.sqrt(o * ls) * low) for o, ls in parts), default=0.0)


def uniformization_gain(outs: Iterable[tuple[int, float]], delta_deg: float) -> tuple[float, float]:
    """(whole-join term, sum of the buckets' terms): sqrt(OUT * max degree) against the sum of sqrt(OUT_i * 2**i)."""
    outs = list(outs)
    return math.sqrt(sum(o for _, o in outs) * delta_deg), sum(math.sqrt(o * 2.0**i) for i, o in outs)


def round_budget(eps: float, delta: float, rounds: int, accounting: str = "advanced") -> float:
    """Budget of one of ``rounds`` rounds, each a private choice and a measurement.

    ``'advanced'``: eps / (16 * sqrt(k ln(1/delta))).  ``'zcdp'``: the largest e with
    k * (e**2/8 + e**2/2) = rho and rho + 2 sqrt(rho ln(1/delta)) = eps (published concentrated accounting).
    """
    if accounting == "advanced":
        return eps / (16 * math.sqrt(rounds * math.log(1 / delta)))
    rho = (math.sqrt(math.log(1 / delta) + eps) - math.sqrt(math.log(1 / delta))) ** 2
    return math.sqrt(rho / (rounds * 0.625))


def auto_rounds(n_hat: float, eps: float, delta: float, dtilde: float, log_domain: float, n_queries: int, most: int | None = None) -> int:
    """Number of rounds that balances the two error terms, at least one; ``most``: a cap that the caller wants."""
    if n_queries < 2 or n_hat <= 0 or dtilde <= 0:
        return 1
    k = n_hat * eps * math.sqrt(log_domain) / (dtilde * math.log(n_queries) * math.sqrt(math.log(1 / delta)))
    return max(1, int(k) if most is None else min(most, int(k)))
