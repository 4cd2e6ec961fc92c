"""Sensitivity statistics: degrees, boundary maxima, residual and smooth bounds, hierarchical degrees.

All statistics are plans over frequency tables; what reaches the driver is one number per
(constant-size) subset of relations.
"""

from __future__ import annotations

import itertools
import math
from collections.abc import Iterable
from typing import Protocol

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..hyper import AttrTree, JoinSpec, boundary, meet, product_factors
from ..plans.elimination import clusters, contract, count_factor, join_size
from ..relation import COUNT, Instance, neighbor


def degrees(frame: DataFrame, attrs: tuple[str, ...], name: str = "deg") -> DataFrame:
    """Sum of frequencies per join value."""
    return frame.groupBy(*attrs).agg(F.sum("freq").alias(name))


def join_attrs(spec: JoinSpec) -> tuple[str, ...]:
    """All attributes that the two relations of a join share (one composite join value)."""
    return meet(spec, range(spec.m))


def degree_table(inst: Instance) -> DataFrame:
    """(join value, deg1, deg2) of a two-table join; absent sides are zero."""
    on = list(join_attrs(inst.spec))
    left, right = (degrees(f, tuple(on), f"deg{i + 1}") for i, f in enumerate(inst.frames))
    zero = F.lit(0).cast("bigint")
    return left.join(right, on, "full").select(*on, F.coalesce("deg1", zero).alias("deg1"), F.coalesce("deg2", zero).alias("deg2"))


def max_degree(inst: Instance) -> DataFrame:
    """One row: the largest degree on either side (the local sensitivity of the count)."""
    on = join_attrs(inst.spec)
    every = degrees(inst.frames[0], on).unionByName(degrees(inst.frames[1], on))
    return every.agg(F.coalesce(F.max("deg"), F.lit(0)).cast("bigint").alias("max_degree"))


def _sub(inst: Instance, rels: Iterable[int]) -> list:
    return [count_factor(inst.frames[i], tuple(c for c in inst.frames[i].columns if c != "freq")) for i in rels]


def aggregate_max(inst: Instance, rels: Iterable[int], given: tuple[str, ...], by: tuple[str, ...] = ()) -> DataFrame:
    """``[by], t``: the join of ``rels`` grouped by ``given``, its largest group (1 for no relations).

    Parts that share none of the given attributes are maximised apart and multiplied, which is exact.
    """
    rels = tuple(rels)
    if not rels:
        return inst.spark.range(1).select(F.lit(1).cast(COUNT).alias("t"))
    parts = clusters(contract(_sub(inst, rels), (*given, *by)))
    out = None
    for p in parts:
        own = [b for b in by if b in p.attrs]
        one = p.frame.groupBy(*own).agg(F.max("val").alias("t"))
        if not own:
            one = one.select(F.coalesce("t", F.lit(0).cast(COUNT)).alias("t"))
        if out is None:
            out = one
        else:
            right = one.withColumnRenamed("t", "t2")
            shared = [c for c in out.columns if c in right.columns]
            both = out.join(right, shared) if shared else out.crossJoin(right)
            out = both.withColumn("t", (F.col("t") * F.col("t2")).cast(COUNT)).drop("t2")
    return out


def boundary_max(inst: Instance, rels: Iterable[int]) -> DataFrame:
    return aggregate_max(inst, rels, boundary(inst.spec, rels))


def subsets(m: int, proper: bool = True) -> list[tuple[int, ...]]:
    return [e for k in range(m if proper else m + 1) for e in itertools.combinations(range(m), k)]


def boundary_table(inst: Instance, sets: list[tuple[int, ...]] | None = None) -> DataFrame:
    """(rels, t) for every proper subset of relations, as one plan: one job, 2**m - 1 rows."""
    out = None
    for e in subsets(inst.spec.m) if sets is None else sets:
        one = boundary_max(inst, e).select(F.lit(",".join(str(i + 1) for i in e)).alias("rels"), "t")
        out = one if out is None else out.unionByName(one)
    return out


def collect_table(table: DataFrame) -> dict[frozenset[int], int]:
    return {frozenset(int(x) - 1 for x in r.rels.split(",") if x): int(r.t) for r in table.collect()}


def local_sensitivity(inst: Instance) -> DataFrame:
    """One row: the largest boundary maximum of all relations but one."""
    every = range(inst.spec.m)
    out = None
    for i in every:
        one = boundary_max(inst, [j for j in every if j != i])
        out = one if out is None else out.unionByName(one)
    return out.agg(F.max("t").cast("bigint").alias("local_sensitivity"))


def ls_hat(table: dict[frozenset[int], float], m: int, s: tuple[int, ...], i: int) -> float:
    """The bound for excluded relation ``i`` when the others may gain ``s`` units."""
    rest = [j for j in range(m) if j != i]
    return sum(table[frozenset(rest) - frozenset(e)] * math.prod(s[j] for j in e) for k in range(m) for e in itertools.combinations(rest, k))


def ls_hat_k(table: dict[frozenset[int], float], m: int, k: int) -> float:
    """Largest such bound over k added units."""
    best = 0.0
    for i in range(m):
        rest = [j for j in range(m) if j != i]
        for cut in itertools.combinations(range(k + len(rest) - 1), len(rest) - 1) if rest else [()]:
            sizes = np.diff([-1, *cut, k + len(rest) - 1]) - 1 if rest else []
            s = [0] * m
            for j, x in zip(rest, sizes, strict=True):
                s[j] = int(x)
            best = max(best, ls_hat(table, m, tuple(s), i))
        if not rest:
            best = max(best, 1.0)
    return best


def search_limit(beta: float) -> int:
    """No optimum gains more units than this in one relation: a further unit grows the affine bound by at most 1 + 1/s."""
    return math.ceil(1 / math.expm1(beta))


def residual_sensitivity(table: dict[frozenset[int], float], m: int, beta: float, limit: int | None = None) -> float:
    """Largest discounted bound over all numbers of added units; independent of the data size once the table is known."""
    limit = search_limit(beta) if limit is None else limit
    if m == 1:
        return 1.0
    best = 0.0
    grid = np.meshgrid(*[np.arange(limit + 1.0)] * (m - 1), indexing="ij")
    discount = np.exp(-beta * sum(grid))
    for i in range(m):
        rest = [j for j in range(m) if j != i]
        axis = dict(zip(rest, grid, strict=True))
        bound = sum(float(table[frozenset(rest) - frozenset(e)]) * np.prod([axis[j] for j in e], axis=0) for k in range(m) for e in itertools.combinations(rest, k))
        best = max(best, float((discount * bound).max()))
    return best


class SmoothBound(Protocol):
    """At least the local sensitivity, and its logarithm changes by at most ``beta`` between neighbours."""

    def value(self, inst: Instance, beta: float) -> float: ...


class ResidualBound:
    def value(self, inst: Instance, beta: float) -> float:
        return residual_sensitivity(collect_table(boundary_table(inst)), inst.spec.m, beta)


class BruteForceSmooth:
    """The least smooth bound, by walking neighbours up to a radius: super-polynomial, for tiny instances."""

    def __init__(self, domain: list[list[tuple]], radius: int = 2) -> None:
        self.domain, self.radius = domain, radius

    def value(self, inst: Instance, beta: float) -> float:
        state = tuple(frozenset((tuple(r[a] for a in s.attrs), int(r["freq"])) for r in f.collect()) for s, f in zip(inst.spec.relations, inst.frames, strict=True))
        return self.value_of(inst.spec, state, beta)

    def value_of(self, spec: JoinSpec, state: tuple, beta: float) -> float:
        """The same for an instance given as sets of (tuple, frequency), without Spark."""
        seen, layer, best = set(), [state], 0.0
        for step in range(self.radius + 1):
            for state in layer:
                best = max(best, math.exp(-beta * step) * local_sensitivity_of(spec, state))
            seen |= set(layer)
            if step < self.radius:
                layer = list({n for state in layer for n in self._next(state)} - seen)
        return best

    def _next(self, state: tuple) -> Iterable[tuple]:
        for i, rows in enumerate(self.domain):
            have = dict(state[i])
            for t in rows:
                for d in (1, -1):
                    if have.get(t, 0) + d >= 0:
                        new = {**have, t: have.get(t, 0) + d}
                        yield (*state[:i], frozenset((k, v) for k, v in new.items() if v), *state[i + 1 :])


def boundary_max_of(spec: JoinSpec, state: tuple, rels: Iterable[int]) -> int:
    """Boundary maximum of a tiny instance given as sets of (tuple, frequency), without Spark."""
    rels = list(rels)
    given = boundary(spec, rels)
    groups: dict[tuple, int] = {}
    joined: list[tuple[dict, int]] = [({}, 1)]
    for j in rels:
        joined = [({**a, **dict(zip(spec.relations[j].attrs, t, strict=True))}, f * n) for a, f in joined for t, n in state[j] if all(a.get(x, v) == v for x, v in zip(spec.relations[j].attrs, t, strict=True))]
    for a, f in joined:
        key = tuple(a[x] for x in given)
        groups[key] = groups.get(key, 0) + f
    return max(groups.values(), default=0 if rels else 1)


def local_sensitivity_of(spec: JoinSpec, state: tuple) -> float:
    """Local sensitivity of such an instance."""
    return float(max((boundary_max_of(spec, state, [j for j in range(spec.m) if j != i]) for i in range(spec.m)), default=0))


def residual_of(spec: JoinSpec, state: tuple, beta: float) -> float:
    """Residual sensitivity of such an instance."""
    return residual_sensitivity({frozenset(e): boundary_max_of(spec, state, e) for e in subsets(spec.m)}, spec.m, beta)


def q_aggregate(inst: Instance, rels: Iterable[int], given: tuple[str, ...]) -> DataFrame:
    """``t``: as :func:`boundary_max` with any upward-closed set of given attributes (with an attribute, its ancestors)."""
    rels = tuple(rels)
    tree = AttrTree(inst.spec)
    for n in tree.nodes:
        if set(n.attrs) & set(given) and not set(tree.ancestors(n)) <= set(given):
            raise ValueError(f"{given} is not closed under ancestors")
    return aggregate_max(inst, rels, given)


def hier_degree(inst: Instance, rels: Iterable[int], given: tuple[str, ...], labels: dict[int, tuple[str, ...]] | None = None) -> DataFrame:
    """(given, labels, deg): for one relation sums of frequencies; for several the number of distinct joinable common tuples."""
    rels = tuple(rels)
    labels = labels or {}
    own = tuple(dict.fromkeys(c for i in rels for c in labels.get(i, ())))
    if len(rels) == 1:
        return inst.frames[rels[0]].groupBy(*given, *own).agg(F.sum("freq").alias("deg"))
    common = meet(inst.spec, rels)
    joined = None
    for i in rels:
        part = inst.frames[i].filter("freq > 0").select(*common, *labels.get(i, ())).distinct()
        joined = part if joined is None else joined.join(part, [c for c in part.columns if c in joined.columns])
    return joined.distinct().groupBy(*given, *own).agg(F.count("*").alias("deg"))


def hier_max_degree(inst: Instance, rels: Iterable[int], given: tuple[str, ...]) -> DataFrame:
    return hier_degree(inst, rels, given).agg(F.coalesce(F.max("deg"), F.lit(0)).cast("bigint").alias("mdeg"))


def degree_product(inst: Instance, rels: Iterable[int]) -> DataFrame:
    """(rels, given, mdeg) for every factor of the product that bounds the boundary maximum."""
    out = None
    for e, y in product_factors(inst.spec, rels):
        one = hier_max_degree(inst, e, y).select(F.lit(",".join(str(i + 1) for i in e)).alias("rels"), F.lit(",".join(y)).alias("given"), "mdeg")
        out = one if out is None else out.unionByName(one)
    return out


def table_from_config(spec: JoinSpec, sigma: dict[str, int], lam: float) -> dict[frozenset[int], float]:
    """Bounds on all boundary maxima if each node's degrees are at most lam * 2**label (``sigma`` by node name)."""
    tree = AttrTree(spec)
    by_atom = {n.atom: n.name for n in tree.nodes}

    def bound(e: tuple[int, ...]) -> float:
        out = 1.0
        for rels, given in product_factors(spec, e):
            # a factor belongs to the node whose relations these are, or (one relation) to its nodes not given
            nodes = [by_atom[frozenset(rels)]] if frozenset(rels) in by_atom else [n.name for n in tree.nodes if frozenset(rels) <= n.atom and not set(n.attrs) <= set(given)]
            out *= math.prod(lam * 2.0 ** sigma[n] for n in nodes)
        return out

    return {frozenset(e): bound(e) if e else 1.0 for e in subsets(spec.m)}


def rs_from_config(spec: JoinSpec, sigma: dict[str, int], lam: float, beta: float) -> float:
    return residual_sensitivity(table_from_config(spec, sigma, lam), spec.m, beta)


def ln_rs_change(inst: Instance, i: int, values: tuple, delta: int, beta: float) -> float:
    """Change of the logarithm of the residual bound to one neighbour (at most ``beta``)."""
    bound = ResidualBound()
    return abs(math.log(bound.value(neighbor(inst, i, values, delta), beta)) - math.log(bound.value(inst, beta)))


def out_size(inst: Instance) -> int:
    return int(join_size(inst).first()["val"] or 0)


