"""Sum-product plans: aggregate below the join, one attribute at a time.

A factor is a DataFrame of attribute columns and a value column ``val``.  :func:`contract` sums
out every attribute that isn't kept: attributes of a single factor by a plain aggregate, shared
ones by joining just the factors that hold them and aggregating at once.  Labels (sub-instances)
and query numbers are attributes that are kept.  No plan ever holds a row of the join's output,
and every join input is one pre-aggregated row a key, which takes the skew out of the keys.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..relation import COUNT, Instance


@dataclass(frozen=True)
class Factor:
    frame: DataFrame
    attrs: tuple[str, ...]


def count_factor(frame: DataFrame, attrs: tuple[str, ...]) -> Factor:
    """A relation's frequencies as exact decimals."""
    return Factor(frame.select(*attrs, F.col("freq").cast(COUNT).alias("val")), tuple(attrs))


def multiply(a: Factor, b: Factor) -> Factor:
    shared = [x for x in a.attrs if x in b.attrs]
    right = b.frame.withColumnRenamed("val", "val_r")
    both = a.frame.join(right, shared) if shared else a.frame.crossJoin(right)
    kind = a.frame.schema["val"].dataType
    value = F.col("val") * F.col("val_r")
    value = value.cast(COUNT) if kind.typeName() == "decimal" and b.frame.schema["val"].dataType.typeName() == "decimal" else value.cast("double")
    attrs = tuple(dict.fromkeys((*a.attrs, *b.attrs)))
    return Factor(both.select(*attrs, value.alias("val")), attrs)


def marginal(f: Factor, keep: tuple[str, ...]) -> Factor:
    attrs = tuple(a for a in f.attrs if a in keep)
    if attrs == f.attrs:
        return f
    kind = f.frame.schema["val"].dataType
    total = F.sum("val")
    total = total.cast(COUNT) if kind.typeName() == "decimal" else total
    grouped = f.frame.groupBy(*attrs).agg(total.alias("val"))
    return Factor(grouped if attrs else grouped.select(F.coalesce("val", F.lit(0).cast(kind)).alias("val")), attrs)


def contract(factors: list[Factor], keep: tuple[str, ...]) -> list[Factor]:
    """Sums out what isn't kept; the result's factors may still share kept attributes."""
    factors = list(factors)
    while True:
        held = lambda a: [f for f in factors if a in f.attrs]
        factors = [marginal(f, tuple(a for a in f.attrs if a in keep or len(held(a)) > 1)) for f in factors]
        shared = sorted({a for f in factors for a in f.attrs if a not in keep})
        if not shared:
            return factors
        width = lambda a: (len({x for f in held(a) for x in f.attrs}), a)
        group = held(min(shared, key=width))
        joined = group[0]
        for f in group[1:]:
            joined = multiply(joined, f)
        factors = [f for f in factors if f not in group] + [joined]


def clusters(factors: list[Factor]) -> list[Factor]:
    """Joins factors that share attributes; the results share none."""
    out: list[Factor] = []
    for f in factors:
        mine = [o for o in out if set(o.attrs) & set(f.attrs)]
        for o in mine:
            f = multiply(o, f)
        out = [o for o in out if o not in mine] + [f]
    return out


def total(factors: list[Factor], keep: tuple[str, ...]) -> DataFrame:
    """One table over the kept attributes."""
    parts = clusters(contract(factors, keep))
    out = parts[0]
    for p in parts[1:]:
        out = multiply(out, p)
    return out.frame


def join_size(inst: Instance, by: tuple[str, ...] = ()) -> DataFrame:
    """``[by], val``: the join size as a decimal, factorised."""
    return total([count_factor(f, tuple(c for c in f.columns if c != "freq")) for f in inst.frames], by)
