"""Registry of queries, and SQL text shared by their oracles."""

from __future__ import annotations

from collections.abc import Callable, Iterable

from pyspark.sql import DataFrame, SparkSession

from ..hyper import JoinSpec, boundary
from ..queries import Family, QuerySet
from ..sources.workloads import EVENT_TYPES, PRIORITIES, TWO

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}

#: Parameters of the registered noisy queries.
EPS, DELTA, SEED = 1.0, 1e-6, "seed7"
LAM = 13.815510557964274  # ln(1 / DELTA) / EPS


def entry(name: str, sql: str | None = None) -> Callable:
    def add(fn: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
        QUERIES[name] = fn
        if sql is not None:
            ORACLES[name] = sql
        return fn

    return add


def rel_sql(spec: JoinSpec, i: int) -> str:
    r = spec.relations[i]
    return f"(select {', '.join(r.attrs)}, count(*)::hugeint as f{i + 1} from ({r.sql()}) group by all)"


def join_sql(spec: JoinSpec, rels: Iterable[int] | None = None) -> str:
    """A from-clause of the natural join over frequency tables, columns f1..fm; parts without common attributes are crossed."""
    rels = list(range(spec.m) if rels is None else rels)
    out, held, left = f"{rel_sql(spec, rels[0])} t{rels[0]}", set(spec.relations[rels[0]].attrs), rels[1:]
    while left:
        nxt = next((i for i in left if held & set(spec.relations[i].attrs)), left[0])
        shared = [a for a in spec.relations[nxt].attrs if a in held]
        out += f" join {rel_sql(spec, nxt)} t{nxt} using ({', '.join(shared)})" if shared else f" cross join {rel_sql(spec, nxt)} t{nxt}"
        held |= set(spec.relations[nxt].attrs)
        left.remove(nxt)
    return out


def product_sql(rels: Iterable[int]) -> str:
    return " * ".join(f"f{i + 1}" for i in rels)


def size_sql(spec: JoinSpec) -> str:
    return f"select coalesce(sum({product_sql(range(spec.m))}), 0)::bigint as val from {join_sql(spec)}"


def t_sql(spec: JoinSpec, rels: tuple[int, ...], given: tuple[str, ...] | None = None) -> str:
    """One row ``t``: the boundary maximum."""
    if not rels:
        return "select 1::bigint as t"
    given = boundary(spec, rels) if given is None else given
    group = f" group by {', '.join(given)}" if given else ""
    return f"select coalesce(max(s), 0)::bigint as t from (select sum({product_sql(rels)}) as s from {join_sql(spec, rels)}{group})"


def uniform_sql(*key: str) -> str:
    """Text of the seeded uniform; keys are SQL expressions."""
    return f"((('0x' || substr(md5(concat_ws('|', '{SEED}', {', '.join(key)})), 1, 13))::ubigint)::double + 0.5) / 4503599627370496.0"


def tlap_sql(b: str, radius: str, u: str) -> str:
    half = f"(({radius}) + ({b}) * ln(exp(-({radius}) / ({b})) + 2 * least({u}, 1 - {u}) * (1 - exp(-({radius}) / ({b})))))"
    return f"(case when {u} < 0.5 then {half} else 2 * ({radius}) - {half} end)"


def ladder_sql(degree: str, lam: float, last: int = 64) -> str:
    return "case " + " ".join(f"when {degree} <= {lam * 2.0**i!r} then {i}" for i in range(1, last)) + f" else {last} end"


def two_queries() -> QuerySet:
    """The 36 default queries of the running example: all-ones and marginals on both sides."""
    return QuerySet((Family.all_ones() + Family.marginal("P", PRIORITIES), Family.all_ones() + Family.marginal("E", EVENT_TYPES)))


def weights_sql(family: Family, attrs: Iterable[str], source: str, q: str) -> str:
    """(attrs, q, w) rows of a family over a table expression."""
    parts = [f"select {', '.join(attrs)}, {i} as {q}, ({w.replace(' as string', ' as varchar')})::double as w_{q} from {source}" for i, w in enumerate(family.weights)]
    return "(" + " union all ".join(parts) + ")"


def answers_sql(spec: JoinSpec, queries: QuerySet) -> str:
    """All non-absent answers by the naive join: ``q1..qm, answer``."""
    m = spec.m
    numbers = [f"q{i + 1}" for i in range(m)]
    base = f"(select * from {join_sql(spec)})"
    text = base
    for i, f in enumerate(queries.families):
        values = "[" + ", ".join(f"({w.replace(' as string', ' as varchar')})::double" for w in f.weights) + "]"
        text = f"(select *, unnest({values}) as w{i + 1}, unnest(range({len(f)})) as q{i + 1} from {text} b{i})"
    weight = " * ".join(f"w{i + 1}" for i in range(m))
    return f"select {', '.join(f'{n}::int as {n}' for n in numbers)}, sum({product_sql(range(m))}::double * {weight}) as answer from {text} z group by all having sum({product_sql(range(m))}::double * {weight}) <> 0"


TWO_ANSWERS = answers_sql(TWO, two_queries())
