"""Seeded releases on the given tables, and their SQL: every draw is a keyed md5, so another engine draws the same noise.

The kernel's rounds are a recursive query over the cells of all sub-instances; the number of rounds is the formula's.
"""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.noise import NoiseSource
from ..hyper import JoinSpec
from ..operators import baselines, partition, release, sensitivity
from ..queries import Family, QuerySet, joint_domain
from ..relation import load
from ..sources.workloads import BINS, EVENT_TYPES, FLAGS, LANG2, LINE1, NATION2, PATH3, PRIORITIES, SEGMENTS, SOURCES, STAR3, STATUSES, TRIANGLE, TWO
from .core import _DEG, _bound_text, _t_columns
from .noise_and_release import _LINE_Q, _STAR_Q
from .registry import DELTA, EPS, LAM, SEED, answers_sql, entry, ladder_sql, rel_sql, size_sql, tlap_sql, two_queries, uniform_sql

SEEDED = NoiseSource.seeded(SEED)
Q = chr(39)


def text(s: object) -> str:
    return f"{Q}{s}{Q}"


def radius_sql(eps: str, delta: str, sens: str = "1.0") -> str:
    """Truncation radius of the noise."""
    return f"(({sens}) / ({eps}) * ln(1 + (exp({eps}) - 1) / ({delta})))"


def laplace_sql(b: str, u: str) -> str:
    return f"(case when {u} < 0.5 then ({b}) * ln(2 * {u}) else -({b}) * ln(2 * (1 - {u})) end)"


def degree_sql(exact: str, eps: float, delta: float, *key: str) -> str:
    """A maximum degree with the noise of half the budget."""
    return f"({exact}) + {tlap_sql(repr(2 / eps), radius_sql(repr(eps / 2), repr(delta / 2)), uniform_sql(*key))}"


def raised_sql(bound: str, beta: float, eps: float, delta: float, *key: str) -> str:
    """A smooth bound raised in the log domain."""
    return f"({bound}) * exp({tlap_sql(repr(2 * beta / eps), radius_sql(repr(eps / 2), repr(delta / 2), repr(beta)), uniform_sql(*key))})"


def kernel_sql(ctes: list[str], cell_attrs: dict[str, tuple], families: tuple[Family, ...], eps: float, delta: float, log_domain: str, rounds: int | None = None, noisy_total: bool = True) -> str:
    """Released masses (average of the rounds) of all sub-instances.

    ``ctes`` define ``stat(sub_id, total, dtilde)`` and ``tr(sub_id, q1.., answer)``.  ``rounds``: None for the formula.
    """
    attrs, n_q = ", ".join(cell_attrs), len(families)
    values = lambda vs: ", ".join(text(v) if isinstance(v, str) else str(v) for v in vs)
    points = "select " + attrs + " from " + ", ".join(f"(select unnest([{values(vs)}]) as {a})" for a, vs in cell_attrs.items())
    weights, place = "pts", "q1"
    for i, fam in enumerate(families):
        texts = ", ".join(f"({w.replace(' as string', ' as varchar')})::double" for w in fam.weights)
        weights = f"(select *, unnest([{texts}]) as w{i + 1}, unnest(range({len(fam)})) as q{i + 1} from {weights} x{i})"
        place = place if i == 0 else f"({place}) * {len(fam)} + q{i + 1}"
    product = " * ".join(f"w{i + 1}" for i in range(n_q))
    numbers = ", ".join(f"q{i + 1}" for i in range(n_q))
    many = 1
    for fam in families:
        many *= len(fam)
    formula = f"greatest(1, floor(n_hat * {eps!r} * sqrt({log_domain}) / (dtilde * ln({many}) * sqrt(ln(1 / {delta!r}::double)))))" if many > 1 else "1"
    total = f"total + {tlap_sql(f'2 * dtilde / {eps!r}', radius_sql(repr(eps / 2), repr(delta / 2), 'dtilde'), uniform_sql(text('total'), 'sub_id'))}" if noisy_total else "total"
    u_choice, u_measure = uniform_sql(text("choice"), "at_round", "sub_id", "query"), uniform_sql(text("measure"), "at_round", "sub_id")
    return f"""
with recursive {', '.join(ctes)},
  pts as materialized ({points}),
  wt as materialized (select {attrs}, {place} as query, {numbers}, {product} as weight from {weights}),
  noised as materialized (select sub_id, dtilde, ({total})::double as n_hat from stat),
  budget as materialized (select *, {eps!r} / (16 * sqrt(n_rounds * ln(1 / {delta!r}::double))) as eps_round from (select *, ({formula if rounds is None else rounds})::int as n_rounds from noised)),
  truth as materialized (select u.sub_id, query, coalesce(t.answer, 0.0)::double as exact from budget u cross join (select distinct query, {numbers} from wt) y left join tr t on t.sub_id = u.sub_id and {' and '.join(f't.q{i + 1} = y.q{i + 1}' for i in range(n_q))}),
  walk as (
    select 0 as at_round, sub_id, {attrs}, ln(n_hat / (select count(*) from pts)) as log_mass, n_hat / (select count(*) from pts) as mass from budget, pts
    union all
    (with
      ans as (select sub_id, query, min(at_round) as at_round, sum(mass * weight) as now from walk join wt using ({attrs}) group by sub_id, query),
      scored as (select ans.*, exact, n_hat, eps_round, dtilde, eps_round / 2 * abs(now - exact) / dtilde - ln(-ln({u_choice})) as score from ans join truth using (sub_id, query) join budget using (sub_id) where at_round < n_rounds),
      pick as (select sub_id, at_round, n_hat, arg_max(query, score) as query, arg_max(now, score) as now, arg_max(exact, score) as exact, min(dtilde / eps_round) as scale from scored group by sub_id, at_round, n_hat),
      step as (select *, (least(n_hat, greatest(-n_hat, exact + {laplace_sql('scale', u_measure)})) - now) / (2 * n_hat) as delta_w from pick),
      moved as (select c.sub_id, c.{', c.'.join(cell_attrs)}, n_hat, p.at_round, c.log_mass + x.weight * p.delta_w as log_mass from walk c join step p using (sub_id) join wt x on x.query = p.query and {' and '.join(f'x.{a} = c.{a}' for a in cell_attrs)}),
      top as (select sub_id, max(log_mass) as highest from moved group by sub_id),
      whole as (select sub_id, sum(exp(log_mass - highest)) as in_all from moved join top using (sub_id) group by sub_id)
    select moved.at_round + 1, sub_id, {attrs}, log_mass, exp(log_mass - highest) * n_hat / in_all from moved join top using (sub_id) join whole using (sub_id)))
select sub_id, {attrs}, round(avg(mass), 2) as mass, round(any_value(dtilde), 6) as dtilde, any_value(n_rounds)::int as rounds
from walk join budget using (sub_id) where at_round > 0 group by sub_id, {attrs}"""


def _shown(cells: DataFrame, attrs: dict[str, tuple]) -> DataFrame:
    kinds = {a: "string" if isinstance(v[0], str) else "int" for a, v in attrs.items()}
    return cells.select("sub_id", *(F.col(a).cast(kinds[a]).alias(a) for a in attrs), F.round("mass", 2).alias("mass"), F.round("dtilde", 6).alias("dtilde"), "rounds")


def _one(spec: JoinSpec, queries: QuerySet, dtilde: str) -> list[str]:
    return [f"stat as (select 'all' as sub_id, ({size_sql(spec)})::double as total, ({dtilde})::double as dtilde)", f"tr as materialized (select 'all' as sub_id, * from ({answers_sql(spec, queries)}))"]


def _max_degree_sql(spec: JoinSpec) -> str:
    key = spec.relations[0].attrs[0]
    return f"select max(d) from (select sum(f1) as d from {rel_sql(spec, 0)} group by {key} union all select sum(f2) from {rel_sql(spec, 1)} group by {key})"


_PE = {"P": PRIORITIES, "E": EVENT_TYPES}
_CUST_LOG = "ln(25.0 * (select count(*) from customer))"
_NATION_Q = QuerySet((Family.all_ones() + Family.marginal("S", SEGMENTS), Family.all_ones() + Family.prefix("V", (0, 1, 2, 3))))
_LANG_Q = QuerySet((Family.all_ones() + Family.marginal("S", SOURCES[:4]), Family.all_ones() + Family.prefix("W", (0, 2))))
_LINE_CELLS = {"G": FLAGS, "Z": STATUSES, "V": BINS}

# one table: sensitivity one
entry("w16_single_table_noisy_release_seeded", kernel_sql(_one(LINE1, _LINE_Q, "1.0"), _LINE_CELLS, _LINE_Q.families, EPS, DELTA, "ln(30)", 40))(
    lambda s, d: _shown(release.release_single(load(s, d, LINE1), _LINE_Q, d, EPS, DELTA, SEEDED, rounds=40).cells, _LINE_CELLS)
)

# two tables: noisy maximum degree
for _name, _spec, _q, _cells, _log, _g in (
    ("r02_two_table_release_seeded", TWO, two_queries(), _PE, _CUST_LOG, 1),
    ("r02_nation_release_seeded", NATION2, _NATION_Q, {"S": SEGMENTS, "V": BINS}, "ln(25.0 * 25)", 1),
    ("r02_self_join_release_seeded", LANG2, _LANG_Q, {"S": SOURCES, "W": BINS}, "ln(4.0 * 100)", 2),
):
    entry(_name, kernel_sql(_one(_spec, _q, f"select {degree_sql(_max_degree_sql(_spec), EPS / _g, DELTA / _g, text('degree'))}"), _cells, _q.families, EPS / _g / 2, DELTA / _g / 2, _log))(
        lambda s, d, p=_spec, q=_q, c=_cells: _shown(release.release_two_table(load(s, d, p), q, d, EPS, DELTA, SEEDED).cells, c)
    )


@entry("r02_two_table_release_frame_kernel_seeded", kernel_sql(_one(NATION2, _NATION_Q, f"select {degree_sql(_max_degree_sql(NATION2), 40.0, DELTA, text('degree'))}"), {"S": SEGMENTS, "V": BINS}, _NATION_Q.families, 20.0, DELTA / 2, "ln(25.0 * 25)", 4))
def r02_frame(s: SparkSession, d: str) -> DataFrame:
    """The same release with the cells as a DataFrame."""
    return _shown(release.release_two_table(load(s, d, NATION2), _NATION_Q, d, 40.0, DELTA, SEEDED, rounds=4, kernel="frame").cells, {"S": SEGMENTS, "V": BINS})


# pad first: uniform rows, then the kernel on the padded answers and their exact total
def _padded(spec: JoinSpec, queries: QuerySet, cells: dict[str, tuple], eps: float, delta: float) -> list[str]:
    n, values = 1, []
    for a, vs in reversed(cells.items()):
        values.append(f"([{', '.join(text(v) if isinstance(v, str) else str(v) for v in vs)}])[1 + (c // {n}) % {len(vs)}] as {a}")
        n *= len(vs)
    weights = "spread"
    for i, fam in enumerate(queries.families):
        texts = ", ".join(f"({w.replace(' as string', ' as varchar')})::double" for w in fam.weights)
        weights = f"(select *, unnest([{texts}]) as w{i + 1}, unnest(range({len(fam)})) as q{i + 1} from {weights} y{i})"
    eta = tlap_sql(f"4 * dtilde / {eps!r}", radius_sql(repr(eps / 4), repr(delta / 4), "dtilde"), uniform_sql(text("padding")))
    return [
        f"deg as materialized (select ({degree_sql(_max_degree_sql(spec), eps, delta, text('degree'))})::double as dtilde)",
        f"eta as materialized (select round({eta})::bigint as e from deg)",
        "rows as (select unnest(range(e)) as i from eta)",
        f"spread as materialized (select {', '.join(values)}, n from (select floor({uniform_sql(text('pad'), 'i')} * {n})::int as c, count(*) as n from rows group by 1))",
        f"tr as materialized (select 'all' as sub_id, q1, q2, sum(answer) as answer from (select * from ({answers_sql(spec, queries)}) union all select q1, q2, sum(n * w1 * w2) from {weights} group by q1, q2) group by q1, q2)",
        f"stat as (select 'all' as sub_id, (({size_sql(spec)}) + e)::double as total, dtilde from deg, eta)",
    ]


entry("r03_padded_release_seeded", kernel_sql(_padded(TWO, two_queries(), _PE, EPS, DELTA), _PE, two_queries().families, EPS / 4, DELTA / 4, _CUST_LOG, None, False))(
    lambda s, d: _shown(release.release_padded(load(s, d, TWO), two_queries(), d, EPS, DELTA, SEEDED).cells, _PE)
)


def _pad_after_sql() -> str:
    """The kernel with the exact total and sensitivity one, then the pad rows of the same draws on its masses."""
    ctes = _padded(TWO, two_queries(), _PE, EPS * 2, DELTA * 2)  # its eta has half of this budget
    exact = [f"stat as (select 'all' as sub_id, ({size_sql(TWO)})::double as total, 1.0::double as dtilde)", f"tr as materialized (select 'all' as sub_id, * from ({answers_sql(TWO, two_queries())}))"]
    deg = f"deg as materialized (select ({degree_sql(_max_degree_sql(TWO), EPS, DELTA, text('degree'))})::double as dtilde)"
    inner = kernel_sql([deg, *ctes[1:4], *exact], _PE, two_queries().families, EPS, DELTA, _CUST_LOG, 3, False)
    last = inner.rindex("select sub_id")
    return inner[:last] + f"select sub_id, P, E, round(avg(mass) + any_value(coalesce(pads, 0)), 2) as mass from walk left join (select P, E, sum(n) as pads from spread group by P, E) y using (P, E) where at_round > 0 group by sub_id, P, E"


@entry("b02_pad_after_seeded", _pad_after_sql())
def b02(s: SparkSession, d: str) -> DataFrame:
    """Not private: the broken order of padding."""
    out = release.release_pad_after(load(s, d, TWO), two_queries(), d, EPS, DELTA, SEEDED, 3, allow_nonprivate=True)
    return _shown(out.cells.withColumn("dtilde", F.lit(0.0)), _PE).select("sub_id", "P", "E", "mass")


# any join: residual sensitivity raised in the log domain
def _residual_sql(m: int, beta: float, source: str, by: str = "") -> str:
    """Largest discounted bound (``rs``) for every row of ``source`` with its t columns."""
    parts = []
    for i in range(1, m + 1):
        rest = [j for j in range(1, m + 1) if j != i]
        grids = ", ".join(f"(select range::double as s{j} from range({sensitivity.search_limit(beta) + 1}))" for j in rest)
        parts.append(f"select {by + ',' if by else ''} max(exp(-{beta!r} * ({' + '.join(f's{j}' for j in rest)})) * ({_bound_text(m, i)})) as b from {source}, {grids}{' group by ' + by if by else ''}")
    return f"select {by + ',' if by else ''} max(b) as rs from ({' union all '.join(parts)}){' group by ' + by if by else ''}"


_SVH = {"S": SEGMENTS, "V": BINS, "H": BINS}
_PATH_Q = QuerySet((Family.all_ones() + Family.prefix("B", ("Brand#13", "Brand#2")), Family.all_ones(), Family.all_ones() + Family.prefix("N", (5, 15))))
_TRI_Q = QuerySet((Family.all_ones() + Family.prefix("M", (1, 3)), Family.all_ones(), Family.all_ones()))
for _name, _spec, _q, _log, _rounds in (
    ("r04_multi_table_release_star3_seeded", STAR3, _STAR_Q, "ln(25.0 * 125)", None),
    ("r04_multi_table_release_path3_seeded", PATH3, _PATH_Q, "ln(625.0 * (select count(*) from part) * (select count(*) from supplier))", 3),
    ("r04_multi_table_release_triangle_seeded", TRIANGLE, QuerySet((Family.all_ones(),) * 3), "ln(375)", None),
):
    _cells = {a: _spec.domains[a].values for a in _spec.attrs if not _spec.domains[a].is_key and len(_spec.atom(a)) == 1}
    _e, _dl = EPS / _spec.group_factor, DELTA / _spec.group_factor
    _rs = f"select rs from (with t as (select {_t_columns(_spec)}) {_residual_sql(_spec.m, 1 / LAM, 't')})"
    if _cells:
        entry(_name, kernel_sql(_one(_spec, _q, f"select {raised_sql(f'({_rs})', 1 / LAM, _e, _dl, text('smooth'))}"), _cells, _q.families, _e / 2, _dl / 2, _log, _rounds))(
            lambda s, d, p=_spec, q=_q, c=_cells, r=_rounds: _shown(release.release_multi_table(load(s, d, p), q, d, EPS, DELTA, SEEDED, rounds=r or "auto", beta=1 / LAM).cells, c)
        )
    else:  # no attribute of its own in any relation: one cell, whose mass is the noisy total
        _total = f"o + {tlap_sql(f'2 * dt / {_e / 2!r}', radius_sql(repr(_e / 4), repr(_dl / 4), 'dt'), uniform_sql(text('total'), text('all')))}"
        entry(_name, f"select 'all' as sub_id, round(({_total}) / 1e6, 2) as mass_millions, round(dt, 3) as dtilde from (select ({size_sql(_spec)})::double as o, {raised_sql(f'({_rs})', 1 / LAM, _e, _dl, text('smooth'))} as dt)")(
            lambda s, d, p=_spec, q=_q: release.release_multi_table(load(s, d, p), q, d, EPS, DELTA, SEEDED, beta=1 / LAM).cells.select("sub_id", F.round(F.col("mass") / 1e6, 2).alias("mass_millions"), F.round("dtilde", 3).alias("dtilde"))
        )


# uniformized: noisy buckets of every customer, a release with half of the budget in each
_BUCKETS = f"(select K, {ladder_sql('x', LAM)}::varchar as sub_id, deg1, deg2 from (select c_custkey as K, coalesce(deg1, 0) as deg1, coalesce(deg2, 0) as deg2, greatest(coalesce(deg1, 0), coalesce(deg2, 0)) + {tlap_sql(repr(2 / EPS), radius_sql(repr(EPS / 2), repr(DELTA / 2)), 'u')} as x from (select c_custkey, deg1, deg2, {uniform_sql(text('deg'), 'c_custkey')} as u from customer left join {_DEG} on K = c_custkey)))"
_TWO_Q = two_queries()
_BY_BUCKET = f"""
  tr as materialized (
    select sub_id, q1, q2, sum(f1 * f2 * w1 * w2)::double as answer from lab
      join (select *, unnest([{', '.join(f'({w})::double' for w in _TWO_Q.families[0].weights)}]) as w1, unnest(range(6)) as q1 from {rel_sql(TWO, 0)}) a using (K)
      join (select *, unnest([{', '.join(f'({w})::double' for w in _TWO_Q.families[1].weights)}]) as w2, unnest(range(6)) as q2 from {rel_sql(TWO, 1)}) b using (K) group by 1, 2, 3)"""

entry("r05_uniformized_release_seeded", kernel_sql(
    [f"lab as materialized {_BUCKETS}", f"stat as materialized (select sub_id, total, keys, {degree_sql('deg', EPS / 2, DELTA / 2, text('degree'), 'sub_id')} as dtilde from (select sub_id, sum(deg1 * deg2)::double as total, count(*) as keys, max(greatest(deg1, deg2))::double as deg from lab group by sub_id))", _BY_BUCKET],
    _PE, _TWO_Q.families, EPS / 4, DELTA / 4, "ln(25.0 * (select keys from stat z where z.sub_id = noised.sub_id))",
))(lambda s, d: _shown(release.release_uniformized(load(s, d, TWO), two_queries(), d, EPS, DELTA, SEEDED).cells, _PE))

_TRUE = f"(select c_custkey as K, coalesce(deg1, 0) as deg1, coalesce(deg2, 0) as deg2, {ladder_sql('greatest(coalesce(deg1, 0), coalesce(deg2, 0))', LAM)}::varchar as sub_id from customer left join {_DEG} on K = c_custkey)"
_HALF_BETA = EPS / 2 / math.log(2 / DELTA)


@entry("r10_inner_release_choice", f"with b as (select sub_id, max(deg1)::double as t1, max(deg2)::double as t2 from {_TRUE} group by 1) select sub_id, 'two' as inner_release, round(greatest(t1, t2), 4) as bound from b union all select sub_id, 'multi', round(rs, 4) from ({_residual_sql(2, _HALF_BETA, 'b', 'sub_id')})")
def r10(s: SparkSession, d: str) -> DataFrame:
    """What the parts of one partition are released at, by either inner release without noise."""
    out = None
    for inner in ("two", "multi"):
        cells = release.release_uniformized(load(s, d, TWO), two_queries(), d, EPS, DELTA, NoiseSource.zero(), rounds=0, lam=LAM, inner=inner).cells
        one = cells.select("sub_id", F.lit(inner).alias("inner_release"), F.round("dtilde", 4).alias("bound")).distinct()
        out = one if out is None else out.unionByName(one)
    return out


# hierarchical: labels of every nation and of every configuration that follows from them
_DEGREES = f"(select n_nationkey as N, coalesce(d1, 0) as d1, coalesce(d2, 0) as d2, coalesce(d3, 0) as d3 from nation left join (select N, sum(f1) as d1 from {rel_sql(STAR3, 0)} group by N) a on a.N = n_nationkey left join (select N, sum(f2) as d2 from {rel_sql(STAR3, 1)} group by N) b on b.N = n_nationkey left join (select N, sum(f3) as d3 from {rel_sql(STAR3, 2)} group by N) c on c.N = n_nationkey)"


def _star_labels(eps: float, delta: float, lam: float, zero: bool = False, last: int = 64) -> list[str]:
    noise = lambda u: "0.0" if zero else tlap_sql(repr(1 / eps), radius_sql(repr(eps), repr(delta)), u)
    leaves = ", ".join(f"{ladder_sql(f'x{i}', lam, last)} as l{i}" for i in (1, 2, 3))
    draws = ", ".join(f"d{i} + {noise(uniform_sql(text(f'c_{a}'), 'N'))} as x{i}" for i, a in ((1, "S"), (2, "V"), (3, "H")))
    return [
        f"leaf as materialized (select N, d1, d2, d3, {leaves} from (select *, {draws} from {_DEGREES}))",
        "grid as (select l1, l2, l3, coalesce(n, 0) as n from (select distinct l1 from leaf) cross join (select distinct l2 from leaf) cross join (select distinct l3 from leaf) left join (select l1 as a, l2 as b, l3 as c, count(*) as n from leaf where d1 > 0 and d2 > 0 and d3 > 0 group by all) on a = l1 and b = l2 and c = l3)",
        f"conf as materialized (select l1, l2, l3, concat_ws(',', l1, l2, l3, {ladder_sql('x', lam, last)}) as sub_id from (select *, n + {noise(uniform_sql(text('c_N'), 'concat_ws(' + text(',') + ', l1, l2, l3)'))} as x from grid))",
    ]


def _star(s: SparkSession, d: str):
    return load(s, d, STAR3), lambda attrs: joint_domain(s, d, STAR3, attrs)


@entry("r08_hierarchical_partition_star3_seeded", f"with {', '.join(_star_labels(EPS, DELTA, 4.0))} select sub_id as config, coalesce(sum(d1 * d2 * d3), 0)::bigint as out_size from conf left join leaf using (l1, l2, l3) group by sub_id")
def r08(s: SparkSession, d: str) -> DataFrame:
    """All configurations, those without a join included."""
    from ..operators.measures import join_size_vector

    inst, domain = _star(s, d)
    return join_size_vector(partition.partition_hierarchical(inst, EPS, DELTA, 4.0, SEEDED, domain)).select("config", "out_size")


@entry("r09_split_on_leaf_seeded", f"with {_star_labels(EPS, DELTA, 4.0)[0]} select N, l1 as c_S from leaf")
def r09(s: SparkSession, d: str) -> DataFrame:
    from ..hyper import AttrTree

    inst, domain = _star(s, d)
    tree = AttrTree(STAR3)
    leaf = next(n for n in tree.nodes if n.attrs == ("S",))
    _, _, known = partition.split_on_attribute(inst, tree, leaf, {}, {}, domain, EPS, DELTA, 4.0, SEEDED)
    return known.select("N", "c_S")


# A large budget, as a tuple's parts share it (49 parts at this bound on the size).
_BIG, _N_MAX = 64.0, 1000.0
_PARTS = 49
_SHARE = _BIG / 2 / _PARTS, DELTA / 2 / _PARTS


def _star_tables() -> str:
    """Boundary maxima of every configuration ``c``."""
    products = {"1": "d1", "2": "d2", "3": "d3", "12": "d1 * d2", "13": "d1 * d3", "23": "d2 * d3"}
    fits = lambda t: " and ".join(f"x.l{i} = c.l{i}" for i in t)
    return ", ".join(f"coalesce((select max({p}) from leaf x where {fits(t)}), 0)::double as t{t}" for t, p in products.items())


def _star_stats() -> list[str]:
    beta = _SHARE[0] / math.log(1 / _SHARE[1])
    tables = _star_tables()
    weights = ["[" + ", ".join(f"({w})::double" for w in f.weights) + "]" for f in _STAR_Q.families]
    return [
        *_star_labels(_BIG / 2 / 2, DELTA / 2 / 2, LAM, last=partition.bucket_count(_N_MAX, LAM)),
        f"bounds as materialized (select sub_id, {tables} from conf c)",
        f"rs as materialized ({_residual_sql(3, beta, 'bounds', 'sub_id')})",
        f"stat as materialized (select sub_id, coalesce(total, 0)::double as total, {raised_sql('rs', beta, *_SHARE, text('smooth'), 'sub_id')} as dtilde from rs left join (select sub_id, sum(d1 * d2 * d3) as total from conf join leaf using (l1, l2, l3) group by sub_id) using (sub_id))",
        f"tr as materialized (select sub_id, q1, q2, q3, sum(f1 * f2 * f3 * w1 * w2 * w3)::double as answer from conf join leaf using (l1, l2, l3) join (select *, unnest({weights[0]}) as w1, unnest(range({len(_STAR_Q.families[0])})) as q1 from {rel_sql(STAR3, 0)}) a using (N) join (select *, unnest({weights[1]}) as w2, unnest(range({len(_STAR_Q.families[1])})) as q2 from {rel_sql(STAR3, 1)}) b using (N) join (select *, unnest({weights[2]}) as w3, unnest(range({len(_STAR_Q.families[2])})) as q3 from {rel_sql(STAR3, 2)}) e using (N) group by 1, 2, 3, 4)",
    ]


@entry("r11_hierarchical_release_star3_seeded", kernel_sql(_star_stats(), _SVH, _STAR_Q.families, _SHARE[0] / 2, _SHARE[1] / 2, "ln(25.0 * 125)", 3))
def r11(s: SparkSession, d: str) -> DataFrame:
    out = release.release_uniformized(load(s, d, STAR3), _STAR_Q, d, _BIG, DELTA, SEEDED, rounds=3, partitioner="hierarchical", lam=LAM, n_max=_N_MAX)
    return _shown(out.cells, _SVH)


# bounds of the hierarchical release on the configurations of exact degrees
_UP, _LOW = f"(pow(ln({25.0 * 125}), 0.25) * sqrt(ln(18)) * sqrt(ln(1e6)))", f"pow(ln({25.0 * 125}), 0.25)"
_PARTS_SQL = f"""with {', '.join(_star_labels(EPS, DELTA, 1.0, True))},
  bounds as materialized (select sub_id, {_star_tables()} from conf c), rs as materialized ({_residual_sql(3, 1 / LAM, 'bounds', 'sub_id')}),
  sizes as (select sub_id, sum(d1 * d2 * d3)::double as o from conf join leaf using (l1, l2, l3) group by sub_id having sum(d1 * d2 * d3) > 0),
  parts as (select sub_id, o, rs, greatest(t12, t13, t23) as ls from sizes join rs using (sub_id) join bounds using (sub_id))"""


@entry("a04_hierarchical_bounds_star3", f"{_PARTS_SQL} select count(*)::bigint as parts, round(sum(sqrt(o * rs * {LAM!r}) + rs * {LAM!r}) * {_UP}, 2) as upper, round(max(least(o, sqrt(o * ls) * {_LOW})), 2) as lower, round(max(sqrt(o * ls) * {_LOW}), 2) as lower_early from parts")
def a04_hierarchical(s: SparkSession, d: str) -> DataFrame:
    from ..functions import bounds
    from ..operators.measures import join_size_vector

    inst, domain = _star(s, d)
    part = partition.partition_hierarchical(inst, EPS, DELTA, 1.0, NoiseSource.zero(), domain)
    sizes = join_size_vector(part).filter("out_size > 0").select(F.col("config").alias("sub_id"), F.col("out_size").cast("double").alias("o"))
    rows = sizes.join(partition.label_bounds(part, 1 / LAM), "sub_id").collect()  # one a configuration
    log_domain = math.log(25 * 125)
    up, low = bounds.f_up(log_domain, EPS, DELTA, len(_STAR_Q)), bounds.f_low(log_domain, EPS)
    upper, lower = bounds.upper_hierarchical([(r["o"], r["bound"]) for r in rows], LAM, up), bounds.lower_hierarchical([(r["o"], r["local"]) for r in rows], low)
    early = max(bounds.lower_join(r["o"], r["local"], low, "early") for r in rows)
    return s.createDataFrame([(len(rows), *(round(float(x), 2) for x in (upper, lower, early)))], "parts bigint, upper double, lower double, lower_early double")


_SIDES = f"(select K, {ladder_sql('d1', LAM)} as l1, {ladder_sql('d2', LAM)} as l2, d1, d2 from (select c_custkey as K, coalesce(deg1, 0) as d1, coalesce(deg2, 0) as d2 from customer left join {_DEG} on K = c_custkey))"


@entry("r12_hierarchical_partitioner_on_two_tables", f"with lab as materialized {_SIDES} select concat_ws(',', a.l1, b.l2) as config, coalesce(sum(d1 * d2), 0)::bigint as out_size from (select distinct l1 from lab) a cross join (select distinct l2 from lab) b left join lab on lab.l1 = a.l1 and lab.l2 = b.l2 group by 1")
def r12(s: SparkSession, d: str) -> DataFrame:
    """The hierarchical partitioner on a two-table join gives the pairs of both sides' buckets."""
    from ..operators.measures import join_size_vector

    part = partition.partition_hierarchical(load(s, d, TWO), EPS, DELTA, LAM, NoiseSource.zero(), lambda attrs: joint_domain(s, d, TWO, attrs), skip_root=True)
    return join_size_vector(part).select("config", "out_size")


# a self join: a unit touches two rows, so baselines run at half the budget
_LANG_DEGREE = degree_sql(_max_degree_sql(LANG2), EPS / 2, DELTA / 2, text("degree"))


@entry("b04_count_release_self_join_seeded", f"select round(o + {tlap_sql(f'2 * b / {EPS / 2!r}', radius_sql(repr(EPS / 4), repr(DELTA / 4), 'b'), uniform_sql(text('count')))}, 2) as released from (select ({size_sql(LANG2)})::double as o, ({_LANG_DEGREE})::double as b)")
def b04(s: SparkSession, d: str) -> DataFrame:
    return s.createDataFrame([(round(baselines.release_count(load(s, d, LANG2), EPS, DELTA, SEEDED), 2),)], "released double")


@entry("b03_independent_answers_self_join_seeded", f"select q1::int as q1, q2::int as q2, round(coalesce(answer, 0) + {laplace_sql(repr(100.0 * len(_LANG_Q) / (EPS / 2)), uniform_sql(text('query'), 'q1', 'q2'))}, 3) as released from (select unnest(range({len(_LANG_Q.families[0])})) as q1) cross join (select unnest(range({len(_LANG_Q.families[1])})) as q2) left join ({answers_sql(LANG2, _LANG_Q)}) using (q1, q2)")
def b03(s: SparkSession, d: str) -> DataFrame:
    return baselines.answer_independently(load(s, d, LANG2), _LANG_Q, EPS, DELTA, SEEDED, 100.0).select("q1", "q2", F.round("released", 3).alias("released"))
