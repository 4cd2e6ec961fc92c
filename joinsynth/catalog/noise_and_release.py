"""Noise and selection (N) and release methods (R) on the given tables."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bounds, noise
from ..functions.noise import NoiseSource
from ..ledger import Ledger
from ..operators import kernel, partition, release, sensitivity
from ..hyper import JoinSpec
from ..queries import Family, QuerySet, answers, dense_answers, domain_frame, joint_domain
from ..relation import load
from ..sources.workloads import BRANDS, EVENT_TYPES, HIER5, LINE1, NATION2, PATH3, PRIORITIES, SEGMENTS, STAR3, TRIANGLE, TWO
from .core import BETA, _DEG, _rs_sql, residual, union_all
from .registry import DELTA, EPS, LAM, SEED, TWO_ANSWERS, answers_sql, entry, ladder_sql, rel_sql, size_sql, tlap_sql, two_queries, uniform_sql

ZERO, SEEDED = NoiseSource.zero(), NoiseSource.seeded(SEED)
TAU_HALF = noise.tau(EPS / 2, DELTA / 2, 1)

# N: noise and selection ---------------------------------------------------------------------------


@entry("n01_laplace_seeded", f"select K, round(case when u < 0.5 then 2.0 * ln(2 * u) else -2.0 * ln(2 * (1 - u)) end, 6) as x from (select c_custkey as K, {uniform_sql(chr(39) + 'lap' + chr(39), 'c_custkey')} as u from customer)")
def n01(s: SparkSession, d: str) -> DataFrame:
    keys = domain_frame(s, d, TWO, "K")
    return keys.select("K", F.round(noise.laplace_col(2.0, noise.uniform_col(SEED, "lap", F.col("K").cast("string"))), 6).alias("x"))


@entry("n02_truncated_laplace_seeded", f"select K, round({tlap_sql('2.0', repr(TAU_HALF), 'u')}, 6) as x from (select c_custkey as K, {uniform_sql(chr(39) + 'tlap' + chr(39), 'c_custkey')} as u from customer)")
def n02(s: SparkSession, d: str) -> DataFrame:
    keys = domain_frame(s, d, TWO, "K")
    return keys.select("K", F.round(noise.tlap_col(2.0, TAU_HALF, noise.uniform_col(SEED, "tlap", F.col("K").cast("string"))), 6).alias("x"))


@entry("n03_tau", "select e as eps, dl as delta, round(1.0 / e * ln(1 + (exp(e) - 1) / dl), 6) as tau from (select distinct l_quantity / 10.0 as e, 1e-6::double / l_linenumber as dl from lineitem)")
def n03(s: SparkSession, d: str) -> DataFrame:
    """Budgets from quantities and line numbers: at most 50 x 7 distinct ones."""
    found = s.read.parquet(f"{d}/lineitem.parquet").select((F.col("l_quantity") / 10.0).alias("e"), (F.lit(1e-6) / F.col("l_linenumber")).alias("dl")).distinct().collect()
    return s.createDataFrame([(r.e, r.dl, round(noise.tau(r.e, r.dl, 1.0), 6)) for r in found], "eps double, delta double, tau double")


@entry("n04_exponential_mechanism_seeded", f"select E, n from (select event_type as E, count(*)::bigint as n from events group by 1) order by 0.005 * n - ln(-ln({uniform_sql(chr(39) + 'em' + chr(39), 'E')})) desc limit 1")
def n04(s: SparkSession, d: str) -> DataFrame:
    scores = s.read.parquet(f"{d}/events.parquet").groupBy(F.col("event_type").alias("E")).agg(F.count("*").alias("n"))
    return noise.exp_mech(scores, "n", "E", 0.01, SEEDED)


def _pick(values: tuple, u: str) -> str:
    return "[" + ", ".join(f"'{v}'" for v in values) + f"][1 + floor({u} * {len(values)})::int]"


@entry("n05_sample_domain_seeded", f"select i, {_pick(PRIORITIES, uniform_sql(chr(39) + 'P' + chr(39), 'i'))} as P, {_pick(EVENT_TYPES, uniform_sql(chr(39) + 'E' + chr(39), 'i'))} as E from (select o_orderkey as i from orders)")
def n05(s: SparkSession, d: str) -> DataFrame:
    pick = lambda name, values: F.element_at(F.array(*map(F.lit, values)), (F.floor(noise.uniform_col(SEED, name, F.col("i").cast("string")) * len(values)) + 1).cast("int"))
    return s.read.parquet(f"{d}/orders.parquet").select(F.col("o_orderkey").alias("i")).select("i", pick("P", PRIORITIES).alias("P"), pick("E", EVENT_TYPES).alias("E"))


@entry("n07_ledger", "with p as (select count(*)::double as n from lineitem group by l_quantity) select 'degrees' as step, 0.5::double as eps, 5e-7::double as delta, 'parallel over join values' as rule union all "
       "select 'parts', (select 0.5 * (max(n) / sum(n)) from p), (select 5e-7 * (max(n) / sum(n)) from p), 'parallel' union all select 'rounding', 0.0::double, 0.0::double, 'post-processing'")
def n07(s: SparkSession, d: str) -> DataFrame:
    """Parts of the rows by quantity, each with the share of the budget that its rows have."""
    counts = [r.n for r in s.read.parquet(f"{d}/lineitem.parquet").groupBy("l_quantity").agg(F.count("*").alias("n")).collect()]
    total = sum(counts)
    ledger = Ledger(EPS, DELTA)
    ledger.spend("degrees", EPS / 2, DELTA / 2, "parallel over join values")
    ledger.parallel("parts", [(EPS / 2 * (n / total), DELTA / 2 * (n / total)) for n in counts])
    ledger.note("rounding")
    return ledger.frame(s)


def _round_counts(s: SparkSession, d: str) -> list[int]:
    """Numbers of rounds: the distinct quantities, at most 50."""
    return [r.k for r in s.read.parquet(f"{d}/lineitem.parquet").select(F.col("l_quantity").cast("int").alias("k")).distinct().collect()]


@entry("n08_round_budget", "select k, round(1.0 / (16 * sqrt(k * ln(1e6))), 8) as eps_round from (select distinct l_quantity::int as k from lineitem)")
def n08(s: SparkSession, d: str) -> DataFrame:
    return s.createDataFrame([(k, round(bounds.round_budget(EPS, DELTA, k), 8)) for k in _round_counts(s, d)], "k int, eps_round double")


@entry("n09_round_budget_concentrated", "select k, round(sqrt(pow(sqrt(ln(1e6) + 1) - sqrt(ln(1e6)), 2) / (k * 0.625)), 8) as eps_round from (select distinct l_quantity::int as k from lineitem)")
def n09(s: SparkSession, d: str) -> DataFrame:
    return s.createDataFrame([(k, round(bounds.round_budget(EPS, DELTA, k, "zcdp"), 8)) for k in _round_counts(s, d)], "k int, eps_round double")


# R: releases --------------------------------------------------------------------------------------


def kernel_sql(answers_text: str, total: str, cell_attrs: dict[str, tuple], families: list[tuple[str, Family]], rounds: int, tail: str, volume: str = "1.0") -> str:
    """The kernel with zero noise as SQL, rounds unrolled: CTEs ``cells_r`` (mass m after round r) and ``pick_r`` (chosen query)."""
    attrs = list(cell_attrs)
    values = lambda v: f"'{v}'" if isinstance(v, str) else str(v)
    ctes = [f"base as materialized (select {', '.join(attrs)} from {', '.join(f'(select unnest([{chr(44).join(values(v) for v in vs)}]) as {a})' for a, vs in cell_attrs.items())})"]
    n_q = len(families)
    weights = "base"
    for i, (_, fam) in enumerate(families):
        texts = ", ".join(f"({w.replace(' as string', ' as varchar')})::double" for w in fam.weights)
        weights = f"(select *, unnest([{texts}]) as w{i + 1}, unnest(range({len(fam)})) as q{i + 1} from {weights} x{i})"
    place = "q1"
    for i in range(1, n_q):
        place = f"({place}) * {len(families[i][1])} + q{i + 1}"
    product = " * ".join(f"w{i + 1}" for i in range(n_q))
    on = " and ".join(f"t.q{i + 1} = w.q{i + 1}" for i in range(n_q))
    ctes += [f"wt as materialized (select {', '.join(attrs)}, {place} as q, {product} as w, {', '.join(f'q{i + 1}' for i in range(n_q))} from {weights})",
             f"tr as materialized ({answers_text})",
             f"truth as materialized (select distinct w.q, coalesce(t.answer, 0.0)::double as t from wt w left join tr t on {on})",
             f"n as materialized (select ({total})::double as n)",
             f"cells_0 as materialized (select base.*, n.n / (select count(*) from base) as m, ln(n.n / (select count(*) from base)) as lw from base, n)"]
    for r in range(1, rounds + 1):
        ctes += [
            f"ans_{r} as materialized (select q, sum(m * w) as a from cells_{r - 1} join wt using ({', '.join(attrs)}) group by q)",
            f"pick_{r} as materialized (select q, abs(a - t) as err, (least(n, greatest(-n, t)) - a) / (2 * n) as step from ans_{r} join truth using (q), n order by round(abs(a - t), 6) desc, q limit 1)",
            f"raw_{r} as materialized (select c.{', c.'.join(attrs)}, c.lw + w.w * p.step as lw from cells_{r - 1} c join pick_{r} p on true join wt w on w.q = p.q and {' and '.join(f'w.{a} = c.{a}' for a in attrs)})",
            f"cells_{r} as materialized (select {', '.join(attrs)}, exp(lw - (select max(lw) from raw_{r})) * n / (select sum(exp(lw - (select max(lw) from raw_{r}))) from raw_{r}) as m, lw from raw_{r}, n)",
        ]
    return "with " + ", ".join(ctes) + " " + tail


_PE = {"P": PRIORITIES, "E": EVENT_TYPES}
_FAM2 = [("R1", two_queries().families[0]), ("R2", two_queries().families[1])]


def _domain(s: SparkSession, d: str, spec: JoinSpec) -> partition.Domain:
    return lambda attrs: joint_domain(s, d, spec, attrs)


def _two(s: SparkSession, d: str):
    return load(s, d, TWO)


def _two_state(s: SparkSession, d: str) -> tuple[kernel.KernelPlan, float, np.ndarray, int]:
    inst = _two(s, d)
    plan, volume = release.kernel_plan(inst, two_queries(), d)
    return plan, volume, dense_answers(answers(inst, two_queries()).collect(), two_queries()), sensitivity.max_degree(inst).first()[0]


@entry("r01a_noisy_total_seeded", f"select round(val + {tlap_sql('2.0 * 86', repr(noise.tau(EPS / 2, DELTA / 2, 86)), 'u')}, 4) as n_hat from ({size_sql(TWO)}), (select {uniform_sql(chr(39) + 'total' + chr(39), chr(39) + 'all' + chr(39))} as u)")
def r01a(s: SparkSession, d: str) -> DataFrame:
    n_hat = kernel.noisy_total(float(sensitivity.out_size(_two(s, d))), 86.0, EPS, DELTA, SEEDED, "all")
    return s.createDataFrame([(round(n_hat, 4),)], "n_hat double")


@entry("r01b_uniform_start", f"select P, E, round(val / 25.0, 4) as mass from ({size_sql(TWO)}), (select distinct o_orderpriority as P from orders), (select distinct event_type as E from events)")
def r01b(s: SparkSession, d: str) -> DataFrame:
    out = release.release_two_table(_two(s, d), two_queries(), d, EPS, DELTA, ZERO, rounds=0)
    return out.cells.select("P", "E", F.round("mass", 4).alias("mass"))


for _k in (1, 2, 3):
    entry(f"r01c_round{_k}_zero_noise_orders_events", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, _k, f"select P, E, round(m, 3) as mass from cells_{_k}"))(
        lambda s, d, k=_k: release.release_two_table(_two(s, d), two_queries(), d, EPS, DELTA, ZERO, rounds=k, out="last").cells.select("P", "E", F.round("mass", 3).alias("mass"))
    )

_AVG = "select P, E, round(avg(m), 3) as mass from (" + " union all ".join(f"select P, E, m from cells_{r}" for r in (1, 2, 3)) + ") group by P, E"


@entry("r01d_average_of_rounds_zero_noise", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 3, _AVG))
def r01d(s: SparkSession, d: str) -> DataFrame:
    out = release.release_two_table(_two(s, d), two_queries(), d, EPS, DELTA, ZERO, rounds=3)
    return out.cells.select("P", "E", F.round("mass", 3).alias("mass"))


@entry("r01d_average_frame_kernel_zero_noise", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 3, _AVG))
def r01d_frame(s: SparkSession, d: str) -> DataFrame:
    plan, volume, truth, _ = _two_state(s, d)
    cells = s.createDataFrame([(*p, volume) for p in plan.points], ["P", "E", "volume"])
    out = kernel.run_frame(cells, two_queries(), truth, float(truth.flat[0]), 1.0, EPS, DELTA, ZERO, 3)
    return out.select("P", "E", F.round("mass", 3).alias("mass"))


@entry("r01e_round_formula", f"select greatest(1, floor(val * sqrt(ln(25.0 * k)) / (b * ln(36.0) * sqrt(ln(1e6)))))::int as rounds from ({size_sql(TWO)}), (select count(*) as k from customer), (select greatest(max(deg1), max(deg2)) as b from {_DEG})")
def r01e(s: SparkSession, d: str) -> DataFrame:
    plan, _, truth, degree = _two_state(s, d)
    return s.createDataFrame([(bounds.auto_rounds(float(truth.flat[0]), EPS, DELTA, degree, plan.log_domain, 36, most=10**6),)], "rounds int")


_LINE_Q = QuerySet((Family.all_ones() + Family.marginal("G", ("A", "N", "R")) + Family.prefix("V", (0, 1, 2, 3)),))


@entry("r01f_single_table_zero_noise", kernel_sql(answers_sql(LINE1, _LINE_Q), size_sql(LINE1), {"G": ("A", "N", "R"), "Z": ("F", "O"), "V": (0, 1, 2, 3, 4)}, [("R1", _LINE_Q.families[0])], 2, "select G, Z, V::int as V, round(m, 3) as mass from cells_2"))
def r01f(s: SparkSession, d: str) -> DataFrame:
    out = release.release_single(load(s, d, LINE1), _LINE_Q, d, EPS, DELTA, ZERO, rounds=2, out="last")
    return out.cells.select("G", "Z", F.col("V").cast("int").alias("V"), F.round("mass", 3).alias("mass"))


@entry("r02_two_table_release_zero_noise", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 2, f"select P, E, round(m, 3) as mass, (select greatest(max(deg1), max(deg2)) from {_DEG})::double as dtilde from cells_2"))
def r02(s: SparkSession, d: str) -> DataFrame:
    out = release.release_two_table(_two(s, d), two_queries(), d, EPS, DELTA, ZERO, rounds=2, out="last")
    return out.cells.select("P", "E", F.round("mass", 3).alias("mass"), "dtilde")


@entry("r02_noisy_degree_seeded", f"select round(b + {tlap_sql('2.0', repr(TAU_HALF), 'u')}, 6) as dtilde from (select greatest(max(deg1), max(deg2)) as b from {_DEG}), (select {uniform_sql(chr(39) + 'degree' + chr(39))} as u)")
def r02_degree(s: SparkSession, d: str) -> DataFrame:
    return release.release_two_table(_two(s, d), two_queries(), d, EPS, DELTA, SEEDED, rounds=1).cells.select(F.round("dtilde", 6).alias("dtilde")).distinct()


_STAR_Q = QuerySet((Family.all_ones() + Family.marginal("S", SEGMENTS), Family.all_ones(), Family.all_ones() + Family.prefix("H", (1, 3))))
_SVH = {"S": SEGMENTS, "V": (0, 1, 2, 3, 4), "H": (0, 1, 2, 3, 4)}


@entry("r04_multi_table_release_star3_zero_noise", kernel_sql(answers_sql(STAR3, _STAR_Q), size_sql(STAR3), _SVH, [(f"R{i + 1}", f) for i, f in enumerate(_STAR_Q.families)], 2,
       f"select S, V::int as V, H::int as H, round(m, 3) as mass, rs as dtilde from cells_2, ({_rs_sql(STAR3)})"))
def r04(s: SparkSession, d: str) -> DataFrame:
    out = release.release_multi_table(load(s, d, STAR3), _STAR_Q, d, EPS, DELTA, ZERO, rounds=2, beta=BETA, out="last")
    return out.cells.select("S", F.col("V").cast("int").alias("V"), F.col("H").cast("int").alias("H"), F.round("mass", 3).alias("mass"), F.round("dtilde", 4).alias("dtilde"))


_PATH_Q2 = QuerySet((Family.all_ones() + Family.marginal("B", BRANDS), Family.all_ones(), Family.all_ones() + Family.prefix("N", (5, 15))))


@entry("r04_multi_table_release_path3_zero_noise", kernel_sql(answers_sql(PATH3, _PATH_Q2), size_sql(PATH3), {"B": BRANDS, "NK": tuple(range(25))}, [("R1", _PATH_Q2.families[0]), ("R2", _PATH_Q2.families[1]), ("R3", Family(tuple(w.replace("N <=", "NK <=") for w in _PATH_Q2.families[2].weights)))], 2,
       f"select B, NK::int as N, round(m, 3) as mass, rs as dtilde from cells_2, ({_rs_sql(PATH3)})"))
def r04_path(s: SparkSession, d: str) -> DataFrame:
    out = release.release_multi_table(load(s, d, PATH3), _PATH_Q2, d, EPS, DELTA, ZERO, rounds=2, beta=BETA, out="last")
    return out.cells.select("B", F.col("N").cast("int").alias("N"), F.round("mass", 3).alias("mass"), F.round("dtilde", 4).alias("dtilde"))


@entry("r04_multi_table_total_star3", f"select round(val::double, 3) as total from ({size_sql(STAR3)})")
def r04_total(s: SparkSession, d: str) -> DataFrame:
    out = release.release_multi_table(load(s, d, STAR3), _STAR_Q, d, EPS, DELTA, ZERO, rounds=2, beta=BETA)
    return out.cells.agg(F.round(F.sum("mass"), 3).alias("total"))


_LABELS = f"(select c_custkey as K, {ladder_sql('greatest(coalesce(deg1, 0), coalesce(deg2, 0))', LAM)} as bucket from customer left join {_DEG} on K = c_custkey)"


@entry("r05_uniformized_totals_zero_noise", f"select bucket::varchar as sub_id, coalesce(sum(n), 0)::bigint as total from (select distinct bucket from {_LABELS}) left join (select bucket as b, deg1 * deg2 as n from {_LABELS} l join {_DEG} g on g.K = l.K) on b = bucket group by 1")
def r05(s: SparkSession, d: str) -> DataFrame:
    out = release.release_uniformized(_two(s, d), two_queries(), d, EPS, DELTA, ZERO, rounds=2, lam=LAM)
    return out.cells.groupBy("sub_id").agg(F.round(F.sum("mass")).cast("bigint").alias("total"))


_NOISY = f"greatest(coalesce(deg1, 0), coalesce(deg2, 0)) + {tlap_sql('2.0', repr(TAU_HALF), 'u')}"


@entry("r06_partition_seeded_orders_events", f"select K, {ladder_sql('x', LAM)} as bucket from (select c_custkey as K, {_NOISY} as x from (select c_custkey, deg1, deg2, {uniform_sql(chr(39) + 'deg' + chr(39), 'c_custkey')} as u from customer left join {_DEG} on K = c_custkey))")
def r06(s: SparkSession, d: str) -> DataFrame:
    part = partition.partition_two_table(_two(s, d), domain_frame(s, d, TWO, "K"), EPS / 2, DELTA / 2, LAM, SEEDED)
    return part.labels


@entry("r07_true_degree_partition", f"select * from {_LABELS}")
def r07(s: SparkSession, d: str) -> DataFrame:
    return partition.partition_true_degrees(_two(s, d), domain_frame(s, d, TWO, "K"), LAM).labels


_LEAVES = ", ".join(f"{ladder_sql(f'd{i}', 1.0)} as l{i}" for i in (1, 2, 3))
_STAR_DEG = "(select N, sum(f1) as d1 from " + rel_sql(STAR3, 0) + " group by N) join (select N, sum(f2) as d2 from " + rel_sql(STAR3, 1) + " group by N) using (N) join (select N, sum(f3) as d3 from " + rel_sql(STAR3, 2) + " group by N) using (N)"


@entry("r08_hierarchical_partition_star3", f"select concat_ws(',', l1, l2, l3, {ladder_sql('n', 1.0)}) as config, o as out_size from (select l1, l2, l3, count(*) as n, sum(d1 * d2 * d3)::bigint as o from (select *, {_LEAVES} from {_STAR_DEG}) group by l1, l2, l3)")
def r08(s: SparkSession, d: str) -> DataFrame:
    """Configurations with a join: labels of the leaves' degrees per nation, then of the number of nations in the configuration."""
    from ..operators.measures import join_size_vector

    vector = join_size_vector(partition.partition_hierarchical(load(s, d, STAR3), EPS, DELTA, 1.0, ZERO, _domain(s, d, STAR3)))
    return vector.filter("out_size > 0").select("config", "out_size")


@entry("r08_hierarchical_union_is_whole", f"select val from ({size_sql(STAR3)})")
def r08_whole(s: SparkSession, d: str) -> DataFrame:
    from ..operators.measures import join_size_vector

    return join_size_vector(partition.partition_hierarchical(load(s, d, STAR3), EPS, DELTA, LAM, SEEDED, _domain(s, d, STAR3))).agg(F.sum("out_size").alias("val"))


@entry("r08_hierarchical_union_is_whole_hier5", f"select val from ({size_sql(HIER5)})")
def r08_hier5(s: SparkSession, d: str) -> DataFrame:
    from ..operators.measures import join_size_vector

    return join_size_vector(partition.partition_hierarchical(load(s, d, HIER5), EPS, DELTA, LAM, ZERO, _domain(s, d, HIER5))).agg(F.sum("out_size").alias("val"))


_ND = "(select n_nationkey as N, count(c_custkey) as deg from nation left join customer on c_nationkey = n_nationkey group by 1)"


@entry("r09_split_on_leaf", f"select N, {ladder_sql('deg', LAM)} as c_S from {_ND}")
def r09(s: SparkSession, d: str) -> DataFrame:
    from ..hyper import AttrTree

    inst = load(s, d, STAR3)
    tree = AttrTree(STAR3)
    leaf = next(n for n in tree.nodes if n.attrs == ("S",))
    _, _, known = partition.split_on_attribute(inst, tree, leaf, {}, {}, _domain(s, d, STAR3), EPS, DELTA, LAM, ZERO)
    return known.select("N", "c_S")


_PAIR_LABEL = f"concat_ws(',', {ladder_sql('coalesce(deg1, 0)', LAM)}, {ladder_sql('coalesce(deg2, 0)', LAM)})"


@entry("r12_pair_buckets", f"select bucket, count(*)::bigint as n_keys, coalesce(sum(deg1 * deg2), 0)::bigint as out_size from (select {_PAIR_LABEL} as bucket, deg1, deg2 from customer left join {_DEG} on K = c_custkey) group by bucket")
def r12(s: SparkSession, d: str) -> DataFrame:
    from ..operators.measures import join_size_vector

    return join_size_vector(partition.partition_true_degrees(_two(s, d), domain_frame(s, d, TWO, "K"), LAM, pairs=True))


@entry("r13_rounded_rows_nearest", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 2, "select P, E, (floor(m) + case when m - floor(m) > 0.5 then 1 else 0 end)::bigint as n from cells_2"))
def r13(s: SparkSession, d: str) -> DataFrame:
    out = release.release_two_table(_two(s, d), two_queries(), d, EPS, DELTA, ZERO, rounds=2, out="last")
    return out.to_rows(ZERO, "nearest").groupBy("P", "E").agg(F.count("*").alias("n"))


@entry("r14_substitution_budget", f"select round(b + {tlap_sql('4.0', repr(noise.tau(EPS / 4, DELTA / 4, 1)), 'u')}, 6) as dtilde from (select greatest(max(deg1), max(deg2)) as b from {_DEG}), (select {uniform_sql(chr(39) + 'degree' + chr(39))} as u)")
def r14(s: SparkSession, d: str) -> DataFrame:
    """A substituted row is two units: the noisy degree of a release at half the budget."""
    return release.release_two_table(_two(s, d), two_queries(), d, EPS, DELTA, SEEDED, rounds=1, dp="substitute").cells.select(F.round("dtilde", 6).alias("dtilde")).distinct()


@entry("r15_public_bound_zero_noise", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 1, "select P, E, round(m, 3) as mass, 500.0::double as dtilde from cells_1"))
def r15(s: SparkSession, d: str) -> DataFrame:
    out = release.release_two_table(_two(s, d), two_queries(), d, EPS, DELTA, ZERO, rounds=1, public_bound=500.0, out="last")
    return out.cells.select("P", "E", F.round("mass", 3).alias("mass"), "dtilde")


_ANS_TAIL = "select w.q1::int as q1, w.q2::int as q2, round(sum(m * w), 2) as released from cells_2 join wt w using (P, E) group by 1, 2"


@entry("q11_answers_on_synthetic_cells", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 2, _ANS_TAIL))
def q11(s: SparkSession, d: str) -> DataFrame:
    out = release.release_two_table(_two(s, d), two_queries(), d, EPS, DELTA, ZERO, rounds=2, out="last")
    return out.answer().select("q1", "q2", F.round("released", 2).alias("released"))


@entry("q12_answers_over_union_of_parts", f"select 0::int as q1, 0::int as q2, round(val::double, 2) as released from ({size_sql(TWO)})")
def q12(s: SparkSession, d: str) -> DataFrame:
    out = release.release_uniformized(_two(s, d), two_queries(), d, EPS, DELTA, ZERO, rounds=2, lam=LAM)
    return out.answer().filter("q1 = 0 and q2 = 0").select("q1", "q2", F.round("released", 2).alias("released"))
