"""Baselines (B), measures (A) and worked instances (W)."""

from __future__ import annotations

import math

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import bounds
from ..functions.noise import tau
from ..operators import baselines, kernel, measures, partition, release, sensitivity
from ..plans.elimination import join_size
from ..queries import answers, dense_answers, domain_frame
from ..relation import COUNT, load, materialise, neighbor, source_rows
from ..sources import instances
from ..sources.formats import cut
from ..sources.workloads import CHAIN3, HIER5, LINE1, NATION2, PATH3, SPECS, STAR3, TWO
from .core import BETA, _DEG, in_bigint, union_all
from .noise_and_release import _FAM2, _LABELS, _LINE_Q, _PE, SEEDED, ZERO, kernel_sql
from .registry import DELTA, EPS, LAM, TWO_ANSWERS, answers_sql, entry, ladder_sql, rel_sql, size_sql, tlap_sql, two_queries, uniform_sql

LOG_D_SQL = "ln(25.0 * (select count(*) from customer))"
F_LOW_SQL = f"sqrt(sqrt({LOG_D_SQL}) / 1.0)"
F_UP_SQL = f"({F_LOW_SQL} * sqrt(ln(36.0)) * sqrt(ln(1e6)))"
Q = "'"

# B: baselines -------------------------------------------------------------------------------------


@entry("b01_exact_total_zero_noise", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 2, "select P, E, round(m, 3) as mass from cells_2"))
def b01(s: SparkSession, d: str) -> DataFrame:
    """Not private: run only as a counter-example."""
    out = release.release_exact_total(load(s, d, TWO), two_queries(), d, EPS, DELTA, ZERO, 2, allow_nonprivate=True, out="last")
    return out.cells.select("P", "E", F.round("mass", 3).alias("mass"))


def _independent_sql(share: str) -> str:
    u = uniform_sql("'query'", "q1", "q2")
    scale = f"(100.0 / ({share}))"
    return (f"select q1, q2, round(coalesce(answer, 0.0) + case when u < 0.5 then {scale} * ln(2 * u) else -{scale} * ln(2 * (1 - u)) end, 3) as released from "
            f"(select a.q1::int as q1, b.q2::int as q2, {u.replace('q1', 'a.q1').replace('q2', 'b.q2')} as u from (select unnest(range(6)) as q1) a, (select unnest(range(6)) as q2) b) left join ({TWO_ANSWERS}) using (q1, q2)")  # fmt: skip


for _c, _share in (("basic", "1.0 / 36"), ("advanced", "1.0 / (2 * sqrt(2 * 36 * ln(2 / 1e-6)))")):
    entry(f"b03_independent_answers_{_c}", _independent_sql(_share))(
        lambda s, d, c=_c: baselines.answer_independently(load(s, d, TWO), two_queries(), EPS, DELTA, SEEDED, 100.0, c).select("q1", "q2", F.round("released", 3).alias("released"))
    )


@entry("b04_count_release_truncated_laplace",
       f"with b as (select greatest(max(deg1), max(deg2)) + {tlap_sql('2.0', repr(tau(EPS / 2, DELTA / 2, 1)), uniform_sql(Q + 'degree' + Q))} as b from {_DEG}) "
       f"select round(val + {tlap_sql('2 * b', f'b * {tau(EPS / 2, DELTA / 2, 1)!r}', uniform_sql(Q + 'count' + Q))}, 2) as released from ({size_sql(TWO)}), b")  # fmt: skip
def b04(s: SparkSession, d: str) -> DataFrame:
    return s.createDataFrame([(round(baselines.release_count(load(s, d, TWO), EPS, DELTA, SEEDED), 2),)], "released double")


@entry("b04_count_release_laplace_cauchy", f"select round(val + (select case when u < 0.5 then 400.0 * ln(2 * u) else -400.0 * ln(2 * (1 - u)) end from (select {uniform_sql(Q + 'count' + Q)} as u)), 3) as laplace, "
       f"round(val + 1200.0 * tan(pi() * ({uniform_sql(Q + 'count' + Q)} - 0.5)), 3) as cauchy from ({size_sql(TWO)})")  # fmt: skip
def b04_laws(s: SparkSession, d: str) -> DataFrame:
    inst = load(s, d, TWO)
    return s.createDataFrame([tuple(round(baselines.release_count(inst, EPS, DELTA, SEEDED, 200.0, law), 3) for law in ("laplace", "cauchy"))], "laplace double, cauchy double")


@entry("b05_truncation", f"select coalesce(sum(deg1 * deg2), 0)::bigint as out_size from {_DEG} where deg1 <= 60 and deg2 <= 60")
def b05(s: SparkSession, d: str) -> DataFrame:
    return baselines.size_frame(baselines.truncate(load(s, d, TWO), 60))


@entry("b06_single_table_kernel_average", kernel_sql(answers_sql(LINE1, _LINE_Q), size_sql(LINE1), {"G": ("A", "N", "R"), "Z": ("F", "O"), "V": (0, 1, 2, 3, 4)}, [("R1", _LINE_Q.families[0])], 2,
       "select G, Z, V::int as V, round(avg(m), 3) as mass from (select * from cells_1 union all select * from cells_2) group by G, Z, V"))
def b06(s: SparkSession, d: str) -> DataFrame:
    out = release.release_single(load(s, d, LINE1), _LINE_Q, d, EPS, DELTA, ZERO, rounds=2)
    return out.cells.select("G", "Z", F.col("V").cast("int").alias("V"), F.round("mass", 3).alias("mass"))


@entry("b07_local_sensitivity_noise_seeded", f"select round(val + b * (select case when u < 0.5 then ln(2 * u) else -ln(2 * (1 - u)) end from (select {uniform_sql(Q + 'count' + Q)} as u)), 3) as released from ({size_sql(TWO)}), (select greatest(max(deg1), max(deg2)) as b from {_DEG})")
def b07(s: SparkSession, d: str) -> DataFrame:
    """Not private: the scale is data."""
    return s.createDataFrame([(round(baselines.flawed_local_noise(load(s, d, TWO), EPS, SEEDED, allow_nonprivate=True), 3),)], "released double")


_TINY_SQL = ("(select a1, a2, c1, c2, count(*)::bigint as customers from (select K, sum(a1)::bigint as a1, sum(a2)::bigint as a2, sum(c1)::bigint as c1, sum(c2)::bigint as c2 from "
             "(select o_custkey as K, (o_orderpriority is not distinct from '1-URGENT')::int as a1, (o_orderpriority is distinct from '1-URGENT')::int as a2, 0 as c1, 0 as c2 from orders "
             "union all select user_id, 0, 0, (event_type is not distinct from 'purchase')::int, (event_type is distinct from 'purchase')::int from events) where K is not null group by K) group by all)")  # fmt: skip


def _tiny_bounds(pages):  # noqa: ANN001, ANN202
    """Both bounds of instances on one join value, two tuples a side, by the tuples' frequencies."""
    brute, sides = sensitivity.BruteForceSmooth([[(1, 1), (2, 1)], [(1, 1), (1, 2)]], 2), (((1, 1), (2, 1)), ((1, 1), (1, 2)))
    for page in pages:
        states = [tuple(frozenset((t, n) for t, n in zip(side, map(int, row[k : k + 2]), strict=True) if n) for side, k in zip(sides, (0, 2), strict=True)) for row in page[["a1", "a2", "c1", "c2"]].itertuples(index=False, name=None)]
        yield page.assign(least_within_two=[round(brute.value_of(instances.ABC, x, BETA), 6) for x in states], residual=[round(sensitivity.residual_of(instances.ABC, x, BETA), 6) for x in states])


@entry("b08_smooth_sensitivity_tiny", f"select a1, a2, c1, c2, customers, round(max(exp(-{BETA!r} * k) * (greatest(a1 + a2, c1 + c2) + k)) filter (where k <= 2), 6) as least_within_two, "
       f"round(max(exp(-{BETA!r} * k) * (greatest(a1 + a2, c1 + c2) + k)), 6) as residual from {_TINY_SQL}, range(100) t(k) group by a1, a2, c1, c2, customers")  # fmt: skip
def b08(s: SparkSession, d: str) -> DataFrame:
    """Every customer's orders (urgent or not) and events (purchases or not) are a tiny instance on one join value; each distinct one is walked once."""
    first, zero, rows = {"P": "1-URGENT", "E": "purchase"}, F.lit(0), None
    for i, r in enumerate(TWO.relations):
        hit = F.col(r.attrs[1]).eqNullSafe(first[r.attrs[1]])
        own = [hit.cast("int"), (~hit).cast("int")]
        one = source_rows(s, d, r).filter("K is not null").select("K", *(c.alias(n) for n, c in zip(("a1", "a2", "c1", "c2"), [zero, zero, *own] if i else [*own, zero, zero], strict=True)))
        rows = one if rows is None else rows.unionByName(one)
    tiny = rows.groupBy("K").agg(*(F.sum(n).alias(n) for n in ("a1", "a2", "c1", "c2"))).groupBy("a1", "a2", "c1", "c2").agg(F.count("*").alias("customers"))
    return tiny.repartition(s.sparkContext.defaultParallelism, "a1", "a2", "c1", "c2").mapInPandas(_tiny_bounds, "a1 bigint, a2 bigint, c1 bigint, c2 bigint, customers bigint, least_within_two double, residual double")


# "after" has one more unit of the orders: the customer with the most line items gets the order with the most.
_CHAIN_SQL = """with r1 as (select c_custkey as K, count(*) as n from customer group by 1), r3 as (select l_orderkey as O, count(*) as n from lineitem group by 1), r2 as (select o_custkey as K, o_orderkey as O from orders),
  near as (select (select K from r2 join r3 using (O) where K is not null group by K order by sum(n) desc, K limit 1) as K, (select O from r3 where O is not null order by n desc, O limit 1) as O),
  both_sides as (select 'before' as side, * from r2 union all select 'after', * from r2 union all select 'after', * from near),
  t12 as (select side, max(t) as t from (select side, O, sum(n) as t from both_sides join r1 using (K) group by side, O) group by side),
  t23 as (select side, max(t) as t from (select side, K, sum(n) as t from both_sides join r3 using (O) group by side, K) group by side),
  t13 as (select coalesce((select max(n) from r1), 0) * coalesce((select max(n) from r3), 0) as t)
  select side, greatest(coalesce(t12.t, 0), t13.t, coalesce(t23.t, 0))::bigint as local_sensitivity, coalesce(t23.t, 0)::bigint as t23 from (values ('before'), ('after')) v(side) left join t12 using (side) left join t23 using (side), t13"""


@entry("b09_two_table_rule_on_three", _CHAIN_SQL)
def b09(s: SparkSession, d: str) -> DataFrame:
    """One unit of the middle table moves a boundary maximum of three tables by as many as the largest order has line items, where two tables allow one."""
    inst = materialise(load(s, d, CHAIN3))
    lines = sensitivity.degrees(inst.frames[2].filter("O is not null"), ("O",))
    bought = inst.frames[1].filter("K is not null").join(lines, "O").groupBy("K").agg(F.sum(F.col("freq").cast(COUNT) * F.col("deg")).alias("deg"))
    heaviest = tuple(r[0] if r else None for r in (x.orderBy(F.desc("deg"), a).select(a).first() for x, a in ((bought, "K"), (lines, "O"))))
    out = []
    for side, x in (("before", inst), ("after", neighbor(inst, 1, heaviest, 1))):
        table = sensitivity.boundary_table(x, [e for e in sensitivity.subsets(3) if len(e) == 2])
        out.append(table.agg(F.lit(side).alias("side"), F.max("t").cast("bigint").alias("local_sensitivity"), F.max(F.when(F.col("rels") == "2,3", F.col("t"))).cast("bigint").alias("t23")))
    return union_all(out)


@entry("b10_whole_join_vs_uniformized_staircase", "select r::int as r, round(sqrt(o * m), 4) as whole_join, round(u, 4) as uniformized from (select r, sum(b * b) as o, max(b) as m from (values (10), (40)) t(r), (select distinct count(*)::bigint as b from orders group by o_custkey) where b <= r group by r) "
       f"join (select r, sum(sqrt(x * pow(2.0, bucket))) as u from (select r, {ladder_sql('b', 1.0)} as bucket, sum(b * b) as x from (values (10), (40)) t(r), (select distinct count(*)::bigint as b from orders group by o_custkey) where b <= r group by 1, 2) group by r) using (r)")  # fmt: skip
def b10(s: SparkSession, d: str) -> DataFrame:
    """A staircase of the degrees that customers have in the orders."""
    degrees = cut(s.read.parquet(f"{d}/orders.parquet").groupBy("o_custkey").agg(F.count("*").alias("B")).select("B").distinct())
    out = []
    for r in (10, 40):
        inst = instances.gen_staircase(s, r, degrees)
        part = partition.partition_true_degrees(inst, inst.frames[0].select("B").distinct(), 1.0)
        out.append(measures.gain(part).select(F.lit(r).alias("r"), F.round("whole_join", 4).alias("whole_join"), F.round("uniformized", 4).alias("uniformized")))
    return union_all(out)


@entry("b11_constant_release", f"select max(abs(coalesce(answer, 0) - 4.0 * n))::double as linf from (select q1, q2, (case when q1 = 0 then 5 else 1 end) * (case when q2 = 0 then 5 else 1 end) as n from (select unnest(range(6)) as q1), (select unnest(range(6)) as q2)) left join ({TWO_ANSWERS}) using (q1, q2)")
def b11(s: SparkSession, d: str) -> DataFrame:
    inst, queries = load(s, d, TWO), two_queries()
    plan, _ = release.kernel_plan(inst, queries, d)
    truth = dense_answers(answers(inst, queries).collect(), queries)
    return s.createDataFrame([(float(np.abs(plan.answers(baselines.constant_release(inst, 25, 100.0)) - truth).max()),)], "linf double")


@entry("b12_zero_rounds", f"select round(max(abs(coalesce(answer, 0) - val / 25.0 * n)), 3) as linf from (select q1, q2, (case when q1 = 0 then 5 else 1 end) * (case when q2 = 0 then 5 else 1 end) as n from (select unnest(range(6)) as q1), (select unnest(range(6)) as q2)) left join ({TWO_ANSWERS}) using (q1, q2), ({size_sql(TWO)})")
def b12(s: SparkSession, d: str) -> DataFrame:
    out = release.release_two_table(load(s, d, TWO), two_queries(), d, EPS, DELTA, ZERO, rounds=0)
    errors = measures.error_table(baselines.complete_answers(load(s, d, TWO), two_queries()), out.answer(), ["q1", "q2"])
    return errors.agg(F.round(F.max("abs_error"), 3).alias("linf"))


@entry("b13_path_partitions", "select count(*)::bigint as middle_parts, (select max(n) from (select count(*) as n from (select distinct l_partkey, l_suppkey from lineitem) group by l_partkey))::bigint as copies_first, 1::bigint as independent_parts, "
       "(select max(n) / min(n)::double from (select count(*) as n from lineitem group by l_partkey)) as worst_spread from (select distinct l_partkey, l_suppkey from lineitem)")  # fmt: skip
def b13(s: SparkSession, d: str) -> DataFrame:
    return partition.explore_path_partitions(load(s, d, PATH3), LAM)


# A: measures --------------------------------------------------------------------------------------

_ERR_TAIL = ("select {out} from (select w.q, sum(m * w) as a from cells_2 join wt w using (P, E) group by w.q) join truth using (q)")


def _errors(s: SparkSession, d: str) -> DataFrame:
    out = release.release_two_table(load(s, d, TWO), two_queries(), d, EPS, DELTA, ZERO, rounds=2, out="last")
    return measures.error_table(baselines.complete_answers(load(s, d, TWO), two_queries()), out.answer(), ["q1", "q2"])


@entry("a01_linf_error_zero_noise", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 2, _ERR_TAIL.format(out="round(max(abs(a - t)), 2) as linf")))
def a01(s: SparkSession, d: str) -> DataFrame:
    return measures.linf_error(_errors(s, d)).select(F.round("linf", 2).alias("linf"))


@entry("a02_error_table_zero_noise", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 2, _ERR_TAIL.format(out="(q // 6)::int as q1, (q % 6)::int as q2, round(t, 2) as exact, round(a, 2) as released")))
def a02(s: SparkSession, d: str) -> DataFrame:
    return _errors(s, d).select("q1", "q2", F.round("exact", 2).alias("exact"), F.round("released", 2).alias("released"))


@entry("a02_error_quantiles_zero_noise", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 2, _ERR_TAIL.format(out="round(max(e), 2) as linf, round(avg(e), 2) as mean_error, round(quantile_cont(e, 0.5), 2) as median_error, round(quantile_cont(e, 0.9), 2) as p90_error, round(max(e / greatest(1, abs(t))), 3) as max_rel_error").replace("from (select", "from (select q, t, a, abs(a - t) as e from (select", 1) + ")"))
def a02_quantiles(s: SparkSession, d: str) -> DataFrame:
    return measures.error_quantiles(_errors(s, d)).select(*(F.round(c, 2).alias(c) for c in ("linf", "mean_error", "median_error", "p90_error")), F.round("max_rel_error", 3).alias("max_rel_error"))


def _log_domain(s: SparkSession, d: str) -> float:
    return math.log(25.0 * domain_frame(s, d, TWO, "K").count())


@entry("a03_error_factors", f"select round({F_LOW_SQL}, 6) as f_low, round({F_UP_SQL}, 6) as f_up, round(ln(1e6), 6) as lam")
def a03(s: SparkSession, d: str) -> DataFrame:
    ld = _log_domain(s, d)
    return s.createDataFrame([(round(bounds.f_low(ld, EPS), 6), round(bounds.f_up(ld, EPS, DELTA, 36), 6), round(LAM, 6))], "f_low double, f_up double, lam double")


_STATS = f"(select sum(deg1 * deg2)::double as o, greatest(max(deg1), max(deg2))::double as b from {_DEG})"
_UNI = f"(select sum(sqrt(o * pow(2.0, bucket) * {LAM!r})) as u, max(least(o, sqrt(o * pow(2.0, bucket) * {LAM!r}) * {F_LOW_SQL})) as l from (select bucket, sum(deg1 * deg2)::double as o from {_LABELS} x join {_DEG} g on g.K = x.K group by 1) where o is not null)"


def _vector(s: SparkSession, d: str) -> list[tuple[int, float]]:
    part = partition.partition_true_degrees(load(s, d, TWO), domain_frame(s, d, TWO, "K"), LAM)
    return [(r.bucket, float(r.out_size)) for r in measures.join_size_vector(part).collect()]


@entry("a04_upper_bounds", f"select round((sqrt(o * (b + {LAM!r})) + (b + {LAM!r}) * sqrt({LAM!r})) * {F_UP_SQL}, 2) as two_table, round((sqrt(o * b) + b * sqrt({LAM!r})) * {F_UP_SQL}, 2) as multi_table, "
       f"round((sqrt(o * b * {LAM!r}) + b * {LAM!r}) * {F_UP_SQL}, 2) as multi_early, round((pow({LAM!r}, 1.5) * (b + {LAM!r}) + u) * {F_UP_SQL}, 2) as uniformized from {_STATS}, {_UNI}")  # fmt: skip
def a04(s: SparkSession, d: str) -> DataFrame:
    inst, vector = load(s, d, TWO), _vector(s, d)
    o, b, up = float(sensitivity.out_size(inst)), float(sensitivity.max_degree(inst).first()[0]), bounds.f_up(_log_domain(s, d), EPS, DELTA, 36)
    row = (bounds.upper_two_table(o, b, LAM, up), bounds.upper_multi_table(o, b, LAM, up), bounds.upper_multi_table(o, b, LAM, up, "early"), bounds.upper_uniformized(vector, b, LAM, up))
    return s.createDataFrame([tuple(round(x, 2) for x in row)], "two_table double, multi_table double, multi_early double, uniformized double")


@entry("a05_lower_bounds", f"select round(b, 2) as sensitivity, round(least(o, sqrt(o * b) * {F_LOW_SQL}), 2) as join_bound, round(l, 2) as uniformized, round(least(n, sqrt(n) * {F_LOW_SQL}), 2) as single_table from {_STATS}, {_UNI}, (select count(*)::double as n from orders)")
def a05(s: SparkSession, d: str) -> DataFrame:
    inst, low = load(s, d, TWO), bounds.f_low(_log_domain(s, d), EPS)
    o, b = float(sensitivity.out_size(inst)), float(sensitivity.max_degree(inst).first()[0])
    n = float(inst.frames[0].agg(F.sum("freq")).first()[0])
    row = (bounds.lower_sensitivity(b), bounds.lower_join(o, b, low), bounds.lower_uniformized(_vector(s, d), LAM, low), bounds.lower_single(n, low))
    return s.createDataFrame([tuple(round(x, 2) for x in row)], "sensitivity double, join_bound double, uniformized double, single_table double")


@entry("a05_lower_bounds_early", f"select round(sqrt(o * b) * {F_LOW_SQL}, 2) as join_bound, round(sqrt(o * b) * {F_LOW_SQL}, 2) > round(o, 2) as above_join_size from {_STATS}")
def a05_early(s: SparkSession, d: str) -> DataFrame:
    inst = load(s, d, TWO)
    o, b = float(sensitivity.out_size(inst)), float(sensitivity.max_degree(inst).first()[0])
    low = round(bounds.lower_join(o, b, bounds.f_low(_log_domain(s, d), EPS), "early"), 2)
    return s.createDataFrame([(low, low > round(o, 2))], "join_bound double, above_join_size boolean")


@entry("a06_join_size_vector", f"select bucket, count(*)::bigint as n_keys, coalesce(sum(deg1 * deg2), 0)::bigint as out_size from {_LABELS} x left join {_DEG} g on g.K = x.K group by bucket")
def a06(s: SparkSession, d: str) -> DataFrame:
    return measures.join_size_vector(partition.partition_true_degrees(load(s, d, TWO), domain_frame(s, d, TWO, "K"), LAM))


@entry("a06_conformance", "select true as conforms")
def a06_conforms(s: SparkSession, d: str) -> DataFrame:
    part = partition.partition_true_degrees(load(s, d, TWO), domain_frame(s, d, TWO, "K"), LAM)
    vector = measures.join_size_vector(part)
    return measures.conforms(vector, vector.withColumn("out_size", (F.col("out_size") * 1.5).cast("bigint")), "bucket", 2.0)


def _trace(s: SparkSession, d: str, rounds: int = 3) -> kernel.Trace:
    inst, queries = load(s, d, TWO), two_queries()
    plan, volume = release.kernel_plan(inst, queries, d)
    truth = dense_answers(answers(inst, queries).collect(), queries)
    trace = kernel.Trace()
    # true totals of the cells are the products of the two marginal indicators
    kernel.run_task(plan, truth, np.full(len(plan.points), volume), float(truth.flat[0]), 1.0, EPS, DELTA, ZERO, rounds, trace=trace, true_cells=truth[1:, 1:].ravel())
    return trace


@entry("a07_round_errors_zero_noise", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 3, " union all ".join(f"select {r}::int as round, q::int as query, round(err, 3) as max_error from pick_{r}" for r in (1, 2, 3))))
def a07(s: SparkSession, d: str) -> DataFrame:
    t = _trace(s, d)
    return s.createDataFrame([(i + 1, q, round(e, 3)) for i, (q, e) in enumerate(zip(t.query, t.error, strict=True))], "round int, query int, max_error double")


_PSI = {r: f"(select sum(share * ln(share / (m / n))) as psi from (select P, E, t / n as share from wt join truth using (q), n where q1 > 0 and q2 > 0 and w = 1 and t > 0) join cells_{r} using (P, E), n)" for r in range(4)}


@entry("a08_potential_drop_zero_noise", kernel_sql(TWO_ANSWERS, size_sql(TWO), _PE, _FAM2, 3,
       " union all ".join(f"select {r + 1}::int as round, round(a.psi, 7) as potential, round(a.psi - b.psi, 7) as decrease from {_PSI[r]} a, {_PSI[r + 1]} b" for r in range(3))))
def a08(s: SparkSession, d: str) -> DataFrame:
    t = _trace(s, d)
    rows = [(i + 1, round(t.potential[i], 7), round(t.potential[i] - t.potential[i + 1], 7)) for i in range(3)]
    return s.createDataFrame(rows, "round int, potential double, decrease double")


@entry("a09_privacy_spent", "select 1.0::double as eps, 1e-6::double as delta")
def a09(s: SparkSession, d: str) -> DataFrame:
    out = release.release_two_table(load(s, d, TWO), two_queries(), d, EPS, DELTA, SEEDED, rounds=1)
    return s.createDataFrame([out.ledger.total], "eps double, delta double")


@entry("a10_inflation_seeded", f"select round((b + {tlap_sql('2.0', repr(tau(EPS / 2, DELTA / 2, 1)), uniform_sql(Q + 'degree' + Q))}) / b, 6) as sensitivity_factor from {_STATS}")
def a10(s: SparkSession, d: str) -> DataFrame:
    out = release.release_two_table(load(s, d, TWO), two_queries(), d, EPS, DELTA, SEEDED, rounds=1)
    exact = float(sensitivity.max_degree(load(s, d, TWO)).first()[0])
    return out.cells.select(F.round(F.col("dtilde") / exact, 6).alias("sensitivity_factor")).distinct()


@entry("a11_partition_stats", f"select 'R1' as relation, count(distinct bucket)::bigint as parts, count(*)::bigint as tuples, count(*)::bigint as copies, 1::bigint as most from {rel_sql(TWO, 0)} r join {_LABELS} l on l.K = r.K "
       f"union all select 'R2', count(distinct bucket)::bigint, count(*)::bigint, count(*)::bigint, 1::bigint from {rel_sql(TWO, 1)} r join {_LABELS} l on l.K = r.K")  # fmt: skip
def a11(s: SparkSession, d: str) -> DataFrame:
    return partition.partition_stats(partition.partition_true_degrees(load(s, d, TWO), domain_frame(s, d, TWO, "K"), LAM))


@entry("a12_uniformization_gain", f"select round(sqrt(o * b), 4) as whole_join, round((select sum(sqrt(o * pow(2.0, bucket))) from (select bucket, sum(deg1 * deg2)::double as o from {_LABELS} x join {_DEG} g on g.K = x.K group by 1)), 4) as uniformized from {_STATS}")
def a12(s: SparkSession, d: str) -> DataFrame:
    part = partition.partition_true_degrees(load(s, d, TWO), domain_frame(s, d, TWO, "K"), LAM)
    return measures.gain(part).select(F.round("whole_join", 4).alias("whole_join"), F.round("uniformized", 4).alias("uniformized"))


# W: worked instances ------------------------------------------------------------------------------


def _described(inst: instances.Instance, name: str) -> DataFrame:
    rows = [f.agg(F.coalesce(F.sum("freq"), F.lit(0)).cast("bigint").alias(f"n{i + 1}")) for i, f in enumerate(inst.frames[:2])]
    size = join_size(inst).select(F.col("val").cast("bigint").alias("out_size"))
    return rows[0].crossJoin(rows[1]).crossJoin(size).crossJoin(sensitivity.local_sensitivity(inst)).select(F.lit(name).alias("name"), "n1", "n2", "out_size", "local_sensitivity")


@entry("w01_collapse", "select * from (values ('present', 50::bigint, 1::bigint, 50::bigint, 50::bigint), ('absent', 50, 0, 0, 50)) t(name, n1, n2, out_size, local_sensitivity)")
def w01(s: SparkSession, d: str) -> DataFrame:
    return _described(instances.gen_collapse(s, 50), "present").unionByName(_described(instances.gen_collapse(s, 50, False), "absent"))


def _flag_table(s: SparkSession, d: str) -> DataFrame:
    rows = s.read.parquet(f"{d}/lineitem.parquet").select(F.concat("l_returnflag", "l_linestatus").alias("A"))
    return rows.groupBy("A").agg(F.ceil(F.count("*") / 1000).cast("bigint").alias("freq"))


_FLAG_SQL = "(select concat(l_returnflag, l_linestatus) as A, ceil(count(*) / 1000.0)::bigint as freq from lineitem group by 1)"


@entry("w02_hard_two_tables", f"select 'example' as name, 9::bigint as n1, 27::bigint as n2, 27::bigint as out_size, 3::bigint as local_sensitivity union all select 'lineitem', sum(freq)::bigint, 5 * sum(freq)::bigint, 5 * sum(freq)::bigint, 5::bigint from {_FLAG_SQL}")
def w02(s: SparkSession, d: str) -> DataFrame:
    table = s.createDataFrame([(1, 4), (2, 3), (3, 2)], "A bigint, freq bigint")
    return _described(instances.gen_hard_two(table, 3), "example").unionByName(_described(instances.gen_hard_two(_flag_table(s, d), 5), "lineitem"))


@entry("w02_amplified_answers", f"select A, (5 * freq)::bigint as answer from {_FLAG_SQL}")
def w02_answers(s: SparkSession, d: str) -> DataFrame:
    return join_size(instances.gen_hard_two(_flag_table(s, d), 5), ("A",)).select("A", F.col("val").cast("bigint").alias("answer"))


@entry("w03_hard_path", "select sum(4 * n)::bigint as out_size, 2::bigint as side from (select row_number() over (order by o_orderpriority) as v, count(*) as n from orders group by o_orderpriority)")
def w03(s: SparkSession, d: str) -> DataFrame:
    from pyspark.sql import Window as W

    counts = s.read.parquet(f"{d}/orders.parquet").groupBy("o_orderpriority").agg(F.count("*").alias("freq"))
    table = counts.withColumn("A", F.row_number().over(W.orderBy("o_orderpriority"))).select("A", "freq")  # five rows
    spec = instances.JoinSpec("P4", (instances.RelationSpec("R1", ("A", "B"), ""), instances.RelationSpec("R2", ("B", "C"), ""), instances.RelationSpec("R3", ("A", "D"), "")))
    inst = instances.gen_hard_multi(spec, table, 4)
    return join_size(inst).select(F.col("val").cast("bigint").alias("out_size")).crossJoin(inst.frames[1].agg(F.max("C").cast("bigint").alias("side")))


_W03 = {
    "star": instances.JoinSpec("S3", (instances.RelationSpec("R1", ("A", "B"), ""), instances.RelationSpec("R2", ("A", "C"), ""), instances.RelationSpec("R3", ("A", "D"), ""))),
    "cycle": instances.JoinSpec("C3", (instances.RelationSpec("R1", ("A", "B"), ""), instances.RelationSpec("R2", ("B", "C"), ""), instances.RelationSpec("R3", ("C", "A"), ""))),
}
_PRIORITY_COUNTS = "(select row_number() over (order by o_orderpriority) as v, count(*) as n from orders group by o_orderpriority)"

for _n in _W03:
    @entry(f"w03_hard_{_n}", f"select v::bigint as A, (9 * n)::bigint as answer, (9 * max(n) over ())::bigint as largest from {_PRIORITY_COUNTS}")
    def _w03(s: SparkSession, d: str, name: str = _n) -> DataFrame:
        """Every value's count amplified by the wanted sensitivity of nine, on a star and on a cycle."""
        from pyspark.sql import Window as W

        counts = s.read.parquet(f"{d}/orders.parquet").groupBy("o_orderpriority").agg(F.count("*").alias("freq"))
        table = counts.withColumn("A", F.row_number().over(W.orderBy("o_orderpriority"))).select("A", "freq")  # five rows
        found = join_size(instances.gen_hard_multi(_W03[name], table, 9), ("A",)).select("A", F.col("val").cast("bigint").alias("answer"))
        return found.crossJoin(found.agg(F.max("answer").alias("largest")))


@entry("w04_staircase", "select * from (values ('10', 55::bigint, 55::bigint, 385::bigint, 10::bigint), ('100', 5050, 5050, 338350, 100)) t(name, n1, n2, out_size, local_sensitivity)")
def w04(s: SparkSession, d: str) -> DataFrame:
    return union_all([_described(instances.gen_staircase(s, r), str(r)) for r in (10, 100)])


@entry("w05_geometric", "select * from (values ('8', 84::bigint, 84::bigint, 112::bigint, 4::bigint), ('64', 5456, 5456, 7936, 16), ('512', 349504, 349504, 520192, 64)) t(name, n1, n2, out_size, local_sensitivity)")
def w05(s: SparkSession, d: str) -> DataFrame:
    return union_all([_described(instances.gen_geometric(s, k), str(k)) for k in (8, 64, 512)])


@entry("w05_gain_grows_with_k", "select k::int as k, round(sqrt(o * d), 4) as whole_join, round(u, 4) as uniformized, round(sqrt(o * d) / u, 6) as gain from "
       "(select k, sum(n * pow(4, i)) as o, max(pow(2, i)) as d from lv group by k) join (select k, sum(sqrt(o * pow(2, b))) as u from (select k, greatest(1, i) as b, sum(n * pow(4, i)) as o from lv group by 1, 2) group by k) using (k)".replace(
           "lv", "(select k, i, floor(k * k / pow(8, i)) as n from (values (8, 2), (64, 4), (512, 6)) t(k, m), (select range as i from range(7)) where i <= m)"))
def w05_gain(s: SparkSession, d: str) -> DataFrame:
    out = []
    for k in (8, 64, 512):
        inst = instances.gen_geometric(s, k)
        part = partition.partition_true_degrees(inst, inst.frames[0].select("B").distinct(), 1.0)
        out.append(measures.gain(part).select(F.lit(k).alias("k"), F.round("whole_join", 4).alias("whole_join"), F.round("uniformized", 4).alias("uniformized"), F.round(F.col("whole_join") / F.col("uniformized"), 6).alias("gain")))
    return union_all(out)


@entry("w06_hard_vector_conforms", f"select bucket, out_size, true as conforms from (select bucket, sum(deg1 * deg2)::bigint as out_size from {_LABELS} x join {_DEG} g on g.K = x.K group by bucket) where out_size > 0")
def w06(s: SparkSession, d: str) -> DataFrame:
    vector = {b: int(o) for b, o in _vector(s, d) if o > 0}
    inst = instances.gen_hard_vector(s, vector, LAM)
    # both sides hold the same join values by construction, the left one a row each
    part = partition.partition_true_degrees(inst, inst.frames[0].select("B"), LAM)
    target = s.createDataFrame(sorted(vector.items()), "bucket int, out_size bigint")
    made = measures.join_size_vector(part).select("bucket", F.col("out_size").alias("made"))
    both = target.join(made, "bucket", "left")
    return both.select("bucket", "out_size", F.coalesce((F.col("made") <= 2 * F.col("out_size")) & (F.col("out_size") <= 2 * F.col("made")), F.lit(False)).alias("conforms"))


for _n in ("HIER5", "PATH3", "STAR3", "TRIANGLE"):
    entry(f"w_join_size_{_n.lower()}", size_sql(SPECS[_n]))(lambda s, d, n=_n: in_bigint(join_size(load(s, d, SPECS[n]))))

for _n in ("LANG2", "EMB2", "CONV2", "CUST_ORD", "ORD_LINE", "PART_LINE", "SUPP_LINE"):
    _spec = SPECS[_n]
    _last_attr = [r.attrs[1] for r in _spec.relations]
    entry(f"w_marginal_{_n.lower()}", f"select {', '.join(_last_attr)}, sum(f1 * f2)::bigint as val from {rel_sql(_spec, 0)} a join {rel_sql(_spec, 1)} b using ({_spec.relations[0].attrs[0]}) group by all")(
        lambda s, d, p=_spec, a=tuple(_last_attr): join_size(load(s, d, p), a).select(*a, F.col("val").cast("bigint").alias("val"))
    )


@entry("w11_buckets_nation_pairs", f"select concat_ws(',', {ladder_sql('coalesce(a, 0)', LAM)}, {ladder_sql('coalesce(b, 0)', LAM)}) as bucket, count(*)::bigint as n_keys, coalesce(sum(a * b), 0)::bigint as out_size from nation left join (select c_nationkey, count(*) as a from customer group by 1) on c_nationkey = n_nationkey left join (select s_nationkey, count(*) as b from supplier group by 1) on s_nationkey = n_nationkey group by 1")
def w11(s: SparkSession, d: str) -> DataFrame:
    return measures.join_size_vector(partition.partition_true_degrees(load(s, d, NATION2), domain_frame(s, d, NATION2, "N"), LAM, pairs=True))


@entry("w18_edge_cases", "select * from (values ('empty_relation', 0::bigint, 1::bigint, 0::bigint, 1::bigint), ('empty_join', 1, 1, 0, 1), ('one_value', 3, 3, 9, 3), ('repeated_rows', 2, 1, 2, 2), ('zero_frequency', 0, 5, 0, 5), ('null_attribute', 1, 1, 1, 1)) t(name, n1, n2, out_size, local_sensitivity)")
def w18(s: SparkSession, d: str) -> DataFrame:
    return union_all([_described(i, n) for n, i in instances.gen_edges(s).items()])


@entry("w07_hier5_answers_by_region", f"select A, sum(f1 * f2 * f3 * f4 * f5)::bigint as val from {' join '.join(f'{rel_sql(HIER5, i)} t{i}' + (' using (A, B, G)' if i == 3 else ' using (A, B)' if i in (1, 2) else ' using (A)' if i == 4 else '') for i in range(5))} group by A")
def w07(s: SparkSession, d: str) -> DataFrame:
    return join_size(load(s, d, HIER5), ("A",)).select("A", F.col("val").cast("bigint").alias("val"))


@entry("w12_star_gain_by_family", f"select H, sum(f1 * f2 * f3)::bigint as val from {rel_sql(STAR3, 0)} a join {rel_sql(STAR3, 1)} b using (N) join {rel_sql(STAR3, 2)} c using (N) group by H")
def w12(s: SparkSession, d: str) -> DataFrame:
    return join_size(load(s, d, STAR3), ("H",)).select("H", F.col("val").cast("bigint").alias("val"))
