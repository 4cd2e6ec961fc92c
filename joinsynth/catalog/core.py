"""Instance algebra (D), query families (Q) and sensitivity statistics (S) on the given tables."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, Row, SparkSession
from pyspark.sql import functions as F

from .. import hyper
from ..operators import sensitivity
from ..plans.elimination import join_size
from ..queries import Family, QuerySet, answers, answers_naive, domain_frame, group_query
from ..relation import frequency, input_size, load, natural_join, neighbor, project, restrict, restrict_by
from ..sources.workloads import BRANDS, CHAIN3, EVENT_TYPES, FLAGS, HIER5, LINE1, NATION2, NATIONS, PATH3, PRIORITIES, SEGMENTS, SPECS, STAR3, TRIANGLE, TWO, TWO_TABLE
from .registry import LAM, SEED, TWO_ANSWERS, answers_sql, entry, join_sql, product_sql, size_sql, t_sql, two_queries

BETA = 1 / LAM


def union_all(parts: list[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def in_bigint(frame: DataFrame, column: str = "val") -> DataFrame:
    """A few exact decimals as bigint, as the SQL has them; a table with a number beyond 64 bits keeps its decimals."""
    rows = frame.collect()
    kept = frame.sparkSession.createDataFrame(rows, frame.schema)
    if any(r[column] is not None and abs(r[column]) >= 2**63 for r in rows):
        return kept
    return kept.withColumn(column, F.col(column).cast("bigint"))


# D: instances -------------------------------------------------------------------------------------

for _i in (0, 1):
    _r = TWO.relations[_i]
    entry(f"d01_frequency_two_r{_i + 1}", f"select {', '.join(_r.attrs)}, count(*)::bigint as freq from ({_r.sql()}) group by all")(
        lambda s, d, i=_i: load(s, d, TWO).frames[i]
    )


@entry("d02_input_size", " union all ".join(f"select '{n}' as spec, '{r.name}' as relation, count(*)::bigint as n from ({r.sql()})" for n in ("TWO", "STAR3") for r in SPECS[n].relations)
       + "".join(f" union all select '{n}', 'all', ({' + '.join(f'(select count(*) from ({r.sql()}))' for r in SPECS[n].relations)})::bigint" for n in ("TWO", "STAR3")))
def d02(s: SparkSession, d: str) -> DataFrame:
    return union_all([input_size(load(s, d, SPECS[n])).select(F.lit(n).alias("spec"), "relation", "n") for n in ("TWO", "STAR3")])


@entry("d03_natural_join_nation", f"select N, S, V, ({product_sql((0, 1))})::bigint as freq from {join_sql(NATION2)}")
def d03(s: SparkSession, d: str) -> DataFrame:
    return natural_join(load(s, d, NATION2)).select("N", "S", "V", F.col("freq").cast("bigint").alias("freq"))


@entry("d04_join_size_naive", size_sql(TWO))
def d04(s: SparkSession, d: str) -> DataFrame:
    return natural_join(load(s, d, TWO)).agg(F.sum("freq").cast("bigint").alias("val"))


@entry("d05_join_size_factorised", " union all ".join(f"select '{n}' as spec, val from ({size_sql(p)})" for n, p in SPECS.items()))
def d05(s: SparkSession, d: str) -> DataFrame:
    return in_bigint(union_all([join_size(load(s, d, p)).select(F.lit(n).alias("spec"), "val") for n, p in SPECS.items()]))


@entry("d06_restrict_tuple", "select P, count(*)::bigint as freq from (select o_custkey as K, o_orderpriority as P from orders) where K = 3 group by P")
def d06(s: SparkSession, d: str) -> DataFrame:
    return project(restrict(load(s, d, TWO).frames[0], {"K": 3, "E": "view"}), ("P",), distinct=False)


@entry("d06_restrict_semijoin", "select K, P, count(*)::bigint as freq from (select o_custkey as K, o_orderpriority as P from orders) where K in (select user_id from events) group by all")
def d06b(s: SparkSession, d: str) -> DataFrame:
    inst = load(s, d, TWO)
    return restrict_by(inst.frames[0], project(inst.frames[1], ("K",)))


@entry("d07_projection_distinct", "select distinct l_suppkey as U from lineitem")
def d07(s: SparkSession, d: str) -> DataFrame:
    return project(load(s, d, PATH3).frames[1], ("U",))


@entry("d08_neighbor", "select count(*)::bigint as n, sum(freq)::bigint as total, (select count(*) from orders join events on o_custkey = user_id)::bigint + (select count(*) from events where user_id = 3)::bigint as val "
       "from (select K, P, count(*) as freq from (select o_custkey as K, o_orderpriority as P from orders union all select 3, '1-URGENT') group by all)")  # fmt: skip
def d08(s: SparkSession, d: str) -> DataFrame:
    near = neighbor(load(s, d, TWO), 0, (3, "1-URGENT"), 1)
    sizes = near.frames[0].agg(F.count("*").alias("n"), F.sum("freq").alias("total"))
    return sizes.crossJoin(join_size(near).select(F.col("val").cast("bigint").alias("val")))


@entry("d09_domain_cells", "select P, E, (select count(*) from customer)::bigint as volume from (select distinct o_orderpriority as P from orders), (select distinct event_type as E from events)")
def d09(s: SparkSession, d: str) -> DataFrame:
    keys = domain_frame(s, d, TWO, "K").agg(F.count("*").alias("volume"))
    return domain_frame(s, d, TWO, "P").crossJoin(domain_frame(s, d, TWO, "E")).crossJoin(keys)


@entry("d10_annotated_relation", "select l_returnflag as G, l_linestatus as Z, sum(l_quantity::bigint)::bigint as freq from lineitem group by all")
def d10(s: SparkSession, d: str) -> DataFrame:
    rows = s.read.parquet(f"{d}/lineitem.parquet").select(F.col("l_returnflag").alias("G"), F.col("l_linestatus").alias("Z"), F.col("l_quantity").cast("bigint").alias("x"))
    return frequency(rows, ("G", "Z"), "x")


# An order is a join: its line numbers are the relations, the return flags (G) and statuses (Z) of its items the attributes.
_LINES_SQL = "(select distinct l_orderkey as o, l_linenumber as r, 'G' || l_returnflag as g, 'Z' || l_linestatus as z from lineitem where l_orderkey is not null and l_linenumber is not null)"
_JOINS_SQL = f"""w as (select *, min(r) over (partition by o, a) as first from (select o, r, g as a from {_LINES_SQL} where g is not null union select o, r, z from {_LINES_SQL} where z is not null)),
  e as (select o, r, coalesce(string_agg(a, ',' order by first, a), '') as held from (select distinct o, r from {_LINES_SQL}) left join w using (o, r) group by o, r),
  specs as (select spec, count(*)::bigint as orders, min(o) as o from (select o, string_agg(r || ':' || held, ';' order by r) as spec from e group by o) group by spec),
  own as (select spec, r, a, first from specs join w using (o)), rels as (select spec, r from specs join e using (o)),
  atoms as (select spec, a, first, list_sort(list(r)) as atom from own group by all),
  crossed as (select distinct x.spec from atoms x join atoms y on x.spec = y.spec and x.a < y.a where list_has_any(x.atom, y.atom) and not list_has_all(x.atom, y.atom) and not list_has_all(y.atom, x.atom))"""


def order_joins(s: SparkSession, d: str) -> DataFrame:
    """(lines, orders): every join that the orders of ``lineitem`` are, as its lines (r, attributes), with the number of orders that are it."""
    rows = s.read.parquet(f"{d}/lineitem.parquet").filter("l_orderkey is not null and l_linenumber is not null")
    line = F.struct(F.col("l_linenumber").alias("r"), F.concat(F.lit("G"), "l_returnflag").alias("g"), F.concat(F.lit("Z"), "l_linestatus").alias("z"))
    lines = rows.groupBy("l_orderkey").agg(F.array_sort(F.collect_set(line)).alias("lines"))
    return lines.groupBy("lines").agg(F.count("*").alias("orders"))


def _spec_of(lines: Iterable[Row]) -> tuple[str, hyper.JoinSpec]:
    """The specification and its text; attributes are in the order in which relations, by number, have them first."""
    held: dict[int, set[str]] = {}
    for x in lines:
        held.setdefault(x["r"], set()).update(a for a in (x["g"], x["z"]) if a is not None)
    first: dict[str, int] = {}
    for r in sorted(held):
        for a in held[r]:
            first.setdefault(a, r)
    attrs = {r: tuple(sorted(held[r], key=lambda a: (first[a], a))) for r in sorted(held)}
    text = ";".join(f"{r}:{','.join(a)}" for r, a in attrs.items())
    return text, hyper.JoinSpec(text, tuple(hyper.RelationSpec(str(r), a, "") for r, a in attrs.items()))


def _order_hypergraphs(pages: Iterator[pd.DataFrame], rows_of: Callable[[hyper.JoinSpec], list[tuple]], columns: list[str]) -> Iterator[pd.DataFrame]:
    for page in pages:
        out = []
        for lines, orders in zip(page["lines"], page["orders"], strict=True):
            text, spec = _spec_of(lines)
            out += [(text, orders, *x) for x in rows_of(spec)]
        yield pd.DataFrame(out, columns=columns)


def _properties(p: hyper.JoinSpec) -> list[tuple]:
    edge = hyper.boundary(p, (0,))
    return [(p.m, hyper.is_acyclic(p), hyper.is_hierarchical(p), ",".join(edge), len(hyper.components(p, range(p.m), edge)))]


def _tree_rows(p: hyper.JoinSpec) -> list[tuple]:
    if not hyper.is_hierarchical(p):
        return []
    tree = hyper.AttrTree(p)
    return [(n.name, ",".join(tree.ancestors(n)), ",".join(p.relations[i].name for i in sorted(n.atom))) for n in tree.post_order()]


def _by_orders(s: SparkSession, d: str, rows_of: Callable[[hyper.JoinSpec], list[tuple]], schema: str) -> DataFrame:
    schema = f"spec string, orders bigint, {schema}"
    columns = [c.split()[0] for c in schema.split(", ")]
    keys = [c for c in columns if c != "orders"]
    # lines that differ in how flags and statuses pair are the same join
    return order_joins(s, d).mapInPandas(lambda pages: _order_hypergraphs(pages, rows_of, columns), schema).groupBy(*keys).agg(F.sum("orders").alias("orders")).select(*columns)


@entry("d11_hypergraph_properties", f"""with recursive {_JOINS_SQL}, edge as (select x.spec, x.a from atoms x join (select spec, min(r) as r from rels group by spec) f on x.spec = f.spec and x.first = f.r where len(x.atom) > 1),
  common as (select x.spec, x.r as r1, y.r as r2, count(*) as n, count(*) filter (where not exists (select 1 from edge where edge.spec = x.spec and edge.a = x.a)) as left_over from own x join own y on x.spec = y.spec and x.a = y.a and x.r <> y.r group by all),
  links as (select spec, t, r1, r2 from common, (select range as t from range(0, 6)) where case when t = 0 then left_over > 0 else n >= t end),
  reach as (select spec, t, r as r1, r as r2 from rels, (select range as t from range(0, 6)) union select x.spec, x.t, x.r1, y.r2 from reach x join links y on x.spec = y.spec and x.t = y.t and x.r2 = y.r1),
  parts as (select spec, t, count(distinct least_r) as n from (select spec, t, r1, min(r2) as least_r from reach group by all) group by spec, t),
  counts as (select spec, (select count(*) from rels where rels.spec = specs.spec) as m, (select sum(len(atom) - 1) from atoms where atoms.spec = specs.spec) as room from specs)
  select spec, orders, m::int as m, coalesce(room, 0) = (select sum(m - n) from parts where parts.spec = specs.spec and t > 0) as acyclic, not exists (select 1 from crossed where crossed.spec = specs.spec) as hierarchical,
  coalesce((select string_agg(a, ',' order by a) from edge where edge.spec = specs.spec), '') as boundary_of_first, (select n from parts where parts.spec = specs.spec and t = 0)::int as parts from specs join counts using (spec)""")  # fmt: skip
def d11(s: SparkSession, d: str) -> DataFrame:
    """Its SQL finds acyclicity apart from ear removal: the heaviest spanning forest of the relations, weighed by common attributes, holds each attribute in one piece."""
    return _by_orders(s, d, _properties, "m int, acyclic boolean, hierarchical boolean, boundary_of_first string, parts int")


@entry("d12_attribute_tree", f"""with {_JOINS_SQL}, nodes as (select spec, atom, min(first) as first, string_agg(a, '' order by a) as node from atoms where spec not in (from crossed) group by spec, atom)
  select spec, orders, node, coalesce((select string_agg(a, ',' order by x.first, a) from atoms x where x.spec = nodes.spec and len(x.atom) > len(nodes.atom) and list_has_all(x.atom, nodes.atom)), '') as ancestors, array_to_string(atom, ',') as relations from nodes join specs using (spec)""")  # fmt: skip
def d12(s: SparkSession, d: str) -> DataFrame:
    """The trees of the orders that are hierarchical joins; the others have none."""
    return _by_orders(s, d, _tree_rows, "node string, ancestors string, relations string")


# Q: query families --------------------------------------------------------------------------------

_ONE = Family.all_ones()
_FAMILIES: dict[str, tuple] = {
    "q01_counting_query": (TWO, QuerySet((_ONE, _ONE))),
    "q02_lifted_attribute": (TWO, QuerySet((Family.marginal("P", PRIORITIES), _ONE))),
    "q03_marginals": (NATION2, QuerySet((Family.joint_marginal(("N", "S"), (NATIONS.values, SEGMENTS)), Family.marginal("V", (0, 1, 2, 3, 4))))),
    "q04_ranges": (LINE1, QuerySet((Family.prefix("V", (0, 1, 2, 3, 4)) + Family.intervals("V", (0, 1, 2, 3, 4)),))),
    "q05_random_sign": (TWO, QuerySet((Family.random_sign(("P",), 6, SEED), Family.random_sign(("E",), 6, SEED)))),
    "q06_weighted": (LINE1, QuerySet((Family.weighted("(V - 2) / 4.0") + Family.weighted("V * 0.5"),))),
    "q07_product_query_set": (STAR3, QuerySet((_ONE + Family.marginal("S", SEGMENTS), _ONE + Family.marginal("V", (0, 1, 2, 3, 4)), _ONE + Family.prefix("H", (0, 1, 2, 3))))),
    "q09_answers_factorised": (TWO, two_queries()),
    "q10_answers_path": (PATH3, QuerySet((Family.marginal("B", BRANDS), _ONE, _ONE + Family.prefix("N", (5, 10, 15))))),
    "q10_answers_chain": (CHAIN3, QuerySet((Family.marginal("S", SEGMENTS), _ONE, Family.marginal("G", FLAGS)))),
    "q10_answers_cyclic": (TRIANGLE, QuerySet((Family.marginal("B", BRANDS), _ONE, Family.marginal("G", FLAGS)))),
    "q10_answers_hierarchical": (HIER5, QuerySet((_ONE, _ONE, Family.marginal("K", PRIORITIES), Family.marginal("L", EVENT_TYPES), _ONE))),
}


def _rounded(frame: DataFrame) -> DataFrame:
    return frame.withColumn("answer", F.round("answer", 3)).filter("answer != 0.0")


for _name, (_spec, _queries) in _FAMILIES.items():
    _n = ", ".join(f"q{i + 1}" for i in range(_spec.m))
    entry(_name, f"select {_n}, round(answer, 3) as answer from ({answers_sql(_spec, _queries)}) where round(answer, 3) <> 0")(
        lambda s, d, p=_spec, q=_queries: _rounded(answers(load(s, d, p), q))
    )


@entry("q07_sampled_queries", "select (range // 12)::int as q1, (range % 12)::int as q2 from range(144) order by md5(concat_ws('|', 3, range)) limit 20")
def q07_sample(s: SparkSession, d: str) -> DataFrame:
    queries = QuerySet((Family.random_sign(("P",), 12, SEED), Family.random_sign(("E",), 12, SEED)))
    return s.createDataFrame(queries.sample(20, 3), "q1 int, q2 int")


@entry("q08_answers_naive", f"select q1, q2, round(answer, 3) as answer from ({TWO_ANSWERS}) where round(answer, 3) <> 0")
def q08(s: SparkSession, d: str) -> DataFrame:
    return _rounded(answers_naive(load(s, d, TWO), two_queries()))


@entry("q13_group_query", "select event_type as E, count(*)::bigint as answer from orders join events on o_custkey = user_id group by 1")
def q13(s: SparkSession, d: str) -> DataFrame:
    return group_query(load(s, d, TWO), "E")


# S: sensitivity -----------------------------------------------------------------------------------

_DEG = "(select K, sum(c1)::bigint as deg1, sum(c2)::bigint as deg2 from (select o_custkey as K, 1 as c1, 0 as c2 from orders union all select user_id, 0, 1 from events) group by K)"


@entry("s01_degrees_orders_events", f"select * from {_DEG}")
def s01(s: SparkSession, d: str) -> DataFrame:
    return sensitivity.degree_table(load(s, d, TWO))


def _max_degree_sql(n: str) -> str:
    p = SPECS[n]
    on = hyper.meet(p, (0, 1))
    sides = " union all ".join(f"select count(*) as c from ({r.sql()}) group by {', '.join(on)}" for r in p.relations)
    return f"select '{n}' as spec, max(c)::bigint as max_degree from ({sides})"


@entry("s02_max_degree_two_tables", " union all ".join(map(_max_degree_sql, TWO_TABLE)))
def s02(s: SparkSession, d: str) -> DataFrame:
    return union_all([sensitivity.max_degree(load(s, d, SPECS[n])).select(F.lit(n).alias("spec"), "max_degree") for n in TWO_TABLE])


def _ls_sql(p: hyper.JoinSpec) -> str:
    return f"select max(t)::bigint as local_sensitivity from ({' union all '.join(t_sql(p, tuple(j for j in range(p.m) if j != i)) for i in range(p.m))})"


for _p in (TWO, STAR3, PATH3, TRIANGLE):
    entry(f"s03_local_sensitivity_{_p.name.lower()}", _ls_sql(_p))(lambda s, d, p=_p: sensitivity.local_sensitivity(load(s, d, p)))


@entry("s04_boundaries", "select * from (values ('1', 'T'), ('2', 'T,U'), ('3', 'U'), ('1,2', 'U'), ('1,3', 'T,U'), ('2,3', 'T')) t(rels, boundary)")
def s04(s: SparkSession, d: str) -> DataFrame:
    sets = [e for e in sensitivity.subsets(3) if e]
    return s.createDataFrame([(",".join(str(i + 1) for i in e), ",".join(hyper.boundary(PATH3, e))) for e in sets], "rels string, boundary string")


@entry("s05_boundary_max_hier5", f"select t from ({t_sql(HIER5, (2, 3, 4))})")
def s05(s: SparkSession, d: str) -> DataFrame:
    return sensitivity.boundary_max(load(s, d, HIER5), (2, 3, 4)).select(F.col("t").cast("bigint").alias("t"))


def _table_sql(p: hyper.JoinSpec) -> str:
    return " union all ".join(f"select '{','.join(str(i + 1) for i in e)}' as rels, t from ({t_sql(p, e)})" for e in sensitivity.subsets(p.m))


for _p in (TWO, STAR3, PATH3, TRIANGLE):
    entry(f"s06_boundary_table_{_p.name.lower()}", _table_sql(_p))(
        lambda s, d, p=_p: sensitivity.boundary_table(load(s, d, p)).select("rels", F.col("t").cast("bigint").alias("t"))
    )


def _t_columns(p: hyper.JoinSpec) -> str:
    return ", ".join(f"({t_sql(p, e)})::double as t{''.join(str(i + 1) for i in e)}" for e in sensitivity.subsets(p.m) if e)


def _bound_text(m: int, i: int) -> str:
    rest = [j for j in range(1, m + 1) if j != i]
    terms = []
    for e in sensitivity.subsets(len(rest), proper=False):
        gained = [rest[k] for k in e]
        left = "".join(str(j) for j in rest if j not in gained)
        terms.append(" * ".join([f"t{left}" if left else "1.0", *(f"s{j}" for j in gained)]))
    return " + ".join(terms)


def _rs_sql(p: hyper.JoinSpec, limit: int = 14) -> str:
    grids = []
    for i in range(1, p.m + 1):
        rest = [j for j in range(1, p.m + 1) if j != i]
        tables = ", ".join(f"(select range::double as s{j} from range({limit + 1}))" for j in rest)
        grids.append(f"select exp(-{BETA!r} * ({' + '.join(f's{j}' for j in rest)})) * ({_bound_text(p.m, i)}) as b from t, {tables}")
    return f"with t as (select {_t_columns(p)}) select round(max(b), 4) as rs from ({' union all '.join(grids)})"


def residual(s: SparkSession, d: str, p: hyper.JoinSpec) -> float:
    return sensitivity.ResidualBound().value(load(s, d, p), BETA)


for _p in (TWO, NATION2, STAR3, PATH3, TRIANGLE):
    entry(f"s08_residual_sensitivity_{_p.name.lower()}", _rs_sql(_p))(
        lambda s, d, p=_p: s.createDataFrame([(residual(s, d, p),)], "rs double").select(F.round("rs", 4).alias("rs"))
    )


@entry("s07_k_step_bound_star3", "with t as (select " + _t_columns(STAR3) + ") select k::int as k, round(max(b), 4) as bound from (" + " union all ".join(
    f"select s{a} + s{b} as k, {_bound_text(3, i)} as b from t, (select range::double as s{a} from range(6)), (select range::double as s{b} from range(6)) where s{a} + s{b} <= 5" for i, a, b in ((1, 2, 3), (2, 1, 3), (3, 1, 2))) + ") group by k")
def s07(s: SparkSession, d: str) -> DataFrame:
    table = sensitivity.collect_table(sensitivity.boundary_table(load(s, d, STAR3)))
    return s.createDataFrame([(k, round(float(sensitivity.ls_hat_k(table, 3, k)), 4)) for k in range(6)], "k int, bound double")


@entry("s09_smooth_bound_contract", "select true as above_local, true as smooth")
def s09(s: SparkSession, d: str) -> DataFrame:
    inst = load(s, d, STAR3)
    above = residual(s, d, STAR3) >= sensitivity.local_sensitivity(inst).first()[0]
    change = sensitivity.ln_rs_change(inst, 0, (1, SEGMENTS[0]), 1, BETA)
    return s.createDataFrame([(above, change <= BETA * (1 + 1e-9))], "above_local boolean, smooth boolean")


@entry("s12_q_aggregate", f"select t from ({t_sql(HIER5, (2, 3), ('A', 'B', 'G'))})")
def s12(s: SparkSession, d: str) -> DataFrame:
    return sensitivity.q_aggregate(load(s, d, HIER5), (2, 3), ("A", "B", "G")).select(F.col("t").cast("bigint").alias("t"))


_R34 = "(select distinct A, B, G from (" + HIER5.relations[2].sql() + ")) join (select distinct A, B, G from (" + HIER5.relations[3].sql() + ")) using (A, B, G)"


@entry("s13_hier_degree_distinct", f"select A, B, count(*)::bigint as deg from {_R34} group by A, B")
def s13(s: SparkSession, d: str) -> DataFrame:
    return sensitivity.hier_degree(load(s, d, HIER5), (2, 3), ("A", "B"))


@entry("s13_hier_degree_single", f"select A, B, G, count(*)::bigint as deg from ({HIER5.relations[3].sql()}) group by all")
def s13b(s: SparkSession, d: str) -> DataFrame:
    return sensitivity.hier_degree(load(s, d, HIER5), (3,), ("A", "B", "G"))


@entry("s14_hier_max_degree", f"select max(c)::bigint as mdeg from (select count(*) as c from {_R34} group by A, B)")
def s14(s: SparkSession, d: str) -> DataFrame:
    return sensitivity.hier_max_degree(load(s, d, HIER5), (2, 3), ("A", "B"))


@entry("s15_degree_product_bound",
       f"select '3,4' as rels, 'A,B' as given, (select max(c) from (select count(*) as c from {_R34} group by A, B))::bigint as mdeg union all "
       + " union all ".join(f"select '{n}', '{g}', (select max(c) from (select count(*) as c from ({HIER5.relations[int(n) - 1].sql()}) group by {g}))::bigint" for n, g in (("3", "A,B,G"), ("4", "A,B,G"), ("5", "A"))))
def s15(s: SparkSession, d: str) -> DataFrame:
    return sensitivity.degree_product(load(s, d, HIER5), (2, 3, 4))


# Factors of the largest hierarchical join by the rule: relations of one attribute, given its ancestors.
_FACTORS = (("1", "A,B"), ("2", "A,B"), ("3", "A,B,G"), ("4", "A,B,G"), ("5", "A"), ("3,4", "A,B"), ("1,2,3,4", "A"), ("1,2,3,4,5", ""))


def _factor_sql(rels: str, given: str) -> str:
    numbers = [int(x) - 1 for x in rels.split(",")]
    if len(numbers) == 1:
        rows = f"({HIER5.relations[numbers[0]].sql()})"
    else:
        common = ", ".join(hyper.meet(HIER5, numbers))
        rows = "(select * from " + " join ".join(f"(select distinct {common} from ({HIER5.relations[i].sql()})) f{i}" + (f" using ({common})" if k else "") for k, i in enumerate(numbers)) + ")"
    return f"select '{rels}' as rels, '{given}' as given, (select max(c) from (select count(*) as c from {rows}{' group by ' + given if given else ''}))::bigint as mdeg"


@entry("s16_factor_structure", " union all ".join(_factor_sql(*f) for f in _FACTORS))
def s16(s: SparkSession, d: str) -> DataFrame:
    """Every factor of the degree product of any boundary, with its value: each belongs to one node of the attribute tree."""
    factors = {f for e in sensitivity.subsets(5, proper=False) if e for f in hyper.product_factors(HIER5, e)}
    inst = load(s, d, HIER5)
    return union_all([sensitivity.hier_max_degree(inst, e, y).select(F.lit(",".join(str(i + 1) for i in e)).alias("rels"), F.lit(",".join(y)).alias("given"), "mdeg") for e, y in sorted(factors)])


_GRID3 = " union all ".join(f"select label, exp(-{BETA!r} * (s{a} + s{b})) * ({_bound_text(3, i)}) as b from x, (select range::double as s{a} from range(15)), (select range::double as s{b} from range(15))" for i, a, b in ((1, 2, 3), (2, 1, 3), (3, 1, 2)))


@entry("s17_rs_from_configuration", f"with x as (select k::int as label, {LAM!r} * pow(2.0, k) as t1, {LAM!r} * pow(2.0, k) as t2, {LAM!r} * pow(2.0, k) as t3, pow({LAM!r} * pow(2.0, k), 2) as t12, pow({LAM!r} * pow(2.0, k), 2) as t13, pow({LAM!r} * pow(2.0, k), 2) as t23 from (values (1), (2), (3)) v(k)) select label, round(max(b), 3) as rs from ({_GRID3}) group by label")
def s17(s: SparkSession, d: str) -> DataFrame:
    tree = hyper.AttrTree(STAR3)
    return s.createDataFrame([(k, round(sensitivity.rs_from_config(STAR3, {n.name: k for n in tree.nodes}, LAM, BETA), 3)) for k in (1, 2, 3)], "label int, rs double")


@entry("s18_worst_case", "select * from (values ('TWO', 2.0, 31.623), ('TRIANGLE', 1.5, 316.228), ('PATH3', 2.0, 316.228)) t(spec, cover, bags) ")
def s18(s: SparkSession, d: str) -> DataFrame:
    rows = [(n, float(round(hyper.fractional_edge_cover(SPECS[n]), 3)), float(round(hyper.worst_case_error(SPECS[n], 10.0, bags=True), 3))) for n in ("TWO", "TRIANGLE", "PATH3")]
    return s.createDataFrame(rows, "spec string, cover double, bags double")

