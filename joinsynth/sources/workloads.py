"""Join specifications over the given tables; every text runs on Spark and on other SQL engines alike."""

from __future__ import annotations

from ..hyper import AttrDomain, JoinSpec, RelationSpec

# Fixed values of the given tables' public domains.
PRIORITIES = ("1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW")
EVENT_TYPES = ("click", "error", "purchase", "signup", "view")
SEGMENTS = ("AUTOMOBILE", "BUILDING", "FURNITURE", "HOUSEHOLD", "MACHINERY")
FLAGS, STATUSES, LANGS, ROLES = ("A", "N", "R"), ("F", "O"), ("de", "en", "es", "fr"), ("assistant", "system", "user")
BRANDS = tuple(f"Brand#{i}" for i in range(1, 26))
SOURCES = tuple(f"src{i}" for i in range(20))
BINS = (0, 1, 2, 3, 4)

_BAL = "cast(least(4, greatest(0, floor(({0} + 1000) / 2200))) as int)"
_CUST_NATION = "{customer} join {nation} on c_nationkey = n_nationkey"


def _keys(sql: str) -> AttrDomain:
    return AttrDomain(sql=sql)


def _vals(*v: object) -> AttrDomain:
    return AttrDomain(values=tuple(v))


CUSTOMER_KEYS = _keys("select c_custkey as K from {customer}")
NATIONS = _vals(*range(25))

TWO = JoinSpec("TWO", (
    RelationSpec("R1", ("K", "P"), "select o_custkey as K, o_orderpriority as P from {orders}"),
    RelationSpec("R2", ("K", "E"), "select user_id as K, event_type as E from {events}"),
), {"K": CUSTOMER_KEYS, "P": _vals(*PRIORITIES), "E": _vals(*EVENT_TYPES)})

NATION2 = JoinSpec("NATION2", (
    RelationSpec("R1", ("N", "S"), "select c_nationkey as N, c_mktsegment as S from {customer}"),
    RelationSpec("R2", ("N", "V"), f"select s_nationkey as N, {_BAL.format('s_acctbal')} as V from {{supplier}}"),
), {"N": NATIONS, "S": _vals(*SEGMENTS), "V": _vals(*BINS)})

CUST_ORD = JoinSpec("CUST_ORD", (
    RelationSpec("R1", ("K", "S"), "select c_custkey as K, c_mktsegment as S from {customer}"),
    RelationSpec("R2", ("K", "P"), "select o_custkey as K, o_orderpriority as P from {orders}"),
), {"K": CUSTOMER_KEYS, "S": _vals(*SEGMENTS), "P": _vals(*PRIORITIES)})

ORD_LINE = JoinSpec("ORD_LINE", (
    RelationSpec("R1", ("O", "P"), "select o_orderkey as O, o_orderpriority as P from {orders}"),
    RelationSpec("R2", ("O", "G"), "select l_orderkey as O, l_returnflag as G from {lineitem}"),
), {"O": _keys("select o_orderkey as O from {orders}"), "P": _vals(*PRIORITIES), "G": _vals(*FLAGS)})

PART_LINE = JoinSpec("PART_LINE", (
    RelationSpec("R1", ("T", "B"), "select p_partkey as T, p_brand as B from {part}"),
    RelationSpec("R2", ("T", "G"), "select l_partkey as T, l_returnflag as G from {lineitem}"),
), {"T": _keys("select p_partkey as T from {part}"), "B": _vals(*BRANDS), "G": _vals(*FLAGS)})

SUPP_LINE = JoinSpec("SUPP_LINE", (
    RelationSpec("R1", ("U", "N"), "select s_suppkey as U, s_nationkey as N from {supplier}"),
    RelationSpec("R2", ("U", "G"), "select l_suppkey as U, l_returnflag as G from {lineitem}"),
), {"U": _keys("select s_suppkey as U from {supplier}"), "N": NATIONS, "G": _vals(*FLAGS)})

LANG2 = JoinSpec("LANG2", (
    RelationSpec("R1", ("L", "S"), "select lang as L, source as S from {documents}"),
    RelationSpec("R2", ("L", "W"), "select lang as L, cast(least(4, floor(n_chars / 1000)) as int) as W from {documents}"),
), {"L": _vals(*LANGS), "S": _vals(*SOURCES), "W": _vals(*BINS)}, group_factor=2)

EMB2 = JoinSpec("EMB2", (
    RelationSpec("R1", ("L", "X"), "select label as L, cast(case when element_at(embedding, 1) >= 0 then 1 else 0 end as int) as X from {embeddings}"),
    RelationSpec("R2", ("L", "Y"), "select label as L, cast(case when element_at(embedding, 2) >= 0 then 1 else 0 end as int) as Y from {embeddings}"),
), {"L": _vals(*range(10)), "X": _vals(0, 1), "Y": _vals(0, 1)}, group_factor=2)

CONV2 = JoinSpec("CONV2", (
    RelationSpec("R1", ("C", "X"), "select conv_id as C, role as X from {conversations}"),
    RelationSpec("R2", ("C", "Y"), "select conv_id as C, cast(least(4, turn) as int) as Y from {conversations}"),
), {"C": _keys("select distinct conv_id as C from {conversations}"), "X": _vals(*ROLES), "Y": _vals(*BINS)}, group_factor=2)

STAR3 = JoinSpec("STAR3", (
    RelationSpec("R1", ("N", "S"), "select c_nationkey as N, c_mktsegment as S from {customer}"),
    RelationSpec("R2", ("N", "V"), f"select s_nationkey as N, {_BAL.format('s_acctbal')} as V from {{supplier}}"),
    RelationSpec("R3", ("N", "H"), "select n_nationkey as N, n_regionkey as H from {nation}"),
), {"N": NATIONS, "S": _vals(*SEGMENTS), "V": _vals(*BINS), "H": _vals(*BINS)})

HIER5 = JoinSpec("HIER5", (
    RelationSpec("R1", ("A", "B", "D"), f"select n_regionkey as A, n_nationkey as B, c_mktsegment as D from {_CUST_NATION}"),
    RelationSpec("R2", ("A", "B", "F"), f"select n_regionkey as A, n_nationkey as B, {_BAL.format('s_acctbal')} as F from {{supplier}} join {{nation}} on s_nationkey = n_nationkey"),
    RelationSpec("R3", ("A", "B", "G", "K"), f"select n_regionkey as A, n_nationkey as B, c_custkey as G, o_orderpriority as K from {{orders}} join {_CUST_NATION.replace('{customer}', '{customer} on o_custkey = c_custkey')}"),
    RelationSpec("R4", ("A", "B", "G", "L"), f"select n_regionkey as A, n_nationkey as B, c_custkey as G, event_type as L from {{events}} join {_CUST_NATION.replace('{customer}', '{customer} on user_id = c_custkey')}"),
    RelationSpec("R5", ("A", "C"), "select n_regionkey as A, n_name as C from {nation}"),
), {
    "A": _vals(*BINS), "B": NATIONS, "D": _vals(*SEGMENTS), "F": _vals(*BINS), "G": _keys("select c_custkey as G from {customer}"), "K": _vals(*PRIORITIES), "L": _vals(*EVENT_TYPES),
    "C": _keys("select n_name as C from {nation}"),
}, public=(
    (("A", "B"), "select n_regionkey as A, n_nationkey as B from {nation}"), (("A", "B", "G"), f"select n_regionkey as A, n_nationkey as B, c_custkey as G from {_CUST_NATION}"),
))

PATH3 = JoinSpec("PATH3", (
    RelationSpec("R1", ("T", "B"), "select p_partkey as T, p_brand as B from {part}"),
    RelationSpec("R2", ("T", "U"), "select l_partkey as T, l_suppkey as U from {lineitem}"),
    RelationSpec("R3", ("U", "N"), "select s_suppkey as U, s_nationkey as N from {supplier}"),
), {"T": PART_LINE.domains["T"], "B": _vals(*BRANDS), "U": SUPP_LINE.domains["U"], "N": NATIONS})

CHAIN3 = JoinSpec("CHAIN3", (
    RelationSpec("R1", ("K", "S"), "select c_custkey as K, c_mktsegment as S from {customer}"),
    RelationSpec("R2", ("K", "O"), "select o_custkey as K, o_orderkey as O from {orders}"),
    RelationSpec("R3", ("O", "G"), "select l_orderkey as O, l_returnflag as G from {lineitem}"),
), {"K": CUSTOMER_KEYS, "S": _vals(*SEGMENTS), "O": ORD_LINE.domains["O"], "G": _vals(*FLAGS)})

_LP = "{lineitem} join {part} on l_partkey = p_partkey"
TRIANGLE = JoinSpec("TRIANGLE", (
    RelationSpec("R1", ("B", "M"), f"select p_brand as B, cast(l_suppkey % 5 as int) as M from {_LP}"),
    RelationSpec("R2", ("M", "G"), f"select cast(l_suppkey % 5 as int) as M, l_returnflag as G from {_LP}"),
    RelationSpec("R3", ("B", "G"), f"select p_brand as B, l_returnflag as G from {_LP}"),
), {"B": _vals(*BRANDS), "M": _vals(*BINS), "G": _vals(*FLAGS)}, group_factor=3)

LINE1 = JoinSpec("LINE1", (
    RelationSpec("R1", ("G", "Z", "V"), "select l_returnflag as G, l_linestatus as Z, cast(least(4, floor((l_quantity - 1) / 10)) as int) as V from {lineitem}"),
), {"G": _vals(*FLAGS), "Z": _vals(*STATUSES), "V": _vals(*BINS)})

SPECS = {s.name: s for s in (TWO, NATION2, CUST_ORD, ORD_LINE, PART_LINE, SUPP_LINE, LANG2, EMB2, CONV2, STAR3, HIER5, PATH3, CHAIN3, TRIANGLE, LINE1)}
TWO_TABLE = ("TWO", "NATION2", "CUST_ORD", "ORD_LINE", "PART_LINE", "SUPP_LINE", "LANG2", "EMB2", "CONV2")
