"""Queries on what larger tables bring: join values by the million, sums beyond 64 bits."""

import pytest

from joinsynth.sources import instances


def test_hard_vector_joins_nothing(spark):
    """A cross join of units and tuples broadcasts a side through the driver."""
    inst = instances.gen_hard_vector(spark, {1: 100, 2: 1000}, 3.0)
    plan = inst.frames[1]._jdf.queryExecution().executedPlan().toString()
    assert "Join" not in plan and "Cartesian" not in plan
    assert sorted(tuple(r) for r in inst.frames[1].groupBy("B").count().groupBy("count").count().collect()) == [(6, 17), (12, 83)]


def test_hard_vector_has_every_tuple_once(spark):
    """Each unit bears every tuple of its bucket; a bucket of less than half a unit has none."""
    inst = instances.gen_hard_vector(spark, {1: 13, 2: 30, 3: 5}, 3.0)
    units = [(0 * 64 + 1, 6), (1 * 64 + 1, 6), (0 * 64 + 2, 12), (1 * 64 + 2, 12)]
    assert sorted(tuple(r) for r in inst.frames[0].collect()) == sorted((b, b, 1) for b, _ in units)
    assert sorted(tuple(r) for r in inst.frames[1].collect()) == sorted((b, c, 1) for b, n in units for c in range(1, n + 1))


def test_hard_vector_is_sized_by_its_rows(spark):
    """Twenty million rows that the planner takes for their 181,818 units are broadcast through the driver to be labelled."""
    from joinsynth.operators import partition

    inst = instances.gen_hard_vector(spark, {3: 20_000_000}, 13.8)
    assert inst.frames[1]._jdf.queryExecution().optimizedPlan().stats().sizeInBytes() >= 8 * 20_000_000 * 0.99
    part = partition.partition_true_degrees(inst, inst.frames[0].select("B"), 13.8)
    assert "Broadcast" not in part.instance.frames[1]._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("query", ["d05_join_size_factorised", "w_join_size_triangle"])
def test_join_sizes_beyond_64_bits_are_exact(spark, tmp_path, query):
    """Two million rows on one triangle: its join size is their cube; smaller sizes stay bigint, as in the SQL."""
    import shutil
    from pathlib import Path

    from joinsynth.catalog import QUERIES

    assert dict(QUERIES[query](spark, "/root/testdata/sf0.001").dtypes)["val"] == "bigint"
    n = 2_200_000
    for f in Path("/root/testdata/sf0.001").glob("*.parquet"):
        if f.stem != "lineitem":
            shutil.copy(f, tmp_path / f.name)
    one = spark.read.parquet("/root/testdata/sf0.001/lineitem.parquet").limit(1)
    one.crossJoin(spark.range(n)).drop("id").write.parquet(str(tmp_path / "lineitem.parquet"))
    got = QUERIES[query](spark, str(tmp_path))
    assert int(got.filter("spec = 'TRIANGLE'" if "spec" in got.columns else "true").first()["val"]) == n**3


@pytest.mark.parametrize("query", ["a03_error_factors", "b10_whole_join_vs_uniformized_staircase", "d09_domain_cells", "n03_tau", "n05_sample_domain_seeded", "n07_ledger", "n08_round_budget", "n09_round_budget_concentrated"])
def test_query_needs_its_table(spark, tmp_path, query):
    """A query that made up its rows would give them for a folder without tables too."""
    from pyspark.errors import AnalysisException

    from joinsynth.catalog import QUERIES

    with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
        QUERIES[query](spark, str(tmp_path))


#: Queries whose data were made up or constant, with the tables that they read now.
MOVED = {
    "b08_smooth_sensitivity_tiny": ("orders", "events"),
    "b09_two_table_rule_on_three": ("customer", "orders", "lineitem"),
    "d11_hypergraph_properties": ("lineitem",),
    "d12_attribute_tree": ("lineitem",),
}


@pytest.mark.parametrize("query", MOVED)
def test_moved_query_needs_each_table(spark, tmp_path, query):
    """Without any one of its tables the query fails."""
    import shutil
    from pathlib import Path

    from pyspark.errors import AnalysisException

    from joinsynth.catalog import QUERIES

    for lacking in MOVED[query]:
        folder = tmp_path / lacking
        folder.mkdir()
        for f in Path("/root/testdata/sf0.001").glob("*.parquet"):
            if f.stem != lacking:
                shutil.copy(f, folder / f.name)
        with pytest.raises(AnalysisException, match="PATH_NOT_FOUND"):
            QUERIES[query](spark, str(folder))


@pytest.fixture
def tiny_tables(spark, tmp_path):
    """A folder with the smallest tables, but the given rows in place of some."""
    import shutil
    from pathlib import Path

    def make(**tables):
        for f in Path("/root/testdata/sf0.001").glob("*.parquet"):
            if f.stem in tables:
                rows = spark.createDataFrame(*tables[f.stem])
                kind = spark.read.parquet(str(f)).schema
                rows.selectExpr(*(f"cast({c.name if c.name in rows.columns else 'null'} as {c.dataType.simpleString()}) as {c.name}" for c in kind)).coalesce(1).write.parquet(str(tmp_path / f.name))
            else:
                shutil.copy(f, tmp_path / f.name)
        return str(tmp_path)

    return make


def same_as_sql(spark, query, folder):
    """The query's rows, which are those of its SQL."""
    from pathlib import Path

    import duckdb

    from joinsynth.catalog import ORACLES, QUERIES

    con = duckdb.connect()
    for t in "nation customer orders lineitem events".split():
        path = Path(folder) / f"{t}.parquet"
        con.execute(f"create view {t} as select * from read_parquet('{path / '*.parquet' if path.is_dir() else path}')")
    got, want = QUERIES[query](spark, folder).toPandas(), con.execute(ORACLES[query]).df()
    assert sorted(got.columns) == sorted(want.columns)
    rows = lambda frame: sorted((tuple(r) for r in frame[sorted(frame.columns)].itertuples(index=False, name=None)), key=repr)
    assert rows(got) == rows(want)
    return got


def test_smooth_bounds_of_every_customer(spark, tiny_tables):
    """A customer without events, one without orders, two alike and a row without customer."""
    orders = [(1, "1-URGENT"), (2, "1-URGENT"), (2, "5-LOW"), (3, None), (3, "1-URGENT"), (None, "5-LOW")]
    folder = tiny_tables(orders=(orders, "o_custkey bigint, o_orderpriority string"), events=([(4, "purchase"), (4, "view"), (4, "view")], "user_id bigint, event_type string"))
    got = {r[:4]: r[4:] for r in same_as_sql(spark, "b08_smooth_sensitivity_tiny", folder).itertuples(index=False, name=None)}
    assert set(got) == {(1, 0, 0, 0), (1, 1, 0, 0), (0, 0, 1, 2)} and got[1, 1, 0, 0][0] == 2
    assert got[0, 0, 1, 2][1] == 4.326129  # exp(-2 beta) * (3 + 2), as the made-up instance had


def test_smooth_bounds_at_the_smallest_tables(spark):
    assert same_as_sql(spark, "b08_smooth_sensitivity_tiny", "/root/testdata/sf0.001")["customers"].sum() == 150


def test_two_table_rule_on_three_moves_by_the_largest_order(spark, tiny_tables):
    """Customer 1 has five line items and gets a second unit of the order with the most, three; an order without customer and a customer without orders count for nothing."""
    orders = ([(10, 1), (11, 1), (12, 2), (13, None)], "o_orderkey bigint, o_custkey bigint")
    lines = ([(10,), (10,), (11,), (11,), (11,), (12,), (12,), (12,), (13,)], "l_orderkey bigint")
    got = same_as_sql(spark, "b09_two_table_rule_on_three", tiny_tables(customer=([(1,), (2,), (3,)], "c_custkey bigint"), orders=orders, lineitem=lines)).set_index("side")
    assert got.loc["before"].to_dict() == {"local_sensitivity": 5, "t23": 5} and got.loc["after"].to_dict() == {"local_sensitivity": 8, "t23": 8}


def test_two_table_rule_on_three_without_rows(spark, tiny_tables):
    empty = dict(customer=([], "c_custkey bigint"), orders=([], "o_orderkey bigint, o_custkey bigint"), lineitem=([], "l_orderkey bigint"))
    assert set(same_as_sql(spark, "b09_two_table_rule_on_three", tiny_tables(**empty))["t23"]) == {0}


LINES = "l_orderkey bigint, l_linenumber int, l_returnflag string, l_linestatus string"
CYCLE = [(1, 1, "A", "F"), (1, 2, "A", "O"), (1, 3, "N", "O"), (1, 4, "N", "F")]
TREE = [(2, 1, "A", "F"), (2, 2, "A", "O"), (2, 2, "R", "O"), (3, 2, "R", "O"), (3, 2, "A", "O"), (3, 1, "A", "F"), (3, 1, "A", "F")]
ODD = [(4, 1, None, None), (4, 2, "A", None), (5, None, "A", "F"), (None, 1, "A", "F")]


def test_hypergraphs_of_orders(spark, tiny_tables):
    """A cycle, two orders that are the same hierarchical join, lines without attributes, rows without order or line."""
    got = same_as_sql(spark, "d11_hypergraph_properties", tiny_tables(lineitem=(CYCLE + TREE + ODD, LINES)))
    rows = {r.spec: (r.orders, r.m, r.acyclic, r.hierarchical, r.boundary_of_first, r.parts) for r in got.itertuples()}
    assert rows == {
        "1:GA,ZF;2:GA,ZO;3:ZO,GN;4:ZF,GN": (1, 4, False, False, "GA,ZF", 2), "1:GA,ZF;2:GA,GR,ZO": (2, 2, True, True, "GA", 2), "1:;2:GA": (1, 2, True, True, "", 2),
    }


def test_attribute_trees_of_orders(spark, tiny_tables):
    """Of the same orders those that are hierarchical have trees; the cycle has none."""
    got = same_as_sql(spark, "d12_attribute_tree", tiny_tables(lineitem=(CYCLE + TREE + ODD, LINES)))
    assert sorted(got.itertuples(index=False, name=None)) == [
        ("1:;2:GA", 1, "GA", "", "2"), ("1:GA,ZF;2:GA,GR,ZO", 2, "GA", "", "1,2"), ("1:GA,ZF;2:GA,GR,ZO", 2, "GRZO", "GA", "2"), ("1:GA,ZF;2:GA,GR,ZO", 2, "ZF", "GA", "1"),
    ]


def test_attribute_trees_where_no_order_has_one(spark, tiny_tables):
    assert same_as_sql(spark, "d12_attribute_tree", tiny_tables(lineitem=(CYCLE, LINES))).empty
