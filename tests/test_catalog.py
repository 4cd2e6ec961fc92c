"""Registered queries against their SQL on the smallest tables."""

import math

import duckdb
import pytest

from joinsynth.catalog import ORACLES, QUERIES

D = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
CHECKED = sorted(n for n in ORACLES if n[0] in "dqsna" or n.startswith(("r0", "r1", "w0", "w1")))


@pytest.fixture(scope="module")
def tables():
    con = duckdb.connect()
    for t in TABLES:
        con.execute(f"create view {t} as select * from read_parquet('{D}/{t}.parquet')")
    return con


def rows(frame):
    frame = frame[sorted(frame.columns)]
    text = lambda x: "null" if x is None or (isinstance(x, float) and math.isnan(x)) else repr(float(x)) if isinstance(x, float) else str(x)
    return sorted(tuple(map(text, r)) for r in frame.itertuples(index=False, name=None))


@pytest.mark.parametrize("name", CHECKED)
def test_query_equals_its_sql(spark, tables, name):
    got, want = QUERIES[name](spark, D).toPandas(), tables.sql(ORACLES[name]).df()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


@pytest.mark.parametrize(("name", "spec", "one"), [("q03_marginals", "NATION2", ""), ("q10_answers_path", "PATH3", "q3 = 0"), ("q10_answers_cyclic", "TRIANGLE", "")])
def test_marginals_cover_the_whole_domain(spark, name, spec, one):
    """Every row of the join enters one marginal's answer: they add up to the join size."""
    from joinsynth.plans.elimination import join_size
    from joinsynth.relation import load
    from joinsynth.sources.workloads import SPECS

    size = join_size(load(spark, D, SPECS[spec])).first()[0]
    assert size > 0
    assert QUERIES[name](spark, D).filter(one or "true").selectExpr("sum(answer)").first()[0] == pytest.approx(float(size))


def test_path_release_asks_for_every_brand():
    from joinsynth.catalog.noise_and_release import _PATH_Q2
    from joinsynth.sources.workloads import BRANDS

    assert all(any(f"'{b}'" in w for w in _PATH_Q2.families[0].weights) for b in BRANDS)
