import math

import numpy as np
import pytest
from pyspark.sql import functions as F

from joinsynth.functions.bounds import lam as lam_of
from joinsynth.functions.noise import NoiseSource, tau, tlap_below, tlap_value
from joinsynth.hyper import AttrTree
from joinsynth.ledger import NotPrivate
from joinsynth.operators import baselines, kernel, measures, partition, release, sensitivity
from joinsynth.plans.elimination import join_size
from joinsynth.queries import Family, QuerySet, answers, answers_naive, dense_answers, domain_frame, joint_domain
from joinsynth.relation import Instance, load, natural_join, neighbor, substitute
from joinsynth.sources import instances
from joinsynth.sources.workloads import CHAIN3, EVENT_TYPES, HIER5, LANG2, LINE1, NATION2, PATH3, PRIORITIES, SEGMENTS, SPECS, STAR3, TRIANGLE, TWO

D = "/root/testdata/sf0.001"
ZERO, SEEDED = NoiseSource.zero(), NoiseSource.seeded("t")
LAM = lam_of(1.0, 1e-6)
Q2 = QuerySet((Family.all_ones() + Family.marginal("P", PRIORITIES), Family.all_ones() + Family.marginal("E", EVENT_TYPES)))


@pytest.fixture(scope="module")
def two(spark):
    inst = load(spark, D, TWO)
    return Instance(inst.spec, tuple(f.cache() for f in inst.frames))


@pytest.mark.parametrize("name", ["TWO", "STAR3", "PATH3", "TRIANGLE", "CHAIN3"])
def test_factorised_plans_equal_the_naive_join(spark, name):
    inst = load(spark, D, SPECS[name])
    naive = natural_join(inst).agg(F.sum("freq")).first()[0]
    assert join_size(inst).first()["val"] == naive
    queries = QuerySet(tuple(Family.random_sign((r.attrs[-1],), 2, name) for r in SPECS[name].relations))
    a = {tuple(r)[:-1]: r["answer"] for r in answers(inst, queries).collect() if abs(r["answer"]) > 1e-9}
    b = {tuple(r)[:-1]: r["answer"] for r in answers_naive(inst, queries).collect() if abs(r["answer"]) > 1e-9}
    assert a == pytest.approx(b)


def test_golden_maxima(spark):
    f = lambda *x: frozenset(i - 1 for i in x)
    star = sensitivity.collect_table(sensitivity.boundary_table(load(spark, D, STAR3)))
    assert star == {f(): 1, f(1): 13, f(2): 1, f(3): 1, f(1, 2): 13, f(1, 3): 13, f(2, 3): 1}
    assert sensitivity.residual_sensitivity(star, 3, 1 / LAM) == pytest.approx(71.14790420708732)
    path = sensitivity.collect_table(sensitivity.boundary_table(load(spark, D, PATH3)))
    assert path == {f(): 1, f(1): 1, f(2): 9, f(3): 1, f(1, 2): 640, f(2, 3): 48, f(1, 3): 1}
    hier = load(spark, D, HIER5)
    assert int(sensitivity.boundary_max(hier, (2, 3, 4)).first()["t"]) == 10725
    product = math.prod(r.mdeg for r in sensitivity.degree_product(hier, (2, 3, 4)).collect())
    assert product == 23760


def test_product_bound_covers_every_subset(spark):
    inst = load(spark, D, STAR3)
    for e in sensitivity.subsets(3):
        if e:
            bound = math.prod(r.mdeg for r in sensitivity.degree_product(inst, e).collect())
            assert int(sensitivity.boundary_max(inst, e).first()["t"]) <= bound


def test_neighbours_move_counts_and_bounds_by_what_is_promised(spark):
    inst = load(spark, D, STAR3)
    size, ls = sensitivity.out_size(inst), sensitivity.local_sensitivity(inst).first()[0]
    rs = sensitivity.ResidualBound().value(inst, 1 / LAM)
    assert rs >= ls
    for i, values, delta in ((0, (3, SEGMENTS[0]), 1), (1, (3, 2), 1), (2, (3, 1), 1)):
        near = neighbor(inst, i, values, delta)
        assert abs(sensitivity.out_size(near) - size) <= ls
        assert abs(math.log(sensitivity.ResidualBound().value(near, 1 / LAM) / rs)) <= 1 / LAM + 1e-9
    two = load(spark, D, TWO)
    before = sensitivity.max_degree(two).first()[0]
    assert abs(sensitivity.max_degree(neighbor(two, 1, (0, "view"), 1)).first()[0] - before) <= 1
    assert sensitivity.out_size(substitute(two, 0, (3, "1-URGENT"), (3, "5-LOW"))) >= 0


def test_smooth_sensitivity_of_a_tiny_instance(spark):
    for name in ("one_value", "empty_join"):
        inst = instances.gen_edges(spark)[name]
        least = sensitivity.BruteForceSmooth([[(1, 1), (2, 1)], [(1, 1), (2, 1)]], 2).value(inst, 0.3)
        assert sensitivity.local_sensitivity(inst).first()[0] <= least <= sensitivity.ResidualBound().value(inst, 0.3) + 1e-9


def test_q_aggregate_wants_a_closed_set(spark):
    with pytest.raises(ValueError):
        sensitivity.q_aggregate(load(spark, D, HIER5), (2, 3), ("G",))


def test_kernel_golden_rounds(spark, two):
    plan, volume = release.kernel_plan(two, Q2, D)
    truth = dense_answers(answers(two, Q2).collect(), Q2)
    trace = kernel.Trace()
    average = kernel.run_task(plan, truth, np.full(25, volume), truth.flat[0], 88, 1, 1e-6, ZERO, 20, trace=trace)
    last = kernel.run_task(plan, truth, np.full(25, volume), truth.flat[0], 88, 1, 1e-6, ZERO, 20, out="last")
    assert trace.error[:3] == pytest.approx([562.8, 517.350147, 506.204669], abs=1e-5) and trace.error[19] == pytest.approx(283.216114, abs=1e-5)
    assert np.abs(plan.answers(average) - truth).max() == pytest.approx(363.752097, abs=1e-5)
    assert np.abs(plan.answers(last) - truth).max() == pytest.approx(267.641764, abs=1e-5)


@pytest.mark.parametrize("noise", [ZERO, SEEDED])
def test_task_and_frame_kernels_agree(spark, two, noise):
    plan, volume = release.kernel_plan(two, Q2, D)
    truth = dense_answers(answers(two, Q2).collect(), Q2)
    task = kernel.run_task(plan, truth, np.full(25, volume), 9000.0, 3.0, 50.0, 1e-6, noise, 4)
    cells = spark.createDataFrame([(*p, volume) for p in plan.points], ["P", "E", "volume"])
    frame = kernel.run_frame(cells, Q2, truth, 9000.0, 3.0, 50.0, 1e-6, noise, 4)
    got = {(r.P, r.E): r.mass for r in frame.collect()}
    assert [got[p] for p in plan.points] == pytest.approx(task.tolist())


def test_releases_spend_exactly_their_budget_and_never_undershoot(spark, two):
    size, degree = sensitivity.out_size(two), sensitivity.max_degree(two).first()[0]
    out = release.release_two_table(two, Q2, D, 1.0, 1e-6, SEEDED, rounds=2)
    row = out.cells.first()
    assert out.ledger.total == pytest.approx((1.0, 1e-6))
    assert degree <= row.dtilde <= degree + 2 * tau(0.5, 5e-7, 1) and row.n_hat >= size
    half = release.release_two_table(two, Q2, D, 1.0, 1e-6, SEEDED, rounds=1, dp="substitute")
    assert half.ledger.total == pytest.approx((0.5, 5e-7))
    capped = release.release_two_table(two, Q2, D, 1.0, 1e-6, ZERO, rounds=1, public_bound=500.0)
    assert capped.cells.first().dtilde == 500.0 and capped.ledger.total == pytest.approx((1.0, 1e-6))
    multi = release.release_multi_table(two, Q2, D, 1.0, 1e-6, SEEDED, rounds=2)
    assert multi.ledger.total == pytest.approx((1.0, 1e-6)) and multi.cells.first().dtilde >= degree
    parts = release.release_uniformized(two, Q2, D, 1.0, 1e-6, SEEDED, rounds=1)
    assert parts.ledger.total == pytest.approx((1.0, 1e-6))
    star = load(spark, D, STAR3)
    ones = QuerySet((Family.all_ones(),) * 3)
    tree = release.release_uniformized(star, ones, D, 1.0, 1e-6, ZERO, rounds=1, partitioner="hierarchical", n_max=100.0)
    assert tree.ledger.total[0] <= 1.0 + 1e-9
    with pytest.raises(ValueError):
        release.release_two_table(star, ones, D, 1.0, 1e-6)
    with pytest.raises(ValueError):
        release.release_uniformized(star, ones, D, 1.0, 1e-6, ZERO, partitioner="hierarchical", max_configs=1)


def test_group_factor_of_self_joins(spark):
    inst = load(spark, D, SPECS["LANG2"])
    queries = QuerySet((Family.all_ones(), Family.all_ones()))
    out = release.release_two_table(inst, queries, D, 1.0, 1e-6, ZERO, rounds=1)
    assert out.ledger.total == pytest.approx((1.0, 1e-6)) and all(s[1] == pytest.approx(0.5) for s in out.ledger.steps)


def test_one_bucket_uniformized_equals_whole_join(spark, two):
    whole = release.release_two_table(two, Q2, D, 1.0, 1e-6, ZERO, rounds=3)
    parts = release.release_uniformized(two, Q2, D, 1.0, 1e-6, ZERO, rounds=3, lam=1e6)
    a = {(r.P, r.E): r.mass for r in whole.cells.collect()}
    assert {(r.P, r.E): r.mass for r in parts.cells.collect()} == pytest.approx(a)


def test_order_and_partitioning_do_not_matter(spark, two):
    mixed = Instance(TWO, tuple(f.repartition(7).orderBy(F.rand(3)) for f in two.frames))
    a, b = (release.release_two_table(i, Q2, D, 1.0, 1e-6, SEEDED, rounds=3).cells.orderBy("cell").collect() for i in (two, mixed))
    assert [r.mass for r in a] == pytest.approx([r.mass for r in b], rel=1e-12)


def test_broken_designs_need_a_word_and_leak(spark):
    on, off = instances.gen_collapse(spark, 200), instances.gen_collapse(spark, 200, present=False)
    queries = QuerySet((Family.all_ones(), Family.all_ones()))
    with pytest.raises(NotPrivate):
        baselines.flawed_local_noise(on, 1.0, SEEDED)
    with pytest.raises(NotPrivate):
        release.release_exact_total(on, queries, D, 1.0, 1e-6, SEEDED, 1)
    assert (sensitivity.out_size(on), sensitivity.out_size(off)) == (200, 0)
    totals = [[kernel.noisy_total(float(sensitivity.out_size(i)), 200 + tau(0.5, 5e-7, 1), 1, 1e-6, NoiseSource.seeded(str(k))) for k in range(40)] for i in (on, off)]
    assert min(totals[0]) < max(totals[1]), "masked totals overlap"
    # padding after an exact release: the heavy cell is empty in one neighbour, never in the other
    rng = np.random.default_rng(0)
    empty = sum(rng.multinomial(500, np.full(10_000, 1e-4))[0] == 0 for _ in range(50))
    assert empty > 25


def test_two_table_partition(spark, two):
    domain = domain_frame(spark, D, TWO, "K")
    true = {r.K: r.bucket for r in partition.partition_true_degrees(two, domain, LAM).labels.collect()}
    degree = {r.K: max(r.deg1, r.deg2) for r in sensitivity.degree_table(two).collect()}
    assert len(true) == 150
    for k, b in true.items():
        assert b == max(1, math.ceil(math.log2(max(degree.get(k, 0), 1e-9) / LAM)))
    part = partition.partition_two_table(two, domain, 0.5, 5e-7, LAM, SEEDED)
    noisy = {r.K: r.bucket for r in part.labels.collect()}
    for k, b in noisy.items():
        assert true[k] <= b <= math.ceil(math.log2(2.0 ** true[k] + 2 * tau(0.5, 5e-7, 1) / LAM))
    vector = measures.join_size_vector(part).collect()
    assert sum(r.out_size for r in vector) == sensitivity.out_size(two) and sum(r.n_keys for r in vector) == 150


def test_bucket_thresholds_belong_below(spark):
    rows = spark.createDataFrame([(0.0,), (2.0,), (2.000001,), (4.0,), (4.1,), (1e30,)], "d double")
    assert [r.b for r in rows.select(partition.bucket_of(F.col("d"), 1.0).alias("b")).collect()] == [1, 1, 2, 2, 3, 64]


@pytest.mark.parametrize(("spec", "noise"), [(STAR3, ZERO), (STAR3, SEEDED), (HIER5, ZERO), (TWO, SEEDED)])
def test_hierarchical_partition_is_a_partition_of_the_join(spark, spec, noise):
    inst, domain = load(spark, D, spec), lambda attrs: joint_domain(spark, D, spec, attrs)
    part = partition.partition_hierarchical(inst, 1.0, 1e-6, 1.0 if spec is STAR3 else LAM, noise, domain)
    vector = measures.join_size_vector(part).collect()
    assert sum(r.out_size for r in vector) == sensitivity.out_size(inst)
    assert len({r.config for r in vector}) == len(vector)
    skipped = partition.partition_hierarchical(inst, 1.0, 1e-6, 1.0 if spec is STAR3 else LAM, noise, domain, skip_root=True)
    assert sum(r.out_size for r in measures.join_size_vector(skipped).collect()) == sensitivity.out_size(inst)


def test_pairs_and_larger_degree_partitions_agree_on_the_join(spark, two):
    domain = domain_frame(spark, D, TWO, "K")
    pairs = measures.join_size_vector(partition.partition_true_degrees(two, domain, LAM, pairs=True)).collect()
    larger = {str(r.bucket): r.out_size for r in measures.join_size_vector(partition.partition_true_degrees(two, domain, LAM)).collect()}
    merged: dict[str, int] = {}
    for r in pairs:
        key = max(r.bucket.split(","), key=int)
        merged[key] = merged.get(key, 0) + r.out_size
    assert merged == larger


def test_zero_noise_hierarchical_labels_are_dyadic(spark):
    inst = load(spark, D, STAR3)
    tree = AttrTree(STAR3)
    leaf = next(n for n in tree.nodes if n.attrs == ("S",))
    split, labels, known = partition.split_on_attribute(inst, tree, leaf, {}, {}, lambda attrs: joint_domain(spark, D, STAR3, attrs), 1.0, 1e-6, 1.0, ZERO)
    degree = {r.N: r.deg for r in sensitivity.hier_degree(inst, (0,), ("N",)).collect()}
    for r in known.collect():
        assert r.c_S == max(1, math.ceil(math.log2(max(1, degree.get(r.N, 0)))))
    assert labels[0] == ("c_S",) and "c_S" in split.frames[0].columns and "c_S" not in split.frames[1].columns


def test_geometric_instances_favour_the_partitioned_release(spark):
    gains = []
    for k in (8, 64, 512):
        inst = instances.gen_geometric(spark, k)
        part = partition.partition_true_degrees(inst, inst.frames[0].select("B").distinct(), 1.0)
        row = measures.gain(part).first()
        gains.append(row.whole_join / row.uniformized)
        assert sum(r.out_size for r in measures.join_size_vector(part).collect()) == sensitivity.out_size(inst)
    assert gains[0] < gains[1] < gains[2]


def test_hard_instances_amplify(spark):
    table = spark.createDataFrame([(1, 4), (2, 3), (3, 2)], "A bigint, freq bigint")
    inst = instances.gen_hard_two(table, 3)
    assert sensitivity.out_size(inst) == 27 and sensitivity.max_degree(inst).first()[0] == 3
    assert {r.A: int(r.val) for r in join_size(inst, ("A",)).collect()} == {1: 12, 2: 9, 3: 6}


def test_rows_keep_the_expected_mass(spark, two):
    out = release.release_two_table(two, Q2, D, 1.0, 1e-6, ZERO, rounds=2)
    counts = [out.to_rows(NoiseSource.seeded(str(i))).count() for i in range(6)]
    total = out.cells.agg(F.sum("mass")).first()[0]
    assert abs(np.mean(counts) - total) < 6 and all(abs(c - total) <= 25 for c in counts)


def test_save_and_view(spark, two, tmp_path):
    out = release.release_two_table(two, Q2, D, 1.0, 1e-6, ZERO, rounds=1)
    for _ in range(2):
        out.save(str(tmp_path / "r"))
    assert spark.read.parquet(str(tmp_path / "r/cells")).count() == 25
    assert spark.read.parquet(str(tmp_path / "r/ledger")).agg(F.sum("eps")).first()[0] == pytest.approx(1.0)
    out.view("v_test")
    assert spark.sql("select sum(mass) as m from v_test").first().m == pytest.approx(sensitivity.out_size(two))


def test_edge_instances(spark):
    queries = QuerySet((Family.all_ones(), Family.all_ones()))
    want = {"empty_relation": (0, 1), "empty_join": (0, 1), "one_value": (9, 3), "repeated_rows": (2, 2), "zero_frequency": (0, 5), "null_attribute": (1, 1)}
    for name, inst in instances.gen_edges(spark).items():
        got = answers(inst, queries).collect()
        assert (sensitivity.out_size(inst), sensitivity.max_degree(inst).first()[0]) == want[name]
        assert sum(r.answer for r in got) == want[name][0]


def test_single_table_and_many_query_baseline(spark):
    line = load(spark, D, LINE1)
    queries = QuerySet((Family.all_ones() + Family.marginal("G", ("A", "N", "R")),))
    out = release.release_single(line, queries, D, 1.0, 1e-6, ZERO, rounds=60, out="last")
    errors = measures.error_table(baselines.complete_answers(line, queries), out.answer(), ["q1"])
    start = release.release_single(line, queries, D, 1.0, 1e-6, ZERO, rounds=0)
    before = measures.error_table(baselines.complete_answers(line, queries), start.answer(), ["q1"])
    assert measures.linf_error(errors).first().linf < measures.linf_error(before).first().linf
    # separate answers get worse with the number of queries
    few, many = (baselines.answer_independently(line, QuerySet((Family.random_sign(("G",), n, "x"),)), 1.0, 1e-6, SEEDED, 1.0) for n in (4, 64))
    exact = [baselines.complete_answers(line, QuerySet((Family.random_sign(("G",), n, "x"),))) for n in (4, 64)]
    gap = [measures.error_quantiles(measures.error_table(e, r, ["q1"])).first().mean_error for e, r in zip(exact, (few, many), strict=True)]
    assert gap[1] > 4 * gap[0]


def test_cyclic_and_path_releases_run(spark):
    ones = QuerySet((Family.all_ones(),) * 3)
    for spec in (TRIANGLE, CHAIN3):
        out = release.release_multi_table(load(spark, D, spec), ones, D, 1.0, 1e-6, SEEDED, rounds=1)
        assert out.cells.first().n_hat >= sensitivity.out_size(load(spark, D, spec))


STAR_Q = QuerySet((Family.all_ones() + Family.marginal("S", SEGMENTS), Family.all_ones(), Family.all_ones()))


@pytest.mark.parametrize("seed", ["a", "b"])
def test_hierarchical_release_of_neighbours_has_the_same_parts(spark, seed):
    """One nation without a supplier, and with one: neither the parts nor their bounds tell them apart."""
    inst = load(spark, D, STAR3)
    inst = Instance(inst.spec, tuple(f.filter("N = 1") for f in inst.frames)).with_frame(1, inst.frames[1].filter("false"))
    other = neighbor(inst, 1, (1, 2), 1)
    outs = []
    for x in (inst, other):
        out = release.release_uniformized(x, STAR_Q, D, 1.0, 1e-6, NoiseSource.seeded(seed), rounds=1, partitioner="hierarchical", n_max=1000.0)
        assert out.ledger.total == pytest.approx((1.0, 1e-6))
        outs.append({r.sub_id: r.dtilde for r in out.cells.select("sub_id", "dtilde").distinct().collect()})
    assert outs[0] and outs[0].keys() == outs[1].keys()
    # a bound's logarithm moves by the smoothness at most
    copies = partition.replication_bound(inst, 1000.0, LAM)
    beta = 1 / lam_of(0.5 / copies, 5e-7 / copies)
    assert all(abs(math.log(a / outs[1][k])) <= beta * (1 + 1e-9) for k, a in outs[0].items())


def test_empty_tables_release_every_part(spark):
    inst = load(spark, D, NATION2)
    none = Instance(inst.spec, tuple(f.filter("false") for f in inst.frames))
    queries = QuerySet((Family.all_ones(), Family.all_ones()))
    for kind in ("two_table", "hierarchical"):
        out = release.release_uniformized(none, queries, D, 1.0, 1e-6, SEEDED, rounds=1, partitioner=kind, n_max=1000.0)
        assert out.cells.count() >= 25 and out.cells.filter("mass is null").count() == 0


def test_every_release_divides_the_budget_of_a_self_join(spark):
    """Noise and ledger of a unit that touches two rows: half of the budget for each row, the whole one in all."""
    inst = load(spark, D, LANG2)
    queries = QuerySet((Family.all_ones(), Family.all_ones() + Family.prefix("W", (0, 2))))
    degree = sensitivity.max_degree(inst).first()[0]
    whole = lambda f, **k: f(inst, queries, D, 1.0, 1e-6, SEEDED, rounds=1, **k)
    for f in (release.release_two_table, release.release_padded):
        out = whole(f)
        assert out.ledger.total == pytest.approx((1.0, 1e-6))
        assert out.cells.first().dtilde == pytest.approx(degree + SEEDED.tlap(4, tau(0.25, 2.5e-7, 1), "degree"))
    assert whole(release.release_multi_table).ledger.total == pytest.approx((1.0, 1e-6))
    out = whole(release.release_uniformized)
    assert out.ledger.total == pytest.approx((1.0, 1e-6))
    # of a part's share one half goes to its degree
    labels = partition.partition_two_table(inst, joint_domain(spark, D, LANG2, ("L",)), 0.25, 2.5e-7, lam_of(0.5, 5e-7), SEEDED)
    exact = {r.sub_id: r.d for r in labels.instance.frames[0].groupBy("L", "bucket").agg(F.sum("freq").alias("d")).groupBy(F.col("bucket").cast("string").alias("sub_id")).agg(F.max("d").alias("d")).collect()}
    for r in out.cells.select("sub_id", "dtilde").distinct().collect():
        assert r.dtilde == pytest.approx(exact.get(r.sub_id, 0) + SEEDED.tlap(2 / 0.25, tau(0.125, 1.25e-7, 1), "degree", r.sub_id))
    substituted = release.release_uniformized(inst, queries, D, 1.0, 1e-6, SEEDED, rounds=1, dp="substitute")
    assert substituted.ledger.total == pytest.approx((0.5, 5e-7))


def test_open_domain_draws_absent_values_as_listing_would(spark, two):
    radius = tau(0.5, 5e-7, 1)
    for u in (0.01, 0.2, 0.5, 0.77, 0.999):
        assert tlap_below(tlap_value(2.0, radius, u), 2.0, radius) == pytest.approx(u)
    listed = partition.partition_two_table(two, domain_frame(spark, D, TWO, "K"), 0.5, 5e-7, LAM, SEEDED)
    part, share = partition.partition_open_domain(two, 10**7, 0.5, 5e-7, LAM, SEEDED)
    want = {r.K: r.bucket for r in listed.labels.collect()}
    seen = {r.K: r.bucket for r in part.labels.filter("K is not null").collect()}
    assert seen and all(want[k] == b for k, b in seen.items())
    shares = {int(r.sub_id): r.share for r in share.collect()}
    assert sum(shares.values()) == pytest.approx(1.0)
    expected = np.diff([0.0, *(tlap_below(LAM * 2.0**i, 2.0, radius) for i in range(1, 8))])
    for i, p in enumerate(expected):
        assert shares.get(i + 1, 0.0) == pytest.approx(p, abs=2e-3)
    out = release.release_uniformized(two, Q2, D, 1.0, 1e-6, SEEDED, rounds=1, domain_size=10**7)
    assert {r.sub_id for r in out.cells.select("sub_id").distinct().collect()} == {str(k) for k in shares}
    assert out.cells.groupBy("sub_id").agg(F.sum("volume").alias("v")).agg(F.sum("v")).first()[0] == pytest.approx(25 * domain_frame(spark, D, TWO, "K").count())


def test_large_cell_tables_stay_frames(spark, two, monkeypatch):
    monkeypatch.setattr(release, "TASK_BYTES", 100)
    frame = release.release_two_table(two, Q2, D, 20.0, 1e-6, SEEDED, rounds=3)
    monkeypatch.setattr(release, "TASK_BYTES", 10**9)
    task = release.release_two_table(two, Q2, D, 20.0, 1e-6, SEEDED, rounds=3)
    assert frame.plan is None
    masses = [{(r.P, r.E): r.mass for r in x.cells.collect()} for x in (frame, task)]
    assert masses[0] == pytest.approx(masses[1])
    assert {tuple(r)[:2]: r.released for r in frame.answer().collect()} == pytest.approx({tuple(r)[:2]: r.released for r in task.answer().collect()})


def test_rounds_follow_the_formula_uncapped(spark, two):
    out = release.release_two_table(two, Q2, D, 1200.0, 1e-6, SEEDED)
    row, plan = out.cells.first(), out.plan
    want = row.n_hat * 600.0 * math.sqrt(plan.log_domain) / (row.dtilde * math.log(36) * math.sqrt(math.log(2e6)))
    assert row.rounds == int(want) > 500


def test_degrees_that_one_tuple_changes(spark):
    """Counted on neighbours of an instance with several labels below a node, against the public bound."""
    assert partition.degree_bound(load(spark, D, STAR3), 1000.0, LAM) == 2
    buckets = partition.bucket_count(1000.0, LAM)
    assert partition.degree_bound(load(spark, D, HIER5), 1000.0, LAM) >= 2 + buckets**2
    inst = load(spark, D, HIER5)
    inst = Instance(inst.spec, tuple(f.filter("A = 0") for f in inst.frames))
    tree, row = AttrTree(HIER5), inst.frames[0].filter("freq = 1").first()
    assert row is not None
    other = neighbor(inst, 0, tuple(row)[:-1], -1)
    domain = lambda attrs: joint_domain(spark, D, HIER5, attrs)
    changed, lam = 0, 0.5
    states = [[x, {}, {}] for x in (inst, other)]
    for node in tree.post_order():
        tables = []
        for state in states:
            given, below = tree.ancestors(node), [partition.label_col(n) for n in tree.below(node)]
            degree = sensitivity.hier_degree(state[0], tuple(sorted(node.atom)), given, state[1])
            tables.append({tuple(r[c] for c in (*given, *below)): r.deg for r in degree.collect()})
        changed += sum(tables[0].get(k, 0) != tables[1].get(k, 0) for k in {*tables[0], *tables[1]})
        # both follow the labels of the first: given equal noisy degrees, only exact degrees differ
        first = partition.split_on_attribute(*states[0][:1], tree, node, *states[0][1:], domain, 1.0, 1e-6, lam, ZERO)
        known = first[2]
        frames = [f.join(known, [c for c in f.columns if c in known.columns]) if i in node.atom else f for i, f in enumerate(states[1][0].frames)]
        states[1] = [Instance(inst.spec, tuple(frames)), first[1], {**states[1][2], node.name: known}]
        states[0] = [first[0], first[1], {**states[0][2], node.name: known}]
    assert 1 <= changed <= partition.degree_bound(inst, 10.0**6, lam)
