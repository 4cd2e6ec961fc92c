import math
from itertools import combinations

import numpy as np
import pytest

from joinsynth import hyper
from joinsynth.functions import bounds, noise
from joinsynth.ledger import BudgetExceeded, Ledger, NotPrivate, per_query, require
from joinsynth.operators import kernel, sensitivity
from joinsynth.sources.workloads import CHAIN3, HIER5, PATH3, SPECS, STAR3, TRIANGLE, TWO

LAM = math.log(1e6)
BETA = 1 / LAM


def test_tree_of_the_five_relation_example():
    tree = hyper.AttrTree(HIER5)
    assert [n.name for n in tree.post_order()] == ["D", "F", "K", "L", "G", "B", "C", "A"]
    by = {n.name: n for n in tree.nodes}
    assert tree.ancestors(by["K"]) == ("A", "B", "G") and tree.ancestors(by["A"]) == ()
    assert hyper.product_factors(HIER5, (2, 3, 4)) == [((2, 3), ("A", "B")), ((2,), ("A", "B", "G")), ((3,), ("A", "B", "G")), ((4,), ("A",))]
    assert hyper.boundary(HIER5, (2, 3, 4)) == ("A", "B")


def test_classes_of_joins():
    assert {n for n, s in SPECS.items() if not hyper.is_hierarchical(s)} == {"PATH3", "CHAIN3", "TRIANGLE"}
    assert {n for n, s in SPECS.items() if not hyper.is_acyclic(s)} == {"TRIANGLE"}
    with pytest.raises(ValueError):
        hyper.AttrTree(PATH3)
    assert hyper.components(CHAIN3, (0, 2)) == [(0,), (2,)]


def test_edge_covers_and_worst_case():
    assert hyper.fractional_edge_cover(TWO) == pytest.approx(2)
    assert hyper.fractional_edge_cover(TRIANGLE) == pytest.approx(1.5)
    assert hyper.fractional_edge_cover(STAR3) == pytest.approx(3)
    assert hyper.worst_case_error(STAR3, 10, bags=True) == pytest.approx(10**2.5)
    assert hyper.worst_case_error(TWO, 100) == pytest.approx(100**1.5)


@pytest.mark.parametrize(("degree", "want"), [(1, 5.463480015261347), (5, 7.298111432159932), (20, 20), (100, 100)])
def test_residual_sensitivity_golden_two(degree, want):
    table = {frozenset(): 1, frozenset({0}): degree, frozenset({1}): degree // 2}
    assert sensitivity.residual_sensitivity(table, 2, BETA) == pytest.approx(want, rel=1e-12)


def test_residual_sensitivity_golden_three_and_search_box():
    f = frozenset
    table = {f(): 1, f({0}): 9, f({1}): 37, f({2}): 49, f({0, 1}): 25, f({0, 2}): 289, f({1, 2}): 64}
    assert sensitivity.residual_sensitivity(table, 3, BETA) == pytest.approx(381.64963312029744, rel=1e-12)
    assert sensitivity.search_limit(BETA) == 14
    rng = np.random.default_rng(0)
    for _ in range(5):
        table = {f(e): int(rng.integers(1, 300)) for k in (1, 2) for e in combinations(range(3), k)} | {f(): 1}
        assert sensitivity.residual_sensitivity(table, 3, BETA) == pytest.approx(sensitivity.residual_sensitivity(table, 3, BETA, limit=60), rel=1e-12)
        by_k = max(math.exp(-BETA * k) * sensitivity.ls_hat_k(table, 3, k) for k in range(29))
        assert by_k == pytest.approx(sensitivity.residual_sensitivity(table, 3, BETA), rel=1e-12)


def test_tau_and_round_budget():
    assert noise.tau(1, 1e-6, 1) == pytest.approx(14.35683599455373)
    assert noise.tau(0.5, 5e-7, 1) == pytest.approx(28.15181275940755)
    assert bounds.round_budget(1, 1e-6, 10, "zcdp") > 4 * bounds.round_budget(1, 1e-6, 10)
    e = bounds.round_budget(1, 1e-6, 7, "zcdp")
    rho = 7 * (e * e / 8 + e * e / 2)
    assert rho + 2 * math.sqrt(rho * math.log(1e6)) == pytest.approx(1)


def test_noise_laws():
    src = noise.NoiseSource.seeded("s")
    u = np.array([src.uniform("x", i) for i in range(20000)])
    lap = np.sort([noise.laplace_value(2.0, x) for x in u])
    cdf = np.where(lap < 0, 0.5 * np.exp(lap / 2), 1 - 0.5 * np.exp(-lap / 2))
    assert np.abs(cdf - np.arange(1, 20001) / 20000).max() < 0.012
    cut = np.array([noise.tlap_value(2.0, 28.15, x) for x in u])
    assert cut.min() >= 0 and cut.max() <= 56.3 and abs(cut.mean() - 28.15) < 0.1 and abs(np.abs(cut - 28.15).mean() - 2) < 0.05
    assert noise.tlap_value(2.0, 5.0, 1e-18) == pytest.approx(0, abs=1e-6) and noise.tlap_value(2.0, 5.0, 1 - 1e-16) == pytest.approx(10, abs=1e-6)
    # empirical privacy of a scalar release of 0 and 1 at eps = 1
    bins = np.linspace(-3, 4, 8)
    a, b = (np.histogram(v + np.array([noise.laplace_value(1.0, x) for x in u]), bins)[0] for v in (0, 1))
    assert (np.maximum(a, b) <= math.e * 1.15 * np.minimum(a, b) + 30).all()


def test_private_choice_follows_its_law():
    rng = np.random.default_rng(3)
    scores = np.array([0.0, 2.0, 4.0])
    pick = np.bincount([noise.exp_mech_index(scores, 1.0, rng.random(3)) for _ in range(6000)], minlength=3) / 6000
    law = np.exp(scores / 2) / np.exp(scores / 2).sum()
    assert np.abs(pick - law).max() < 0.03
    assert noise.exp_mech_index(np.array([1.0, 3.0, 3.0]), 1.0, None) == 1


def test_os_noise_is_fresh_and_keyed():
    a, b = noise.NoiseSource.os(), noise.NoiseSource.os()
    assert a.uniform("k") == a.uniform("k") != b.uniform("k")


def test_ledger_rules():
    ledger = Ledger(1.0, 1e-6)
    ledger.spend("a", 0.5, 5e-7)
    ledger.parallel("b", [(0.5, 5e-7)] * 9)
    assert ledger.total == pytest.approx((1.0, 1e-6))
    with pytest.raises(BudgetExceeded):
        ledger.spend("c", 0.01)
    assert Ledger(1, 1e-6, "substitute").budget() == (0.5, 5e-7)
    assert per_query(1, 1e-6, 10)[0] == 0.1 and per_query(1, 1e-6, 10_000, "advanced")[0] > per_query(1, 1e-6, 10_000)[0]
    with pytest.raises(NotPrivate):
        require(False, "x")


def test_bounds_order():
    low, up = bounds.f_low(10, 1), bounds.f_up(10, 1, 1e-6, 36)
    assert low < bounds.f_up(10, 1, 1e-6, 36, tight=True) < up
    assert bounds.lower_join(1e6, 100, low) < bounds.upper_two_table(1e6, 100, LAM, up)
    assert bounds.upper_multi_table(1e6, 100, LAM, up) < bounds.upper_multi_table(1e6, 100, LAM, up, "early")
    assert bounds.auto_rounds(1e5, 1, 1e-6, 0.0, 5, 36) == bounds.auto_rounds(1e5, 1, 1e-6, 1, 5, 1) == 1
    whole, parts = bounds.uniformization_gain([(i, 100.0) for i in range(1, 6)], 32)
    assert parts <= math.sqrt(500 * sum(2.0**i for i in range(1, 6))) + 1e-9 and whole > 0


def _plan(rng, shape=(4, 3), sizes=(5, 4)):
    points = [(i, j) for i in range(shape[0]) for j in range(shape[1])]
    w = [rng.choice([-1.0, 0.0, 1.0], (n, k)) for n, k in zip(sizes, shape, strict=True)]
    return kernel.KernelPlan(points, ("A", "B"), (w[0][:, [p[0] for p in points]], w[1][:, [p[1] for p in points]]), math.log(len(points)))


def test_kernel_matches_a_dense_histogram_and_its_invariants():
    rng = np.random.default_rng(1)
    plan = _plan(rng)
    cells = rng.integers(0, 50, 12).astype(float)
    truth = plan.answers(cells)
    direct = np.array([[sum(cells[c] * plan.weights[0][i, c] * plan.weights[1][j, c] for c in range(12)) for j in range(4)] for i in range(5)])
    assert np.allclose(truth, direct)
    trace = kernel.Trace()
    zero = noise.NoiseSource.zero()
    mass = kernel.run_task(plan, truth, np.ones(12), cells.sum(), 1.0, 1, 1e-6, zero, 40, trace=trace, true_cells=cells)
    assert mass.sum() == pytest.approx(cells.sum()) and (mass >= 0).all()
    assert trace.potential[0] <= math.log(12) + 1e-9
    for e, a, b in zip(trace.error, trace.potential, trace.potential[1:], strict=False):
        assert a - b >= e * e / (4 * cells.sum() ** 2) - 1e-12
    # a cell of volume 7 behaves as seven equal points
    wide = kernel.KernelPlan(plan.points * 7, plan.attrs, tuple(np.tile(w, 7) for w in plan.weights), math.log(84))
    many = kernel.run_task(wide, truth, np.ones(84), cells.sum(), 1.0, 1, 1e-6, zero, 40)
    assert np.allclose(many.reshape(7, 12).sum(axis=0), kernel.run_task(plan, truth, np.full(12, 7.0), cells.sum(), 1.0, 1, 1e-6, zero, 40))


def test_kernel_special_cases():
    plan = _plan(np.random.default_rng(2))
    zero, seeded = noise.NoiseSource.zero(), noise.NoiseSource.seeded("z")
    nothing = kernel.run_task(plan, np.zeros((5, 4)), np.ones(12), 0.0, 1.0, 1, 1e-6, zero, 3)
    assert not nothing.any()
    start = kernel.run_task(plan, np.zeros((5, 4)), np.ones(12), 24.0, 1.0, 1, 1e-6, zero, 0)
    assert np.allclose(start, 2.0)
    noisy = kernel.run_task(plan, np.zeros((5, 4)), np.ones(12), 24.0, 1.0, 1, 1e-6, seeded, 5)
    assert noisy.sum() == pytest.approx(24.0) and np.isfinite(noisy).all()
    assert np.array_equal(noisy, kernel.run_task(plan, np.zeros((5, 4)), np.ones(12), 24.0, 1.0, 1, 1e-6, seeded, 5))
    volumes = np.array([0.0] * 6 + [1.0] * 6)
    assert not kernel.run_task(plan, np.zeros((5, 4)), volumes, 24.0, 1.0, 1, 1e-6, zero, 3)[:6].any()


def test_noisy_selection_is_near_maximal():
    """With a large budget the chosen query's error is close to the largest one, and the last errors shrink."""
    rng = np.random.default_rng(4)
    plan = _plan(rng)
    cells = rng.integers(0, 5000, 12).astype(float)
    truth = plan.answers(cells)
    trace = kernel.Trace()
    kernel.run_task(plan, truth, np.ones(12), cells.sum(), 1.0, 2000.0, 1e-6, noise.NoiseSource.seeded("n"), 60, trace=trace)
    assert trace.error[-1] < 0.5 * trace.error[0]
