"""Closed forms, tuning and accounting against the published anchors and against simulation."""

import math
import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from privsketch.functions import accounting, theory, tune
from privsketch.functions.theory import SketchParams
from privsketch.operators import measure, oracles, simulate


@given(st.integers(4, 400), st.floats(0.5, 0.99), st.integers(0, 10**6), st.integers(1, 10**6), st.data())
def test_short_estimator_equals_the_long_one(m, p, c, n, data):
    s = data.draw(st.integers(1, m // 2))
    if abs(p - s / m) < 1e-3:
        return
    assert theory.estimate(c, n, p, s / m) == pytest.approx(theory.long_estimate(c, n, p, theory.q_of(p, s, m), m), rel=1e-9, abs=1e-6)


@given(st.integers(4, 1000), st.floats(0.5, 0.999), st.data())
def test_relations_invert(m, p, data):
    s = data.draw(st.integers(1, m // 2))
    assert theory.q_of(p, s, m) == pytest.approx((p * (s - 1) + (1 - p) * s) / (m - 1))
    eps = math.log(p * (m - s) / ((1 - p) * s))
    assert theory.p_of(s, eps, m) == pytest.approx(p)
    assert theory.s_of(p, eps, m) in (s, s + 1)


def test_parameters_that_carry_nothing_are_refused():
    with pytest.raises(ValueError):
        theory.estimate(1.0, 1.0, 0.5, 8 / 16)
    with pytest.raises(ValueError):
        SketchParams(4, 16, 9, 0.6)


@pytest.mark.parametrize("m,s,p", [(5, 2, 0.7), (6, 3, 0.6), (6, 1, 0.9), (4, 2, 0.5)])
def test_privacy_by_enumeration(m, s, p):
    sp = SketchParams(1, m, s, p)
    table = measure.subset_probabilities(sp)
    assert all(sum(v[r] for v in table.values()) == pytest.approx(1) for r in range(m))
    assert measure.empirical_eps(sp) == pytest.approx(sp.eps)
    own = sum(v[0] for x, v in table.items() if 1 in x)
    other = sum(v[0] for x, v in table.items() if 2 in x)
    assert own == pytest.approx(p) and other == pytest.approx(sp.q)
    if (m, s, p) == (5, 2, 0.7):
        assert sp.eps == pytest.approx(1.25276, abs=1e-5)


@pytest.mark.parametrize("form,k,want", [("published", 500, {0.5: 0.8723, 0.1: 0.7864, 0.02: 0.6588}), ("exact", 500, {0.5: 0.9241, 0.1: 0.8070, 0.02: 0.6674})])
def test_optimal_p_anchors(form, k, want):
    for lam, p in want.items():
        assert tune.best_p(5.0, lam, k, form) == pytest.approx(p, abs=1e-3)


@pytest.mark.parametrize("eps", [1.0, 2.0, 3.75, 5.0])
def test_closed_form_optima(eps):
    assert tune.best_p(eps, 1e-12, 1) == pytest.approx(0.5, abs=1e-4)
    assert tune.best_p(eps, 0.5, 1) == pytest.approx(math.exp(eps / 2) / (1 + math.exp(eps / 2)), abs=1e-4)
    assert tune.best_p(eps, 1.0, 1) == pytest.approx(math.exp(eps) / (1 + math.exp(eps)), abs=1e-4)


def test_published_k_moves_p_down_and_exact_does_not():
    ps = [tune.best_p(4.0, 0.1, k, "published") for k in (1, 10, 1000)]
    assert ps == pytest.approx([0.7264, 0.6982, 0.6956], abs=1e-3)
    assert len({round(tune.best_p(4.0, 0.1, k), 6) for k in (1, 10, 1000)}) == 1


def test_optimal_p_rises_with_eps_and_frequency():
    for lam in (0.01, 0.1, 0.5):
        ps = [tune.best_p(e, lam, 1) for e in (0.5, 1, 2, 3, 4, 5)]
        assert ps == sorted(ps)
    ps = [tune.best_p(4.0, lam, 1) for lam in (0.001, 0.01, 0.1, 0.5)]
    assert ps == sorted(ps) and ps[0] < 0.53


def test_census_settings():
    assert theory.eps_of(0.74, 7, 100) == pytest.approx(3.633, abs=1e-3)
    assert theory.eps_of(0.57, 3, 100) == pytest.approx(3.758, abs=1e-3)
    assert theory.split_budget(3.75, 3.75 / 2)[0] == pytest.approx(0.867, abs=1e-3)


@settings(max_examples=30, deadline=None)
@given(st.floats(0.3, 6), st.floats(0.001, 0.9), st.integers(8, 300))
def test_integer_tuning_spends_the_budget_and_is_no_worse(eps, lam, m):
    a, b = tune.tune_integer(eps, lam, 1, m), tune.tune(eps, lam, 1, m)
    assert a.eps_real == pytest.approx(eps, abs=1e-6) or a.p < 0.5
    assert b.eps_real <= eps + 1e-9 or b.s == m // 2


def test_tuned_beats_classical_at_every_target():
    for f in (1e2, 1e3, 1e4, 1e5):
        lam = f / 1e6
        p = tune.best_p(4.0, lam, 1)
        assert theory.objective(p, lam, 4.0, 1) <= theory.objective(1 / (1 + math.exp(-2)), lam, 4.0, 1) + 1e-12
    published = [math.sqrt((f * (p - p * p / 65536) + (1e6 - f) * (u - u * u / 65536)) / (p - u) ** 2) / f for f in (1e2, 1e4) for p in [tune.best_p(4.0, f / 1e6, 65536, "published")] for u in [theory.s_of(p, 4.0, 1024) / 1024]]
    assert published == pytest.approx([2.833, 0.0313], rel=2e-3)


def test_communication_anchors():
    for eps, p, m, s in ((3, 0.5, 1000, 48), (3, 0.5, 10000, 475), (5, 0.5, 1000, 7), (5, 0.5, 10000, 67), (3, 0.6, 1000, 70), (5, 0.6, 10000, 101)):
        assert theory.s_of(p, eps, m) == s
    assert theory.report_bits(1, 1000, 48)["bits_cells"] == 480 and theory.report_bits(1, 10000, 475)["bits_cells"] == 6650


def test_amplification_anchors_and_cap():
    for eps, n, want in ((1, 1e5, 0.0686), (4, 1e6, 0.1665), (5, 1e6, 0.2656)):
        assert accounting.amplify(eps, n, 1e-8) == pytest.approx(want, abs=1e-3)
    assert accounting.amplification_cap(1e5, 1e-8) == pytest.approx(6.48, abs=0.01)
    assert accounting.amplify(7.0, 1e5, 1e-8) == 7.0 and accounting.amplify(1.0, 10, 1e-8) == 1.0
    assert accounting.amplify(1, 1e6, 1e-8) < accounting.amplify(1, 1e5, 1e-8)


@given(st.floats(0.1, 10), st.floats(1e-10, 1e-3))
def test_calibration_round_trip(eps, delta):
    t, b = accounting.calibrate(eps, delta)
    e, dl = accounting.discovery_eps_delta(t, b)
    assert e == pytest.approx(eps) and dl == pytest.approx(delta)
    assert t == pytest.approx(1 - math.log(2 * delta) / eps)


def test_calibration_variants():
    assert accounting.calibrate(1, 1e-5)[0] == pytest.approx(11.82, abs=0.01)
    t1, t2 = accounting.calibrate(1, 1e-5)[0], accounting.calibrate(1, 1e-5, "replace")[0]
    assert t2 > t1 and accounting.calibrate(1, 1e-5, cap=3)[1] == pytest.approx(3)


def test_unary_budgets():
    for eps in (0.5, 2.0, 4.0):
        for p, q in (oracles.sue_pq(eps), oracles.oue_pq(eps), oracles.tuned_unary_pq(eps, 0.1)):
            assert theory.unary_eps(p, q) == pytest.approx(eps, abs=1e-6)
        p, q = oracles.direct_pq(eps, 7)
        assert math.log(p / q) == pytest.approx(eps) and p + 6 * q == pytest.approx(1)
    assert 0.5 <= oracles.best_theta(2.0) <= 1
    # one-cell subsets over the whole domain are direct encoding
    assert theory.p_of(1, 2.0, 10) == pytest.approx(oracles.direct_pq(2.0, 10)[0])


def support_runs(k, m, s, p, counts, runs, seed):
    """Honest simulation: fresh hash functions and reports every run; estimates of the items."""
    rng = np.random.default_rng(seed)
    n, item = sum(counts), np.repeat(np.arange(len(counts)), counts)
    q = (s - p) / (m - 1)
    out = np.zeros((runs, len(counts)))
    for r in range(runs):
        cells = rng.integers(0, m, (k, len(counts)))
        row = rng.integers(0, k, n)
        own = cells[row, item]
        for d in range(len(counts)):
            hit = own == cells[row, d]
            out[r, d] = (np.where(hit, rng.random(n) < p, rng.random(n) < q)).sum()
    return (out - n * s / m) / (p - s / m)


def test_variance_follows_the_exact_form():
    k, m, s, p, counts = 50, 16, 2, 0.8, (1000, 300, 100, 20)
    sp, n, moment = SketchParams(k, m, s, p), sum(counts), sum(c * c for c in counts)
    est = support_runs(k, m, s, p, counts, 1000, 1)
    for d, f in enumerate(counts):
        assert abs(est[:, d].mean() - f) < 4 * math.sqrt(theory.variance(f, n, moment, sp) / 1000)
        assert est[:, d].var() == pytest.approx(theory.variance(f, n, moment, sp), rel=0.15)
    assert theory.variance(1000, n, moment, sp, "published") > 2 * theory.variance(1000, n, moment, sp)
    one = SketchParams(1, m, s, p)
    assert theory.variance(300, n, moment, one) == pytest.approx(theory.variance(300, n, moment, one, "published"))


def test_marginal_simulator_agrees():
    sp, counts = SketchParams(8, 16, 3, 0.6), np.array([500, 200, 50, 50])
    got = simulate.draw(500, counts[1:], sp, 4000, np.random.default_rng(3))
    want = theory.variance(500, 800, int((counts**2).sum()), sp)
    assert abs(got.mean() - 500) < 4 * math.sqrt(want / 4000) and got.var() == pytest.approx(want, rel=0.12)


def test_collision_part_does_not_depend_on_p():
    random.seed(1)
    for p in (0.5, 0.7, 0.9):
        sp = SketchParams(8, 64, 5, p)
        assert theory.variance(10, 1000, 5000, sp) - theory.variance(10, 1000, 5000, sp, "limit") == pytest.approx((5000 - 100 - 990) / (8 * 63))
    assert theory.pure_variance(10, 1000, 0.5, 0.1) == pytest.approx((10 * 0.25 + 990 * 0.09) / 0.16)


def test_both_searches_agree():
    for eps in (1.0, 3.75, 5.0):
        for lam in (0.5, 0.1, 0.02):
            for k in (1, 50, 500):
                assert abs(tune.best_p_by_thirds(eps, lam, k) - tune.best_p(eps, lam, k, "published")) < 1e-6
