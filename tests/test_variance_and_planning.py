"""Variance formulas against simulation and enumeration; planning rules."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from tuplestat.plans import montecarlo as MC, planner as P, variance as V

EPS = (0.5, 0.2, 0.1, 0.05, 0.02, 0.01)
#: Relative variance of one and of four rounds, n = 5000, m = 50, ten workers.
TARGETS = {0.5: (1.0018, 1.0004), 0.2: (1.0071, 1.0018), 0.1: (1.0160, 1.0040), 0.05: (1.0337, 1.0084), 0.02: (1.0865, 1.0216), 0.01: (1.1730, 1.0433), 0.001: (2.4864, 1.3716)}


@pytest.mark.parametrize("eps", TARGETS)
def test_reference_values(eps):
    c = V.epsilon_law(eps)
    vn = V.var_complete(c, 5000, 50)
    assert V.var_local(c, 5000, 50, 10) / vn == pytest.approx(TARGETS[eps][0], abs=6e-5)
    assert V.var_repartitioned(c, 5000, 50, 10, 4) / vn == pytest.approx(TARGETS[eps][1], abs=6e-5)


def test_large_configuration():
    for v2, want in ((0.001, (1.818, 1.409, 1.164, 1.082, 1.033, 1.008)), (0.1, (1.0099, 1.0049, 1.0020, 1.0010, 1.0004, 1.0001))):
        c = V.Components(0.1, v2, 1.0)
        vn = V.var_complete(c, 100_000, 200)
        for t, w in zip((1, 2, 5, 10, 25, 100), want):
            assert V.var_repartitioned(c, 100_000, 200, 100, t) / vn == pytest.approx(w, abs=6e-4)


def test_discrete_law_by_enumeration():
    for eps in EPS:
        c = V.epsilon_law(eps)
        x, wx = np.array([2.0, 0.0]), np.array([1 - eps, eps])
        z, wz = np.array([1.0, -1.0]), np.array([eps, 1 - eps])
        h = (z[None] < x[:, None]).astype(float)
        u = wx @ h @ wz
        assert u == pytest.approx(1 - eps * eps)
        assert (wx @ (h @ wz - u) ** 2, wz @ (wx @ h - u) ** 2) == (pytest.approx(c.v1), pytest.approx(c.v2))
        assert u * (1 - u) == pytest.approx(c.v)
        assert c.v0 / (c.v1 + c.v2) == pytest.approx((1 - eps) / (2 * eps))


def test_empty_worker_probability():
    assert V.swor_empty_probability(5000, 50, 10) == pytest.approx(0.00502, abs=1e-5)
    assert V.swor_empty_probability(5000, 50, 10, False) == pytest.approx(0.00515, abs=1e-5)
    assert V.swor_empty_probability(100_000, 200, 100) == pytest.approx(0.1337, abs=1e-4)
    assert V.swor_bias(0.8, 100_000, 200, 100) == pytest.approx(-0.8 * 0.1337, abs=1e-4)
    assert V.swor_numeric(V.epsilon_law(0.1), 5000, 50, 10) >= V.var_complete(V.epsilon_law(0.1), 5000, 50)


def test_dominance_at_equal_pairs():
    rng = np.random.default_rng(1)
    for _ in range(3000):
        n, m = rng.integers(10, 5000, 2)
        w = int(rng.integers(1, min(n, m) + 1))
        c = V.Components(*rng.random(3))
        b, t0 = int(rng.integers(1, 200)), int(rng.integers(1, 6))
        if V.equal_budget(n, m, w, t0, b) >= 1:
            assert V.dominance_gap(c, n, m, w, t0, b) >= -1e-12


def test_components_are_unbiased(spark):
    rng = np.random.default_rng(2)
    x, z = rng.normal(size=30), rng.normal(size=12)
    h = (z[None] < x[:, None]).astype(float)
    u, r, c = h.mean(), h.mean(1), h.mean(0)
    ms0 = ((h - r[:, None] - c[None] + u) ** 2).sum() / (29 * 11)
    rows = [(float(a), True) for a in x] + [(float(a), False) for a in z]
    got = V.auc_components(spark.createDataFrame(rows, "s double, f boolean"), F.col("s"), F.col("f")).first()
    assert got.v0 == pytest.approx(ms0)
    assert got.v1 == pytest.approx((12 * ((r - u) ** 2).sum() / 29 - ms0) / 12)
    assert got.v2 == pytest.approx((30 * ((c - u) ** 2).sum() / 11 - ms0) / 30)


def test_conditional_variance_is_exact():
    rng = np.random.default_rng(3)
    x, z = rng.normal(size=24), rng.normal(size=12)
    h = (z[None] < x[:, None]).astype(float)
    u, r, c = h.mean(), h.mean(1), h.mean(0)
    ms0 = ((h - r[:, None] - c[None] + u) ** 2).sum() / (23 * 11)
    got = [MC.one_run(x, z, 4, 1, 5, "prop_swor", np.random.default_rng([1, k]))["local"] for k in range(4000)]
    assert np.mean(got) == pytest.approx(u, abs=4 * np.std(got) / 63)
    assert np.var(got) == pytest.approx(V.conditional_variance(ms0, 24, 12, 4, 1), rel=0.12)


def test_monte_carlo_follows_theory(spark):
    n, m, w, t, b = 400, 40, 8, 3, 40
    runs = MC.law_runs(spark, 1500, n, m, (0.2,), w, t, b)
    got = {r.estimator: r for r in MC.mc_summary(runs, ("eps", "estimator"), {0.2: 0.96}).collect()}
    c = V.epsilon_law(0.2)
    want = {
        "complete": V.var_complete(c, n, m),
        "incomplete": V.var_incomplete(c, n, m, w * b),
        "local": V.var_local(c, n, m, w),
        "local_incomplete": V.var_local_incomplete(c, n, m, w, b),
        "repartitioned": V.var_repartitioned(c, n, m, w, t),
        "repartitioned_incomplete": V.var_repartitioned_incomplete(c, n, m, w, t, b),
    }
    for name, v in want.items():
        assert got[name].variance == pytest.approx(v, rel=0.2), name
        assert abs(got[name].bias) < 5 * (v / 1500) ** 0.5
    assert got["complete"].variance < got["repartitioned"].variance < got["local"].variance


def test_draws_with_replacement_follow_their_formula(spark):
    n, m, w, t = 60, 24, 4, 2
    runs = MC.law_runs(spark, 3000, n, m, (0.3,), w, t, 10, "prop_swr")
    got = MC.mc_summary(runs.where("estimator = 'repartitioned'"), ("eps",)).first().variance
    assert got == pytest.approx(V.var_prop_swr(V.epsilon_law(0.3), n, m, w, t), rel=0.15)


def test_planner():
    c = V.Components(0.1, 0.001, 1.0)
    t = P.rounds_for(c, 100_000, 200, 100, 1.05)
    vn = V.var_complete(c, 100_000, 200)
    assert V.var_repartitioned(c, 100_000, 200, 100, t) <= 1.05 * vn < V.var_repartitioned(c, 100_000, 200, 100, t - 1)
    assert P.diagnose(c, 100_000, 200, 100)[0] == "shuffle"
    assert P.diagnose(V.Components(0.1, 0.1, 1.0), 100_000, 200, 100)[0] == "minority_limited"
    assert P.pairs("complete", 5000, 50) == 250_000 and P.pairs("local", 5000, 50, 10) == 25_000
    assert P.pairs("repartitioned", 100_000, 200, 100, 10) == 2_000_000
    assert P.best_under_budget(c, 100_000, 200, 100, 500_000, 10**6)[:2] == (2, 0)
    t, b, v = P.best_under_budget(c, 100_000, 200, 100, 50_000, 10**6)
    assert b * t * 100 <= 50_000 and v > 0
    assert P.choose_plan(True, 10**12, 1000, 10, 4)["execution"] == "no_shuffle"
    assert P.choose_plan(True, 10**12, 10**12, 10**4, 4)["execution"] == "iterative"
    assert P.choose_plan(False, 10**12, 10**12, 10**4, 4)["form"] == "draws"
    with pytest.raises(ValueError):
        P.rounds_for(c, 10, 10, 2, 1.0)


def test_degeneracy_and_rates():
    assert V.is_degenerate(V.Components(0, 0, 1.0)) and not V.is_degenerate(V.Components(1.0, 1.0, 1.0))
    r = V.rate_table(10**6, (1, 1))
    assert r["sampled_tuples"] < r["subsampled_rows"]
