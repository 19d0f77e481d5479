"""Closed forms against exact enumeration, identities and limits."""

import itertools
from fractions import Fraction

import pytest

from binsketch.functions import theory as t

CASES = [(16, 4, 5, 2, 4), (12, 4, 4, 2, 3), (12, 3, 5, 2, 4), (12, 6, 6, 1, 4)]  # D, k, f, a, f1


def enumerated(d, k, f, a, f1):
    """The joint law of (holes, matches) over all placements; elements 0..a-1 are shared, a..f1-1 in the first set alone."""
    law, n = {}, 0
    w = d // k
    for places in itertools.combinations(range(d), f):
        # which of the sorted positions are shared: every choice is equally likely
        for shared in itertools.combinations(range(f), a):
            n += 1
            first = {}
            for i, p in enumerate(places):
                first.setdefault(p // w, i)
            key = (k - len(first), sum(i in shared for i in first.values()))
            law[key] = law.get(key, 0) + 1
    return {key: Fraction(c, n) for key, c in law.items()}


@pytest.mark.parametrize("d,k,f,a,f1", CASES)
def test_laws_are_exact(d, k, f, a, f1):
    law = enumerated(d, k, f, a, f1)
    e = lambda g: sum(p * g(j, m) for (j, m), p in law.items())
    q = t.q_exact
    fr = Fraction
    assert e(lambda j, m: j) == t.empty_mean(d, k, f, q)
    assert e(lambda j, m: j * j) - e(lambda j, m: j) ** 2 == t.empty_var(d, k, f, q)
    assert e(lambda j, m: m) == t.match_mean(d, k, f, a, q)
    assert e(lambda j, m: m * m) - e(lambda j, m: m) ** 2 == t.match_var(d, k, f, a, q)
    assert e(lambda j, m: j * m) - e(lambda j, m: j) * e(lambda j, m: m) == t.match_empty_cov(d, k, f, a, q) <= 0
    assert law == t.joint_pmf(d, k, f, a)
    assert e(lambda j, m: fr(m, k - j)) == fr(a, f)  # unbiased
    var = float(e(lambda j, m: fr(m, k - j) ** 2) - fr(a, f) ** 2)
    assert var == pytest.approx(t.unbiased_var(d, k, f, a, exact=True), abs=1e-12)
    pmf = t.empty_pmf(d, k, f)
    assert sum(pmf) == 1 and pmf[k] == 0
    assert [sum(p for (j, _), p in law.items() if j == i) for i in range(k + 1)] == pmf


def test_bounds_and_limits():
    assert t.empty_mean(1 << 16, 512, 2000) <= t.empty_mean_bound(512, 2000)
    assert t.empty_share_expanded(65536, 64, 200) == pytest.approx(t.empty_mean(65536, 64, 200) / 64, rel=1e-6)
    assert t.empty_share_sparse(100, 500) == pytest.approx(0.0067, abs=2e-4)
    assert t.inv_nonempty(16, 4, 5, exact=True) >= t.inv_nonempty(16, 4, 5)
    for f, k, g in ((2, 8, 0.533), (500, 500, 0.582), (2500, 500, 0.807), (4000, 512, 0.873), (500, 4096, 0.510)):
        assert t.variance_ratio(f, k) == pytest.approx(g, abs=1e-3)
    assert t.unbiased_var(1 << 16, 64, 1, 1) == 0 and t.variance_ratio(1, 8) == 0
    assert t.q(16, 4, 13, 1) == 0
    assert all(t.widths_gap(1024, k, f) >= -1e-9 for k in (8, 64) for f in (5, 400))
    assert t.suggest_k(5 * 128) == 128
    assert t.ragged_empty_var(64, 400) > 0


def test_simulation_agrees(spark):
    from binsketch.plans.laws import simulate

    for r in simulate(spark, 60, [256]).collect():
        n = r.n
        assert abs(r.e - r.empty_mean) <= 4 * (r.empty_var / n) ** 0.5 + 0.02
        assert abs(r.m - r.match_mean) <= 4 * (r.match_var / n) ** 0.5 + 0.02
        assert abs(r.bias) <= 4 * (r.unbiased_var / n) ** 0.5 + 1e-9
        assert r.mse <= 2.2 * r.classic_var
