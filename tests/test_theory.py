import math

import pytest
from hypothesis import given
from hypothesis import strategies as st

from coverdistinct.functions import theory
from coverdistinct.operators import planner
from coverdistinct.operators.counters import max_term_likelihood

share = st.floats(0.001, 0.9)
size = st.integers(2, 10_000)


@given(share, share, size, size)
def test_variance_before_and_after_substitution(p0, p1, length, m):
    n = 10_000.0
    before = theory.var_before_substitution(n * (1 - p0), p0, p1, length, m)
    assert math.isclose(before, n * n * theory.rel_var_sampled(p0, p1, length, m), rel_tol=1e-9)
    before = theory.var_before_substitution(n * (1 - p0), p0, p1, length, m, 2.0)
    assert math.isclose(before, n * n * theory.rel_var_subsampled(p0, p1, length, m), rel_tol=1e-9)


@given(share, share, size, size)
def test_efficiency_one_is_the_plain_theorem_and_more_storage_helps(p0, p1, u, m):
    v = theory.rel_var_subsampled(p0, p1, u, m)
    assert v == theory.rel_var_subsampled(p0, p1, u, m, are=1.0)
    assert theory.rel_var_subsampled(p0, p1, u + 1, m) < v and theory.rel_var_subsampled(p0, p1, u, m + 1) < v
    assert theory.rel_var_subsampled(p0, p1, u, m, are=0.93) > v
    assert theory.rel_var_subsampled(p0, p1, u, m, l=u * 10, form="two_term") <= v


@given(share, share, st.integers(3, 400))
def test_best_split_beats_every_other(p0, p1, budget):
    m, u = planner.best_split(budget, p0, p1)
    c = planner.coefficient(p0, p1)
    assert m + u == budget and m >= 2 and u >= 1
    best = min(planner.variance(budget - x, x, c) for x in range(1, budget - 1))
    assert planner.variance(m, u, c) <= best * (1 + 1e-9)


def test_budget_reaches_its_target():
    b = planner.budget_for(0.01, 0.09, 0.08)
    m, u = planner.best_split(b, 0.09, 0.08)
    assert theory.rel_var_subsampled(0.09, 0.08, u, m) <= 0.0101


def test_constants_of_the_harmonic_mean():
    for m in (16, 32, 64):
        exact = theory.alpha(m)
        near = theory.alpha(m + 1)
        assert abs(exact - near) < 0.02
    assert abs(theory.alpha(127) - theory.alpha(128)) < 0.001


def test_product_and_delta_laws():
    assert theory.product_law(2, 0.1, 3, 0.2) == (6, pytest.approx(9 * 0.1 + 4 * 0.2))
    assert theory.product_law(2, 0.1, 3, 0.2, exact=True)[1] == pytest.approx(9 * 0.1 + 4 * 0.2 + 0.02)
    assert theory.inverse_law(0.1, 0.5) == pytest.approx(0.1 * 16)


def test_reservoir_insertions_and_storage():
    assert theory.reservoir_insertions(10, 5) == 5
    assert theory.reservoir_insertions(100, 100_000) == pytest.approx(100 * (1 + math.log(1000)))
    assert theory.storage("sampled", 100, 505_000) == 505_100 and theory.storage("subsampled", 92, u=8) == 100


def test_max_term_inversion_finds_the_expected_histogram():
    m, n = 256, 5000
    cdf = lambda k: math.exp(-(n / m) * 2.0 ** -k)
    hist = {k: m * (cdf(k) - (cdf(k - 1) if k else 0)) for k in range(40)}
    assert max_term_likelihood(hist, m) == pytest.approx(n, rel=0.02)
    assert max_term_likelihood({}, m) == 0
