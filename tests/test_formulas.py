"""Closed formulas against numbers computed by hand."""

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from ownerdp.functions.noise import rounding_step
from ownerdp.measures import best_clamp, clamp_error, normal_steps, poisson_steps
from ownerdp.operators.bounds import bounds_threshold
from ownerdp.operators.threshold import delta_for_threshold, owner_threshold, single_owner_suppression
from ownerdp.params import PrivacyParams, default_delta, epsilon_for_error, error_vs_aggs, laplace_median_error

pytestmark = pytest.mark.filterwarnings("ignore:delta")


@pytest.mark.parametrize(("eps", "delta", "c_u", "tau"), [(0.1, 6.78e-7, 1, 136.11), (0.1, 2.07e-4, 5, 470.95), (0.1, 2.07e-4, 1, 78.90), (0.1, 6.78e-7, 5, 757.02)])
def test_threshold(eps, delta, c_u, tau):
    assert owner_threshold(eps, delta, c_u) == pytest.approx(tau, abs=0.2)


@pytest.mark.parametrize(("n", "c_u", "tau", "half"), [(1500, 1, 47.55, 94.10), (1500, 5, 314.1, 627.3), (100, 1, 15.28, 29.55), (100, 5, 150.3, 299.7), (15000, 1, 86.53, 172.1), (1000, 1, 41.79, 82.57)])
def test_threshold_by_owners(n, c_u, tau, half):
    d = default_delta(n, 0.1)
    assert owner_threshold(0.1, d, c_u) == pytest.approx(tau, rel=2e-3)
    assert owner_threshold(0.05, d, c_u) == pytest.approx(half, rel=2e-3)


@pytest.mark.parametrize(("n", "delta"), [(1500, 4.756e-3), (100, 0.1199), (15000, 9.646e-5), (1000, 8.466e-3), (150, 0.0812), (10, 0.588), (150_000, 6.775e-7), (10_000, 2.07e-4)])
def test_default_delta(n, delta):
    assert default_delta(n, 0.1) == pytest.approx(delta, rel=2e-3)


def test_default_delta_warns_where_it_guarantees_nothing():
    with pytest.warns(UserWarning, match="no real guarantee"):
        default_delta(100, 0.1)


@settings(max_examples=60, deadline=None)
@given(st.floats(0.01, 5), st.floats(1e-9, 0.3), st.integers(1, 50))
def test_threshold_and_its_inverse(eps, delta, c_u):
    assert delta_for_threshold(eps, owner_threshold(eps, delta, c_u), c_u) == pytest.approx(delta, rel=1e-6)


def test_a_threshold_hides_one_owner_as_often_as_it_should():
    """A noisy count of one owner stays below tau with probability (1 - delta)^(1 / c_u)."""
    for c_u in (1, 5):
        tau = owner_threshold(0.1, 0.12, c_u)
        below = 1 - 0.5 * math.exp(-(tau - 1) * 0.1 / c_u)
        assert below == pytest.approx(single_owner_suppression(0.12, c_u), rel=1e-9)


def test_bounds_threshold():
    assert bounds_threshold(10, 1 - 1e-9) == pytest.approx(241.7, abs=0.1)
    assert bounds_threshold(1, 1 - 1e-9) == pytest.approx(24.17, abs=0.01)
    assert bounds_threshold(0.2, 1 - 1e-9) == pytest.approx(4.83, abs=0.01)


def test_published_errors_follow_from_the_formulas():
    assert laplace_median_error(373, 0.1) / 1_478_493 == pytest.approx(0.00175, rel=0.01)
    assert laplace_median_error(50_000, 0.05) / 10_000 / 38_273 == pytest.approx(0.00181, rel=0.01)
    assert 1 - 10_000 / 1_478_493 == pytest.approx(0.993, abs=1e-3)
    assert laplace_median_error(1, 0.1) / 1_478_493 == pytest.approx(4.727e-6, rel=0.01)
    assert single_owner_suppression(2.07e-4, 5) == pytest.approx(0.9999606, abs=3e-6)
    assert single_owner_suppression(2.07e-4, 1) == pytest.approx(0.999796, abs=5e-6)


def test_error_grows_with_aggregates_and_budget_inverts():
    assert error_vs_aggs(1, 0.1, 8) == pytest.approx(8 * laplace_median_error(1, 0.1))
    assert laplace_median_error(3, epsilon_for_error(3, 0.7)) == pytest.approx(0.7)


def test_shares():
    s = PrivacyParams(1.0, 1e-5, 5).split(3)
    assert s.per_aggregate == pytest.approx(1 / 20) and s.count_of_query == pytest.approx(1 / 4)
    assert PrivacyParams(1.0, c_u=5).split(2, needs_count=False).per_aggregate == pytest.approx(0.1)
    assert PrivacyParams(1.0, c_u=5).split(2, needs_count=False, has_keys=False).per_aggregate == pytest.approx(0.5)
    for bad in ({"eps": 0}, {"eps": 1, "delta": 1}, {"eps": 1, "c_u": 0}, {"eps": math.inf}):
        with pytest.raises(ValueError):
            PrivacyParams(**bad)


def test_clamping_has_an_inner_optimum():
    assert best_clamp(50, 150, 100, 0.1) == pytest.approx(140)
    sweep = {u: clamp_error(50, 150, -200, u, 100, 0.1) for u in range(51, 151)}
    assert min(sweep, key=sweep.get) == 140
    expected = {u: clamp_error(50, 150, -200, u, 100, 0.1, "expected") for u in range(51, 151)}
    assert min(expected, key=expected.get) in range(105, 114)
    assert expected[140] == pytest.approx(34.1, abs=0.3) and expected[120] == pytest.approx(32.1, abs=0.3)


def test_rounding_step_is_above_the_scale():
    assert rounding_step(10) == 16 and rounding_step(8) == 16 and rounding_step(0.3) == 0.5


def test_distributions_have_the_mean_asked_for():
    u = (np.arange(20_000) + 0.5) / 20_000
    for steps in (normal_steps(100.0, 25.0, 300), poisson_steps(100.0, 300)):
        n = np.searchsorted(steps, u)
        assert n.mean() == pytest.approx(100, abs=0.1)
    assert np.searchsorted(poisson_steps(100.0, 300), u).std() == pytest.approx(10, abs=0.05)
