import math

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from innersearch.functions import chisq
from innersearch.operators import costmodel, ringindex, signcells
from innersearch.operators.baselines import shell_lsh


@pytest.mark.parametrize(
    "m, values",
    [
        (3, (1.423652, 2.365974, 3.664871, 6.251389)),
        (4, (2.194698, 3.356694, 4.878433, 7.779440)),
        (6, (3.827552, 5.348121, 7.231135, 10.644641)),
        (8, (5.527422, 7.344121, 9.524458, 13.361566)),
        (10, (7.267218, 9.341818, 11.780723, 15.987179)),
    ],
)
def test_quantiles(m, values):
    assert [round(chisq.quantile(m, p), 6) for p in (0.3, 0.5, 0.7, 0.9)] == list(values)


@given(st.integers(1, 20), st.floats(0.01, 0.99))
@settings(max_examples=60, deadline=None)
def test_quantile_inverts_cdf(m, p):
    assert chisq.cdf(m, chisq.quantile(m, p)) == pytest.approx(p, abs=1e-9)


@given(st.floats(0.01, 40))
@settings(max_examples=40, deadline=None)
def test_closed_form_for_two_degrees(x):
    assert chisq.cdf(2, x) == pytest.approx(1 - math.exp(-x / 2), abs=1e-12)


@pytest.mark.parametrize("n, m", [(17770, 6), (624961, 8), (31420, 6), (11164866, 10), (500, 3), (1000, 4), (2000, 4), (10000, 5), (10**6, 8), (10**8, 11), (10**9, 13), (4 * 10**11, 17)])
def test_best_dimension(n, m):
    assert signcells.best_dimension(n) == m


def test_selectivity_and_params():
    assert ringindex.selectivity(5, 40, 10) == pytest.approx(1 / 2000)
    k_p, n_key, k_sp = ringindex.params_for(2_000_000, 1000)
    assert 1000 <= k_p * n_key * k_sp <= 4000


def test_collision_width():
    assert round(shell_lsh.width(2.0), 3) == 2.719
    assert shell_lsh.params(10_000)["threshold"] <= shell_lsh.params(10_000)["functions"]


def test_cost_model_is_convex_in_m():
    costs = [costmodel.probe_cost(17770, m) for m in range(1, 20)]
    at = costs.index(min(costs))
    assert all(a > b for a, b in zip(costs[:at], costs[1 : at + 1], strict=True)) and all(a < b for a, b in zip(costs[at:], costs[at + 1 :], strict=False))
