import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from multiscale_scatter.functions import geometry as G
from multiscale_scatter.queries.geometry_queries import DENSITY_CASES

KNOWN = [1.0, 2.0, 10 / 7, 10 / 31, 10 / 7, 1.0416666667]


@pytest.mark.parametrize("case,theta", list(zip(DENSITY_CASES, KNOWN)))
def test_density_theta(case, theta):
    assert G.density_theta_exact(*case) == pytest.approx(theta, abs=1e-9)
    assert G.density_theta(*case) == pytest.approx(theta, abs=1e-9)
    assert G.viewport_capacity(G.density_theta_exact(*case) * (1 + 1e-12), *case[:4]) <= case[4]


@settings(max_examples=60, deadline=None)
@given(st.integers(50, 2000), st.integers(50, 2000), st.integers(5, 300), st.integers(5, 300), st.integers(1, 500))
def test_breakpoints_equal_bisection(wv, hv, wb, hb, cap):
    assert G.density_theta_exact(wv, hv, wb, hb, cap) == pytest.approx(G.density_theta(wv, hv, wb, hb, cap), rel=1e-9)


def test_no_bound_at_zero():
    with pytest.raises(ValueError):
        G.viewport_capacity(0, 10, 10, 1, 1)
    assert G.effective_theta(None, 0.3) == 0.3
    assert G.effective_theta(1.0, 0.3) == 1.0
