import math

import numpy as np
import pytest
from hypothesis import given, settings, strategies as st

from densegrid.functions import geometry as g


@pytest.mark.parametrize("d,r,box,reachable", [(1, 1, 3, 2), (2, 2, 25, 20), (3, 2, 125, 116), (4, 2, 625, 608), (5, 3, 16807, 3902), (6, 3, 117649, 28196), (7, 3, 823543, 197066)])
def test_counts(d, r, box, reachable):
    assert (g.reach(d), g.box_offset_count(d), g.reachable_offset_count(d)) == (r, box, reachable)


@pytest.mark.parametrize("d,box,reachable", [(10, 3.487e9, 5.282e7), (20, 6.727e20, 1.207e16), (40, 1.106e47, 8.270e32), (54, 2.781e66, 5.522e44)])
def test_large_counts(d, box, reachable):
    assert g.box_offset_count(d) == pytest.approx(box, rel=1e-3)
    assert g.reachable_offset_count(d) == pytest.approx(reachable, rel=1e-3)


@settings(max_examples=300, deadline=None)
@given(st.integers(1, 9), st.integers(0, 2**32 - 1))
def test_no_pair_within_eps_is_out_of_reach(d, seed):
    rng = np.random.default_rng(seed)
    eps = float(rng.choice([1.0, 2.0, 3.7, 150.0]))
    a = rng.integers(-50, 50, d) if seed % 2 else rng.normal(0, 5 * eps, d)
    step = rng.normal(size=d)
    b = a + step / np.linalg.norm(step) * eps * rng.choice([1.0, 0.999, 0.3])
    if seed % 3 == 0:  # ties along an axis
        b = a.astype(float)
        b[rng.integers(d)] += eps
    if ((a - b) ** 2).sum() > eps * eps:
        return
    c = g.cell_scale(d, eps)
    delta = np.abs(np.floor(a * c) - np.floor(b * c))
    assert delta.max() <= g.safe_reach(d)
    assert (np.maximum(delta - 1, 0) ** 2).sum() <= d


def test_eps2_keeps_ties():
    assert g.eps2(10, True) == 100 and g.eps2(math.sqrt(50), True) == 50
