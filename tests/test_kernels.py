import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from rowblock import kernels as k
from rowblock.errors import GramNotPositiveDefinite, RankDeficient


def rows(m, n, seed=0):
    return np.random.default_rng(seed).standard_normal((m, n))


@settings(max_examples=40, deadline=None)
@given(st.integers(1, 6), st.lists(st.integers(0, 9), min_size=1, max_size=6), st.integers(0, 99))
def test_any_cut_gives_the_same_triangle(n, cuts, seed):
    a = rows(n + sum(cuts), n, seed)
    r, at = None, 0
    for c in [*cuts, n]:
        if c:
            r = k.fold_r(r, a[at : at + c])
        at += c
    assert np.allclose(r, k.qr_r(a), atol=1e-11)
    assert (np.diagonal(r) >= 0).all()


def test_full_factors():
    a = rows(50, 5)
    q, r = k.qr_full(a)
    assert np.allclose(q @ r, a) and np.allclose(q.T @ q, np.eye(5)) and np.allclose(r, np.triu(r))


def test_short_and_empty_blocks():
    assert k.qr_r(rows(2, 4)).shape == (2, 4)
    assert k.qr_r(np.zeros((0, 4))).shape == (0, 4)


def test_inverse_and_solves_agree():
    r = k.qr_r(rows(30, 6))
    a = rows(10, 6, 1)
    assert np.allclose(a @ k.invert_upper(r), k.solve_right(a, r))
    assert np.allclose(r @ k.solve_upper(r, a[0]), a[0])


def test_failures_have_types():
    with pytest.raises(GramNotPositiveDefinite):
        k.cholesky_upper(np.array([[1.0, 2], [2, 1]]))
    with pytest.raises(RankDeficient):
        k.invert_upper(np.array([[1.0, 2], [0, 0]]))
