"""Pivots that are only rounding: whether they come out above zero depends on the order of sums."""

import numpy as np
import pytest

from rowblock.errors import GramNotPositiveDefinite
from rowblock.kernels import cholesky_upper


def test_a_pivot_within_rounding_is_no_pivot():
    gram = np.array([[1.0, 1.0], [1.0, 1.0 + 2e-16]])
    assert gram[1, 1] > 1
    with pytest.raises(GramNotPositiveDefinite):
        cholesky_upper(gram)


def test_badly_scaled_columns_are_fine():
    assert np.allclose(np.diagonal(cholesky_upper(np.diag([1e20, 1.0, 1e-20]))), [1e10, 1, 1e-10])
