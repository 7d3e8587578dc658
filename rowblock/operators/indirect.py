"""Q from R: the indirect methods, their refinement, and products with small matrices."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..blocks import map_rows
from ..errors import FactorizationError
from ..kernels import invert_upper, solve_right
from ..matrix import NarrowMatrix
from . import gram as g
from . import rtree


def multiply_small(nm: NarrowMatrix, m: np.ndarray, prefix: str = "q") -> DataFrame:
    """A times a small matrix: a map-only pass, the small matrix goes with the tasks."""
    return map_rows(nm, lambda rows: rows @ m, m.shape[1], prefix)


def apply_r_inverse(nm: NarrowMatrix, r: np.ndarray, how: str = "inverse") -> DataFrame:
    """Q = A inverse(R), by the explicit inverse, by substitution, or by a projection in generated code (n <= 12)."""
    if how == "inverse":
        return multiply_small(nm, invert_upper(r))
    if how == "solve":
        return map_rows(nm, lambda rows: solve_right(rows, r), nm.n)
    if how == "sql":
        if nm.n > g.SQL_WIDEST:
            raise FactorizationError(f"projections are meant for at most {g.SQL_WIDEST} columns")
        w, inverse = nm.wide(), invert_upper(r)
        product = lambda j: sum((F.col(w.cols[i]) * F.lit(float(inverse[i, j])) for i in range(1, j + 1)), F.col(w.cols[0]) * F.lit(float(inverse[0, j])))
        return w.df.select(*w.keys, *(product(j).alias(f"q{j}") for j in range(w.n)))
    raise FactorizationError(f"no way {how!r}")


def as_matrix(q: DataFrame, nm: NarrowMatrix) -> NarrowMatrix:
    """A computed Q as a matrix again."""
    return NarrowMatrix(q, nm.keys, tuple(c for c in q.columns if c not in nm.keys), None, nm.n, nm.on_bad_row, vars(q).get("made_from"))


def first_r(nm: NarrowMatrix, method: str, **how) -> np.ndarray:
    """R by Gram and Cholesky, or by the tree."""
    if method == "cholesky":
        return g.cholesky_r(g.to_numpy(g.gram(nm, **how), nm.n))
    if method == "rtree":
        return rtree.r_factor(nm, **how)
    raise FactorizationError(f"no indirect method {method!r}")


def refine(nm: NarrowMatrix, method: str, steps: int = 1, fused: bool = True, stage=None, **how) -> tuple[DataFrame, np.ndarray]:
    """Q and R after factoring the computed Q again, steps times.

    Fused, no intermediate Q is written: each pass replays the small inverses on the rows of A, one after the other.
    """
    factors = [first_r(nm, method, **how)]
    if fused:
        chain: list[np.ndarray] = [invert_upper(factors[0])]
        for _ in range(steps):
            now = as_matrix(_replay(nm, list(chain)), nm)
            factors.append(first_r(now, method, **how))
            chain.append(invert_upper(factors[-1]))
        q = _replay(nm, list(chain))
    else:
        q = apply_r_inverse(nm, factors[0])
        for k in range(steps):
            now = as_matrix(stage.write(q, f"q{k}"), nm)
            factors.append(first_r(now, method, **how))
            q = apply_r_inverse(now, factors[-1])
    r = factors[0]
    for f in factors[1:]:
        r = f @ r
    return q, np.triu(r)


def _replay(nm: NarrowMatrix, chain: list[np.ndarray]) -> DataFrame:
    def kernel(rows: np.ndarray) -> np.ndarray:
        for m in chain:
            rows = rows @ m
        return rows

    return map_rows(nm, kernel, nm.n)
