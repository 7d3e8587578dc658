"""Singular values and vectors, least squares and principal components, from the small R."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..kernels import solve_upper
from ..matrix import NarrowMatrix
from ..staging import Stage
from . import direct as d
from . import rtree
from .indirect import as_matrix, multiply_small


@dataclass
class SVDResult:
    """A = U diag(sigma) V'; u is a lazy frame or None; columns of V have a positive entry of largest size."""

    u: DataFrame | None
    sigma: np.ndarray
    v: np.ndarray


def _oriented(u: np.ndarray, vt: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    flip = np.sign(vt[np.arange(len(vt)), np.abs(vt).argmax(axis=1)])
    flip[flip == 0] = 1
    return u * flip, vt * flip[:, None]


def singular_values(nm: NarrowMatrix) -> np.ndarray:
    return np.linalg.svd(rtree.r_factor(nm), compute_uv=False)


def condition_number(nm: NarrowMatrix) -> float:
    s = singular_values(nm)
    return float(s[0] / s[-1]) if s[-1] > 0 else float("inf")


def numerical_rank(nm: NarrowMatrix, tolerance: float = 1e-12) -> int:
    s = singular_values(nm)
    return int((s > tolerance * s[0]).sum()) if len(s) and s[0] > 0 else 0


def svd(nm: NarrowMatrix, k: int | None = None, left: bool = True, keep_q: bool = False, n_blocks: int | None = None, block_rows: int | None = None, stage: Stage | None = None) -> SVDResult:
    """Without left vectors one pass over A. With them the passes of the direct method: U of the small R is folded into the slices;
    keep_q instead makes Q first and multiplies it afterwards."""
    if not left:
        _, s, vt = np.linalg.svd(rtree.r_factor(nm))
        _, vt = _oriented(np.eye(len(vt)), vt)
        return SVDResult(None, s[:k], vt[:k].T)
    stage = stage or Stage(nm.df.sparkSession)
    table = stage.write(d.direct_local(nm, n_blocks, block_rows), "svd_blocks")
    rs = d.triangles(table)
    count = rs.count()
    size = d.gather_bytes(count, nm.n)
    slices, r = d.combine_on_driver(rs, nm.n) if size <= d.STACK_BYTES else d.combine_recursively(rs, nm.n, count, max(2, d.STACK_BYTES // (8 * nm.n**2)), stage)
    u, s, vt = np.linalg.svd(r)
    u, vt = _oriented(u, vt)
    how = "broadcast" if size <= d.BROADCAST_BYTES else "join"
    if keep_q:
        q = as_matrix(d.direct_apply(table, slices, nm.n, how), nm)
        return SVDResult(multiply_small(q, u[:, :k], "u"), s[:k], vt[:k].T)
    out = d.direct_apply(table, slices, nm.n, how, u[:, :k])
    return SVDResult(out.withColumnsRenamed({f"q{i}": f"u{i}" for i in range(len(s[:k]))}), s[:k], vt[:k].T)


def least_squares(nm: NarrowMatrix, target_col: str | None = None) -> tuple[np.ndarray, float]:
    """Coefficients of the last column (or the named one) on the others, and the residual's norm, from the R of [A b]."""
    if target_col is not None:
        w = nm.wide()
        cols = tuple(c for c in w.cols if c != target_col) + (target_col,)
        nm = NarrowMatrix(w.df.select(*w.keys, *cols), w.keys, cols, None, w.n, w.on_bad_row)
    r = rtree.r_factor(nm)
    k = nm.n - 1
    return solve_upper(r[:k, :k], r[:k, k]), float(abs(r[k, k])) if len(r) > k else 0.0


def pca(nm: NarrowMatrix, k: int | None = None) -> tuple[np.ndarray, np.ndarray]:
    """Variances and directions (columns) of the centred matrix, in one pass: the R of [1 A] without its first row and column."""
    r = rtree.r_factor(nm.with_intercept())
    count = round(float(r[0, 0] ** 2))
    _, s, vt = np.linalg.svd(r[1:, 1:])
    _, vt = _oriented(np.eye(len(vt)), vt)
    return (s**2 / (count - 1))[:k], vt[:k].T


def leverage_scores(q: DataFrame, keys: tuple[str, ...]) -> DataFrame:
    """(key columns, leverage): squared norms of the rows of Q."""
    return q.select(*keys, sum((F.col(c) * F.col(c) for c in q.columns if c not in keys), F.lit(0.0)).alias("leverage"))
