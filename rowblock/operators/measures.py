"""How good a factorization is: residual and loss of orthogonality."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..blocks import map_rows
from ..kernels import spectral_norm
from ..matrix import NarrowMatrix
from . import gram as g
from . import rtree


def orthogonality(q: NarrowMatrix, norm: str = "2") -> float:
    """Norm of Q'Q - I."""
    off = g.to_numpy(g.gram(q, "entry_sym"), q.n) - np.eye(q.n)
    return spectral_norm(off) if norm == "2" else float(np.linalg.norm(off))


def difference(nm: NarrowMatrix, q: DataFrame, r: np.ndarray) -> NarrowMatrix:
    """A - QR by row key. Keys have to be distinct."""
    a = nm.df.select(*nm.keys, nm.values().alias("a"))
    right = q.select(*(F.col(k).alias(f"of_{k}") for k in nm.keys), F.array(*(c for c in q.columns if c not in nm.keys)).alias("q"))
    cond = [F.col(k).eqNullSafe(F.col(f"of_{k}")) for k in nm.keys]
    both = a.join(right, cond).select(*nm.keys, F.concat("a", "q").alias("aq"))
    n = nm.n
    joined = NarrowMatrix(both, nm.keys, (), "aq", 2 * n, nm.on_bad_row)
    error = map_rows(joined, lambda rows: rows[:, :n] - rows[:, n:] @ r, n, "e")
    return NarrowMatrix(error, nm.keys, tuple(f"e{i}" for i in range(n)), None, n, made=vars(error).get("made_from"))


def residual(nm: NarrowMatrix, q: DataFrame, r: np.ndarray, norm: str = "2") -> float:
    """Norm of A - QR over that of R; the error is reduced to a triangle first, so nothing is squared."""
    e = rtree.r_factor(difference(nm, q, r))
    return spectral_norm(e) / spectral_norm(r) if norm == "2" else float(np.linalg.norm(e) / np.linalg.norm(r))


def unmatched_rows(nm: NarrowMatrix, q: DataFrame) -> int:
    """Rows of A without a row of Q, and the other way round: none in a right result."""
    a, b = nm.df.select(*nm.keys), q.select(*nm.keys)
    return a.exceptAll(b).count() + b.exceptAll(a).count()
