"""Small dense work of one task, in NumPy. Every R here has a non-negative diagonal."""

from __future__ import annotations

import numpy as np

from .errors import GramNotPositiveDefinite, RankDeficient

EPS = float(np.finfo(np.float64).eps)


def signs(r: np.ndarray) -> np.ndarray:
    """-1 for rows of R whose diagonal is negative, else 1."""
    return np.where(np.diagonal(r)[: r.shape[0]] < 0, -1.0, 1.0)


def qr_r(block: np.ndarray) -> np.ndarray:
    """R of a block with min(rows, columns) rows."""
    if not len(block):
        return np.zeros((0, block.shape[1]))
    r = np.linalg.qr(block, mode="r")
    return signs(r)[:, None] * r + 0.0


def qr_full(block: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Thin Q and R of a block."""
    q, r = np.linalg.qr(block, mode="reduced")
    s = signs(r)
    return q * s, s[:, None] * r + 0.0


def fold_r(r: np.ndarray | None, chunk: np.ndarray) -> np.ndarray:
    """R of what r stands for with a chunk's rows below it: memory for one chunk and one triangle."""
    return qr_r(chunk if r is None or not len(r) else np.vstack([r, chunk]))


def cholesky_upper(gram: np.ndarray) -> np.ndarray:
    """Upper triangular R with R'R = gram. A pivot that is within the rounding of its column's squared norm is noise and counts as none."""
    try:
        r = np.linalg.cholesky(gram).T
    except np.linalg.LinAlgError as e:
        raise GramNotPositiveDefinite(str(e)) from e
    if not np.isfinite(r).all():
        raise GramNotPositiveDefinite("not finite")
    if (np.diagonal(r) ** 2 <= len(r) * EPS * np.diagonal(gram)).any():
        raise GramNotPositiveDefinite("a pivot is within rounding")
    return r


def check_invertible(r: np.ndarray) -> None:
    d = np.abs(np.diagonal(r))
    if len(d) < r.shape[1] or not len(d) or d.min() <= r.shape[1] * EPS * d.max():
        raise RankDeficient(f"diagonal of R from {d.min() if len(d) else 0:.3g} to {d.max() if len(d) else 0:.3g}")


def invert_upper(r: np.ndarray) -> np.ndarray:
    """Inverse of an upper triangle, column by column."""
    check_invertible(r)
    n = len(r)
    out = np.zeros_like(r)
    for j in range(n):
        out[j, j] = 1 / r[j, j]
        for i in range(j - 1, -1, -1):
            out[i, j] = -(r[i, i + 1 : j + 1] @ out[i + 1 : j + 1, j]) / r[i, i]
    return out


def solve_right(block: np.ndarray, r: np.ndarray) -> np.ndarray:
    """X with X R = block, by substitution over columns."""
    check_invertible(r)
    x = np.empty_like(block)
    for j in range(r.shape[1]):
        x[:, j] = (block[:, j] - x[:, :j] @ r[:j, j]) / r[j, j]
    return x


def solve_upper(r: np.ndarray, b: np.ndarray) -> np.ndarray:
    """x with R x = b."""
    check_invertible(r)
    x = np.zeros(r.shape[1])
    for i in range(r.shape[1] - 1, -1, -1):
        x[i] = (b[i] - r[i, i + 1 :] @ x[i + 1 :]) / r[i, i]
    return x


def spectral_norm(m: np.ndarray) -> float:
    return float(np.linalg.norm(m, 2)) if m.size else 0.0
