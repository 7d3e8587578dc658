"""Column-by-column Householder QR over the whole matrix: stable, and slow, for comparison.

Reflector j is H = I - beta v v' with v zero in the rows of earlier pivots, the column's current value elsewhere, and
changed in the pivot row j. Pivot rows are the first n rows in key order.

Forms: ``three_pass`` (norm, products and update as jobs of their own, A rewritten each time), ``two_pass`` (the norm of the
next column comes with the update), and ``one_pass``, which rewrites nothing: the norm is one of the n products, and as a row's
entry of v is its own current value, a row can replay all earlier updates from their small vectors.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..blocks import map_blocks, to_matrix
from ..errors import FactorizationError, TooFewRows
from ..kernels import signs
from ..matrix import NarrowMatrix
from ..staging import Stage


@dataclass
class Reflectors:
    """What is kept of a factorization: the vectors w = beta v'A of the updates, pivot rows and passes."""

    n: int
    updates: list[np.ndarray] = field(default_factory=list)
    betas: list[float] = field(default_factory=list)
    tops: list[float] = field(default_factory=list)
    pivots: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))
    pivot_keys: list = field(default_factory=list)
    r: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))
    passes: int = 0
    seconds: list[float] = field(default_factory=list)


def replay(rows: np.ndarray, updates: list[np.ndarray]) -> np.ndarray:
    """Rows that are no pivots after the given updates."""
    rows = rows.copy()
    for j, w in enumerate(updates):
        rows -= rows[:, j : j + 1] * w
    return rows


def _products(nm: NarrowMatrix, updates: list[np.ndarray], j: int) -> np.ndarray:
    """Sums of a_ij a_ik over all rows, as if none were a pivot."""
    n = nm.n

    def kernel(blocks: Iterator[np.ndarray]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(n)
        for block in blocks:
            now = replay(block, updates)
            total += now[:, j] @ now
        yield pa.RecordBatch.from_arrays([pa.array(range(n), pa.int32()), pa.array(total)], names=["k", "s"])

    out = np.zeros(n)
    for row in map_blocks(nm, kernel, "k int, s double").groupBy("k").agg(F.sum("s").alias("s")).collect():
        out[row["k"]] = row["s"]
    return out


def first_rows(nm: NarrowMatrix) -> tuple[list, np.ndarray]:
    """Keys and values of the n pivot rows."""
    rows = nm.df.select(F.struct(*nm.keys).alias("k"), nm.values().alias("a")).orderBy("k", "a").limit(nm.n).collect()
    if len(rows) < nm.n:
        raise TooFewRows(f"{len(rows)} rows, {nm.n} columns")
    return [r["k"] for r in rows], np.array([r["a"] for r in rows], dtype=float)


def _reflect(state: Reflectors, pivots: np.ndarray, plain: np.ndarray, products: np.ndarray, j: int) -> None:
    """One step on the driver: what the pivot rows add is put right, then w, beta and the pivot rows are updated."""
    n = state.n
    sums = products - plain[:, j] @ plain + pivots[j:, j] @ pivots[j:]
    norm = float(np.sqrt(max(sums[j], 0.0)))
    top = pivots[j, j]
    alpha = -np.copysign(norm, top)
    head = top - alpha
    vv = sums[j] - top * top + head * head
    va = sums + (head - top) * pivots[j]
    beta = 2 / vv if vv > 0 else 0.0
    w = beta * va
    w[:j] = 0.0
    state.updates.append(w)
    state.betas.append(beta)
    state.tops.append(head)
    plain -= plain[:, j : j + 1].copy() * w
    below = pivots[j + 1 :, j : j + 1].copy()
    pivots[j] -= head * w
    pivots[j + 1 :] -= below * w
    pivots[j, :j] = 0.0
    assert pivots.shape == (n, n)


def factor(nm: NarrowMatrix, form: str = "one_pass", max_columns: int | None = None, stage: Stage | None = None) -> Reflectors:
    """R and the reflectors; with max_columns, only the first steps, for extrapolating their time."""
    if form not in ("one_pass", "two_pass", "three_pass"):
        raise FactorizationError(f"no form {form!r}")
    state = Reflectors(nm.n)
    state.pivot_keys, state.pivots = first_rows(nm)
    now, plain = state.pivots.copy(), state.pivots.copy()
    steps = min(nm.n, max_columns or nm.n)
    if form == "one_pass":
        for j in range(steps):
            began = time.perf_counter()
            _reflect(state, now, plain, _products(nm, state.updates, j), j)
            state.passes += 1
            state.seconds.append(time.perf_counter() - began)
    else:
        _rewriting(nm, form, state, now, plain, steps, stage)
    r = np.triu(now)
    state.r = signs(r)[:, None] * r + 0.0 if steps == nm.n else r
    return state


def _rewriting(nm: NarrowMatrix, form: str, state: Reflectors, now: np.ndarray, plain: np.ndarray, steps: int, stage: Stage | None) -> None:
    """Forms that write the updated A in every step."""
    stage = stage or Stage(nm.df.sparkSession)
    a = nm.array().df.select("a")
    norm = None
    for j in range(steps):
        began = time.perf_counter()
        if norm is None:
            norm = a.agg(F.sum(F.pow(F.get("a", j), 2)).alias("s")).first()["s"]
            state.passes += 1
        sums = np.array(a.agg(*(F.sum(F.get("a", j) * F.get("a", k)).alias(f"s{k}") for k in range(nm.n))).first(), dtype=float)
        sums[j] = norm
        state.passes += 1
        _reflect(state, now, plain, sums, j)
        w = F.array(*(F.lit(float(x)) for x in state.updates[-1]))
        changed = a.select(F.zip_with("a", w, lambda x, y: x - F.get("a", j) * y).alias("a"))
        norm = None
        if form == "two_pass" and j + 1 < nm.n:
            from pyspark.sql import Observation

            seen = Observation(f"next{j}")
            a = stage.write(changed.observe(seen, F.sum(F.pow(F.get("a", j + 1), 2)).alias("s")), f"a{j + 1}")
            norm = seen.get["s"]
        else:
            a = stage.write(changed, f"a{j + 1}")
        state.passes += 1
        state.seconds.append(time.perf_counter() - began)


def q_factor(nm: NarrowMatrix, state: Reflectors) -> DataFrame:
    """Q from the reflectors: E - V (T V_top'), with T from the Gram matrix of V. Keys have to be distinct."""
    n, updates, tops = nm.n, state.updates, state.tops

    def entries(rows: np.ndarray, pivot: np.ndarray) -> np.ndarray:
        """Rows of V."""
        rows, out = rows.copy(), np.zeros_like(rows)
        for j, w in enumerate(updates):
            v = np.where(pivot == j, tops[j], np.where((pivot >= 0) & (pivot < j), 0.0, rows[:, j]))
            out[:, j] = v
            rows -= v[:, None] * w
        return out

    keys = list(nm.keys)
    marks = nm.df.sparkSession.createDataFrame([(*k, i) for i, k in enumerate(state.pivot_keys)], nm.df.select(*keys).schema.add("pivot", "integer"))
    cond = [nm.df[k].eqNullSafe(marks[k]) for k in keys]
    marked = nm.df.select(*keys, nm.values().alias("a")).join(F.broadcast(marks), cond, "left").select(*(nm.df[k] for k in keys), "a", F.coalesce("pivot", F.lit(-1)).alias("pivot"))  # n marks
    policy, k = nm.on_bad_row, len(keys)

    def task_gram(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        g = np.zeros((n, n))
        for b in batches:
            v = entries(to_matrix(b.column(k), n, policy)[0], b.column(k + 1).to_numpy())
            g += v.T @ v
        i, j = (x.ravel() for x in np.indices((n, n)))
        yield pa.RecordBatch.from_arrays([pa.array(i, pa.int32()), pa.array(j, pa.int32()), pa.array(g.ravel())], names=["i", "j", "v"])

    vtv = np.zeros((n, n))
    for row in marked.mapInArrow(task_gram, "i int, j int, v double").groupBy("i", "j").agg(F.sum("v").alias("v")).collect():
        vtv[row["i"], row["j"]] = row["v"]
    t = np.zeros((n, n))
    for j, beta in enumerate(state.betas):
        t[j, j] = beta
        t[:j, j] = -beta * t[:j, :j] @ vtv[:j, j]
    top = entries(state.pivots, np.arange(n))
    raw = np.triu(replay_pivots(state))
    flip = signs(raw)
    small = t @ top.T

    def rows_of_q(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            pivot = b.column(k + 1).to_numpy()
            q = -entries(to_matrix(b.column(k), n, policy)[0], pivot) @ small
            at = np.flatnonzero(pivot >= 0)
            q[at, pivot[at]] += 1.0
            q *= flip
            yield pa.RecordBatch.from_arrays([*b.columns[:k], *(pa.array(np.ascontiguousarray(q[:, i])) for i in range(n))], names=[*keys, *(f"q{i}" for i in range(n))])

    schema = nm.df.select(*keys).schema
    for i in range(n):
        schema = schema.add(f"q{i}", "double")
    return marked.mapInArrow(rows_of_q, schema)


def replay_pivots(state: Reflectors) -> np.ndarray:
    """Pivot rows after all updates, with the signs as the reflectors gave them."""
    now = state.pivots.copy()
    for j, w in enumerate(state.updates):
        below = now[j + 1 :, j : j + 1].copy()
        now[j] -= state.tops[j] * w
        now[j + 1 :] -= below * w
    return now
