"""Householder QR by panels: a tree factors b columns at once, and their block reflector is made from its R.

For a panel Q R of the rows that are no earlier pivots, Q minus a diagonal of signs has an LU form whose
unit factor is the reflectors V, so a row's entry of V is its panel values times a small matrix. Like the one-pass form this
rewrites nothing: rows replay earlier panels from small matrices. A panel takes two passes, so n columns take 2 n / b.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..blocks import to_matrix
from ..kernels import fold_r, invert_upper, qr_r, signs
from ..matrix import NarrowMatrix
from .householder import first_rows


@dataclass
class Panel:
    """Columns c0 to c1: v = panel values times m, top for the panel's own pivot rows; rows lose v w; t is the block's T."""

    c0: int
    c1: int
    m: np.ndarray
    top: np.ndarray
    w: np.ndarray
    t: np.ndarray

    def entries(self, rows: np.ndarray, pivot: np.ndarray) -> np.ndarray:
        v = rows[:, self.c0 : self.c1] @ self.m
        v[(pivot >= 0) & (pivot < self.c0)] = 0.0
        own = np.flatnonzero((pivot >= self.c0) & (pivot < self.c1))
        v[own] = self.top[pivot[own] - self.c0]
        return v


@dataclass
class PanelFactors:
    n: int
    pivots: np.ndarray
    marked: DataFrame
    panels: list[Panel] = field(default_factory=list)
    r: np.ndarray = field(default_factory=lambda: np.zeros((0, 0)))
    flip: np.ndarray = field(default_factory=lambda: np.zeros(0))
    passes: int = 0


def replay(rows: np.ndarray, pivot: np.ndarray, panels: list[Panel]) -> tuple[np.ndarray, list[np.ndarray]]:
    """Rows after the panels, and their entries of all reflectors."""
    rows, entries = rows.copy(), []
    for p in panels:
        entries.append(p.entries(rows, pivot))
        rows -= entries[-1] @ p.w
    return rows, entries


def reflectors(q1: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(V1, U, signs) with q1 - diag(signs) = V1 U; the signs are chosen so that no pivot is small."""
    b = len(q1)
    u, low, s = q1.copy(), np.eye(b), np.zeros(b)
    for k in range(b):
        s[k] = -1.0 if u[k, k] >= 0 else 1.0
        u[k, k] -= s[k]
        low[k + 1 :, k] = u[k + 1 :, k] / u[k, k]
        u[k + 1 :, k:] -= np.outer(low[k + 1 :, k], u[k, k:])
    return low, np.triu(u), s


def _mark(nm: NarrowMatrix, keys: list) -> DataFrame:
    marks = nm.df.sparkSession.createDataFrame([(*k, i) for i, k in enumerate(keys)], nm.df.select(*nm.keys).schema.add("pivot", "integer"))
    cond = [nm.df[k].eqNullSafe(marks[k]) for k in nm.keys]
    return nm.df.select(*nm.keys, nm.values().alias("a")).join(F.broadcast(marks), cond, "left").select(*(nm.df[k] for k in nm.keys), "a", F.coalesce("pivot", F.lit(-1)).alias("pivot"))  # n marks


def factor(nm: NarrowMatrix, b: int = 4) -> PanelFactors:
    """R and the panels. Keys have to be distinct."""
    n, policy = nm.n, nm.on_bad_row
    keys, pivots = first_rows(nm)
    out = PanelFactors(n, pivots, _mark(nm, keys))
    slim = out.marked.select("a", "pivot")
    for c0 in range(0, n, b):
        c1, done = min(n, c0 + b), list(out.panels)

        def triangle(batches: Iterator[pa.RecordBatch], c0: int = c0, c1: int = c1, done: list[Panel] = done) -> Iterator[pa.RecordBatch]:
            r = None
            for x in batches:
                pivot = x.column(1).to_numpy()
                rows = replay(to_matrix(x.column(0), n, policy)[0], pivot, done)[0]
                r = fold_r(r, rows[(pivot < 0) | (pivot >= c0), c0:c1])
            if r is not None and len(r):
                yield pa.RecordBatch.from_arrays([pa.array([r.ravel()], pa.list_(pa.float64()))], names=["r"])

        rs = slim.mapInArrow(triangle, "r array<double>").collect()  # one small triangle from each task
        r = qr_r(np.vstack([np.array(x["r"]).reshape(-1, c1 - c0) for x in rs]))
        inverse = invert_upper(r)
        now, _ = replay(pivots, np.arange(n), done)
        top, u, s = reflectors(now[c0:c1, c0:c1] @ inverse)
        panel = Panel(c0, c1, inverse @ invert_upper(u), top, np.zeros((c1 - c0, n)), -(u * s) @ np.linalg.inv(top).T)

        def products(batches: Iterator[pa.RecordBatch], panel: Panel = panel, done: list[Panel] = done) -> Iterator[pa.RecordBatch]:
            total = np.zeros((panel.c1 - panel.c0, n))
            for x in batches:
                pivot = x.column(1).to_numpy()
                rows = replay(to_matrix(x.column(0), n, policy)[0], pivot, done)[0]
                total += panel.entries(rows, pivot).T @ rows
            i, j = (y.ravel() for y in np.indices(total.shape))
            yield pa.RecordBatch.from_arrays([pa.array(i, pa.int32()), pa.array(j, pa.int32()), pa.array(total.ravel())], names=["i", "j", "v"])

        for x in slim.mapInArrow(products, "i int, j int, v double").groupBy("i", "j").agg(F.sum("v").alias("v")).collect():
            panel.w[x["i"], x["j"]] = x["v"]
        panel.w = panel.t.T @ panel.w
        out.panels.append(panel)
        out.passes += 2
    raw = np.triu(replay(pivots, np.arange(n), out.panels)[0])
    out.flip = signs(raw)
    out.r = out.flip[:, None] * raw + 0.0
    return out


def q_factor(nm: NarrowMatrix, state: PanelFactors) -> DataFrame:
    """Q = E - V (T V_top'), with T put together from the panels' by the products of their reflectors."""
    n, policy, k, panels = nm.n, nm.on_bad_row, len(nm.keys), state.panels

    def task_products(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((n, n))
        for x in batches:
            v = np.hstack(replay(to_matrix(x.column(0), n, policy)[0], x.column(1).to_numpy(), panels)[1])
            total += v.T @ v
        i, j = (y.ravel() for y in np.indices((n, n)))
        yield pa.RecordBatch.from_arrays([pa.array(i, pa.int32()), pa.array(j, pa.int32()), pa.array(total.ravel())], names=["i", "j", "v"])

    vtv = np.zeros((n, n))
    for x in state.marked.select("a", "pivot").mapInArrow(task_products, "i int, j int, v double").groupBy("i", "j").agg(F.sum("v").alias("v")).collect():
        vtv[x["i"], x["j"]] = x["v"]
    t = np.zeros((n, n))
    for p in panels:
        t[p.c0 : p.c1, p.c0 : p.c1] = p.t
        t[: p.c0, p.c0 : p.c1] = -t[: p.c0, : p.c0] @ vtv[: p.c0, p.c0 : p.c1] @ p.t
    small = t @ np.hstack(replay(state.pivots, np.arange(n), panels)[1]).T
    names = [*nm.keys, *(f"q{i}" for i in range(n))]

    def rows_of_q(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for x in batches:
            pivot = x.column(k + 1).to_numpy()
            q = -np.hstack(replay(to_matrix(x.column(k), n, policy)[0], pivot, panels)[1]) @ small
            at = np.flatnonzero(pivot >= 0)
            q[at, pivot[at]] += 1.0
            q *= state_flip
            yield pa.RecordBatch.from_arrays([*x.columns[:k], *(pa.array(np.ascontiguousarray(q[:, i])) for i in range(n))], names=names)

    state_flip = state.flip
    schema = nm.df.select(*nm.keys).schema
    for i in range(n):
        schema = schema.add(f"q{i}", "double")
    return state.marked.mapInArrow(rows_of_q, schema)
