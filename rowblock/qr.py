"""One call for all factorizations."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame

from .errors import FactorizationError, GramNotPositiveDefinite
from .matrix import NarrowMatrix
from .operators import direct as d
from .operators import gram as g
from .operators import householder as h
from .operators import indirect
from .operators import panel as p
from .staging import Stage

METHODS = ("cholesky", "rtree", "direct", "direct_rec", "householder")


@dataclass
class RunReport:
    """What a run did: method, planned reads of the data (``plans.experiments.rows_read`` counts them), seconds of the steps that have run; Q is lazy."""

    method: str
    passes: float = 0
    steps: dict[str, float] = field(default_factory=dict)
    reason: str = ""

    def step_shares(self) -> dict[str, float]:
        total = sum(self.steps.values()) or 1.0
        return {k: v / total for k, v in self.steps.items()}


@dataclass
class QRResult:
    """A = QR. q is a lazy frame (key columns, q0, ...) or None, r has a non-negative diagonal."""

    q: DataFrame | None
    r: np.ndarray
    report: RunReport
    nm: NarrowMatrix
    stage: Stage | None = None

    @property
    def r_df(self) -> DataFrame:
        return g.to_frame(self.nm.df.sparkSession, self.r, upper_only=True)

    @property
    def q_matrix(self) -> NarrowMatrix:
        return indirect.as_matrix(self.q, self.nm)

    def leading(self, k: int) -> np.ndarray:
        """R of the first k columns, without another scan."""
        return self.r[:k, :k]

    def release(self) -> None:
        if self.stage:
            self.stage.release()


def qr(nm: NarrowMatrix, method: str = "auto", refine: int = 0, want_q: bool = True, n_blocks: int | None = None, stage: Stage | None = None, fallback: bool = False, **opts) -> QRResult:
    """Factor a narrow matrix. See METHODS; "auto" asks the planner, with the options cond and stable. Other options go to the method."""
    reason = ""
    if method == "auto":
        from .plans.planner import choose_method

        method, refine, reason = choose_method(None, nm.n, opts.get("cond"), want_q, opts.get("stable", True), n_blocks=n_blocks or nm.df.rdd.getNumPartitions())
    report = RunReport(method + ("+ir" if refine else ""), reason=reason)
    stage = stage or Stage(nm.df.sparkSession)
    began = time.perf_counter()
    q: DataFrame | None = None
    if method in ("cholesky", "rtree"):
        how = {k: v for k, v in opts.items() if k in ("strategy", "fan_in", "exact_scale", "block_rows")}
        try:
            if refine and want_q:
                q, r = indirect.refine(nm, method, refine, opts.get("fused", True), stage, **how)
            else:
                r = indirect.first_r(nm, method, **how)
                q = indirect.apply_r_inverse(nm, r, opts.get("how", "inverse")) if want_q else None
        except GramNotPositiveDefinite:
            if not fallback:
                raise
            return qr(nm, "direct", 0, want_q, n_blocks, stage)
        report.passes = 1 + want_q + (refine if want_q else 0) * (1 if opts.get("fused", True) else 2)
    elif method in ("direct", "direct_rec"):
        if not want_q:
            return qr(nm, "rtree", want_q=False, n_blocks=n_blocks, stage=stage)
        q, r = d.direct(nm, stage, n_blocks, opts.get("block_rows"), opts.get("combine", "recursive" if method == "direct_rec" else "auto"), opts.get("fan_in"), opts.get("deliver", "auto"), replay=opts.get("replay", False), buckets=opts.get("buckets"), seconds=report.steps)
        report.passes = 2
    elif method == "householder" and opts.get("form") == "panel":
        panels = p.factor(nm, opts.get("panel", 4))
        r = panels.r
        q = p.q_factor(nm, panels) if want_q else None
        report.passes = panels.passes + 2 * want_q
    elif method == "householder":
        state = h.factor(nm, opts.get("form", "one_pass"), opts.get("max_columns"), stage)
        r = state.r
        q = h.q_factor(nm, state) if want_q else None
        report.passes = state.passes + 2 * want_q
    else:
        raise FactorizationError(f"no method {method!r}; there are {METHODS}")
    report.steps["plan and small work" if report.steps else "factor"] = time.perf_counter() - began - sum(report.steps.values())
    return QRResult(q, r, report, nm, stage)


__all__ = ["METHODS", "QRResult", "RunReport", "qr"]
