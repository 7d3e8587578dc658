"""Which method to use, decided before any job."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators import direct as d

#: The Gram matrix squares the condition number, so half the digits are the limit.
CHOLESKY_COND = 1e7


def choose_method(m: int | None, n: int, cond: float | None = None, want_q: bool = True, stable: bool = True, n_blocks: int = 8) -> tuple[str, int, str]:
    """(method, refinement steps, reason)."""
    if not want_q:
        return "rtree", 0, "only R is wanted: one pass"
    if not stable and cond is not None and cond < CHOLESKY_COND:
        return "cholesky", 0, "well conditioned, and orthogonality needn't be guaranteed"
    if cond is not None and cond < CHOLESKY_COND and (n <= 4 or n >= 100):
        return "cholesky", 1, "one refinement suffices, and is cheapest at this width"
    if d.gather_bytes(n_blocks, n) > d.STACK_BYTES:
        return "direct_rec", 0, "orthogonal whatever the conditioning; the stacked Rs are too large for one task"
    return "direct", 0, "orthogonal whatever the conditioning"


def choices_table(spark: SparkSession, numbers_of_blocks: list[int]) -> DataFrame:
    """Decisions over a grid of needs."""
    rows = []
    for n in (4, 10, 50, 100):
        for want_q in (True, False):
            for cond in (None, 1e3, 1e12):
                for blocks in numbers_of_blocks:
                    method, ir, _ = choose_method(10**9, n, cond, want_q, True, blocks)
                    rows.append((n, want_q, cond, blocks, method, ir))
    return spark.createDataFrame(rows, "n int, want_q boolean, cond double, blocks long, method string, refine int")
