"""Gram matrices A'A, by several strategies, and the triangular factor from them."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..blocks import map_blocks
from ..errors import FactorizationError
from ..kernels import cholesky_upper
from ..matrix import NarrowMatrix

SQL_WIDEST = 12  # above it, generated code for n(n+1)/2 sums gets too big
STRATEGIES = ("row", "entry", "entry_sym", "tree", "sql", "row_outer")


def _task_gram(rows: Iterator[np.ndarray], n: int) -> np.ndarray | None:
    total = None
    for block in rows:
        if len(block):
            total = block.T @ block + (0 if total is None else total)
    return total


def _by_row(nm: NarrowMatrix) -> DataFrame:
    """A key for each matrix row: each task sends n rows of its own Gram matrix."""
    n = nm.n

    def kernel(rows: Iterator[np.ndarray]) -> Iterator[pa.RecordBatch]:
        g = _task_gram(rows, n)
        if g is not None:
            yield pa.RecordBatch.from_arrays([pa.array(range(n), pa.int32()), pa.array(g.tolist(), pa.list_(pa.float64()))], names=["i", "row"])

    parts = map_blocks(nm, kernel, "i int, row array<double>")
    summed = parts.groupBy("i").agg(F.array(*(F.sum(F.get("row", j)) for j in range(n))).alias("row"))
    return summed.select("i", F.posexplode("row").alias("j", "v"))


def _entries(nm: NarrowMatrix, upper: bool, salted: int = 0) -> DataFrame:
    n = nm.n
    i, j = np.triu_indices(n) if upper else tuple(x.ravel() for x in np.indices((n, n)))

    def kernel(rows: Iterator[np.ndarray]) -> Iterator[pa.RecordBatch]:
        g = _task_gram(rows, n)
        if g is not None:
            yield pa.RecordBatch.from_arrays([pa.array(i, pa.int32()), pa.array(j, pa.int32()), pa.array(g[i, j])], names=["i", "j", "v"])

    parts = map_blocks(nm, kernel, "i int, j int, v double")
    if salted:
        parts = parts.groupBy((F.spark_partition_id() % salted).alias("salt"), "i", "j").agg(F.sum("v").alias("v"))
    return parts.groupBy("i", "j").agg(F.sum("v").alias("v"))


def _mirrored(cells: DataFrame) -> DataFrame:
    """All n*n entries from those with i <= j; each is sent out twice, so that A is read once."""
    cell = lambda i, j: F.struct(F.col(i).alias("i"), F.col(j).alias("j"), F.col("v").alias("v"))
    both = F.when(F.col("i") == F.col("j"), F.array(cell("i", "j"))).otherwise(F.array(cell("i", "j"), cell("j", "i")))
    return cells.select(F.explode(both).alias("c")).select("c.i", "c.j", "c.v")


def _by_sql(nm: NarrowMatrix, exact_scale: int | None) -> DataFrame:
    """One aggregate with a sum for each entry of the triangle; with a scale, over decimals and so exact."""
    if nm.n > SQL_WIDEST:
        raise FactorizationError(f"one aggregate is meant for at most {SQL_WIDEST} columns")
    w = nm.wide()
    value = lambda c: F.col(c).cast(f"decimal(18,{exact_scale})") if exact_scale is not None else F.col(c)
    pairs = [(i, j) for i in range(w.n) for j in range(i, w.n)]
    one = w.df.agg(*(F.sum(value(w.cols[i]) * value(w.cols[j])).cast("double").alias(f"g{i}_{j}") for i, j in pairs))
    cells = F.array(*(F.struct(F.lit(i).alias("i"), F.lit(j).alias("j"), F.col(f"g{i}_{j}").alias("v")) for i, j in pairs))
    return _mirrored(one.select(F.inline(cells)))


def _row_outer(nm: NarrowMatrix) -> DataFrame:
    """Every row sends its own outer product: the form without combining, to show why blocks are combined first."""
    a = nm.array()
    rows = a.df.select(F.posexplode("a").alias("i", "x"), "a").select("i", F.transform("a", lambda y: y * F.col("x")).alias("row"))
    summed = rows.groupBy("i").agg(F.array(*(F.sum(F.get("row", j)) for j in range(nm.n))).alias("row"))
    return summed.select("i", F.posexplode("row").alias("j", "v"))


def gram(nm: NarrowMatrix, strategy: str = "entry_sym", fan_in: int = 8, exact_scale: int | None = None) -> DataFrame:
    """(i, j, v) with all n*n entries, indices from 0."""
    if exact_scale is not None or strategy == "sql":
        return _by_sql(nm, exact_scale)
    if strategy == "row":
        return _by_row(nm)
    if strategy == "entry":
        return _entries(nm, False)
    if strategy == "entry_sym":
        return _mirrored(_entries(nm, True))
    if strategy == "tree":
        return _mirrored(_entries(nm, True, fan_in))
    if strategy == "row_outer":
        return _row_outer(nm)
    raise FactorizationError(f"no strategy {strategy!r}; there are {STRATEGIES}")


def gram_from_long(df: DataFrame, key: str, j: str, v: str) -> DataFrame:
    """Gram matrix of the coordinate form, by a join of the table with itself on the row key."""
    x = df.select(F.col(key).alias("k"), F.col(j).cast("int").alias("i"), F.col(v).cast("double").alias("x"))
    y = df.select(F.col(key).alias("k"), F.col(j).cast("int").alias("j"), F.col(v).cast("double").alias("y"))
    return x.join(y, "k").groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("v"))


def to_numpy(cells: DataFrame, n: int) -> np.ndarray:
    """n*n entries to the driver; absent ones are zero."""
    out = np.zeros((n, n))
    for r in cells.collect():
        out[r["i"], r["j"]] = r["v"] or 0.0
    return out


def to_frame(spark: SparkSession, m: np.ndarray, upper_only: bool = False) -> DataFrame:
    """(i, j, v) of a small matrix."""
    rows = [(int(i), int(j), float(m[i, j]) + 0.0) for i in range(m.shape[0]) for j in range(m.shape[1]) if j >= i or not upper_only]
    return spark.createDataFrame(rows, "i int, j int, v double")


def cholesky_r(g: np.ndarray) -> np.ndarray:
    return cholesky_upper(g)
