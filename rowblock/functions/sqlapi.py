"""The methods as SQL functions of a session."""

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql.udtf import AnalyzeArgument, AnalyzeResult
from pyspark.sql.types import ArrayType, DoubleType, IntegerType, StructType

from ..kernels import fold_r, qr_r


def gram_partial(rows: pd.Series) -> np.ndarray:
    """Gram matrix, row by row, of the arrays of a group."""
    a = np.vstack(rows.to_numpy())
    return (a.T @ a).ravel()


def r_of(rows: pd.Series) -> np.ndarray:
    """R, row by row, of the arrays of a group."""
    return qr_r(np.vstack(rows.to_numpy())).ravel()


def r_merge(triangles: pd.Series) -> np.ndarray:
    """R of the matrices whose square Rs are given row by row."""
    n = round(len(triangles.iloc[0]) ** 0.5)
    return qr_r(np.vstack([np.array(t).reshape(-1, n) for t in triangles])).ravel()


def mat_row_times(rows: pd.Series, small: pd.Series) -> pd.Series:
    """Each array times a small matrix that is given row by row, the same for all rows of a batch."""
    if not len(rows):
        return pd.Series([], dtype=object)
    a = np.vstack(rows.to_numpy())
    m = np.asarray(small.iloc[0], dtype=float).reshape(a.shape[1], -1)
    return pd.Series(list(a @ m))


class QrR:
    """Table function: (i, j, v) of the R of the numeric columns of a table; call it with a partition to bound a task's rows, and merge."""

    @staticmethod
    def analyze(table: AnalyzeArgument) -> AnalyzeResult:
        return AnalyzeResult(StructType().add("i", IntegerType()).add("j", IntegerType()).add("v", DoubleType()))

    def __init__(self) -> None:
        self.r, self.rows = None, []

    def eval(self, row) -> None:
        self.rows.append([float(x) for x in row])
        if len(self.rows) >= 4096:
            self.r, self.rows = fold_r(self.r, np.array(self.rows)), []

    def terminate(self) -> Iterator[tuple]:
        if self.rows:
            self.r = fold_r(self.r, np.array(self.rows))
        if self.r is not None:
            for i in range(len(self.r)):
                for j in range(i, self.r.shape[1]):
                    yield i, j, float(self.r[i, j])


def register(spark: SparkSession) -> None:
    """gram_partial, r_of, r_merge, qr_r, and vector functions that generated code can inline."""
    from pyspark.sql.functions import udtf

    for f in (gram_partial, r_of, r_merge):
        spark.udf.register(f.__name__, F.pandas_udf(f, ArrayType(DoubleType())))
    spark.udf.register("mat_row_times", F.pandas_udf(mat_row_times, ArrayType(DoubleType())))
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION pass_bound(m DOUBLE, n DOUBLE, key_bytes DOUBLE, read_s DOUBLE, write_s DOUBLE) RETURNS DOUBLE COMMENT 'seconds to read and write a matrix once' RETURN (8 * m * n + key_bytes * m) * (read_s + write_s) / {2**30}.0D")
    spark.udtf.register("qr_r", udtf(QrR))
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_dot(x ARRAY<DOUBLE>, y ARRAY<DOUBLE>) RETURNS DOUBLE RETURN aggregate(zip_with(x, y, (a, b) -> a * b), CAST(0 AS DOUBLE), (s, v) -> s + v)")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_norm(x ARRAY<DOUBLE>) RETURNS DOUBLE RETURN sqrt(aggregate(x, CAST(0 AS DOUBLE), (s, v) -> s + v * v))")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION vec_axpy(c DOUBLE, x ARRAY<DOUBLE>, y ARRAY<DOUBLE>) RETURNS ARRAY<DOUBLE> RETURN zip_with(x, y, (a, b) -> c * a + b)")
