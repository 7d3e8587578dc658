"""The data model: a narrow matrix, many rows and few columns, as a DataFrame with a row key.

Two layouts: *wide*, a scalar column for each matrix column, which prunes on Parquet, and *array*, one
``array<double>`` column, for many columns. Row order carries no meaning. A row's key may be several columns.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .errors import FactorizationError

WIDEST = 64


@dataclass(frozen=True)
class NarrowMatrix:
    """``df`` with key columns and either value columns (wide) or one array column of ``n`` values.

    ``made`` is set if df's values are a kernel's on the rows of another matrix: what needs no keys then takes both in one Python worker.
    """

    df: DataFrame
    keys: tuple[str, ...]
    cols: tuple[str, ...] = ()
    array_col: str | None = None
    n: int = 0
    on_bad_row: str = "fail"
    made: tuple[NarrowMatrix, Callable[[np.ndarray], np.ndarray]] | None = field(default=None, compare=False)

    # construction

    @classmethod
    def from_columns(cls, df: DataFrame, keys: list[str], cols: list[str], on_bad_row: str = "fail") -> NarrowMatrix:
        """Scalar columns of any numeric type, cast to double; -0.0 becomes 0.0. A key that is a value column too is called key_<name>."""
        if not cols or len(set(cols)) != len(cols):
            raise FactorizationError("value columns have to be given, each once")
        named = {k: f"key_{k}" if k in cols else k for k in keys}
        values = [(F.col(c).cast("double") + F.lit(0.0)).alias(c) for c in cols]
        return cls(df.select(*(F.col(k).alias(v) for k, v in named.items()), *values), tuple(named.values()), tuple(cols), None, len(cols), on_bad_row)

    @classmethod
    def from_array(cls, df: DataFrame, keys: list[str], col: str, n: int | None = None, on_bad_row: str = "fail") -> NarrowMatrix:
        """An array column; n is read from one row where it isn't declared."""
        if n is None:
            first = df.where(F.col(col).isNotNull()).select(F.size(col).alias("n")).limit(1).collect()
            if not first:
                raise FactorizationError("no row to read the number of columns from")
            n = first[0]["n"]
        return cls(df.select(*keys, F.col(col).cast("array<double>").alias("a")), tuple(keys), (), "a", n, on_bad_row)

    @classmethod
    def from_long(cls, df: DataFrame, key: str, j: str, v: str, n: int, on_bad_row: str = "fail") -> NarrowMatrix:
        """Coordinate form (key, column index from 0, value); absent entries are zero."""
        entry = lambda k: F.coalesce(F.sum(F.when(F.col(j) == k, F.col(v).cast("double"))), F.lit(0.0))
        wide = df.groupBy(key).agg(*(entry(k).alias(f"a{k}") for k in range(n)))
        return cls.from_columns(wide, [key], [f"a{k}" for k in range(n)], on_bad_row)

    @classmethod
    def from_groups(cls, df: DataFrame, key: str, rows: str, n: int, on_bad_row: str = "fail") -> NarrowMatrix:
        """A key that stands for several rows, held as an array of arrays; a row's key gets its place in the group."""
        each = df.select(key, F.posexplode(rows).alias("row_no", "a"))
        return cls.from_array(each, [key, "row_no"], "a", n, on_bad_row)

    # layouts

    def wide(self) -> NarrowMatrix:
        if self.array_col is None:
            return self
        cols = tuple(f"a{i}" for i in range(self.n))
        return replace(self, made=None, df=self.df.select(*self.keys, *(F.get(self.array_col, i).alias(c) for i, c in enumerate(cols))), cols=cols, array_col=None)

    def array(self) -> NarrowMatrix:
        if self.array_col is not None:
            return self
        return replace(self, made=None, df=self.df.select(*self.keys, F.array(*self.cols).alias("a")), cols=(), array_col="a")

    def values(self) -> Column:
        return F.col(self.array_col) if self.array_col else F.array(*self.cols)

    # derived matrices

    def leading(self, k: int) -> NarrowMatrix:
        """The first k columns; on the wide layout the others are never read."""
        if self.array_col:
            return replace(self, made=None, df=self.df.select(*self.keys, F.slice(self.array_col, 1, k).alias(self.array_col)), n=k)
        return replace(self, made=None, df=self.df.select(*self.keys, *self.cols[:k]), cols=self.cols[:k], n=k)

    def with_intercept(self, name: str = "intercept") -> NarrowMatrix:
        """A column of ones in front."""
        if self.array_col:
            return replace(self, made=None, df=self.df.select(*self.keys, F.concat(F.array(F.lit(1.0)), self.array_col).alias(self.array_col)), n=self.n + 1)
        return replace(self, made=None, df=self.df.select(*self.keys, F.lit(1.0).alias(name), *self.cols), cols=(name, *self.cols), n=self.n + 1)

    def scaled(self, factors: list[float]) -> NarrowMatrix:
        """Each column times its factor."""
        if self.array_col:
            by = F.array(*(F.lit(float(f)) for f in factors))
            return replace(self, made=None, df=self.df.select(*self.keys, F.zip_with(self.array_col, by, lambda x, f: x * f).alias(self.array_col)))
        return replace(self, made=None, df=self.df.select(*self.keys, *((F.col(c) * F.lit(float(f))).alias(c) for c, f in zip(self.cols, factors, strict=True))))

    def column_norms(self) -> list[float]:
        """Euclidean norms of the columns, from one aggregate."""
        w = self.wide()
        row = w.df.agg(*(F.sqrt(F.sum(F.col(c) * F.col(c))).alias(f"n{i}") for i, c in enumerate(w.cols))).first()
        return [x or 0.0 for x in row]

    def equilibrated(self) -> NarrowMatrix:
        """Columns scaled to unit norm; zero columns stay."""
        return self.scaled([1 / x if x else 1.0 for x in self.column_norms()])

    def count(self) -> int:
        return self.df.count()

    def append(self, other: NarrowMatrix) -> NarrowMatrix:
        """Rows of both; layouts and widths have to agree."""
        if self.n != other.n:
            raise FactorizationError("widths differ")
        a, b = self.array(), other.array()
        return replace(a, made=None, df=a.df.unionByName(b.df))
