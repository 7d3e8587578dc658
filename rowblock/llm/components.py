"""Connected components of a link table; only tables of few links are gathered.

Up to ``LOCAL_LINKS`` distinct links, 3.2 MB, are joined on the driver: each round of the other way leaves files of all its exchanges, however few the
links. Beyond that, the same result without gathering links anywhere: alternates two rewirings until nothing changes: every vertex first sends its larger neighbours to its
least neighbour, then its smaller ones. Both keep the components, and the number of links
never grows. Each round is an aggregate and a join, so a hub with very many links is summed up
map-side and its links are split by the skew handling of the join.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import cut_lineage

MAX_ROUNDS = 60
LOCAL_LINKS = 200_000  # the result is the same


def _large_star(links: DataFrame) -> DataFrame:
    both = links.select("a", "b").union(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
    least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("u"), F.least("m", "a").alias("m"))
    return both.where("b > a").join(least, F.col("a") == F.col("u")).select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()


def _small_star(links: DataFrame) -> DataFrame:
    down = links.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b"))
    least = down.groupBy("a").agg(F.min("b").alias("m")).withColumnRenamed("a", "u")
    moved = down.join(least, F.col("a") == F.col("u")).select(F.col("b").alias("a"), F.col("m").alias("b"))
    return moved.union(least.select(F.col("u").alias("a"), F.col("m").alias("b"))).where("a <> b").distinct()


def _mark(links: DataFrame) -> tuple:
    return tuple(links.agg(F.count(F.lit(1)), F.sum(F.xxhash64("a", "b").bitwiseAND(F.lit((1 << 40) - 1)))).first())


def _joined(links: pa.Table) -> pa.Table:
    """(vertex, root) by a forest over the vertices in their order, whose roots are the least ones."""
    a, b = links.column("a").to_numpy(), links.column("b").to_numpy()
    vertices, places = np.unique(np.concatenate([a, b]), return_inverse=True)
    above = list(range(len(vertices)))

    def top(x: int) -> int:
        while above[x] != x:
            above[x] = x = above[above[x]]
        return x

    for x, y in zip(places[: len(a)].tolist(), places[len(a) :].tolist(), strict=True):
        x, y = top(x), top(y)
        above[max(x, y)] = min(x, y)
    roots = np.fromiter(map(top, range(len(vertices))), np.int64, len(vertices))
    return pa.table({"vertex": pa.array(vertices, pa.int64()), "root": pa.array(vertices[roots], pa.int64())})


def connected_components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(vertex, root) for every vertex with a link to another; root is the least vertex of its component."""
    now = cut_lineage(links.select(F.col(a).alias("a"), F.col(b).alias("b")).where("a <> b").distinct())
    mark = _mark(now)
    if 0 < mark[0] <= LOCAL_LINKS and all(f.dataType == T.LongType() for f in now.schema):
        return now.sparkSession.createDataFrame(_joined(now.toArrow()), "vertex long, root long")
    for _ in range(MAX_ROUNDS):
        if not mark[0]:
            break
        now = cut_lineage(_small_star(_large_star(now)))
        before, mark = mark, _mark(now)
        if before == mark:
            break
    else:
        raise RuntimeError("components did not settle")
    return now.select(F.col("a").alias("vertex"), F.col("b").alias("root")).union(now.select(F.col("b").alias("vertex"), F.col("b").alias("root"))).distinct()
