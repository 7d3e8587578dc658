"""From tables to matrices and back: joins, windows, aggregates and set operations that features need."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

BROADCAST_ROWS = 100_000


def broadcast_if_small(df: DataFrame, most_rows: int = BROADCAST_ROWS) -> DataFrame:
    """A broadcast hint behind a check: at most so many rows are looked at."""
    return F.broadcast(df) if df.limit(most_rows + 1).count() <= most_rows else df


def range_join(points: DataFrame, spans: DataFrame, at: str, start: str, end: str, width: float) -> DataFrame:
    """Points with the spans [start, end) that hold them: both sides meet in bins of a width, so it is an equality join with a check."""
    binned = points.withColumn("bin", F.floor(F.col(at) / width))
    spread = spans.withColumn("bin", F.explode(F.sequence(F.floor(F.col(start) / width), F.floor((F.col(end)) / width))))
    return binned.join(spread, "bin").where((F.col(at) >= F.col(start)) & (F.col(at) < F.col(end))).drop("bin")


def count_within(points: DataFrame, name: str, at: str, width: int) -> DataFrame:
    """(name, n): for every point the number of points in [at, at + width), for whole numbers at.

    Points are summed by place first. A bin is as wide as the span, so a span is the end of its own bin and the start of the next; both
    come from running sums within a bin, found by an as-of step in one window over bins, never from pairs of points.
    """
    places = points.groupBy(F.col(at).alias("at")).agg(F.count(F.lit(1)).alias("m"))
    opens = places.select("at", (F.floor(F.col("at") / width)).alias("bin"), "m", F.lit(1).alias("opens"))
    # The same place seen from the bin after it, a width later: how much of that bin comes before it.
    closes = places.select((F.col("at") + width).alias("at"), (F.floor(F.col("at") / width) + 1).alias("bin"), F.lit(0).cast("long").alias("m"), F.lit(0).alias("opens"))
    before = Window.partitionBy("bin").orderBy("at").rangeBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy("bin")
    seen = opens.unionByName(closes).withColumns({"before": F.coalesce(F.sum("m").over(before), F.lit(0)), "all": F.sum("m").over(whole)})
    own = seen.where("opens = 1").select("at", (F.col("all") - F.col("before")).alias("rest"))
    then = seen.where("opens = 0").select((F.col("at") - width).alias("at"), F.col("before").alias("more"))
    counted = own.join(then, "at").select("at", (F.col("rest") + F.col("more")).alias("n"))
    return points.join(counted, points[at] == counted["at"]).select(name, "n")


def as_of(rows: DataFrame, by: list[str], ts: str, tie: str, value: str, when: Column, out: str) -> DataFrame:
    """The latest earlier value of the rows that satisfy a condition, by key; a row itself doesn't count."""
    w = Window.partitionBy(*by).orderBy(ts, tie).rowsBetween(Window.unboundedPreceding, -1)
    return rows.withColumn(out, F.last(F.when(when, F.col(value)), ignorenulls=True).over(w))


def one_hot(df: DataFrame, col: str, vocabulary: list[str], prefix: str) -> DataFrame:
    """A 0/1 column for each declared value; other values give zeros."""
    return df.withColumns({f"{prefix}_{v}": F.coalesce((F.col(col) == v).cast("double"), F.lit(0.0)) for v in vocabulary})


def key_sample(df: DataFrame, keys: list[str], one_in: int) -> DataFrame:
    """The rows of about one key in so many, always the same ones: for estimates that plans use, never for results."""
    return df.where(F.pmod(F.xxhash64(*keys), F.lit(one_in)) == 0)


def salted_sum(df: DataFrame, keys: list[str], value: str, salts: int = 16) -> DataFrame:
    """Sums by key in two levels, so that a hot key is summed by several tasks."""
    part = df.withColumn("salt", F.pmod(F.xxhash64(*df.columns), F.lit(salts))).groupBy(*keys, "salt").agg(F.sum(value).alias(value))
    return part.groupBy(*keys).agg(F.sum(value).alias(value))


def top_k(df: DataFrame, by: list[str], order: list[Column], k: int) -> DataFrame:
    w = Window.partitionBy(*by).orderBy(*order)
    return df.withColumn("place", F.row_number().over(w)).where(F.col("place") <= k)
