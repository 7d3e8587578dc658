"""Matrices on the given tables that the experiments use."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..matrix import NarrowMatrix

LINE_KEY = ["l_orderkey", "l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice"]
SHAPES = {4: (2, 2), 10: (5, 2), 25: (5, 5), 50: (10, 5), 100: (10, 10)}


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _numbered(df: DataFrame) -> DataFrame:
    """lineitem with its key under plain names, so that keys and values don't share columns."""
    return df.select(*(F.col(k).alias(f"k{i}") for i, k in enumerate(LINE_KEY)), "l_quantity", "l_extendedprice", "l_discount", "l_tax")


LINE_KEYS = [f"k{i}" for i in range(len(LINE_KEY))]
RAW4 = ["l_quantity", "l_extendedprice", "l_discount", "l_tax"]


def raw4(spark: SparkSession, sf_dir: str) -> NarrowMatrix:
    """Quantity, price, discount and tax of order lines."""
    return NarrowMatrix.from_columns(_numbered(table(spark, sf_dir, "lineitem")), LINE_KEYS, RAW4)




def cheb(spark: SparkSession, sf_dir: str, n: int) -> NarrowMatrix:
    """Products of Chebyshev polynomials of quantity and price: well conditioned at any width of SHAPES."""
    a, b = SHAPES[n]
    df = _numbered(table(spark, sf_dir, "lineitem"))
    df = df.select(*LINE_KEYS, ((F.col("l_quantity") - 25.5) / 24.5).alias("x"), F.greatest(F.lit(-1.0), F.least(F.lit(1.0), (F.col("l_extendedprice") - 52950.0) / 52050.0)).alias("y"))
    # each polynomial is a column of its own, made from the two before it
    for v, degree in (("x", a), ("y", b)):
        df = df.withColumns({f"{v}0": F.lit(1.0), f"{v}1": F.col(v)})
        for i in range(2, degree):
            df = df.withColumn(f"{v}{i}", 2 * F.col(v) * F.col(f"{v}{i - 1}") - F.col(f"{v}{i - 2}"))
    named = df.select(*LINE_KEYS, *((F.col(f"x{i}") * F.col(f"y{j}")).alias(f"t{i}_{j}") for i in range(a) for j in range(b)))
    return NarrowMatrix.from_columns(named, LINE_KEYS, [f"t{i}_{j}" for i in range(a) for j in range(b)])


def dial(spark: SparkSession, sf_dir: str, k: int) -> NarrowMatrix:
    """Columns that differ from the first by 10^-k: the condition number is about 4.5 * 10^k."""
    df = _numbered(table(spark, sf_dir, "lineitem"))
    b = [F.col("l_quantity") / 50, F.col("l_extendedprice") / 105000, F.col("l_discount") * 10, F.col("l_tax") * 12.5]
    step = float(10.0**-k)
    return NarrowMatrix.from_columns(df.select(*LINE_KEYS, b[0].alias("d0"), *((b[0] + step * b[j]).alias(f"d{j}") for j in (1, 2, 3))), LINE_KEYS, ["d0", "d1", "d2", "d3"])


def vander(spark: SparkSession, sf_dir: str, n: int) -> NarrowMatrix:
    """Powers of the scaled quantity: conditioning gets worse with each column."""
    df = _numbered(table(spark, sf_dir, "lineitem")).withColumn("x", F.col("l_quantity") / 50)
    for i in range(n):
        df = df.withColumn(f"p{i}", F.lit(1.0) if i == 0 else F.col(f"p{i - 1}") * F.col("x"))
    return NarrowMatrix.from_columns(df, LINE_KEYS, [f"p{i}" for i in range(n)])


def embeddings(spark: SparkSession, sf_dir: str) -> NarrowMatrix:
    return NarrowMatrix.from_array(table(spark, sf_dir, "embeddings"), ["vec_id"], "embedding", 64)


def orders5(spark: SparkSession, sf_dir: str) -> NarrowMatrix:
    """Orders with features of their customers: 1, price, balance, month, weekday."""
    o, c = table(spark, sf_dir, "orders"), table(spark, sf_dir, "customer")
    df = o.join(c, F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", F.lit(1.0).alias("one"), "o_totalprice", "c_acctbal", F.month("o_orderdate").alias("month"), (F.weekday("o_orderdate") + 1).alias("weekday"))
    return NarrowMatrix.from_columns(df, ["o_orderkey"], ["one", "o_totalprice", "c_acctbal", "month", "weekday"])


def part2(spark: SparkSession, sf_dir: str) -> NarrowMatrix:
    return NarrowMatrix.from_columns(table(spark, sf_dir, "part"), ["p_partkey"], ["p_size", "p_retailprice"])


def letters27(spark: SparkSession, sf_dir: str) -> NarrowMatrix:
    """One and the number of each letter of a document's text."""
    text = F.lower(F.coalesce("text", F.lit("")))
    letters = "abcdefghijklmnopqrstuvwxyz"
    df = table(spark, sf_dir, "documents").select("doc_id", F.lit(1.0).alias("one"), *((F.length(text) - F.length(F.replace(text, F.lit(c)))).cast("double").alias(f"n_{c}") for c in letters))
    return NarrowMatrix.from_columns(df, ["doc_id"], ["one", *(f"n_{c}" for c in letters)])


def pages5(spark: SparkSession, sf_dir: str) -> NarrowMatrix:
    """Counts of tags and entities, and the length, of a page."""
    html = F.coalesce("html", F.lit(""))
    count = lambda s: ((F.length(html) - F.length(F.replace(html, F.lit(s)))) / len(s)).cast("double")
    df = table(spark, sf_dir, "pages").select("page_id", count("<p").alias("p"), count("<a").alias("a"), count("<li").alias("li"), count("&amp;").alias("amp"), F.length(html).cast("double").alias("chars"))
    return NarrowMatrix.from_columns(df, ["page_id"], ["p", "a", "li", "amp", "chars"])


def turns4(spark: SparkSession, sf_dir: str) -> NarrowMatrix:
    """Turns of conversations, held as groups of rows under the conversation's key."""
    c = table(spark, sf_dir, "conversations").where("conv_id IS NOT NULL")
    row = F.array(F.lit(1.0), F.col("turn").cast("double"), F.length(F.coalesce("text", F.lit(""))).cast("double"), (F.coalesce("role", F.lit("")) == "user").cast("double"))
    return NarrowMatrix.from_groups(c.groupBy("conv_id").agg(F.sort_array(F.collect_list(row)).alias("rows")), "conv_id", "rows", 4)


def events10(spark: SparkSession, sf_dir: str) -> NarrowMatrix:
    """Polynomials of an event's value and hour."""
    df = table(spark, sf_dir, "events")
    df = df.select("event_id", F.greatest(F.lit(-1.0), F.least(F.lit(1.0), F.col("value") / 300 - 1)).alias("x"), (F.hour("ts") / 11.5 - 1).alias("y"))
    df = df.withColumns({"x0": F.lit(1.0), "x1": F.col("x"), "y0": F.lit(1.0), "y1": F.col("y")})
    for i in range(2, 5):
        df = df.withColumn(f"y{i}", 2 * F.col("y") * F.col(f"y{i - 1}") - F.col(f"y{i - 2}"))
    named = df.select("event_id", *((F.col(f"x{i}") * F.col(f"y{j}")).alias(f"t{i}_{j}") for i in range(2) for j in range(5)))
    return NarrowMatrix.from_columns(named, ["event_id"], [f"t{i}_{j}" for i in range(2) for j in range(5)])
