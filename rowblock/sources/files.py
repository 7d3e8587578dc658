"""Tables in and out of files of several formats, always with a given schema."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T

FORMATS = ("parquet", "orc", "csv", "json", "text")


def write(df: DataFrame, path: str, kind: str = "parquet", partition_by: tuple[str, ...] = ()) -> None:
    if kind not in FORMATS:
        raise ValueError(f"no format {kind!r}")
    writer = df.write.mode("overwrite")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    if kind == "csv":
        writer = writer.option("header", True)
    if kind in ("csv", "json"):
        writer = writer.option("timestampFormat", "yyyy-MM-dd'T'HH:mm:ss.SSSSSS")
    writer.format(kind).save(path)


def read(spark: SparkSession, path: str, kind: str, schema: T.StructType) -> DataFrame:
    """Nothing is inferred, so no pass over the data is spent on it."""
    if kind not in FORMATS:
        raise ValueError(f"no format {kind!r}")
    reader = spark.read.schema(schema)
    if kind == "csv":
        reader = reader.option("header", True)
    if kind in ("csv", "json"):
        reader = reader.option("timestampFormat", "yyyy-MM-dd'T'HH:mm:ss.SSSSSS")
    return reader.format(kind).load(path)


def matrix_rows(df: DataFrame, keys: list[str], cols: list[str], path: str) -> None:
    """A matrix as lines of text: key fields and values, separated by commas."""
    from pyspark.sql import functions as F

    df.select(F.concat_ws(",", *keys, *cols).alias("value")).write.mode("overwrite").text(path)


def bucketed(df: DataFrame, name: str, buckets: int, key: str) -> DataFrame:
    """A table whose files are dealt by a key, so that joins on it need no exchange."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)
    return df.sparkSession.table(name)
