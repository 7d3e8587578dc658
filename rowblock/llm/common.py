"""Small helpers shared by the training-data operators."""

from __future__ import annotations

import tempfile
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..memory import give_back

BATCH_ROWS = 1000


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def checkpoint_folder(spark: SparkSession) -> str:
    """The shared folder of the cluster; a temporary one only where none is set (tests, one machine)."""
    context = spark.sparkContext
    current = context.getCheckpointDir()
    if current:
        return current
    shared = spark.conf.get("spark.checkpoint.dir", None) or context.getConf().get("spark.checkpoint.dir")
    context.setCheckpointDir(shared or tempfile.mkdtemp(prefix="rowblock-checkpoint-"))
    return context.getCheckpointDir()


def cut_lineage(df: DataFrame) -> DataFrame:
    """Materialise a result in the shared folder: it is computed once, whatever reads it, and outlives executors.

    Spark deletes files of shuffles and checkpoints once the driver has collected what refers to them, so it is made to collect.
    """
    checkpoint_folder(df.sparkSession)
    kept = df.checkpoint(eager=True)
    df.sparkSession._jvm.System.gc()
    return kept


def text_or_empty(column: str | Column = "text") -> Column:
    """A text of null counts as empty throughout this subpackage."""
    return F.coalesce(F.col(column) if isinstance(column, str) else column, F.lit(""))


def computed_once(value: Column, otherwise: Column) -> Column:
    """value, behind a condition that always holds but that the optimiser can't foresee.

    It doesn't push filters through a projection that holds such a column, so it doesn't copy the
    expensive columns below it into the filter, where each copy would be computed again.
    """
    return F.when(F.monotonically_increasing_id() >= 0, value).otherwise(otherwise)


def utf8(column: str | Column = "text") -> Column:
    """The bytes of a text, for kernels that work on bytes."""
    return text_or_empty(column).cast("binary")


def map_arrow(df: DataFrame, kernel, schema) -> DataFrame:
    """mapInArrow with batches of few rows: texts are long, and a batch is held several times over.

    When a task is done, its worker, which Spark keeps for later tasks, gives free memory back.
    """
    conf, key = df.sparkSession.conf, "spark.sql.execution.arrow.maxRecordsPerBatch"
    if not 0 < int(conf.get(key)) <= BATCH_ROWS:
        conf.set(key, str(BATCH_ROWS))

    def bounded(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from kernel(batches)
        finally:
            give_back()

    return df.mapInArrow(bounded, schema)


def with_field(df: DataFrame, name: str, kind: str) -> T.StructType:
    """The schema of df with one more column."""
    return T.StructType([*df.schema.fields, T.StructField(name, T._parse_datatype_string(kind))])


def free_name(df: DataFrame, wanted: str) -> str:
    """A column name that df does not have yet, in any case."""
    taken = {c.lower() for c in df.columns}
    while wanted.lower() in taken:
        wanted += "_"
    return wanted


def batches_of(rows: Iterator[tuple], schema: pa.Schema, size: int = 20_000) -> Iterator[pa.RecordBatch]:
    """Record batches from an iterator of row tuples."""
    held: list[tuple] = []
    for row in rows:
        held.append(row)
        if len(held) >= size:
            yield as_batch(held, schema)
            held = []
    if held:
        yield as_batch(held, schema)


def as_batch(rows: list[tuple], schema: pa.Schema) -> pa.RecordBatch:
    columns = zip(*rows, strict=True) if rows else [[] for _ in schema]
    return pa.RecordBatch.from_arrays([pa.array(list(c), f.type) for c, f in zip(columns, schema, strict=True)], schema=schema)
