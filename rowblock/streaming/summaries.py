"""Running summaries of unbounded rows. Gram matrices add up, and triangles merge, so a stream keeps only small state."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..kernels import fold_r
from ..staging import shared_folder


def row_stream(spark: SparkSession, folder: str, schema, files_per_trigger: int | None = None) -> DataFrame:
    """Rows of files as they arrive in a folder."""
    reader = spark.readStream.schema(schema)
    if files_per_trigger:
        reader = reader.option("maxFilesPerTrigger", files_per_trigger)
    return reader.parquet(folder)


def running_gram(rows: DataFrame, cols: list[str], groups: list[str]) -> DataFrame:
    """Sums of products by group, updated with every batch."""
    n = len(cols)
    return rows.groupBy(*groups).agg(F.count(F.lit(1)).alias("n"), *(F.sum(F.col(cols[i]) * F.col(cols[j])).alias(f"g{i}_{j}") for i in range(n) for j in range(i, n)))


def windowed_gram(rows: DataFrame, ts: str, cols: list[str], width: str, slide: str | None = None, late: str = "2 hours") -> DataFrame:
    """Gram sums of each window of time; rows that come later than the watermark are left out."""
    marked = rows.withWatermark(ts, late)
    of = F.window(ts, width, slide) if slide else F.window(ts, width)
    return running_gram(marked.withColumn("w", of), cols, ["w"])


def running_r(rows: DataFrame, group: str, cols: list[str]) -> DataFrame:
    """(group, r) after every batch: the state of a group is one triangle, whatever the number of rows."""
    n = len(cols)

    def step(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        r = np.array(state.get[0]).reshape(-1, n) if state.exists else None
        for f in frames:
            r = fold_r(r, f[cols].to_numpy(dtype=float))
        state.update((r.ravel().tolist(),))
        yield pd.DataFrame({group: [key[0]], "r": [r.ravel().tolist()]})

    return rows.groupBy(group).applyInPandasWithState(step, f"{group} string, r array<double>", "r array<double>", "update", GroupStateTimeout.NoTimeout)


def distinct_rows(rows: DataFrame, key: str, ts: str, late: str) -> DataFrame:
    """Each row key once, as far as the watermark reaches."""
    return rows.withWatermark(ts, late).dropDuplicatesWithinWatermark([key])


def drain(stream: DataFrame, mode: str, keys: list[str] | None = None, checkpoint: str | None = None) -> DataFrame:
    """Run a stream over all that is there, and give its last result as a table in the shared folder."""
    spark = stream.sparkSession
    run = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"

    def keep(batch: DataFrame, number: int) -> None:
        batch.withColumn("batch_no", F.lit(number)).write.mode("overwrite").parquet(f"{run}/out/part={number:08d}")

    query = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", checkpoint or f"{run}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    out = spark.read.parquet(f"{run}/out").drop("part")
    if keys:
        latest = out.groupBy(*keys).agg(F.max("batch_no").alias("batch_no"))
        out = out.join(latest, [*keys, "batch_no"])
    elif mode == "complete":
        out = out.join(out.agg(F.max("batch_no").alias("batch_no")), "batch_no")
    return out.drop("batch_no")
