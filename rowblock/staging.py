"""Tables between the steps of a run, in the folder that driver and executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """What spark.checkpoint.dir names; a temporary folder only where nothing is set (tests, one machine)."""
    context = spark.sparkContext
    if not context.getCheckpointDir():
        set_to = spark.conf.get("spark.checkpoint.dir", None) or context.getConf().get("spark.checkpoint.dir")
        context.setCheckpointDir(set_to or tempfile.mkdtemp(prefix="rowblock-"))
    return context.getCheckpointDir()


ROW_GROUP_BYTES = 8 << 20  # what a task holds while it writes, and at most has in memory of a file it reads


class Stage:
    """A folder for one run's tables. Each is written once and committed, so that all that is read later fits together."""

    def __init__(self, spark: SparkSession) -> None:
        self.spark, self.path = spark, f"{shared_folder(spark)}/run-{uuid.uuid4().hex}"
        self.tables: list[str] = []

    def write(self, df: DataFrame, name: str) -> DataFrame:
        df.write.option("parquet.block.size", ROW_GROUP_BYTES).parquet(f"{self.path}/{name}")
        return self.read(name)

    def write_bucketed(self, df: DataFrame, name: str, buckets: int, key: str) -> DataFrame:
        """A table whose files are dealt by a key. Two of them with as many buckets join on it without an exchange."""
        table = f"rowblock_{self.path.rpartition('-')[2]}_{name}"
        df.write.option("path", f"{self.path}/{name}").option("parquet.block.size", ROW_GROUP_BYTES).bucketBy(buckets, key).saveAsTable(table)
        self.tables.append(table)
        return self.spark.table(table)

    def read(self, name: str) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/{name}")

    def release(self) -> None:
        """Delete the run's tables; frames that still read them are of no use afterwards."""
        for table in self.tables:
            self.spark.sql(f"DROP TABLE IF EXISTS {table}")
        jvm = self.spark._jvm
        path = jvm.org.apache.hadoop.fs.Path(self.path)
        path.getFileSystem(self.spark._jsc.hadoopConfiguration()).delete(path, True)
