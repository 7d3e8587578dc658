"""Dealt blocks: each in a partition of its own."""

from pyspark.sql import functions as F

from rowblock.blocks import assign
from rowblock.functions import fixtures as fx


def test_every_dealt_block_has_a_partition_of_its_own(spark, sf):
    dealt = assign(fx.raw4(spark, sf), 16).select("block_id", F.spark_partition_id().alias("p")).distinct().collect()
    assert len(dealt) == 16 and len({x["p"] for x in dealt}) == 16
