"""Packing where many rows share an id."""

from collections import Counter

import pytest
from pyspark.sql import functions as F

from rowblock.llm import packing
from tests.llm.test_operators import JSON, RANKS


@pytest.mark.parametrize("doc_id", ["CAST(NULL AS LONG)", "7L"])
def test_equal_rows_spread_over_groups(spark, doc_id):
    df = spark.range(0, 400, 1, 2).selectExpr(f"{doc_id} AS doc_id", "'some words of a text' AS text", "id AS grp", "id AS content")
    out = packing.pack(df, JSON, RANKS, capacity=64, group_docs=20).collect()
    total = {r["doc_tokens"] for r in out}
    assert len(total) == 1 and sum(r["length"] for r in out) == 400 * total.pop()
    groups = Counter(r["sequence_id"] >> 32 for r in out if r["start"] == 0)
    assert len(groups) == 20 and max(groups.values()) == 20


def test_different_texts_under_one_id_are_packed_apart(spark):
    df = spark.createDataFrame([(1, "a b c"), (1, "a b c d e"), (1, None), (2, "")], "doc_id long, text string")
    out = packing.pack(df, JSON, RANKS, capacity=8).groupBy("doc_id", "doc_tokens").agg(F.sum("length").alias("n")).collect()
    assert all(r["n"] == r["doc_tokens"] for r in out) and len(out) == 4
