"""The target of op6 is every good document, whichever way it is marked."""

import pytest
from pyspark.sql import functions as F

from rowblock.llm import lm_scoring
from rowblock.llm.toxicity import held_out


@pytest.mark.parametrize("limit", [lm_scoring.BROADCAST_IDS, -1])
def test_every_good_document_is_counted(spark, monkeypatch, limit):
    monkeypatch.setattr(lm_scoring, "BROADCAST_IDS", limit)
    docs = spark.range(60_000).select(F.when(F.col("id") > 0, F.col("id")).alias("doc_id"), F.lit("ab").alias("text"))
    labels = spark.range(60_000).select(F.col("id").alias("doc_id"), (F.col("id") % 4 > 0).cast("int").alias("quality"))
    want = labels.where("quality = 1").where(~held_out(F.col("doc_id"))).count()
    marked = lm_scoring.mark_target(docs, labels)
    assert want > 20_000 and marked.count() == 60_000 and marked.where("target").count() == want
