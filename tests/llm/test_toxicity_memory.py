"""Training gives the driver's memory back."""

from rowblock.llm import toxicity
from tests.llm.test_toxicity import sample


def test_the_driver_gives_memory_back_after_training(spark, monkeypatch):
    calls = []
    fit = toxicity.fit
    monkeypatch.setattr(toxicity, "fit", lambda *a: calls.append("fit") or fit(*a))
    monkeypatch.setattr(toxicity, "give_back", lambda: calls.append("given back"))
    rows = sample(2, 60)
    docs = spark.createDataFrame([(i, t) for i, (t, _) in enumerate(rows)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, y) for i, (_, y) in enumerate(rows)], "doc_id long, toxic int")
    toxicity.learn(docs, labels)
    assert calls == ["fit", "given back"]
