"""The n-gram counts of op6 are exact, and both ways to look losses up give the slow model's scores."""

from collections import Counter

import numpy as np
import pytest

from rowblock.llm import lm_scoring

TEXTS = [bytes(np.random.default_rng(k).integers(32, 127, 4000, dtype=np.uint8)).decode() for k in range(30)] + ["", None, "ab", "ab"]


def test_counts_are_exact(spark):
    data = [(t or "").encode() for t in TEXTS]
    want = Counter()
    for x in data:
        for k in range(4):
            want.update(((k + 1) << 32) | int.from_bytes((b"\0\0\0" + x)[i + 3 - k : i + 4], "big") for i in range(len(x)))
    counts = lm_scoring.Counts()
    for x in data:
        counts.add(x)
    grams, n = counts.take()
    assert len(want) > 90_000 and dict(zip(grams.tolist(), n.tolist(), strict=True)) == want


@pytest.mark.parametrize("limit", [lm_scoring.BROADCAST_GRAMS, -1])
def test_scores_against_the_model(spark, monkeypatch, limit):
    monkeypatch.setattr(lm_scoring, "BROADCAST_GRAMS", limit)
    docs = spark.createDataFrame(list(enumerate(TEXTS)), "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i % 2 == 0)) for i in range(34)], "doc_id long, quality int")
    chosen = [i for i in range(34) if i % 2 == 0]
    held = {r[0] for r in labels.where(lm_scoring.held_out(lm_scoring.F.col("doc_id"))).select("doc_id").collect()}
    models = []
    for ids in (range(34), [i for i in chosen if i not in held]):
        counts = lm_scoring.Counts()
        for i in ids:
            counts.add((TEXTS[i] or "").encode())
        models.append(lm_scoring.Model(counts.take()))
    got = lm_scoring.score(docs, labels).collect()
    assert len(got) == 34
    for r in got:
        data = (TEXTS[r["doc_id"]] or "").encode()
        want = [m.loss(*lm_scoring.places(data)) / len(data) if data else 0 for m in models]
        assert [r["background_loss"], r["target_loss"]] == pytest.approx(want, rel=1e-5) and r["n_tokens"] == len(data)
