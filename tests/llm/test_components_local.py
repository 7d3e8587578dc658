"""Components of few links take no rounds of rewriting, and are those of the rounds."""

import numpy as np
import pytest

from rowblock.llm import components


def found(links) -> dict:
    return {r["vertex"]: r["root"] for r in components.connected_components(links).collect()}


def test_few_links_need_no_rounds(spark, monkeypatch):
    monkeypatch.setattr(components, "_small_star", lambda links: pytest.fail("a round of rewriting"))
    links = spark.createDataFrame([(k + 1, k) for k in range(500)] + [(-9, -7), (7, 7), (-9, -7), (None, 3)], "a long, b long")
    assert found(links) == {k: 0 for k in range(501)} | {-9: -9, -7: -9}
    assert found(links.where("a > 1000")) == {}


def test_both_ways_give_the_same(spark, monkeypatch):
    edges = np.random.default_rng(3).integers(-(1 << 62), 1 << 62, 300)[np.random.default_rng(4).integers(0, 300, (220, 2))].tolist()
    links = spark.createDataFrame([tuple(e) for e in edges], "a long, b long")
    local = found(links)
    monkeypatch.setattr(components, "LOCAL_LINKS", 0)
    assert len(local) > 100 and found(links) == local
