"""The pipeline on a small fixture against plain Python, and the queries' SQL."""

import re

import duckdb
import pytest

import corpus_pipeline
from rowblock.llm import queries
from tests.llm.test_near_stage import brute_heads
from tests.llm.test_operators import brute_quality, low


def test_stages_against_brute_force(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    kept = [r for r in docs.collect()]
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, docs, sf)
        assert out.columns == docs.columns
        out.write.parquet(str(tmp_path / name))
        docs = spark.read.parquet(str(tmp_path / name))
        ids = {r["doc_id"] for r in docs.collect()}
        if name == "quality":  # too few labels to certify a cutoff, so the base rules alone decide
            want = {r["doc_id"] for r in kept if (q := brute_quality(r["text"] or ""))[0] >= 20 and 100 * q[4] <= 30 * q[0]}
            assert ids == want
        if name == "exact_dedup":
            last = {}
            for r in kept:
                last[low(r["text"] or "")] = max(r["doc_id"], last.get(low(r["text"] or ""), -1))
            assert ids == set(last.values())
        if name == "near_dedup":
            rows = sorted(kept, key=lambda r: r["doc_id"])
            assert ids == {rows[i]["doc_id"] for i in brute_heads([r["text"] or "" for r in rows])}
        kept = [r for r in kept if r["doc_id"] in ids]
    packed = corpus_pipeline.STAGES[-1][1](spark, docs, sf).collect()
    assert {r["doc_id"] for r in packed} == {r["doc_id"] for r in kept}
    whole = {}
    for r in packed:
        whole[r["doc_id"]] = whole.get(r["doc_id"], 0) + r["length"]
    assert all(whole[r["doc_id"]] == r["doc_tokens"] for r in packed)
    assert len(corpus_pipeline.run(spark, sf).collect()) == len(packed)


@pytest.mark.parametrize("name", sorted(queries.ORACLES))
def test_against_sql(spark, sf, name):
    con = duckdb.connect()
    for t in ("documents", "labels", "pages"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    df = queries.QUERIES[name](spark, sf)
    cursor = con.execute(queries.ORACLES[name])
    own = [d[0] for d in cursor.description]
    assert sorted(own) == sorted(df.columns)
    want = sorted(repr(tuple(dict(zip(own, r, strict=True))[c] for c in sorted(own))) for r in cursor.fetchall())
    assert sorted(repr(tuple(r[c] for c in sorted(own))) for r in df.collect()) == want


def test_native_operators_plan_without_python(spark, sf):
    for name in ("op1_line_dedup", "op8_quality_rules", "op9_url_filters"):
        plan = queries.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
        assert not re.search("Python|Arrow|Pandas", plan)
