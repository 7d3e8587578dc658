"""Tables at which certified cutoffs and host reputations act, through the queries and their SQL; odd rows; clashing names."""

import random

import duckdb
import pytest
from pyspark.sql import functions as F

from rowblock.llm import quality_rules, queries, url_filters


def against_sql(spark, folder, name, tables):
    """The query's rows by key, after comparing all of them with its SQL's."""
    con = duckdb.connect()
    for table, df in tables.items():
        df.write.parquet(f"{folder}/{table}.parquet")
        con.sql(f"CREATE VIEW {table} AS SELECT * FROM '{folder}/{table}.parquet/*.parquet'")
    df = queries.QUERIES[name](spark, str(folder))
    names = sorted(df.columns)
    got = sorted(repr(tuple(r[c] for c in names)) for r in df.collect())
    cursor = con.execute(queries.ORACLES[name])
    own = [d[0] for d in cursor.description]
    assert got == sorted(repr(tuple(dict(zip(own, r, strict=True))[c] for c in names)) for r in cursor.fetchall())
    return {r[0]: r for r in df.collect()}


def test_cutoffs_act(spark, tmp_path):
    rng = random.Random(4)
    rows, marks = [], []
    for i in range(3400):
        bad = i % 17 == 0
        words = [f"w{rng.randint(0, 99999)}" + ("#$%&" if bad else "") for _ in range(25)]
        rows.append((i, " ".join(words), "en" if i < 3000 else "fr"))
        marks.append((i, int(not bad), 0))
    docs = spark.createDataFrame([*rows, (9000, None, None), (9001, "", "xx")], "doc_id long, text string, lang string")
    got = against_sql(spark, tmp_path, "op8_quality_rules", {"documents": docs, "labels": spark.createDataFrame(marks, "doc_id long, quality int, toxic int")})
    en, fr = [got[i] for i in range(3000)], [got[i] for i in range(3000, 3400)]
    assert not any(r["base_failed"] for r in en + fr) and all(r["kept"] == (r["doc_id"] % 17 != 0) for r in en)
    assert all(r["kept"] for r in fr)  # too few labels to certify anything
    assert got[9000]["base_failed"] and not got[9001]["kept"]


def test_a_cutoff_that_costs_too_many_good_documents_is_not_certified(spark):
    control = quality_rules.RiskControl()
    names = [*control.grid]
    rows = [("en", k % 10 > 0, *([0.45] * len(names) if k % 25 == 0 or k % 10 == 0 else [0.0] * len(names))) for k in range(6000)]
    df = spark.createDataFrame(rows, "stratum string, good boolean, " + ", ".join(f"{n} double" for n in names))
    assert {r["cutoff"] for r in quality_rules.choose_cutoffs(df, control).where("rule = 'symbol_rate'").collect()} <= {None, 0.5}


def test_clashing_names_of_quality_rules(spark):
    names = ["cut_stratum", "cut_symbol_rate", "base_failed", "kept", "n_words", "text_", "words_", "labelled_id"]
    text = " ".join(f"word{k}" for k in range(30))
    df = spark.createDataFrame([(1, text, "en", *names), (2, "few", None, *names)], "doc_id long, text string, lang string, " + ", ".join(f"{n} string" for n in names))
    labels = spark.createDataFrame([(1, 1), (2, None)], "doc_id long, quality int")
    out = quality_rules.keep_good(df, labels)
    assert out.columns == df.columns and [tuple(r) for r in out.collect()] == [(1, text, "en", *names)]


def pages_of(hosts):
    return [(k, f"http://{h}/p{k}", None) for k, h in enumerate(hosts)]


def test_host_verdicts_act(spark, tmp_path):
    hosts = ["bad.site.net"] * 60 + ["good.site.net"] * 60 + ["a.shop.co.uk"] * 40 + ["b.shop.co.uk"] * 3 + ["x.other.co.uk"] * 40 + ["10.0.0.1"] * 30 + ["10.0.0.2:8080", "user@Bad.site.net:80", "lone"] + ["q.org"] * 5
    rows = [*pages_of(hosts), (900, None, None), (901, "no scheme", None), (902, "x:///only/path", None)]
    bad = {"bad.site.net", "a.shop.co.uk", "10.0.0.1"}
    labels = [(k, int(h not in bad), 0) for k, h in enumerate(hosts) if k % 7 and not h.startswith("b.shop")] + [(900, 0, 1), (901, 0, 1), (902, 0, 1), (5, None, None)]
    got = against_sql(spark, tmp_path, "op9_url_filters", {"pages": spark.createDataFrame(rows, "page_id long, url string, html string"), "labels": spark.createDataFrame(labels, "doc_id long, quality int, toxic int")})
    verdicts = {}
    for k, h in enumerate(hosts):
        verdicts.setdefault(h, set()).add(got[k]["verdict"])
    assert verdicts["bad.site.net"] == verdicts["a.shop.co.uk"] == verdicts["10.0.0.1"] == verdicts["user@Bad.site.net:80"] == {"block"}
    assert verdicts["good.site.net"] == verdicts["x.other.co.uk"] == verdicts["lone"] == verdicts["q.org"] == {"allow"}
    assert verdicts["10.0.0.2:8080"] == {"allow"}  # not the domain of the other address
    assert [got[k]["verdict"] for k in (900, 901, 902)] == ["allow"] * 3


def test_domains_and_suffixes(spark):
    names = ["a.b.co.uk", "co.uk", "b.co.uk", "x.y.com", "y.com", "com", "1.2.3.4", "[::1]", ""]
    df = spark.createDataFrame([(n,) for n in names], "n string")
    domain, suffix = url_filters.domain_and_suffix(F.col("n"), url_filters.SUFFIXES)
    got = {r["n"]: (r["d"], r["s"]) for r in df.select("n", domain.alias("d"), suffix.alias("s")).collect()}
    assert got == {"a.b.co.uk": ("b.co.uk", "co.uk"), "co.uk": ("co.uk", "co.uk"), "b.co.uk": ("b.co.uk", "co.uk"), "x.y.com": ("y.com", "com"), "y.com": ("y.com", "com"), "com": ("com", "com"), "1.2.3.4": ("1.2.3.4", "1.2.3.4"), "[::1]": ("[::1]", "[::1]"), "": ("", "")}


def test_empty_pages(spark):
    pages = spark.createDataFrame([], "page_id long, url string, html string")
    for labels in ([], [(1, 0, 1)]):
        assert url_filters.judge(pages, spark.createDataFrame(labels, "doc_id long, quality int, toxic int")).count() == 0


def test_repeated_page_ids_are_judged_one_by_one(spark):
    pages = spark.createDataFrame([(1, "a://x.com/", "h"), (1, "a://y.org/", "h"), (None, "a://example.org/es/1", None)], "page_id long, url string, html string")
    got = url_filters.judge(pages, spark.createDataFrame([(1, 0, 0)], "doc_id long, quality int, toxic int")).collect()
    assert sorted(r["host"] for r in got) == ["example.org", "x.com", "y.org"]


@pytest.mark.parametrize("name", ["op9_url_filters"])
def test_the_plan_is_small(spark, sf, name):
    plan = queries.QUERIES[name](spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert plan.count("Exchange") < 25 and "NestedLoop" not in plan
