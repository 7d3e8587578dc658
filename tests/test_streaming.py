import numpy as np

from rowblock.operators import relational as rel
from rowblock.sources import dial
from rowblock.streaming import summaries as st


def stream(spark, folder, rows, parts=3):
    df = spark.createDataFrame(rows, "g string, x double, y double, ts timestamp")
    for k in range(parts):
        df.where(f"abs(hash(x, y)) % {parts} = {k}").coalesce(1).write.mode("append").parquet(folder)
    return st.row_stream(spark, folder, df.schema, 1)


def rows(n=60):
    from datetime import datetime, timedelta

    rng = np.random.default_rng(1)
    return [("ab"[i % 2], float(rng.normal()), float(rng.normal()), datetime(2024, 1, 1) + timedelta(hours=i)) for i in range(n)]


def test_running_triangle_equals_the_batch(spark, tmp_path):
    data = rows()
    out = {r["g"]: np.array(r["r"]).reshape(2, 2) for r in st.drain(st.running_r(stream(spark, str(tmp_path / "a"), data), "g", ["x", "y"]), "update", ["g"]).collect()}
    for key in "ab":
        a = np.array([r[1:3] for r in data if r[0] == key])
        ref = np.linalg.qr(a, mode="r")
        assert np.allclose(out[key], np.sign(np.diagonal(ref))[:, None] * ref)


def test_restart_goes_on_from_the_checkpoint(spark, tmp_path):
    data = rows()
    s = stream(spark, str(tmp_path / "a"), data[:30])
    state = str(tmp_path / "state")
    st.drain(st.running_r(s, "g", ["x", "y"]), "update", ["g"], state)
    spark.createDataFrame(data[30:], "g string, x double, y double, ts timestamp").write.mode("append").parquet(str(tmp_path / "a"))
    out = {r["g"]: np.array(r["r"]).reshape(2, 2) for r in st.drain(st.running_r(s, "g", ["x", "y"]), "update", ["g"], state).collect()}
    a = np.array([r[1:3] for r in data if r[0] == "a"])
    ref = np.linalg.qr(a, mode="r")
    assert np.allclose(out["a"], np.sign(np.diagonal(ref))[:, None] * ref)


def test_windows_and_late_rows(spark, tmp_path):
    out = st.drain(st.windowed_gram(stream(spark, str(tmp_path / "a"), rows()), "ts", ["x"], "1 day", "6 hours", late="3650 days"), "complete")
    assert out.count() > 0
    plain = st.drain(st.windowed_gram(stream(spark, str(tmp_path / "b"), rows()), "ts", ["x"], "1 day", late="3650 days"), "complete")
    assert plain.agg({"n": "sum"}).first()[0] == 60


def test_dial_source(spark):
    dial.register(spark)
    df = spark.read.format("dial_matrix").option("rows", 400).option("columns", 3).option("cond", 1e4).load()
    a = np.array([r["a"] for r in df.orderBy("id").collect()])
    assert a.shape == (400, 3) and 1e3 < np.linalg.cond(a) < 1e5


def test_range_join_equals_the_pairs(spark):
    pts = spark.createDataFrame([(i, float(i)) for i in range(50)], "p int, at double")
    spans = spark.createDataFrame([(1, 3.0, 3.0), (2, 4.5, 30.0), (3, -5.0, 2.0)], "s int, a double, b double")
    got = {(r["p"], r["s"]) for r in rel.range_join(pts, spans, "at", "a", "b", 7.0).collect()}
    assert got == {(i, s) for i in range(50) for s, a, b in ((1, 3, 3), (2, 4.5, 30), (3, -5, 2)) if a <= i < b}
