import numpy as np
import pytest

from rowblock.errors import BadRow, FactorizationError, GramNotPositiveDefinite, TooFewRows
from rowblock.functions import fixtures as fx
from rowblock.matrix import NarrowMatrix
from rowblock.operators import direct as d
from rowblock.operators import gram as g
from rowblock.operators import measures, rtree
from rowblock.operators import svd as sv
from rowblock.plans import costmodel as cm
from rowblock.plans import experiments as ex
from rowblock.plans.planner import choose_method
from rowblock.qr import qr

CASES = [
    ("cholesky", {}), ("cholesky", {"refine": 1}), ("rtree", {}), ("rtree", {"refine": 2}), ("rtree", {"refine": 1, "fused": False}), ("rtree", {"how": "solve"}), ("direct", {}), ("direct", {"block_rows": 300}), ("direct", {"n_blocks": 5, "combine": "task"}),
    ("direct", {"n_blocks": 7, "replay": True, "deliver": "join"}), ("direct_rec", {"fan_in": 2, "block_rows": 300}), ("householder", {}), ("householder", {"form": "two_pass"}), ("householder", {"form": "three_pass"}), ("householder", {"form": "panel", "panel": 2}), ("householder", {"form": "panel", "panel": 9}),
]


def matrix(spark, a, parts=3):
    return NarrowMatrix.from_array(spark.createDataFrame([(i, row.tolist()) for i, row in enumerate(a)], "id long, a array<double>").repartition(parts), ["id"], "a", a.shape[1])


@pytest.fixture(scope="module")
def small():
    return np.random.default_rng(3).standard_normal((1200, 5))


@pytest.mark.parametrize(("method", "opts"), CASES, ids=lambda x: str(x))
def test_every_method_factors(spark, small, method, opts):
    nm = matrix(spark, small)
    res = qr(nm, method, **opts)
    ref = np.linalg.qr(small, mode="r")
    ref = np.sign(np.diagonal(ref))[:, None] * ref
    assert np.allclose(res.r, ref, atol=1e-10)
    q = np.array([[r[f"q{i}"] for i in range(5)] for r in sorted(res.q.collect(), key=lambda r: r["id"])])
    assert q.shape == small.shape and np.allclose(q @ res.r, small, atol=1e-10) and np.allclose(q.T @ q, np.eye(5), atol=1e-10)
    assert measures.orthogonality(res.q_matrix) < 1e-12 and measures.residual(nm, res.q, res.r) < 1e-12
    assert measures.unmatched_rows(nm, res.q) == 0
    res.release()


@pytest.mark.parametrize("rows", [1, 4, 5, 6, 1000])
def test_blocks_of_any_size(spark, small, rows):
    assert np.allclose(qr(matrix(spark, small[:60]), "direct", block_rows=rows).r, qr(matrix(spark, small[:60]), "rtree", want_q=False).r, atol=1e-10)


def test_edges(spark, small):
    square = small[:5]
    assert np.allclose(abs(np.linalg.det(qr(matrix(spark, square), "direct").r)), abs(np.linalg.det(square)))
    with pytest.raises(TooFewRows):
        qr(matrix(spark, small[:3]), "direct")
    with pytest.raises(GramNotPositiveDefinite):
        qr(matrix(spark, np.hstack([small, np.zeros((len(small), 1))])), "cholesky")
    double = np.hstack([small, small[:, :1]])
    assert qr(matrix(spark, double), "cholesky", fallback=True).report.method == "direct" if _breaks(spark, double) else True
    assert measures.orthogonality(qr(matrix(spark, double), "direct").q_matrix) < 1e-12
    one = qr(matrix(spark, small[:, :1]), "direct")
    assert np.isclose(one.r[0, 0], np.linalg.norm(small[:, 0]))
    with pytest.raises(FactorizationError):
        qr(matrix(spark, small), "unknown")


def _breaks(spark, a):
    try:
        qr(matrix(spark, a), "cholesky", want_q=False)
    except GramNotPositiveDefinite:
        return True
    return False


def test_bad_rows(spark):
    df = spark.createDataFrame([(1, [1.0, 2.0]), (2, [3.0, float("nan")]), (3, [2.0, 1.0]), (4, [1.0]), (5, None), (6, [1.0, 1.0])], "id int, a array<double>")
    with pytest.raises(Exception, match="BadRow|values"):
        qr(NarrowMatrix.from_array(df, ["id"], "a", 2), "direct")
    res = qr(NarrowMatrix.from_array(df, ["id"], "a", 2, on_bad_row="drop"), "direct")
    assert {r["id"] for r in res.q.collect()} == {1, 3, 6}
    assert issubclass(BadRow, ValueError)


def test_gram_strategies(spark, small):
    nm = matrix(spark, small)
    for s in g.STRATEGIES:
        assert np.allclose(g.to_numpy(g.gram(nm, s), 5), small.T @ small), s


def test_layouts(spark, small):
    nm = matrix(spark, small)
    assert np.allclose(rtree.r_factor(nm.wide()), rtree.r_factor(nm))
    assert np.allclose(rtree.r_factor(nm.leading(2)), rtree.r_factor(nm)[:2, :2])
    assert np.allclose(nm.equilibrated().column_norms(), 1)
    assert np.allclose(rtree.r_factor(nm.append(nm)), np.sqrt(2) * rtree.r_factor(nm))
    assert nm.with_intercept().n == 6 and nm.count() == 1200


def test_svd_family(spark, small):
    nm = matrix(spark, small)
    u, s, vt = np.linalg.svd(small, full_matrices=False)
    for keep in (True, False):
        res = sv.svd(nm, keep_q=keep, block_rows=300)
        assert np.allclose(res.sigma, s) and np.allclose(np.abs(res.v.T), np.abs(vt))
        got = np.array([[r[f"u{i}"] for i in range(5)] for r in sorted(res.u.collect(), key=lambda r: r["id"])])
        assert np.allclose(np.abs(got), np.abs(u))
    assert np.allclose(sv.singular_values(nm), s) and np.isclose(sv.condition_number(nm), s[0] / s[-1]) and sv.numerical_rank(nm) == 5
    x, left = sv.least_squares(nm)
    ref, res, *_ = np.linalg.lstsq(small[:, :4], small[:, 4], rcond=None)
    assert np.allclose(x, ref) and np.isclose(left**2, res[0])
    variances, directions = sv.pca(nm)
    assert np.allclose(variances, np.sort(np.linalg.eigvalsh(np.cov(small.T)))[::-1]) and directions.shape == (5, 5)


def test_direct_is_stable_where_others_are_not(spark, sf):
    nm = fx.dial(spark, sf, 12)
    assert measures.orthogonality(qr(nm, "direct").q_matrix) < 1e-12
    assert measures.orthogonality(qr(nm, "rtree").q_matrix) > 1e-8


def test_plans(spark, sf):
    nm = fx.raw4(spark, sf)
    plan = lambda df: df._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan(d.direct_local(nm)) and "Exchange" not in plan(rtree.local_r(nm))
    from rowblock.staging import Stage

    table = Stage(spark).write(d.direct_local(nm), "blocks")
    assert "ReadSchema: struct<block_id:bigint,r:array<double>>" in plan(table.select("block_id", "r"))


def test_bounds_reproduce_the_published_ones():
    for shape, bounds in zip(cm.PUBLISHED, cm.PUBLISHED_BOUNDS, strict=True):
        c = cm.Cluster(shape[2], shape[3])
        for method, bound in zip(cm.MODELLED, bounds, strict=True):
            own = cm.lower_bound(method, shape[0], shape[1], cm.published_tasks(shape, method), c)
            assert abs(own / bound - 1) < 0.03, (shape, method, own, bound)


def test_choices():
    assert choose_method(10, 4, want_q=False)[0] == "rtree"
    assert choose_method(10, 10)[0] == "direct"
    assert choose_method(10, 50, n_blocks=400_000)[0] == "direct_rec"
    assert choose_method(10, 10, 100.0, stable=False)[0] == "cholesky"


def test_crashing_tasks_do_not_change_the_result(spark, small, tmp_path):
    nm = matrix(spark, small, 12)
    clean = rtree.r_factor(nm)
    assert np.allclose(ex.fault_run(nm, 0.5, str(tmp_path)), clean)
    assert any(tmp_path.iterdir())


def test_merge_of_summaries(spark, sf):
    from rowblock.queries import _flagged

    low = rtree.r_factor_by(_flagged(spark, sf), ["l_returnflag", "l_linestatus"])
    total = rtree.merge_summaries(low, 4, [])
    assert np.allclose(g.to_numpy(total, 4), rtree.r_factor(_flagged(spark, sf)), atol=1e-9)


def test_long_form(spark):
    df = spark.createDataFrame([(1, 0, 2.0), (1, 1, 1.0), (2, 1, 3.0), (3, 0, 1.0)], "k int, j int, v double")
    assert np.allclose(g.to_numpy(g.gram_from_long(df, "k", "j", "v"), 2), [[5, 2], [2, 10]])
    assert np.allclose(rtree.r_factor(NarrowMatrix.from_long(df, "k", "j", "v", 2))[0, 0], np.sqrt(5))


def test_bucketed_blocks_join_without_an_exchange(spark, small):
    nm = matrix(spark, small)
    res = qr(nm, "direct", block_rows=100, buckets=3)
    plan = res.q._jdf.queryExecution().executedPlan().toString()
    assert "SortMergeJoin" in plan and "Exchange" not in plan
    assert measures.orthogonality(res.q_matrix) < 1e-12
    res.release()


def test_crashes_change_nothing_but_time(spark, sf):
    made = fx.cheb(spark, sf, 4)
    runs = ex.fault_sweep(NarrowMatrix(made.df.repartition(16), made.keys, made.cols, None, 4), (0, 1 / 8, 1 / 2))
    assert [p for p, *_ in runs] == [0, 1 / 8, 1 / 2] and all(np.allclose(r, runs[0][3], rtol=1e-10) for *_, r in runs)


def test_duplicated_columns_raise_where_r_has_to_be_inverted(spark, sf):
    from rowblock.errors import RankDeficient

    given = fx.raw4(spark, sf)
    nm = NarrowMatrix(given.df.withColumn("again", given.df[given.cols[0]]), given.keys, (*given.cols, "again"), None, 5)
    with pytest.raises((RankDeficient, GramNotPositiveDefinite)):
        qr(nm, "rtree").q.count()
    with pytest.raises((RankDeficient, GramNotPositiveDefinite)):
        qr(nm, "cholesky", refine=1).q.count()
    assert measures.orthogonality(qr(nm, "direct").q_matrix) < 1e-12


@pytest.mark.parametrize("batch", ["100", "10000"])
def test_blocks_have_their_rows_however_they_are_batched(spark, sf, batch):
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", batch)
    try:
        nm = fx.raw4(spark, sf)
        nm = NarrowMatrix(nm.df.coalesce(1), nm.keys, nm.cols, None, nm.n)
        assert rtree.local_r(nm, 2500).count() == 3
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)


def test_many_slices_go_out_by_ranges_without_moving_q(spark, sf, monkeypatch):
    nm = fx.cheb(spark, sf, 10)
    want = {tuple(r)[: len(nm.keys)]: tuple(r)[len(nm.keys) :] for r in qr(nm, "direct", n_blocks=40).q.collect()}
    monkeypatch.setattr(d, "BROADCAST_BYTES", 8 * 40 * 100 // 5)
    q = qr(nm, "direct", n_blocks=40).q
    plan = q._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in plan and "Exchange hashpartitioning" not in plan
    got = {tuple(r)[: len(nm.keys)]: tuple(r)[len(nm.keys) :] for r in q.collect()}
    assert got.keys() == want.keys() and all(np.allclose(got[k], want[k], atol=1e-10) for k in want)
