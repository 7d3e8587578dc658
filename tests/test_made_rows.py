"""Rows made from a matrix and what is summed over them share one Python worker, and no keys go there."""

import numpy as np

from rowblock.functions import fixtures
from rowblock.operators import gram, measures
from rowblock.operators.indirect import apply_r_inverse, as_matrix, first_r
from rowblock.plans.experiments import rows_read
from rowblock.qr import qr


def test_a_made_matrix_takes_one_worker(spark, sf):
    nm = fixtures.raw4(spark, sf)
    q = as_matrix(apply_r_inverse(nm, first_r(nm, "rtree")), nm)
    plan = gram.gram(q)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("MapInArrow") == 1
    seen = np.array([[r[c] for c in q.cols] for r in q.df.collect()])
    assert np.allclose(gram.to_numpy(gram.gram(q), 4), seen.T @ seen, atol=1e-12)
    assert measures.orthogonality(q) < 1e-10


def test_a_derived_matrix_is_not_the_made_one(spark, sf):
    nm = fixtures.raw4(spark, sf)
    q = as_matrix(apply_r_inverse(nm, first_r(nm, "rtree")), nm)
    doubled = gram.to_numpy(gram.gram(q.scaled([2.0] * 4)), 4)
    assert np.allclose(doubled, 4 * gram.to_numpy(gram.gram(q), 4))
    assert np.allclose(gram.to_numpy(gram.gram(q.leading(2)), 2), gram.to_numpy(gram.gram(q), 4)[:2, :2])


def test_reads_are_counted_as_before(spark, sf):
    def run(nm):
        res = qr(nm, "rtree", refine=1)
        res.q.write.format("noop").mode("overwrite").save()

    assert rows_read(fixtures.cheb(spark, sf, 4), run) == 3
