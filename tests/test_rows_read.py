"""Reads of a matrix are counted by a key column alone."""

import re

from rowblock.functions import fixtures as fx
from rowblock.operators import svd as sv
from rowblock.plans import experiments as ex
from rowblock.qr import qr


def test_no_values_go_to_the_counter(spark, sf):
    seen = []
    nm = fx.cheb(spark, sf, 10)

    def run(a):
        seen.append(a.df._jdf.queryExecution().executedPlan().toString())
        qr(a, "cholesky").q.write.format("noop").mode("overwrite").save()

    assert ex.rows_read(nm, run) == 2
    assert "MapInArrow" not in seen[0] and re.search(r"ArrowEvalPython \[count\(\w+#\d+L\)", seen[0])
    assert ex.rows_read(nm, sv.singular_values) == 1
    assert ex.rows_read(nm, lambda a: None) == 0
