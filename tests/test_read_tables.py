"""Queries of the cost model that take their shapes from a given table."""

import pytest

from rowblock.queries import QUERIES


@pytest.mark.parametrize("name", ["k2_step_bytes_published", "k4_published", "k9_choices", "k11_sizes", "u5_pass_bound"])
def test_the_given_table_is_read(spark, sf, tmp_path, name):
    lines = spark.read.parquet(f"{sf}/lineitem.parquet")
    QUERIES[name](spark, sf).count()
    lines.where("l_linenumber = 1").write.parquet(f"{tmp_path}/lineitem.parquet")
    few, every = QUERIES[name](spark, str(tmp_path)).collect(), QUERIES[name](spark, sf).collect()
    assert 0 < len(few) < len(every)


def test_the_source_meets_the_given_orders(spark, sf, tmp_path):
    from rowblock.relational_queries import QUERIES as around

    spark.read.parquet(f"{sf}/orders.parquet").limit(70).write.parquet(f"{tmp_path}/orders.parquet")
    assert tuple(around["o6_dial_source"](spark, str(tmp_path)).first()) == (70, 4)
