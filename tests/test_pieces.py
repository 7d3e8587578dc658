"""Blocks of the direct method that are written in pieces and factored in parts."""

from pyspark.sql import functions as F

from rowblock.functions import fixtures as fx
from rowblock.operators import direct as d
from rowblock.operators import measures
from rowblock.qr import qr


def test_no_row_of_the_stage_table_holds_a_whole_large_block(spark, sf):
    nm = fx.raw4(spark, sf)
    table = d.direct_local(nm, 1)
    most, rows, blocks = table.agg(F.max(F.size("keys")), F.sum(F.size("keys")), F.countDistinct("block_id")).first()
    assert most * (8 * nm.n + 40) <= d.PIECE_BYTES and rows == 6000 and blocks == 1
    assert d.triangles(table).count() == 1


def test_a_dealt_block_of_several_parts_has_one_triangle_and_every_row(spark, sf):
    nm = fx.cheb(spark, sf, 10)
    res = qr(nm, "direct", n_blocks=2, block_rows=500)
    assert d.triangles(d.direct_local(nm, 2, 500)).count() == 2
    assert measures.unmatched_rows(nm, res.q) == 0
    assert measures.orthogonality(res.q_matrix) < 1e-12 and measures.residual(nm, res.q, res.r) < 1e-13
