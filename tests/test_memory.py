"""Workers of the direct method give memory back after each block."""

import numpy as np
import pyarrow as pa

from rowblock.functions import fixtures as fx
from rowblock.operators import direct as d


def test_a_task_gives_memory_back_after_each_block(spark, sf, monkeypatch):
    calls, kernels = [], []
    monkeypatch.setattr(d, "give_back", lambda: calls.append(1))
    nm = fx.raw4(spark, sf)
    frame = type(nm.df)
    monkeypatch.setattr(frame, "mapInArrow", lambda self, kernel, schema: kernels.append(kernel) or self)
    d.direct_local(nm, 2, 50)
    rng = np.random.default_rng(1)
    batch = lambda block: pa.RecordBatch.from_arrays([pa.array([block] * 60, pa.int64()), pa.array([{"k": i} for i in range(60)]), pa.array(rng.random((60, 4)).tolist(), pa.list_(pa.float64()))], names=["block_id", "k", "a"])
    made = list(kernels[0](iter([batch(0), batch(1)])))
    assert {b.column(0)[0].as_py() for b in made} == {0, 1} and len(calls) == 2
