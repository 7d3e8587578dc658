"""From rows to blocks: what a task sees of a matrix, and blocks that are the same in every run.

The number of blocks is a parameter and not what the scan happens to give. A block is a bucket of a hash of
the key, so its content doesn't depend on which task, attempt or job makes it.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .errors import BadRow
from .matrix import NarrowMatrix

TARGET_BYTES = 16 << 20


def key_hash(nm: NarrowMatrix) -> Column:
    return F.xxhash64(*nm.keys)


def block_rows_for(n: int, key_bytes: int = 32, budget: int = TARGET_BYTES) -> int:
    """Rows of a block that fit a budget of memory."""
    return max(n, budget // (8 * n + key_bytes))


def blocks_for(rows: int, n: int, key_bytes: int = 32, budget: int = TARGET_BYTES) -> int:
    return max(1, -(-rows // block_rows_for(n, key_bytes, budget)))


def assign(nm: NarrowMatrix, n_blocks: int) -> DataFrame:
    """(block_id, keys, a), dealt to one partition for each block (by its id, as a hash of few ids puts several into one) and sorted by key, so that a block's rows and their order can be had again."""
    packed = nm.df.select(F.pmod(key_hash(nm), F.lit(n_blocks)).alias("block_id"), F.struct(*nm.keys).alias("k"), nm.values().alias("a"))
    return packed.repartitionById(n_blocks, F.col("block_id").cast("int")).sortWithinPartitions("block_id", "k", "a")


def to_matrix(values: pa.Array, n: int, on_bad_row: str = "fail") -> tuple[np.ndarray, np.ndarray]:
    """Rows of an Arrow list column as a matrix, and which rows are in it."""
    keep = np.ones(len(values), dtype=bool)
    if not len(values):
        return np.zeros((0, n)), keep
    lengths = values.value_lengths().fill_null(-1).to_numpy(zero_copy_only=False)
    flat = values.flatten()
    if not (lengths == n).all():
        keep = lengths == n
        if on_bad_row == "fail":
            raise BadRow(f"{int((~keep).sum())} rows don't have {n} values")
        flat = values.filter(pa.array(keep)).flatten()
    out = flat.to_numpy(zero_copy_only=False).astype(np.float64, copy=False).reshape(-1, n)
    fine = np.isfinite(out).all(axis=1)
    if not fine.all():
        if on_bad_row == "fail":
            raise BadRow(f"{int((~fine).sum())} rows hold nulls, NaN or infinities")
        keep = keep.copy()
        keep[np.flatnonzero(keep)[~fine]] = False
        out = out[fine]
    return out, keep


def map_blocks(nm: NarrowMatrix, kernel: Callable[[Iterator[np.ndarray]], Iterator[pa.RecordBatch]], schema: str) -> DataFrame:
    """A map-only pass: the kernel sees the matrices of a task's Arrow batches. Values that are made from another matrix are made in the same worker, and no keys go there."""
    n, policy = nm.n, nm.on_bad_row
    if nm.made and not nm.df.is_cached:
        base, rows = nm.made

        def checked(block: np.ndarray) -> np.ndarray:
            out = rows(block)
            fine = np.isfinite(out).all(axis=1)
            if fine.all():
                return out
            if policy == "fail":
                raise BadRow(f"{int((~fine).sum())} rows hold nulls, NaN or infinities")
            return out[fine]

        return map_blocks(base, lambda blocks: kernel(map(checked, blocks)), schema)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from kernel(to_matrix(b.column(0), n, policy)[0] for b in batches)

    return nm.df.select(nm.values().alias("a")).mapInArrow(run, schema)


def map_rows(nm: NarrowMatrix, kernel: Callable[[np.ndarray], np.ndarray], width: int, prefix: str = "q") -> DataFrame:
    """A map-only pass that gives each row's new values under its key: key columns, then prefix0, prefix1, ..."""
    n, policy, k = nm.n, nm.on_bad_row, len(nm.keys)
    given = nm.df.select(*nm.keys, nm.values().alias("row_values"))
    schema = given.drop("row_values").schema
    for i in range(width):
        schema = schema.add(f"{prefix}{i}", "double")
    names = schema.names

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows, keep = to_matrix(b.column(k), n, policy)
            if not keep.all():
                b = b.filter(pa.array(keep))
            out = kernel(rows)
            yield pa.RecordBatch.from_arrays([*b.columns[:k], *(pa.array(np.ascontiguousarray(out[:, i])) for i in range(width))], names=names)

    out = given.mapInArrow(run, schema)
    out.made_from = nm, kernel
    return out
