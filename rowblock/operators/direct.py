"""Direct block QR: keep each block's own Q, factor the stacked Rs, and multiply by slices of that second Q.

Step 1 maps each block to its Q and R and writes them as one committed table, in pieces of some rows each, so that no row of that
table is large; the R stands with a block's first piece. A block is what a task has read, up to a
number of rows; only where blocks have to be made again (replay) or their number is given are rows dealt to them by a hash, and a block of more
rows than fit is factored in parts, of which one is in memory and the others wait in a file of the task. Step 2 reads the Rs alone
(the rest is pruned), stacks them by block id and factors the stack: on the driver, in one task, or, when the
stack is large, by the same method again over groups of blocks. Step 3 joins each block with its slice
and multiplies. Q is orthogonal to working accuracy whatever the conditioning of A.
"""

from __future__ import annotations

import itertools
import pickle
import tempfile
import time
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..blocks import assign, block_rows_for, to_matrix
from ..errors import FactorizationError, TooFewRows
from ..kernels import qr_full
from ..matrix import NarrowMatrix
from ..memory import give_back
from ..staging import Stage

STACK_BYTES = 64 << 20
BROADCAST_BYTES = 8 << 20
MOST_RANGES = 64
PIECE_BYTES = 1 << 17
BATCH_BYTES = 16 << 20

Part = tuple[pa.Array, pa.Array]


def _part(held: list[pa.RecordBatch]) -> Part:
    """Keys and values, the last two columns, as one array each."""
    return tuple(pa.concat_arrays([b.column(k) for b in held]) for k in (-2, -1))


def _runs(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, pa.RecordBatch]]:
    """Block ids and rows of one block each, from batches sorted by block id."""
    for b in batches:
        ids = b.column(0).to_numpy(zero_copy_only=False)
        cuts = [0, *(np.flatnonzero(np.diff(ids)) + 1), len(ids)]
        for start, end in zip(cuts, cuts[1:], strict=False):
            if start < end:
                yield int(ids[start]), b.slice(start, end - start)


def _parts(runs: Iterable[pa.RecordBatch], most: int) -> Iterator[Part]:
    """A block's rows in parts of exactly so many, the last one of what is left."""
    held: list[pa.RecordBatch] = []
    size = 0
    for b in runs:
        while size + b.num_rows >= most:
            held.append(b.slice(0, most - size))
            b = b.slice(most - size)
            yield _part(held)
            held, size = [], 0
        if b.num_rows:
            held.append(b)
            size += b.num_rows
    if held:
        yield _part(held)


def _stage_schema(key_type: T.DataType) -> T.StructType:
    double = T.ArrayType(T.DoubleType())
    return T.StructType([T.StructField("block_id", T.LongType()), T.StructField("keys", T.ArrayType(key_type)), T.StructField("q", double), T.StructField("r", double), T.StructField("r_rows", T.IntegerType())])


def _pieces(block_id: int, keys: pa.Array, q: np.ndarray, r: np.ndarray | None) -> Iterator[pa.RecordBatch]:
    """Rows of the stage table, each with up to PIECE_BYTES of a block's Q and keys (more for few rows, which a slice would outweigh); r goes with the first one."""
    lists = lambda a: pa.ListArray.from_arrays(pa.array([0, len(a)], pa.int32()), a)
    most = max(4 * q.shape[1], PIECE_BYTES // (8 * q.shape[1] + max(1, keys.nbytes // len(keys))))
    for start in range(0, len(q), most):
        part = q[start : start + most]
        triangle = pa.array([None if r is None else r.ravel()], pa.list_(pa.float64()))
        yield pa.RecordBatch.from_arrays([pa.array([block_id], pa.int64()), lists(pa.concat_arrays([keys.slice(start, len(part))])), lists(pa.array(part.ravel())), triangle, pa.array([q.shape[1]], pa.int32())], names=["block_id", "keys", "q", "r", "r_rows"])
        r = None


def _factored(block_id: int, parts: Iterable[Part], n: int, policy: str) -> Iterator[pa.RecordBatch]:
    """The stage table's rows of a block. If it has several parts, their Qs wait in a file until the stacked Rs are factored."""
    rs: list[np.ndarray] = []
    with tempfile.TemporaryFile(prefix="block-") as waiting:
        last = None
        for keys, values in parts:
            rows, keep = to_matrix(values, n, policy)
            if not len(rows):
                continue
            if last:
                pickle.dump(last, waiting, 5)
            q, r = qr_full(rows)
            last = (keys if keep.all() else keys.filter(pa.array(keep))), q
            rs.append(r)
        if not rs:
            return
        if len(rs) == 1:
            yield from _pieces(block_id, *last, rs[0])
            return
        pickle.dump(last, waiting, 5)
        last = None
        seconds, r = _stacked(rs)
        waiting.seek(0)
        for k, second in enumerate(seconds):
            keys, q = pickle.load(waiting)
            yield from _pieces(block_id, keys, q @ second, None if k else r)


def direct_local(nm: NarrowMatrix, n_blocks: int | None = None, block_rows: int | None = None) -> DataFrame:
    """(block_id, keys, q, r, r_rows), some rows for each block that has rows; ``triangles`` are the first ones.

    Without n_blocks this is map only: a block is up to block_rows rows of a task, and its id is the task's and its place. With
    it, rows are dealt to as many blocks by a hash of the key, so that the same blocks can be made again; block_rows then bounds a block's parts.
    """
    _bounded_batches(nm.df)
    n, policy = nm.n, nm.on_bad_row
    most = max(n, block_rows or block_rows_for(n))
    if n_blocks:
        dealt = assign(nm, n_blocks)

        def again(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for block_id, runs in itertools.groupby(_runs(batches), lambda x: x[0]):
                yield from _factored(block_id, _parts((b for _, b in runs), most), n, policy)
                give_back()

        return dealt.mapInArrow(again, _stage_schema(dealt.schema["k"].dataType))
    given = nm.df.select(F.struct(*nm.keys).alias("k"), nm.values().alias("a"))

    def once(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        base, made, held, size = TaskContext.get().partitionId() << 32, 0, [], 0
        pieces = (b.slice(start, most) for b in batches for start in range(0, b.num_rows, most))
        for piece in pieces:
            if held and size + piece.num_rows > most:
                part, held = _part(held), []
                yield from _factored(base + made, [part], n, policy)
                del part
                give_back()
                made, size = made + 1, 0
            held.append(piece)
            size += piece.num_rows
        if held:
            part, held = _part(held), []
            yield from _factored(base + made, [part], n, policy)
            del part
            give_back()

    return given.mapInArrow(once, _stage_schema(given.schema["k"].dataType))


def _bounded_batches(df: DataFrame) -> None:
    """Lower the session's limit of what goes to a Python worker at once, as replay has two workers for each task."""
    conf, key = df.sparkSession.conf, "spark.sql.execution.arrow.maxBytesPerBatch"
    given = conf.get(key).removesuffix("b")
    if not given.isdigit() or int(given) > BATCH_BYTES:
        conf.set(key, f"{BATCH_BYTES}b")


def triangles(stage_table: DataFrame) -> DataFrame:
    """(block_id, r), one row for each block."""
    return stage_table.where("r IS NOT NULL").select("block_id", "r")


def _slices(ids: list[int], rs: list[list[float]], n: int) -> tuple[list[np.ndarray], np.ndarray]:
    return _stacked([np.array(r).reshape(-1, n) for r in rs])


def _stacked(stacked: list[np.ndarray]) -> tuple[list[np.ndarray], np.ndarray]:
    """Slices of the second Q for triangles stacked in the given order, and the final R. Short triangles have short slices."""
    q, r = qr_full(np.vstack(stacked))
    ends = np.cumsum([len(x) for x in stacked])
    return [q[e - len(x) : e] for e, x in zip(ends, stacked, strict=True)], r


def combine_on_driver(rs: DataFrame, n: int) -> tuple[DataFrame, np.ndarray]:
    rows = sorted(rs.select("block_id", "r").collect(), key=lambda x: x["block_id"])
    parts, r = _slices([x["block_id"] for x in rows], [x["r"] for x in rows], n)
    made = [(x["block_id"], p.ravel().tolist()) for x, p in zip(rows, parts, strict=True)]
    return rs.sparkSession.createDataFrame(made, "block_id long, q2 array<double>"), r


def combine_in_task(rs: DataFrame, n: int, stage: Stage) -> tuple[DataFrame, np.ndarray]:
    """The combine as one task; the final R comes as the slice of block -1."""

    def kernel(table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("block_id").to_numpy())
        ids, given = table.column("block_id").to_pylist(), table.column("r").to_pylist()
        parts, r = _slices([ids[k] for k in order], [given[k] for k in order], n)
        return pa.table({"block_id": pa.array([ids[k] for k in order] + [-1], pa.int64()), "q2": pa.array([p.ravel() for p in parts] + [r.ravel()], pa.list_(pa.float64()))})

    out = stage.write(rs.select("block_id", "r").groupBy(F.lit("all").alias("everything")).applyInArrow(kernel, "block_id long, q2 array<double>"), "slices")
    r = np.array(out.where("block_id = -1").first()["q2"]).reshape(-1, n)
    return out.where("block_id >= 0"), r


def combine_recursively(rs: DataFrame, n: int, count: int, fan_in: int, stage: Stage) -> tuple[DataFrame, np.ndarray]:
    """The same method over groups of triangles, level by level, and the slices carried down again.

    Every level is a table (node, parent, q2) with the parents' triangles; a level is smaller than the one below by the fan-in.
    """
    fan_in = max(2, fan_in)

    def kernel(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        order = np.argsort(table.column("node").to_numpy())
        ids, given = table.column("node").to_pylist(), table.column("r").to_pylist()
        parts, r = _slices([ids[k] for k in order], [given[k] for k in order], n)
        parent = key[0].as_py()
        none: list = [None]
        return pa.table({"node": pa.array([ids[k] for k in order] + none, pa.int64()), "parent": pa.array([parent] * (len(ids) + 1), pa.int64()), "q2": pa.array([p.ravel() for p in parts] + none, pa.list_(pa.float64())), "r": pa.array(none * len(ids) + [r.ravel()], pa.list_(pa.float64()))})

    levels, now = [], rs.select(F.col("block_id").alias("node"), "r")
    while count > fan_in:
        groups = -(-count // fan_in)
        dealt = now.withColumn("parent", F.pmod(F.xxhash64("node"), F.lit(groups)))
        level = stage.write(dealt.groupBy("parent").applyInArrow(kernel, "node long, parent long, q2 array<double>, r array<double>"), f"level{len(levels)}")
        levels.append(level.where("node IS NOT NULL").select("node", "parent", "q2"))
        now, count = level.where("node IS NULL").select(F.col("parent").alias("node"), "r"), groups
    top, r = combine_on_driver(now.withColumnRenamed("node", "block_id"), n)
    slices = top.withColumnRenamed("block_id", "node")
    for level in reversed(levels):
        above = slices.select(F.col("node").alias("parent"), F.col("q2").alias("up"))
        slices = _times(level.join(above, "parent").select("node", "q2", "up"), n)
    return slices.withColumnRenamed("node", "block_id"), r


def _times(pairs: DataFrame, n: int) -> DataFrame:
    """(node, q2 up) from (node, q2, up), both with n columns."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = [(np.array(x).reshape(-1, n) @ np.array(y).reshape(-1, n)).ravel() for x, y in zip(b.column(1).to_pylist(), b.column(2).to_pylist(), strict=True)]
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(out, pa.list_(pa.float64()))], names=["node", "q2"])

    return pairs.mapInArrow(kernel, "node long, q2 array<double>")


def direct_apply(stage_table: DataFrame, slices: DataFrame, n: int, how: str = "join", fold: np.ndarray | None = None) -> DataFrame:
    """(key columns, q0, ...): each block's Q times its slice, and times a small matrix if one is folded in."""
    _bounded_batches(stage_table)
    blocks = stage_table.select("block_id", "keys", "q", "r_rows")
    both = blocks.join(F.broadcast(slices) if how == "broadcast" else slices, "block_id")
    width = n if fold is None else fold.shape[1]
    keys = blocks.schema["keys"].dataType.elementType
    schema = T.StructType([*keys.fields, *(T.StructField(f"q{i}", T.DoubleType()) for i in range(width))])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for k in range(b.num_rows):
                one = b.slice(k, 1)
                rows = one.column(2)[0].as_py()
                small = one.column(3).flatten().to_numpy().reshape(rows, n)
                q = one.column(1).flatten().to_numpy().reshape(-1, rows) @ (small if fold is None else small @ fold)
                own = one.column(0).flatten().flatten()
                yield pa.RecordBatch.from_arrays([*own, *(pa.array(np.ascontiguousarray(q[:, i])) for i in range(width))], names=schema.names)

    return both.select("keys", "q", "r_rows", "q2").mapInArrow(kernel, schema)


def apply_by_ranges(stage_table: DataFrame, slices: DataFrame, n: int, size: int, stage: Stage, fold: np.ndarray | None = None) -> DataFrame:
    """direct_apply in ranges of block ids, each with its own slices broadcast: no Q moves, and a branch reads the files' parts of its range only."""
    kept = stage.write(slices, "slices_by_range")
    parts = -(-size // BROADCAST_BYTES)
    cuts = sorted({int(c) for c in kept.approxQuantile("block_id", [k / parts for k in range(1, parts)], 0.0)})
    edges = [None, *cuts, None]
    out = None
    for low, high in zip(edges, edges[1:], strict=False):
        within = lambda df: df.where((F.lit(True) if low is None else F.col("block_id") > low) & (F.lit(True) if high is None else F.col("block_id") <= high))  # noqa: B023, E731
        branch = direct_apply(within(stage_table), within(kept), n, "broadcast", fold)
        out = branch if out is None else out.unionByName(branch)
    return out


def slice_traffic(blocks: int, n: int) -> int:
    """Bytes when every task gets all slices."""
    return 8 * blocks * blocks * n * n


def gather_bytes(blocks: int, n: int) -> int:
    """Bytes of the stacked Rs."""
    return 8 * blocks * n * n


def direct(nm: NarrowMatrix, stage: Stage, n_blocks: int | None = None, block_rows: int | None = None, combine: str = "auto", fan_in: int | None = None, deliver: str = "auto", want_q: bool = True, replay: bool = False, buckets: int | None = None, seconds: dict[str, float] | None = None):
    """(q, r): q is a lazy frame over the stage table (None if not wanted).

    combine: driver, task, recursive, or auto (recursive when the stack exceeds STACK_BYTES). deliver: broadcast (behind
    a check of the slices' size), ranges (several broadcasts, each within that size, for a range of blocks), join, or auto (the first of these that fits). With buckets, blocks and slices are tables bucketed by block, whose join moves neither:
the way for very many blocks, as a block is as large as its part of A. With replay the local Qs aren't written: step 3 factors the blocks again.
    """
    n, began = nm.n, time.perf_counter()
    if replay and not n_blocks:
        raise FactorizationError("blocks can be made again only if their number is given")
    local = direct_local(nm, n_blocks, block_rows)
    kept = triangles(local) if replay else local
    table = stage.write_bucketed(kept, "blocks", buckets, "block_id") if buckets else stage.write(kept, "blocks")
    rs = triangles(table)
    count = rs.count()
    if seconds is not None:
        seconds["local factors"], began = time.perf_counter() - began, time.perf_counter()
    size = gather_bytes(count, n)
    if not count:
        raise TooFewRows("no rows")
    if combine == "auto":
        combine = "recursive" if size > STACK_BYTES else "driver"
    if combine == "driver":
        slices, r = combine_on_driver(rs, n)
    elif combine == "task":
        slices, r = combine_in_task(rs, n, stage)
    elif combine == "recursive":
        slices, r = combine_recursively(rs, n, count, fan_in or max(2, STACK_BYTES // (8 * n * n)), stage)
    else:
        raise FactorizationError(f"no combine {combine!r}")
    if seconds is not None:
        seconds["combine"] = time.perf_counter() - began
    if len(r) < n:
        raise TooFewRows(f"{len(r)} rows, {n} columns")
    if not want_q:
        return None, r
    if buckets:
        slices, deliver = stage.write_bucketed(slices, "bucketed_slices", buckets, "block_id").hint("merge"), "join"
    if deliver == "auto":
        deliver = "broadcast" if size <= BROADCAST_BYTES else "ranges" if size <= MOST_RANGES * BROADCAST_BYTES and not replay else "join"
    if deliver == "ranges":
        return apply_by_ranges(table, slices, n, size, stage), r
    if deliver == "broadcast" and size > BROADCAST_BYTES:
        raise FactorizationError("the slices are too large to broadcast")
    return direct_apply(local if replay else table, slices, n, deliver), r
