"""R by a tree of local factorizations: the R of stacked rows is the R of their stacked Rs, for any tree."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..blocks import map_blocks, to_matrix
from ..kernels import fold_r, qr_r
from ..matrix import NarrowMatrix

COLLECT_BYTES = 64 << 20
R_SCHEMA = "node long, r array<double>, r_rows int"


def _r_batch(node: list[int], rs: list[np.ndarray]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(node, pa.int64()), pa.array([r.ravel() for r in rs], pa.list_(pa.float64())), pa.array([len(r) for r in rs], pa.int32())], names=["node", "r", "r_rows"])


def local_r(nm: NarrowMatrix, block_rows: int | None = None) -> DataFrame:
    """(node, r, r_rows): one triangle for each task, or for each block of so many rows of it, however they come in batches; the node is a label for dealing out only."""
    n = nm.n

    def kernel(rows: Iterator[np.ndarray]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        base, r, made, room = TaskContext.get().partitionId() << 32, None, 0, block_rows or 0
        for block in rows:
            if not block_rows:
                r = fold_r(r, block)
            while block_rows and len(block):
                part, block = block[:room], block[room:]
                r, room = fold_r(r, part), room - len(part)
                if not room:
                    yield _r_batch([base + made], [r])
                    r, made, room = None, made + 1, block_rows
        if r is not None:
            yield _r_batch([base + made], [r])

    return map_blocks(nm, kernel, R_SCHEMA)


def stack(table: pa.Table | pa.RecordBatch, n: int) -> np.ndarray:
    """The rows of all triangles of a table, in the order of their nodes."""
    if not table.num_rows:
        return np.zeros((0, n))
    order = np.argsort(table.column("node").to_numpy(), kind="stable")
    rs = table.column("r").to_pylist()
    return np.vstack([np.array(rs[k]).reshape(-1, n) for k in order])


def merge_level(rs: DataFrame, n: int, groups: int) -> DataFrame:
    """One level of the tree: nodes are dealt to groups, each gives one triangle."""

    def merge(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        return pa.Table.from_batches([_r_batch([key[0].as_py()], [qr_r(stack(table, n))])])

    dealt = rs.withColumn("parent", F.pmod(F.xxhash64("node"), F.lit(groups)))
    return dealt.groupBy("parent").applyInArrow(merge, R_SCHEMA)


def r_tree(rs: DataFrame, n: int, count: int | None = None, fan_in: int | None = None, levels: list[int] | None = None) -> np.ndarray:
    """The R of all triangles. With a fan-in, levels of that many go before the last; without, they go as soon as the stack is big. levels gets the number of triangles before each level."""
    count = count if count is not None else rs.count()
    step = fan_in or max(2, COLLECT_BYTES // (8 * n * n))
    while count > step:
        if levels is not None:
            levels.append(count)
        groups = -(-count // step)
        rs, count = merge_level(rs, n, groups), groups
    if levels is not None:
        levels.append(count)
    return qr_r(stack(rs.toArrow(), n))


def r_factor(nm: NarrowMatrix, fan_in: int | None = None, block_rows: int | None = None, levels: list[int] | None = None) -> np.ndarray:
    """R alone, in one pass over the rows; fewer rows than columns give fewer rows of R."""
    rs = local_r(nm, block_rows)
    adaptive = "AdaptiveSparkPlan" in nm.df._jdf.queryExecution().executedPlan().toString()
    if not block_rows and not adaptive:
        return r_tree(rs, nm.n, nm.df.rdd.getNumPartitions(), fan_in, levels)
    rs = rs.persist()  # their number isn't known beforehand; counting them mustn't factor twice
    try:
        return r_tree(rs, nm.n, None, fan_in, levels)
    finally:
        rs.unpersist()


def r_factor_by(nm: NarrowMatrix, groups: list[str], salt: int = 16) -> DataFrame:
    """(group columns, i, j, v): a triangle for each group of rows.

    Rows of a group are first factored by a salt of their key, so that a hot group is dealt to several tasks.
    """
    n, policy = nm.n, nm.on_bad_row
    salted = nm.df.select(*groups, F.pmod(F.xxhash64(*nm.keys), F.lit(salt)).alias("salt"), nm.values().alias("a"))
    types = [f"{salted.schema[g].name} {salted.schema[g].dataType.simpleString()}" for g in groups]

    def part(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        r = None
        for b in table.select(["a"]).to_batches():
            r = fold_r(r, to_matrix(b.column(0), n, policy)[0])
        return pa.table({**{g: pa.array([k.as_py()], k.type) for g, k in zip(groups, key, strict=False)}, "r": pa.array([r.ravel()], pa.list_(pa.float64()))})

    def whole(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        r = qr_r(np.vstack([np.array(x).reshape(-1, n) for x in table.column("r").to_pylist()]))
        return pa.table({**{g: pa.array([k.as_py()], k.type) for g, k in zip(groups, key, strict=False)}, "r": pa.array([r.ravel()], pa.list_(pa.float64()))})

    schema = ", ".join([*types, "r array<double>"])
    merged = salted.groupBy(*groups, "salt").applyInArrow(part, schema).groupBy(*groups).applyInArrow(whole, schema)
    each = merged.select(*groups, F.posexplode("r").alias("at", "v"))
    return each.select(*groups, F.floor(F.col("at") / n).cast("int").alias("i"), (F.col("at") % n).cast("int").alias("j"), "v").where("i <= j")


def merge_summaries(summaries: DataFrame, n: int, groups: list[str]) -> DataFrame:
    """Roll triangles (group columns, i, j, v) up to fewer group columns by the merge law, without the rows."""
    own = [c for c in summaries.columns if c not in ("i", "j", "v")]
    packed = summaries.groupBy(*own).agg(F.sort_array(F.collect_list(F.struct("i", "j", "v"))).alias("cells"))
    types = [f"{g} {packed.schema[g].dataType.simpleString()}" for g in groups]
    packed = packed if groups else packed.withColumn("everything", F.lit(0))

    def merge(key: tuple[pa.Scalar, ...], table: pa.Table) -> pa.Table:
        stacked = []
        for cells in table.column("cells").to_pylist():
            m = np.zeros((n, n))
            for c in cells:
                m[c["i"], c["j"]] = c["v"]
            stacked.append(m)
        r = qr_r(np.vstack(stacked))
        i, j = np.triu_indices(n)
        named = {g: pa.array([k.as_py()] * len(i), k.type) for g, k in zip(groups, key, strict=False)}
        return pa.table({**named, "i": pa.array(i, pa.int32()), "j": pa.array(j, pa.int32()), "v": pa.array(r[i, j])})

    return packed.groupBy(*(groups or ["everything"])).applyInArrow(merge, ", ".join([*types, "i int, j int, v double"]))
