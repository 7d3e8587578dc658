"""Documents scored by the difference of two language models' cross-entropies.

Both models predict the next byte from the three before it, interpolated down to single bytes, so they share one vocabulary
(256 bytes) and one smoothing. The background model counts all documents. The target model counts all
that are labelled as good, outside the fold held out for measuring. Their ids are broadcast up to ``BROADCAST_IDS``, beyond that a join moves the texts. A document's score is its mean loss per byte under the background
minus that under the target: the higher, the more it looks like the target.

All counts are exact and keyed by the gram itself. Every task adds up its own documents before the shuffle, and the counts stay a
table. As each scored document is also counted, the losses of every four-byte gram that can occur follow from joins of that table
with itself. This table of losses, which grows with the distinct grams of the input, is broadcast up to ``BROADCAST_GRAMS``; beyond that the
grams of each document, summed up, are joined with it.

At the first bytes of a text the context isn't counted, so a ratio may exceed 1 there; it counts as 1.

Defined results: null and empty texts have no bytes, no loss and score 0; repeated rows count as often as they occur; a
repeated label counts once; an empty table gives an empty result; without target documents all scores are 0.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import cut_lineage, map_arrow, utf8
from .toxicity import held_out

STRENGTH = (0.5, 16.0, 16.0, 16.0)  # of the lower order, for orders 1 to 4
FLUSH_BYTES = 2 << 20
HELD_GRAMS = 1_000_000  # of one model in a task, before they are handed on
BROADCAST_IDS = 4_000_000  # 32 MB
BROADCAST_GRAMS = 8_000_000  # 128 MB


def places(data: bytes) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """For orders 1 to 4, the gram that ends at each byte, and for 1 to 3 that which ends before it, as order << 32 | bytes.

    What stands before the text is zero.
    """
    n = len(data)
    one = np.frombuffer(b"\0\0\0" + data, dtype=np.uint8).astype(np.int64)
    two = one[1:] | one[:-1] << 8
    three = two[1:] | one[:-2] << 16
    four = three[1:] | one[:-3] << 24
    single, double, triple = one[2:] | 1 << 32, two[1:] | 2 << 32, three | 3 << 32
    return [single[1:], double[1:], triple[1:], four | 4 << 32], [single[:n], double[:n], triple[:n]]


class Counts:
    """Exact counts of all orders of one model: sorted grams and how often each occurs."""

    def __init__(self) -> None:
        self.total = (np.empty(0, np.int64), np.empty(0, np.int64))
        self.waiting: list[bytes] = []
        self.bytes = 0

    def add(self, data: bytes) -> None:
        if data:
            self.waiting.append(data)
            self.bytes += len(data)
            if self.bytes >= FLUSH_BYTES:
                self.flush()

    def flush(self) -> None:
        if self.waiting:
            fours = np.concatenate([places(x)[0][3] for x in self.waiting])
            four, n = np.unique(fours, return_counts=True)
            found, times = [self.total[0]], [self.total[1]]
            for order in (4, 3, 2, 1):  # a shorter gram ends each longer one
                found.append(four & (1 << 8 * order) - 1 | order << 32)
                times.append(n)
            grams, at = np.unique(np.concatenate(found), return_inverse=True)
            total = np.zeros(len(grams), dtype=np.int64)
            np.add.at(total, at, np.concatenate(times))
            self.total = (grams, total)
        self.waiting, self.bytes = [], 0

    def take(self) -> tuple[np.ndarray, np.ndarray]:
        """What was counted since the last time."""
        self.flush()
        out, self.total = self.total, (np.empty(0, np.int64), np.empty(0, np.int64))
        return out


def _interpolated(single, pairs):
    """The probability from that of order 1 and, for orders 2 to 4, the counts of gram and context."""
    p = single
    for order, (gram, context) in enumerate(pairs, 1):
        p = (gram + STRENGTH[order] * p) / (context + STRENGTH[order])
    return p


class Model:
    """Interpolated next-byte probabilities from exact counts."""

    def __init__(self, total: tuple[np.ndarray, np.ndarray]) -> None:
        self.grams, self.n = total
        self.bytes = int(self.n[self.grams >> 32 == 1].sum())

    def count(self, grams: np.ndarray) -> np.ndarray:
        if not len(self.grams):
            return np.zeros(len(grams))
        at = np.minimum(np.searchsorted(self.grams, grams), len(self.grams) - 1)
        return np.where(self.grams[at] == grams, self.n[at], 0).astype(np.float64)

    def loss(self, at: list[np.ndarray], before: list[np.ndarray]) -> float:
        """Nats over all bytes."""
        single = (self.count(at[0]) + STRENGTH[0]) / (self.bytes + STRENGTH[0] * 256)
        p = _interpolated(single, [(self.count(at[k]), self.count(before[k - 1])) for k in (1, 2, 3)])
        return float(-np.log(np.clip(p, 1e-12, 1.0)).sum())


def mark_target(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(t, target): the bytes of every document, and whether it is one of the target's."""
    good = labels.where("quality = 1 AND doc_id IS NOT NULL").where(~held_out(F.col("doc_id"))).select(F.col("doc_id").cast("long").alias("good_id")).distinct()
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), utf8("text").alias("t"))
    if good.count() > BROADCAST_IDS:
        return slim.join(good.hint("merge"), F.col("doc_id") == F.col("good_id"), "left").select("t", F.col("good_id").isNotNull().alias("target"))
    sent = docs.sparkSession.sparkContext.broadcast(np.sort(good.toArrow().column(0).to_numpy()))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids = sent.value
        for batch in batches:
            own = batch.column(0)
            known = own.fill_null(0).to_numpy(zero_copy_only=False)
            at = np.minimum(np.searchsorted(ids, known), max(len(ids) - 1, 0))
            found = (ids[at] == known) & own.is_valid().to_numpy(zero_copy_only=False) if len(ids) else np.zeros(len(known), dtype=bool)
            yield pa.RecordBatch.from_arrays([batch.column(1), pa.array(found)], names=["t", "target"])

    return map_arrow(slim, kernel, "t binary, target boolean")


def gather(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """(gram, n0, n1): counts of all documents and of the target's."""

    def rows(both: tuple[Counts, Counts]) -> Iterator[pa.RecordBatch]:
        for kind, counts in enumerate(both):
            grams, n = counts.take()
            for i in range(0, len(grams), 100_000):
                part, none = slice(i, i + 100_000), np.zeros(len(grams[i : i + 100_000]), dtype=np.int64)
                yield pa.RecordBatch.from_arrays([pa.array(grams[part]), pa.array(none if kind else n[part]), pa.array(n[part] if kind else none)], names=["gram", "n0", "n1"])

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        both = (Counts(), Counts())
        for batch in batches:
            for x, target in zip(batch.column(0), batch.column(1).to_pylist(), strict=True):
                data = x.as_py()
                both[0].add(data)
                if target:
                    both[1].add(data)
            if len(both[0].total[0]) > HELD_GRAMS:
                yield from rows(both)
        yield from rows(both)

    parts = map_arrow(mark_target(docs, labels), kernel, "gram long, n0 long, n1 long")
    return cut_lineage(parts.groupBy("gram").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1")))


def gram_losses(counts: DataFrame) -> DataFrame:
    """(gram, l0, l1): for each four-byte gram the loss of its last byte under the background and under the target."""
    all_bytes = counts.where("gram >> 32 = 1").agg(F.coalesce(F.sum("n0"), F.lit(0)), F.coalesce(F.sum("n1"), F.lit(0))).first()
    g = F.col("gram")
    tail = lambda order, shift=0: F.shiftright(g, shift).bitwiseAND(F.lit((1 << 8 * order) - 1)).bitwiseOR(F.lit(order << 32))
    wide = counts.where("gram >> 32 = 4").select("gram", F.col("n0").alias("g4_0"), F.col("n1").alias("g4_1"))
    for name, order, shift in (("g3", 3, 0), ("c3", 3, 8), ("g2", 2, 0), ("c2", 2, 8), ("g1", 1, 0), ("c1", 1, 8)):
        own = counts.where(f"gram >> 32 = {order}").select(F.col("gram").alias(f"{name}_gram"), F.col("n0").alias(f"{name}_0"), F.col("n1").alias(f"{name}_1"))
        wide = wide.join(own if order == 3 else F.broadcast(own), tail(order, shift) == F.col(f"{name}_gram"), "left")  # 65,536 rows at most are broadcast

    def loss(kind: int) -> Column:
        n = lambda name: F.coalesce(F.col(f"{name}_{kind}"), F.lit(0)).cast("double")
        single = (n("g1") + STRENGTH[0]) / (all_bytes[kind] + STRENGTH[0] * 256)
        p = _interpolated(single, [(n("g2"), n("c1")), (n("g3"), n("c2")), (n("g4"), n("c3"))])
        return -F.log(F.least(F.greatest(p, F.lit(1e-12)), F.lit(1.0)))

    return cut_lineage(wide.select("gram", loss(0).alias("l0"), loss(1).alias("l1")))


def score(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, n_tokens (bytes), target_loss and background_loss per token, and score for every document."""
    counts = gather(docs, labels)
    blind = counts.where("n1 > 0").isEmpty()
    losses = gram_losses(counts)
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), utf8("text").alias("t"))
    summed = _sums_by_join(slim, losses) if losses.count() > BROADCAST_GRAMS else _sums_by_broadcast(slim, losses)
    per = lambda c: F.when(F.col("n_tokens") > 0, F.col(c) / F.col("n_tokens")).otherwise(F.lit(0.0))
    out = summed.select("doc_id", "n_tokens", per("s1").alias("target_loss"), per("s0").alias("background_loss"))
    return out.withColumn("score", F.lit(0.0) if blind else F.col("background_loss") - F.col("target_loss"))


def _sums_by_broadcast(slim: DataFrame, losses: DataFrame) -> DataFrame:
    table = losses.orderBy("gram").toArrow()
    sent = slim.sparkSession.sparkContext.broadcast(tuple(table.column(k).to_numpy().astype(kind) for k, kind in (("gram", np.int64), ("l0", np.float32), ("l1", np.float32))))

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        grams, *of = sent.value
        for batch in batches:
            n, sums = [], ([], [])
            for x in batch.column(1):
                data = x.as_py()
                n.append(len(data))
                at = np.searchsorted(grams, places(data)[0][3])  # each gram was counted
                for k in (0, 1):
                    sums[k].append(of[k][at].sum(dtype=np.float64) if data else 0.0)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(sums[0], pa.float64()), pa.array(sums[1], pa.float64())], names=["doc_id", "n_tokens", "s0", "s1"])

    return map_arrow(slim, kernel, "doc_id long, n_tokens long, s0 double, s1 double")


def _sums_by_join(slim: DataFrame, losses: DataFrame) -> DataFrame:

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        row = TaskContext.get().partitionId() << 40
        for batch in batches:
            for doc, x in zip(batch.column(0), batch.column(1), strict=True):
                data = x.as_py()
                grams, times = np.unique(places(data)[0][3], return_counts=True) if data else (np.zeros(1, np.int64), np.zeros(1, np.int64))
                m = len(grams)
                yield pa.RecordBatch.from_arrays([pa.array([row] * m), pa.array([doc.as_py()] * m, pa.int64()), pa.array([len(data)] * m), pa.array(grams), pa.array(times)], names=["row", "doc_id", "n_tokens", "own", "times"])
                row += 1

    each = map_arrow(slim, kernel, "row long, doc_id long, n_tokens long, own long, times long").join(losses, F.col("own") == F.col("gram"), "left")
    total = lambda k: F.coalesce(F.sum(F.col(f"l{k}") * F.col("times")), F.lit(0.0)).alias(f"s{k}")
    return each.groupBy("row", "doc_id", "n_tokens").agg(total(0), total(1)).drop("row")
