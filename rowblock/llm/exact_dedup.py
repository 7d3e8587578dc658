"""Exact deduplication by a grace hash over complete contents.

Each Arrow batch of the scan first drops its own copies, so that a text that a third of all rows
share is shuffled once a batch and not once a row. What is left is dealt by a 64-bit hash of the
normalised text. A task keeps the distinct texts in an open-addressing table that compares
complete contents; when the table is full, texts it does not know go to spill files by further
hash bits, and each file is treated the same way with another hash, until it fits.

Defined results: a null text counts as empty and is a copy of other empty texts; texts are equal when they
are the same after lower-casing A-Z; the row with the largest ``doc_id`` stays (null is smallest),
and of rows that share that id too, the one whose text has the larger bytes, then any one of
them; an empty table gives an empty result; other columns, whatever their names, ride along.
"""

from __future__ import annotations

import hashlib
import tempfile
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import free_name, map_arrow, text_or_empty, utf8

TABLE_BYTES = 96 << 20
SPILL_FAN_OUT = 16


class ContentTable:
    """Open addressing with linear probing; two keys are the same only when all their bytes are."""

    def __init__(self, slots: int = 1024) -> None:
        self.slots = np.full(slots, -1, dtype=np.int64)
        self.hashes: list[int] = []
        self.keys: list[bytes] = []
        self.bytes = 0

    def __len__(self) -> int:
        return len(self.keys)

    def find(self, h: int, key: bytes) -> int:
        """The entry of key, or -1 - slot where it belongs."""
        mask = len(self.slots) - 1
        at = h & mask
        while (entry := int(self.slots[at])) >= 0:
            if self.hashes[entry] == h and self.keys[entry] == key:
                return entry
            at = (at + 1) & mask
        return -1 - at

    def add(self, slot: int, h: int, key: bytes) -> int:
        entry = len(self.keys)
        self.slots[slot] = entry
        self.hashes.append(h)
        self.keys.append(key)
        self.bytes += len(key) + 200
        if 3 * len(self.keys) > 2 * len(self.slots):
            self._grow()
        return entry

    def _grow(self) -> None:
        self.slots = np.full(2 * len(self.slots), -1, dtype=np.int64)
        mask = len(self.slots) - 1
        for entry, h in enumerate(self.hashes):
            at = h & mask
            while self.slots[at] >= 0:
                at = (at + 1) & mask
            self.slots[at] = entry


def content_hash(key: bytes, level: int = 0) -> int:
    return xxhash.xxh3_64_intdigest(key, seed=level)


def _rank(doc_id: int | None, raw: bytes) -> tuple:
    return (doc_id is not None, doc_id or 0, raw)


def first_of_batch(batches: Iterator[pa.RecordBatch], id_at: int, raw_at: int) -> Iterator[pa.RecordBatch]:
    """Of each batch, the row that stays of every text, with the text's hash and number of rows."""
    for batch in batches:
        ids, raws = batch.column(id_at).to_pylist(), batch.column(raw_at)
        table, winner, count = ContentTable(), [], []
        for row, doc_id in enumerate(ids):
            key = raws[row].as_py().lower()
            h = content_hash(key)
            if (entry := table.find(h, key)) < 0:
                table.add(-1 - entry, h, key)
                winner.append(row)
                count.append(1)
            else:
                count[entry] += 1
                if _rank(doc_id, raws[row].as_py()) > _rank(ids[winner[entry]], raws[winner[entry]].as_py()):
                    winner[entry] = row
        out = batch.take(pa.array(winner, pa.int64()))
        signed = np.array(table.hashes, dtype=np.uint64).view(np.int64)
        yield pa.RecordBatch.from_arrays([*out.columns, pa.array(signed), pa.array(count, pa.int64())], names=[str(i) for i in range(out.num_columns + 2)])


def grace(batches: Iterator[pa.RecordBatch], id_at: int, raw_at: int, budget: int = TABLE_BYTES, level: int = 0) -> Iterator[pa.RecordBatch]:
    """Of all rows of a partition, the one that stays of every text; the last column is the group's size."""
    table, held, ids, raws, count = ContentTable(), [], [], [], []
    with tempfile.TemporaryDirectory(prefix="grace-") as folder:
        files: dict[int, pa.RecordBatchStreamWriter] = {}
        for batch in batches:
            size = batch.column(batch.num_columns - 1).to_pylist()
            doc_ids, texts = batch.column(id_at).to_pylist(), batch.column(raw_at)
            spilled: dict[int, list[int]] = {}
            for row, doc_id in enumerate(doc_ids):
                raw = texts[row].as_py()
                key = raw.lower()
                h = content_hash(key, level)
                entry = table.find(h, key)
                if entry >= 0:
                    count[entry] += size[row]
                    if _rank(doc_id, raw) > _rank(ids[entry], raws[entry]):
                        held[entry], ids[entry], raws[entry] = batch.take(pa.array([row])), doc_id, raw
                elif table.bytes < budget or not len(table):
                    table.add(-1 - entry, h, key)
                    table.bytes += len(raw)
                    held.append(batch.take(pa.array([row])))
                    ids.append(doc_id)
                    raws.append(raw)
                    count.append(size[row])
                else:
                    spilled.setdefault((h >> 32) % SPILL_FAN_OUT, []).append(row)
            for part, rows in spilled.items():
                if part not in files:
                    files[part] = pa.ipc.new_stream(str(Path(folder, str(part))), batch.schema)
                files[part].write_batch(batch.take(pa.array(rows, pa.int64())))
        for file in files.values():
            file.close()
        for start in range(0, len(held), 1000):
            out = pa.Table.from_batches(held[start : start + 1000]).combine_chunks().to_batches()[0]
            yield pa.RecordBatch.from_arrays([*out.columns[:-1], pa.array(count[start : start + 1000], pa.int64())], names=out.schema.names)
        del table, held, ids, raws, count
        for part in files:
            with pa.ipc.open_stream(str(Path(folder, str(part)))) as stream:
                yield from grace(iter(stream), id_at, raw_at, budget, level + 1)
            Path(folder, str(part)).unlink()


def survivors(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", size_col: str | None = None, budget: int = TABLE_BYTES) -> DataFrame:
    """The rows that stay, with all their columns and, if size_col is given, the size of their group."""
    names = docs.columns
    raw, hashed, size = (free_name(docs, c) for c in ("raw_text", "content_hash", "group_size"))
    given = docs.withColumn(raw, utf8(text_col))
    id_at, raw_at = names.index(id_col), len(names)
    wide = T.StructType([*given.schema.fields, T.StructField(hashed, T.LongType()), T.StructField(size, T.LongType())])
    width = len(wide.fields)

    def named(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays(batch.columns, names=wide.names)

    def local(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        yield from named(first_of_batch(batches, id_at, raw_at))

    def final(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        plain = (pa.RecordBatch.from_arrays(b.columns, names=[str(i) for i in range(width)]) for b in batches)
        yield from named(grace(plain, id_at, raw_at, budget))

    kept = map_arrow(map_arrow(given, local, wide).repartition(hashed), final, wide)
    return kept.select(*names, *([F.col(size).alias(size_col)] if size_col else []))


def text_digests(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id and the SHA-256 of each normalised text."""

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [hashlib.sha256(x.as_py().lower()).hexdigest() for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.string())], names=["doc_id", "text_sha256"])

    return map_arrow(docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("t")), digest, "doc_id long, text_sha256 string")


def membership(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every row with the row that stays for it: doc_id, keep_id, group_size, kept, text_sha256.

    A row that repeats the id and the text of the row that stays is marked as kept as well;
    ``survivors`` keeps one of them.
    """
    slim = docs.select(F.col(id_col).cast("long").alias("doc_id"), text_or_empty(text_col).alias("text"))
    groups = survivors(slim, size_col="group_size")
    rows = text_digests(docs, id_col, text_col)
    return rows.join(_heads(groups), "text_sha256").select("doc_id", "keep_id", "group_size", F.col("doc_id").eqNullSafe(F.col("keep_id")).alias("kept"), "text_sha256")


def _heads(groups: DataFrame) -> DataFrame:
    """Digest, id and size of each group, from its surviving row."""

    def digest(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = [hashlib.sha256(x.as_py().lower()).hexdigest() for x in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found, pa.string()), batch.column(2)], names=["keep_id", "text_sha256", "group_size"])

    return map_arrow(groups.select("doc_id", utf8("text").alias("t"), "group_size"), digest, "keep_id long, text_sha256 string, group_size long")
