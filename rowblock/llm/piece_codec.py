"""Encoding to piece ids and decoding, by a streaming Viterbi over compiled transitions (see ``piece_machine``).

The given model ranks merges, so a path's score is whether all its neighbouring pieces stand: each prefix has one valid
backpointer, and what is committed equals the library's ids.

Defined results: null and empty texts have no ids, and no ids decode to the empty text; repeated rows are coded one by one; a mark of the
model that stands in a text decodes to a space, as the library has it; an empty table gives an empty result.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import free_name, map_arrow, text_or_empty, with_field
from .piece_machine import MARK, machine


def encode(docs: DataFrame, model_path: str, ids_col: str = "ids", text_col: str = "text") -> DataFrame:
    """docs with the ids of each text."""
    given = docs.withColumn(free_name(docs, "encoded_text"), text_or_empty(text_col))
    names = [*docs.columns, ids_col]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = machine(model_path)
        for batch in batches:
            found = pa.array([coder.encode(x.as_py()) for x in batch.column(batch.num_columns - 1)], pa.list_(pa.int32()))
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], found], names=names)

    return map_arrow(given, kernel, with_field(docs, ids_col, "array<int>"))


def decode(coded: DataFrame, model_path: str, text_col: str = "text", ids_col: str = "ids") -> DataFrame:
    """coded with the text of each list of ids; null is decoded as no ids."""
    given = coded.withColumn(free_name(coded, "decoded_ids"), F.coalesce(F.col(ids_col), F.array().cast("array<int>")))
    names = [*coded.columns, text_col]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = machine(model_path)
        for batch in batches:
            found = pa.array([coder.decode(x.as_py()) for x in batch.column(batch.num_columns - 1)], pa.string())
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], found], names=names)

    return map_arrow(given, kernel, with_field(coded, text_col, "string"))


def coded_digests(docs: DataFrame, model_path: str) -> DataFrame:
    """doc_id, n_tokens, ids_crc32 (little-endian unsigned 32-bit ids) and whether decoding gives the text back."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = machine(model_path)
        for batch in batches:
            n, crc, same = [], [], []
            for x in batch.column(1):
                text = x.as_py()
                ids = coder.encode(text)
                n.append(len(ids))
                crc.append(zlib.crc32(np.fromiter(ids, "<u4", len(ids)).tobytes()))
                same.append(coder.decode(ids) == text.replace(MARK, " "))
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), pa.array(crc, pa.int64()), pa.array(same, pa.bool_())], names=["doc_id", "n_tokens", "ids_crc32", "round_trip"])

    return map_arrow(docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_or_empty().alias("t")), kernel, "doc_id long, n_tokens long, ids_crc32 long, round_trip boolean")
