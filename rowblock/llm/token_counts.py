"""Token counts by a compiled finite-state transducer (see ``piece_machine``).

Defined results: null and empty texts have no bytes and no tokens; repeated rows are counted one by one; an empty table
gives an empty result; strings that look like special tokens are ordinary text.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import free_name, map_arrow, text_or_empty, with_field
from .piece_machine import machine


def with_token_counts(docs: DataFrame, model_path: str, count_col: str = "n_tokens", text_col: str = "text") -> DataFrame:
    """docs with the number of tokens of each text; row by row, nothing is shuffled."""
    given = docs.withColumn(free_name(docs, "counted_text"), text_or_empty(text_col))
    names = [*docs.columns, count_col]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        count = machine(model_path).count
        for batch in batches:
            found = [count(x.as_py()) for x in batch.column(batch.num_columns - 1)]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(found, pa.int64())], names=names)

    return map_arrow(given, kernel, with_field(docs, count_col, "long"))


def token_counts(docs: DataFrame, model_path: str, limit: int = 4096) -> DataFrame:
    """doc_id, n_bytes, n_tokens, over_limit."""
    slim = docs.select("doc_id", F.octet_length(text_or_empty()).cast("long").alias("n_bytes"), "text")
    counted = with_token_counts(slim, model_path)
    return counted.select("doc_id", "n_bytes", "n_tokens", (F.col("n_tokens") > limit).alias("over_limit"))
