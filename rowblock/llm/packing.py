"""Packing documents into training sequences: first-fit decreasing on a tournament tree.

A document's ids are cut into pieces of one whole sequence each and a remainder. Remainders are dealt
to randomised groups (by a hash of id and text, and one group further for each equal row of a task) of about ``GROUP_DOCS`` documents, and every group is
packed by itself: remainders in order of decreasing length go to the first open sequence with
room, found by walking down a tree whose nodes hold the largest room below them. Room that is
left is filled by cutting remainders of the emptiest sequences, and the last open sequence of a group is
cut into sequences of powers of two, which need no padding.

Defined results: null counts as empty (one piece of the end id alone); ties are broken by id and start; rows
with the same id are packed as separate documents; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import map_arrow, text_or_empty

GROUP_DOCS = 4096
SEED = 42
OUT = pa.schema([(n, pa.int64()) for n in ("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")])
PIECE = pa.schema([("grp", pa.int64()), ("doc_id", pa.int64()), ("start", pa.int64()), ("length", pa.int64()), ("ids_crc32", pa.int64()), ("doc_tokens", pa.int64()), ("ids", pa.binary())])


class Tournament:
    """Rooms of sequences in the order they were opened; each inner node holds the largest room below it."""

    def __init__(self, capacity: int, leaves: int) -> None:
        self.size = 1 << max(0, leaves - 1).bit_length()
        self.room = [capacity] * (2 * self.size)

    def first_fit(self, length: int) -> int:
        """The first sequence with room for length, which is taken from it."""
        room, at = self.room, 1
        while at < self.size:
            at *= 2
            if room[at] < length:
                at += 1
        room[at] -= length
        leaf = at - self.size
        while at > 1:
            at //= 2
            room[at] = max(room[2 * at], room[2 * at + 1])
        return leaf


def first_fit_decreasing(lengths: list[int], capacity: int) -> list[list[int]]:
    """Items of each sequence; lengths have to be in decreasing order."""
    tree = Tournament(capacity, len(lengths))
    bins: list[list[int]] = []
    for item, length in enumerate(lengths):
        leaf = tree.first_fit(length)
        while leaf >= len(bins):
            bins.append([])
        bins[leaf].append(item)
    return bins


def fill_up(bins: list[list[tuple[int, int, int]]], capacity: int, tolerance: int) -> list[list[tuple[int, int, int]]]:
    """Cut pieces (item, start, length) of the emptiest sequences to fill the room of the others.

    What stays open in the end is one sequence, cut at powers of two.
    """
    fill = lambda b: sum(p[2] for p in b)
    bins = sorted(bins, key=fill, reverse=True)
    done: list[list[tuple[int, int, int]]] = []
    first, last = 0, len(bins) - 1
    while first < last:
        room = capacity - fill(bins[first])
        while room > tolerance and first < last:
            item, start, length = bins[last].pop()
            taken = min(room, length)
            bins[first].append((item, start, taken))
            if taken < length:
                bins[last].append((item, start + taken, length - taken))
            room -= taken
            last -= not bins[last]
        if first < last or room <= tolerance or not bins[first]:
            done.append(bins[first])
            first += 1
    if first == last and bins[first]:
        done += cut_at_powers(bins[first], capacity, tolerance)
    return done


def cut_at_powers(pieces: list[tuple[int, int, int]], capacity: int, tolerance: int) -> list[list[tuple[int, int, int]]]:
    total = sum(p[2] for p in pieces)
    if total >= capacity - tolerance:
        return [pieces]
    out, queue = [], list(pieces)
    for power in (1 << k for k in range(total.bit_length() - 1, -1, -1) if total >> k & 1):
        own, need = [], power
        while need:
            item, start, length = queue.pop(0)
            taken = min(need, length)
            own.append((item, start, taken))
            if taken < length:
                queue.insert(0, (item, start + taken, length - taken))
            need -= taken
        out.append(own)
    return out


@lru_cache(maxsize=2)
def _encoder(json_path: str, ranks_path: str | None):
    """Text to ids as the json's library gives them; the ranks are the same vocabulary for a faster library."""
    from tokenizers import Tokenizer

    slow = Tokenizer.from_file(json_path)
    plain = lambda text: slow.encode(text, add_special_tokens=False).ids
    if ranks_path is None:
        return plain
    import public_tokenizers
    import tiktoken

    with open(ranks_path, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    fast = tiktoken.Encoding("ranks", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    special = [t.content for t in slow.get_added_tokens_decoder().values()]
    return lambda text: plain(text) if any(s in text for s in special) else fast.encode_ordinary(text)


def token_pieces(docs: DataFrame, groups: int, json_path: str, ranks_path: str | None, capacity: int, end_id: int, id_col: str, text_col: str) -> DataFrame:
    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = _encoder(json_path, ranks_path)
        met: dict[int, int] = {}  # rows of this task by id and text; equal ones go to groups of their own, in whatever order they come
        for batch in batches:
            rows = []
            for doc_id, content, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), batch.column(2), strict=True):
                met[content] = met.get(content, -1) + 1
                group = (content + met[content]) % groups
                ids = np.array([*encode(text.as_py()), end_id], dtype="<u4")
                for start in range(0, len(ids), capacity):
                    part = ids[start : start + capacity]
                    whole = len(part) == capacity
                    at = (group + start // capacity) % groups if whole else group
                    rows.append((at, doc_id, start, len(part), zlib.crc32(part.tobytes()) if whole else None, len(ids), None if whole else part.astype("<u2" if ids.max() < 65_536 else "<u4").tobytes()))
                if len(rows) >= 5000:
                    yield _columns(rows)
                    rows = []
            if rows:
                yield _columns(rows)

    content = F.xxhash64(F.lit(SEED), F.col(id_col), text_or_empty(text_col))
    return map_arrow(docs.select(F.col(id_col).cast("long").alias("doc_id"), content.alias("content"), text_or_empty(text_col).alias("text")), kernel, "grp long, doc_id long, start long, length long, ids_crc32 long, doc_tokens long, ids binary")


def _columns(rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(zip(*rows, strict=True), PIECE, strict=True)], schema=PIECE)


def pack_group(table: pa.Table, capacity: int, tolerance: int) -> pa.Table:
    group, doc, start, length, crc, total, ids = (table.column(n).to_pylist() for n in PIECE.names)
    order = sorted(range(len(doc)), key=lambda i: (-length[i], doc[i] is None, doc[i] or 0, start[i], crc[i] or 0))
    whole, rest = [i for i in order if ids[i] is None], [i for i in order if ids[i] is not None]
    bins = first_fit_decreasing([length[i] for i in rest], capacity)
    sequences = fill_up([[(rest[k], 0, length[rest[k]]) for k in b] for b in bins], capacity, tolerance)
    out = [(doc[i], start[i], length[i], crc[i], total[i], n, 0) for n, i in enumerate(whole)]
    for n, pieces in enumerate(sequences, len(whole)):
        offset = 0
        for i, at, size in pieces:
            width = len(ids[i]) // length[i]
            part = np.frombuffer(ids[i], f"<u{width}")[at : at + size].astype("<u4")
            out.append((doc[i], start[i] + at, size, zlib.crc32(part.tobytes()), total[i], n, offset))
            offset += size
    base = group[0] << 32
    columns = [list(c) for c in zip(*out, strict=True)]
    columns[5] = [base + n for n in columns[5]]
    return pa.table([pa.array(c, pa.int64()) for c in columns], schema=OUT)


def pack(docs: DataFrame, json_path: str, ranks_path: str | None = None, capacity: int = 2048, end_id: int = 1, tolerance: int = 4, group_docs: int = GROUP_DOCS, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Pieces of all documents with their place in a sequence.

    Columns: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset. Rooms of at most ``tolerance`` ids stay open.
    """
    groups = max(1, -(-docs.count() // group_docs))
    pieces = token_pieces(docs, groups, json_path, ranks_path, capacity, end_id, id_col, text_col)
    return pieces.groupBy("grp").applyInArrow(lambda table: pack_group(table, capacity, tolerance), "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long")
