"""SimHash near-duplicates by deletion-variant signatures.

Two fingerprints that differ in at most ``max_bits`` = 3 of 64 bits differ in at most one bit of one
of two 32-bit segments. So each distinct fingerprint is indexed under each segment as it is and
under each of its 32 one-wildcard variants. Equal variants meet by the shuffle; a link is verified on all
64 bits and made under one variant only: the first segment with at most one differing bit, and in
it the wildcard that stands at this bit. Within a variant's rows a breadth-first search makes the
links of a spanning forest, never all pairs. Components of links are found by ``components``.

Defined results: null counts as empty; texts without words have fingerprint zero and are linked
like others; equal fingerprints are always linked; repeated rows and ties share a component; a
null ``doc_id`` is ignored as a component's name unless all ids are null; an empty table gives an empty result.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import cut_lineage, map_arrow, utf8
from .components import connected_components

SEGMENT = 32
EXACT = 32  # the code of a segment without wildcard
DENSE_RUN = 2048


def fingerprint(text: bytes, words_per_shingle: int = 3, seed: int = 42) -> int:
    """64 majority bits over the hashes of a text's word shingles, with repeats."""
    words = text.lower().split()  # of bytes: A-Z only, and white space is 0x20 and 0x09-0x0D
    if not words:
        return 0
    if len(words) < words_per_shingle:
        shingles = [b" ".join(words)]
    else:
        shingles = map(b" ".join, zip(*(words[i:] for i in range(words_per_shingle)), strict=False))
    digest = xxhash.xxh64_intdigest
    hashes = np.array([digest(s, seed) for s in shingles], dtype="<u8")
    ones = np.zeros(64, dtype=np.int64)
    for start in range(0, len(hashes), 65_536):
        part = hashes[start : start + 65_536]
        ones += np.unpackbits(part.view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.uint32)
    return int(np.packbits(2 * ones > len(hashes), bitorder="little").view("<u8")[0])


def fingerprints(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words_per_shingle: int = 3) -> DataFrame:
    """(doc_id, fp) with the fingerprint as a signed long."""

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            found = np.array([fingerprint(x.as_py(), words_per_shingle) for x in batch.column(1)], dtype=np.uint64)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(found.view(np.int64))], names=["doc_id", "fp"])

    return map_arrow(docs.select(F.col(id_col).cast("long").alias("doc_id"), utf8(text_col).alias("t")), kernel, "doc_id long, fp long")


def variants(fps: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Keys of all variants of unsigned fingerprints, and the fingerprint of each."""
    keys = []
    for segment in (0, 1):
        value = (fps >> np.uint64(SEGMENT * segment)) & np.uint64(0xFFFFFFFF)
        for code in range(EXACT + 1):
            masked = value if code == EXACT else value & ~np.uint64(1 << code)
            keys.append(np.uint64(segment << 38 | code << 32) | masked)
    return np.concatenate(keys), np.tile(fps, len(keys))


def _linked(x: np.uint64, others: np.ndarray, segment: int, code: int, max_bits: int) -> np.ndarray:
    """Which others link to x, and are found first under this segment and code."""
    diff = others ^ x
    near = np.bitwise_count(diff) <= max_bits
    if code != EXACT:
        near &= (diff >> np.uint64(SEGMENT * segment + code)) & np.uint64(1) == 1
    if segment:
        near &= np.bitwise_count(diff & np.uint64(0xFFFFFFFF)) >= 2
    return near


def _forest(members: np.ndarray, segment: int, code: int, max_bits: int) -> Iterator[tuple[np.uint64, np.ndarray]]:
    """Links of a spanning forest of the members' link graph: a vertex and its newly found neighbours."""
    left = members
    while len(left) > 1:
        queue, left = [left[0]], left[1:]
        while queue and len(left):
            x = queue.pop()
            near = _linked(x, left, segment, code, max_bits)
            if near.any():
                found = left[near]
                yield x, found
                queue.extend(found)
                left = left[~near]


def links_of_run(members: np.ndarray, segment: int, code: int, max_bits: int = 3) -> Iterator[tuple[np.uint64, np.ndarray]]:
    """Links among all fingerprints with one variant key; long runs are first cut by pieces of their other segment.

    Links differ in at most three bits, so of four pieces of eight bits at least one is the same.
    """
    if code != EXACT:
        bit = (members >> np.uint64(SEGMENT * segment + code)) & np.uint64(1)
        if bit.all() or not bit.any():
            return
    if len(members) <= DENSE_RUN or max_bits > 3:
        yield from _forest(members, segment, code, max_bits)
        return
    for piece in range(4):
        at = (members >> np.uint64(SEGMENT * (1 - segment) + 8 * piece)) & np.uint64(0xFF)
        order = np.argsort(at, kind="stable")
        for part in np.split(members[order], np.flatnonzero(np.diff(at[order])) + 1):
            yield from _forest(part, segment, code, max_bits)


def link_sorted(batches: Iterator[tuple[np.ndarray, np.ndarray]], max_bits: int = 3) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Links from (keys, fingerprints) sorted by key, over batch borders."""
    held_k, held_f = np.empty(0, np.uint64), np.empty(0, np.uint64)
    for keys, fps in batches:
        keys, fps = np.concatenate([held_k, keys]), np.concatenate([held_f, fps])
        if not len(keys):
            continue
        last = np.searchsorted(keys, keys[-1], "left")
        yield from _link_whole(keys[:last], fps[:last], max_bits)
        held_k, held_f = keys[last:], fps[last:]
    yield from _link_whole(held_k, held_f, max_bits)


def _link_whole(keys: np.ndarray, fps: np.ndarray, max_bits: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    if len(keys) < 2:
        return
    starts = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]])
    lengths = np.diff(np.r_[starts, len(keys)])
    a, b = [], []
    for start, length in zip(starts[lengths > 1], lengths[lengths > 1], strict=True):
        key = int(keys[start])
        for x, found in links_of_run(fps[start : start + length], key >> 38, key >> 32 & 63, max_bits):
            a.append(np.full(len(found), x))
            b.append(found)
    if a:
        yield np.concatenate(a), np.concatenate(b)


def near_links(distinct: DataFrame, max_bits: int = 3) -> DataFrame:
    """(a, b): links of spanning forests over the distinct fingerprints fp, enough for their components."""
    if max_bits > 3:
        raise ValueError("two segments with one wildcard find links of at most 3 bits")

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            fps = batch.column(0).to_numpy(zero_copy_only=False).view(np.uint64)
            for start in range(0, len(fps), 2000):
                keys, own = variants(fps[start : start + 2000])
                yield pa.RecordBatch.from_arrays([pa.array(keys.view(np.int64)), pa.array(own.view(np.int64))], names=["key", "fp"])

    def link(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        arrays = ((b.column(0).to_numpy().view(np.uint64), b.column(1).to_numpy().view(np.uint64)) for b in batches)
        for a, b in link_sorted(arrays, max_bits):
            yield pa.RecordBatch.from_arrays([pa.array(a.view(np.int64)), pa.array(b.view(np.int64))], names=["a", "b"])

    indexed = distinct.select("fp").mapInArrow(index, "key long, fp long")
    return indexed.repartition("key").sortWithinPartitions("key").mapInArrow(link, "a long, b long")


def near_duplicates(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", words_per_shingle: int = 3, max_bits: int = 3) -> DataFrame:
    """(doc_id, fingerprint, component_id) for every row."""
    marked = cut_lineage(fingerprints(docs, id_col, text_col, words_per_shingle))
    distinct = cut_lineage(marked.groupBy("fp").agg(F.min("doc_id").alias("least_id")))
    roots = connected_components(near_links(distinct, max_bits))
    rooted = cut_lineage(distinct.join(roots, distinct["fp"] == roots["vertex"], "left").select("fp", "least_id", F.coalesce("root", "fp").alias("root")))
    # Written, so that the join deals both sides anew, and can split the fingerprints of a very large component.
    named = cut_lineage(rooted.groupBy("root").agg(F.min("least_id").alias("component_id")))
    labels = rooted.join(named, "root").select("fp", "component_id")
    return marked.join(labels, "fp").select("doc_id", F.lpad(F.lower(F.hex("fp")), 16, "0").alias("fingerprint"), "component_id")


def one_of_each(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of docs whose id names their component."""
    groups = near_duplicates(docs, id_col, text_col)
    heads = groups.where(F.col("doc_id").eqNullSafe(F.col("component_id"))).select(F.col("doc_id").alias("head")).distinct()
    return docs.join(heads, docs[id_col].eqNullSafe(heads["head"]), "left_semi")
