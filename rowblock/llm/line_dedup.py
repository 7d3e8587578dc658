"""Removal of repeated passages by content-defined chunks of lines (DataFrame functions only).

A text is cut into lines, and a chunk ends where a rolling hash over the hashes of the last two lines is in the lowest
``1 / divisor`` of its range; so the same passage is cut at the same lines wherever it stands. Chunks of two or
more lines that occur again anywhere are removed, but for their first occurrence (least id, then place). At the edges of a passage
chunks differ by what stands around it, and a short passage may hold no whole chunk. So in what is left the rolling window itself
is the chunk: any two neighbouring lines that occur again are removed, but for their first occurrence. Every passage of two
or more lines thus goes whole, and every line stays somewhere. Chunks of empty lines alone stay.

Only 64-bit keys are shuffled to find repeats. A bitmap over the repeated keys, sized by their number and never larger than
``most_bits``, then lets through the texts that may repeat (beyond that, a join on the keys does); these are grouped by their complete
text, which is the comparison by bytes. Texts of documents move once, to meet the list of their lines to remove.

Defined results: null counts as empty and an empty text has one empty line; rows are told apart by id and text, so rows that only share
an id, null too, are documents of their own, and rows equal in both are one document and keep or lose the same lines; all other columns
stay, whatever their names; an empty table gives an empty result.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import computed_once, cut_lineage, text_or_empty

BUCKET_BITS = 32_768  # of Spark's bitmap aggregate
LEAST_BITS = 1 << 20


@dataclass(frozen=True)
class Chunking:
    divisor: int = 3
    base: int = 1_000_003
    modulus: int = 4_294_967_291  # a prime below 2^32
    most_bits: int = 1 << 28  # 32 MB, the size of what is broadcast at most
    bits_per_key: int = 16

    @property
    def cut(self) -> int:
        return self.modulus // self.divisor


def line_hash(line: Column) -> Column:
    """32 bits of a line's MD5, so that other engines can repeat it."""
    return F.conv(F.substring(F.md5(line), 1, 8), 16, 10).cast("long")


def with_lines(docs: DataFrame, id_col: str, text_col: str, *more: Column) -> DataFrame:
    """(row, text_hash, doc, lines, ...): row and text_hash name a row by its id and text."""
    text = text_or_empty(text_col)
    doc = F.col(id_col).cast("long")
    return docs.select(F.xxhash64(doc, text).alias("row"), F.xxhash64(text).alias("text_hash"), doc.alias("doc"), F.split(text, "\n", -1).alias("lines"), *more)


def with_spans(lined: DataFrame, chunking: Chunking) -> DataFrame:
    """lined with spans, the (first line, number of lines) of each chunk."""
    out = lined.withColumn("hashes", F.transform("lines", line_hash))
    h, n = F.col("hashes"), F.size("lines")
    rolled = lambda i: F.pmod(F.get(h, i - 2) * chunking.base + F.get(h, i - 1), F.lit(chunking.modulus))
    # A chunk starts at line 0 and after a line, other than the first, whose rolling hash is low.
    out = out.withColumn("starts", F.filter(F.sequence(F.lit(0), n - 1), lambda i: (i == 0) | ((i >= 2) & (rolled(i) < chunking.cut))))
    s = F.col("starts")
    cut = F.transform(s, lambda at, k: F.struct(at.alias("first"), (F.coalesce(F.get(s, k + 1), n) - at).alias("n")))
    return out.withColumn("spans", computed_once(cut, F.array().cast("array<struct<first:int,n:int>>"))).drop("hashes", "starts")


def _joined(first: Column, n: Column | int) -> Column:
    return F.array_join(F.slice("lines", first + 1, n), "\n")


def _has_text(t: Column) -> Column:
    return F.length(F.replace(t, F.lit("\n"), F.lit(""))) > 0


def chunk_pieces(docs: DataFrame, chunking: Chunking, id_col: str, text_col: str) -> DataFrame:
    """(row, text_hash, doc, first, n, t, key) of each chunk of two or more lines."""
    each = with_spans(with_lines(docs, id_col, text_col), chunking).select("row", "text_hash", "doc", "lines", F.explode("spans").alias("s")).where("s.n >= 2")
    pieces = each.select("row", "text_hash", "doc", "s.first", "s.n", _joined(F.col("s.first"), F.col("s.n")).alias("t"))
    return pieces.where(_has_text(F.col("t"))).withColumn("key", F.xxhash64("t"))


def _pairs(starts: Column, line: str) -> Column:
    """(first, key) of the two-line windows that start at these lines, from the lines' hashes."""
    h = F.col(line)
    empty = F.xxhash64(F.lit(""))
    windows = F.transform(starts, lambda i: F.struct(i.alias("first"), F.xxhash64(F.get(h, i), F.get(h, i + 1)).alias("key"), (F.get(h, i).eqNullSafe(empty) & F.get(h, i + 1).eqNullSafe(empty)).alias("blank")))
    return F.filter(windows, lambda w: ~w["blank"])


def _window_starts(n: Column) -> Column:
    return F.when(n >= 2, F.sequence(F.lit(0), n - 2)).otherwise(F.array().cast("array<int>"))


def window_keys(docs: DataFrame, gone: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(key) of the windows that aren't within a removed chunk; hashes of lines move, not lines."""
    hashed = with_lines(docs, id_col, text_col).select("row", "text_hash", F.transform("lines", lambda x: F.xxhash64(x)).alias("h"))
    inner = gone.select("row", "text_hash", F.explode(F.sequence(F.col("first"), F.col("first") + F.col("n") - 2)).alias("at"))
    inner = inner.groupBy("row", "text_hash").agg(F.collect_set("at").alias("inside"))  # at most a document's own lines
    both = hashed.join(inner, ["row", "text_hash"], "left")
    starts = F.array_except(_window_starts(F.size("h")), F.coalesce("inside", F.array().cast("array<int>")))
    return both.select(F.explode(_pairs(starts, "h")).alias("w")).select("w.key")


def window_pieces(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(row, text_hash, doc, first, n, t, key) of each two neighbouring lines."""
    lined = with_lines(docs, id_col, text_col).withColumn("h", F.transform("lines", lambda x: F.xxhash64(x)))
    each = lined.select("row", "text_hash", "doc", "lines", F.explode(_pairs(_window_starts(F.size("lines")), "h")).alias("w"))
    return each.select("row", "text_hash", "doc", "w.first", F.lit(2).alias("n"), _joined(F.col("w.first"), F.lit(2)).alias("t"), "w.key")


def repeated_keys(keys: DataFrame) -> DataFrame:
    return cut_lineage(keys.groupBy("key").agg(F.count(F.lit(1)).alias("times")).where("times > 1").select("key"))


def only_repeated(pieces: DataFrame, again: DataFrame, chunking: Chunking) -> DataFrame:
    """pieces whose key may be in again; which it is, the complete texts decide later."""
    wanted = again.count() * chunking.bits_per_key
    if wanted > chunking.most_bits:
        return pieces.join(again, "key", "left_semi")
    bits = max(LEAST_BITS, 1 << max(0, wanted - 1).bit_length())
    at = lambda key: F.pmod(key, F.lit(bits))
    bucket, bit = F.floor(at(F.col("key")) / BUCKET_BITS).cast("long"), F.pmod(at(F.col("key")), F.lit(BUCKET_BITS))
    bitmaps = again.select(bucket.alias("bucket"), bit.alias("bit")).groupBy("bucket").agg(F.bitmap_construct_agg("bit").alias("bits"))
    byte = F.conv(F.hex(F.substring(F.col("bits"), F.floor(F.col("bit") / 8).cast("int") + 1, F.lit(1))), 16, 10).cast("int")
    met = F.call_function("shiftright", byte, F.pmod(F.col("bit"), F.lit(8)).cast("int")).bitwiseAND(F.lit(1)) == 1
    marked = pieces.withColumns({"of": bucket, "bit": bit}).join(F.broadcast(bitmaps), F.col("of") == F.col("bucket"))  # bits / 8 bytes at most
    return marked.where(met).select(pieces.columns)


def later_ones(pieces: DataFrame, again: DataFrame, chunking: Chunking) -> DataFrame:
    """(row, text_hash, first, n) of the pieces whose complete text stands at an earlier place as well."""
    place = F.struct("doc", "row", "text_hash", F.col("first"))
    candidates = only_repeated(pieces, again, chunking).withColumn("place", place)
    firsts = candidates.groupBy("t").agg(F.min("place").alias("least"), F.max("place").alias("most")).where("least <> most")
    firsts = firsts.select(F.col("t").alias("same"), F.xxhash64("t").alias("same_key"), "least")
    later = candidates.withColumn("text_key", F.xxhash64("t")).join(firsts, (F.col("text_key") == F.col("same_key")) & (F.col("t") == F.col("same"))).where("place > least")
    return later.select("row", "text_hash", "first", "n")


def removals(docs: DataFrame, chunking: Chunking, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(row, text_hash, gone, n_gone): for each row with any, its lines that have to go and how many whole chunks they hold."""
    chunks = chunk_pieces(docs, chunking, id_col, text_col)
    gone = cut_lineage(later_ones(chunks, repeated_keys(chunks.select("key")), chunking).distinct())
    again = repeated_keys(window_keys(docs, gone, id_col, text_col))
    edges = later_ones(window_pieces(docs, id_col, text_col), again, chunking)
    every = gone.withColumn("whole", F.lit(1)).union(edges.withColumn("whole", F.lit(0)))
    lines = every.withColumn("own", F.sequence(F.col("first"), F.col("first") + F.col("n") - 1))
    at = lines.select("row", "text_hash", F.posexplode("own").alias("k", "line"), F.when(F.col("whole") == 1, F.col("first")).alias("chunk"))
    return at.groupBy("row", "text_hash").agg(F.collect_set("line").alias("gone"), F.count_distinct("chunk").alias("n_gone"))


def without_repeats(docs: DataFrame, chunking: Chunking | None = None, id_col: str = "doc_id", text_col: str = "text", counts: bool = False) -> DataFrame:
    """docs with repeated chunks taken out of their texts; with counts, also n_lines, n_chunks, removed_chunks, removed_lines."""
    chunking = chunking or Chunking()
    gone = removals(docs, chunking, id_col, text_col)
    given = F.struct(*(F.col(f"`{c}`").alias(f"c{k}") for k, c in enumerate(docs.columns))).alias("given")
    both = with_lines(docs, id_col, text_col, given).join(gone, ["row", "text_hash"], "left")
    n = F.size("lines")
    left = F.array_except(F.sequence(F.lit(0), n - 1), "gone")
    text = F.array_join(F.transform(left, lambda i: F.get("lines", i)), "\n")
    own = F.col(f"given.c{docs.columns.index(text_col)}")
    columns = [(F.when(F.col("gone").isNull(), own).otherwise(text) if c == text_col else F.col(f"given.c{k}")).alias(c) for k, c in enumerate(docs.columns)]
    if not counts:
        return both.select(*columns)
    extra = [
        n.cast("long").alias("n_lines"),
        F.size("spans").cast("long").alias("n_chunks"),
        F.coalesce("n_gone", F.lit(0)).cast("long").alias("removed_chunks"),
        F.coalesce(F.size("gone"), F.lit(0)).cast("long").alias("removed_lines"),
    ]
    return with_spans(both, chunking).select(*columns, *extra)


def digests(docs: DataFrame, chunking: Chunking | None = None) -> DataFrame:
    """doc_id, n_lines, n_chunks, removed_chunks, removed_lines, kept_chars and text_md5 of what is left."""
    out = without_repeats(docs.select("doc_id", "text"), chunking, counts=True)
    left = text_or_empty()
    return out.select("doc_id", "n_lines", "n_chunks", "removed_chunks", "removed_lines", F.length(left).cast("long").alias("kept_chars"), F.md5(left).alias("text_md5"))
