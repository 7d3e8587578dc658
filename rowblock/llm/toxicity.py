"""Toxicity by compression distance: two zstandard dictionaries, windows of words, calibrated thresholds.

Training takes a bounded sample of labelled documents. Its first three quarters give the dictionaries. Each kind of text is reduced to
the stretches that are its own: substrings of six bytes with ``least_contexts`` or more different continuations in it, and relative to
the amount of text at least ``ratio`` times as many as in the other kind (copies of one document count once). zstandard's trainer makes
one dictionary of the toxic kind's stretches and one of the ordinary kind's. Both are followed by the same base, which the
trainer makes of ordinary text without the toxic kind's stretches; so what is common costs the same under both.

A text is cut into windows of six words, every three words. Each is compressed under both dictionaries; its gain is the number of bytes
that the toxic one saves. (A common carrier ends every window: the compressor stores very short inputs as they are.) The last
quarter of the sample calibrates: thresholds are the least gains that at most one in 200, 1,000 and 5,000 ordinary windows
reach, and a logistic curve turns how often a text reaches them, and its highest gains, into a score. The curve is that of a sample
of which ``toxic_share`` is toxic. Windows that both dictionaries compress to one size gain nothing; most of these are known without
compressing (``Differences``).

Scores depend on the text and nothing else. Defined results: null and empty texts get the score of a text
without windows; repeated rows get the same score; an empty table gives an empty result; a sample without toxic or without ordinary
documents gives the prior to every text.
"""

from __future__ import annotations

import hashlib
import math
import pickle
import random
from collections import Counter
from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field
from itertools import accumulate

import numpy as np
import pyarrow as pa
import zstandard as zstd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_name, give_back, map_arrow, utf8, with_field

LETTERS = bytes(c if c >= 128 or 97 <= c <= 122 else 32 for c in range(256))  # all else separates words
LONGEST_WORD = 48  # longer ones are cut
PIECE = 6  # bytes of a substring that may be a kind's own
CONTEXT = 12  # bytes that tell its occurrences apart


@dataclass(frozen=True)
class Training:
    """Bounds of the labelled sample (documents and bytes of each kind) and the shape of windows and dictionaries."""

    toxic_docs: int = 2000
    ordinary_docs: int = 4000
    toxic_bytes: int = 8 << 20
    ordinary_bytes: int = 16 << 20
    window: int = 6
    stride: int = 3
    own_bytes: int = 8192
    base_bytes: int = 65_536
    base_pairs: int = 300_000
    common_words: int = 1500
    least_contexts: int = 6
    ratio: float = 8.0
    rates: tuple[float, ...] = (1 / 200, 1 / 1000, 1 / 5000)
    toxic_share: float = 0.3  # what toxic texts count for in the logistic curve


@dataclass
class Model:
    ordinary: bytes
    toxic: bytes
    carrier: bytes
    window: int
    stride: int
    prior: float
    thresholds: tuple[int, ...]
    weights: np.ndarray
    key: str = field(default="")

    def __post_init__(self) -> None:
        self.key = self.key or hashlib.md5(self.ordinary + self.toxic + repr((self.window, self.stride, self.prior, self.thresholds)).encode() + self.weights.tobytes()).hexdigest()


def words_of(text: bytes) -> list[bytes]:
    words = text.decode(errors="replace").lower().encode().translate(LETTERS).split()
    if max(map(len, words), default=0) > LONGEST_WORD:
        words = [w[i : i + LONGEST_WORD] for w in words for i in range(0, len(w), LONGEST_WORD)]
    return words


class Differences:
    """Which windows two dictionaries of one length may compress differently, where they differ in their heads alone.

    The compressor searches a dictionary from its end, and what it takes from a head is longer than any match in the common rest. So a
    window's sizes differ only if one of its substrings stands in a head and not in the rest. Length by length, from ``SHORTEST`` bytes
    on, a table tells by a hash of a substring whether it stands in no head (longer ones don't either), in a head and the rest (longer
    ones may tell), or in a head alone. Substrings that share a slot count as the one that tells more, so no window is missed; a second
    table with other slots takes back most of what that adds.
    """

    SHORTEST, LONGEST = 4, 256  # the compressor's least match; a substring so long counts as one of a head alone
    SLOTS = 18  # bits

    def __init__(self, ordinary: bytes, toxic: bytes) -> None:
        whole = [np.frombuffer(c, np.uint8) for c in (ordinary, toxic)]
        differ = np.flatnonzero(whole[0] != whole[1])
        head = int(differ[-1]) + 1 if len(differ) else 0
        # A match that begins in a head may end in the rest, and the compressor finds none that begins in the last eight bytes.
        parts = [(x, np.arange(head)) for x in whole] + [(whole[0], np.arange(head, max(head, len(ordinary) - 8)))]
        self.tables: list[np.ndarray] = []  # two for each length
        long = short = None
        for size in range(self.SHORTEST, self.LONGEST):
            if long is None:
                parts = [(x, at[at + size <= len(x)]) for x, at in parts]
                long, short = ([self._first(x, at, kind) for x, at in parts] for kind in (np.uint64, np.uint32))
            else:
                grown = [at + size <= len(x) for x, at in parts]
                parts = [(x, at[g]) for (x, at), g in zip(parts, grown, strict=True)]
                long, short = ([self._longer(h[g], x[at + size - 1]) for (x, at), h, g in zip(parts, hs, grown, strict=True)] for hs in (long, short))
            both = [np.isin(h, long[-1]) for h in long[:-1]]
            pair = np.zeros((2, 1 << self.SLOTS), np.uint8)
            for most in (1, 2):
                for h, b in zip(short, both, strict=False):
                    chosen = h[b if most == 1 else ~b]
                    pair[0, self._slot(chosen)] = most
                    pair[1, self._second_slot(chosen)] = most
            self.tables.append(pair)
            if not any(b.any() for b in both):
                return
            both.append(np.isin(long[-1], np.concatenate([h[b] for h, b in zip(long, both, strict=False)])))
            parts = [(x, at[b]) for (x, at), b in zip(parts, both, strict=True)]
            long, short = ([h[b] for h, b in zip(hs, both, strict=True)] for hs in (long, short))

    def _slot(self, hashes: np.ndarray) -> np.ndarray:
        return hashes >> np.uint32(32 - self.SLOTS)

    def _second_slot(self, hashes: np.ndarray) -> np.ndarray:
        return (hashes * np.uint32(0x85EBCA6B)) >> np.uint32(32 - self.SLOTS)

    @staticmethod
    def _longer(hashes: np.ndarray, byte: np.ndarray) -> np.ndarray:
        kind, turn = (np.uint64, 29) if hashes.dtype == np.uint64 else (np.uint32, 15)
        out = hashes ^ byte.astype(kind)
        out *= kind(0x9E3779B97F4A7C15 if kind is np.uint64 else 0x9E3779B1)
        out ^= out >> kind(turn)
        return out

    def _first(self, x: np.ndarray, at: np.ndarray, kind: type) -> np.ndarray:
        out = np.zeros(len(at), kind)
        for k in range(self.SHORTEST):
            out = self._longer(out, x[at + k])
        return out

    def of(self, windows: list[bytes], tail: int) -> np.ndarray:
        """For each window whether its sizes may differ; its last ``tail`` bytes are the end of both dictionaries, where the longest match is found first."""
        x = np.frombuffer(b"\n".join(windows) + b"\n" * self.SHORTEST, np.uint8)  # no dictionary holds a line feed
        sizes = np.fromiter(map(len, windows), np.int32, len(windows))
        starts = (np.cumsum(sizes + 1) - sizes - 1).astype(np.int32)
        inner = np.maximum(sizes - tail, 0)
        own = np.repeat(np.arange(len(windows), dtype=np.int32), inner)
        at = np.arange(len(own), dtype=np.int32) + (starts - (np.cumsum(inner) - inner).astype(np.int32))[own]
        out, size, hashes = np.zeros(len(windows), bool), self.SHORTEST, self._first(x, at, np.uint32)
        for table, second in self.tables:
            kinds = table[self._slot(hashes)]
            likely = np.flatnonzero(kinds == 2)
            kinds[likely] = second[self._second_slot(hashes[likely])]
            out[own[likely[kinds[likely] == 2]]] = True
            more = np.flatnonzero((kinds == 1) & ~out[own])
            at, own, hashes = at[more], own[more], hashes[more]
            if not len(at):
                return out
            hashes = self._longer(hashes, x[np.minimum(at + size, len(x) - 1)])
            size += 1
        out[own] = True
        return out


class Windows:
    """Gains of a text's windows under a model's dictionaries, and the score they give."""

    AT_ONCE = 4096  # windows that are looked at together

    def __init__(self, model: Model) -> None:
        self.model = model
        params = zstd.ZstdCompressionParameters(window_log=18, hash_log=17, chain_log=18, search_log=6, min_match=4, target_length=64, strategy=zstd.STRATEGY_BTLAZY2, write_content_size=False, write_dict_id=False)
        self.compress = []
        for content in (model.ordinary, model.toxic):
            dictionary = zstd.ZstdCompressionDict(content, dict_type=zstd.DICT_TYPE_RAWCONTENT)
            dictionary.precompute_compress(compression_params=params)
            self.compress.append(zstd.ZstdCompressor(dict_data=dictionary, compression_params=params).compress)
        self.differences = Differences(model.ordinary, model.toxic)

    def gains(self, text: bytes) -> np.ndarray:
        return next(self.all_gains([text]))

    def all_gains(self, texts: Iterable[bytes]) -> Iterator[np.ndarray]:
        """Of each text; only windows whose sizes may differ are compressed, the others gain nothing."""
        held: list[bytes] = []
        counts: list[int] = []
        done: list[np.ndarray] = []  # of the first text in counts, if it is long
        for text in texts:
            counts.append(0)
            for window in self.windows(text):
                held.append(window)
                counts[-1] += 1
                if len(held) >= self.AT_ONCE:
                    done.append(self._gains(held))
                    held = []
            if not held or len(counts) >= 256:
                yield from self._split(done, held, counts)
                held, counts, done = [], [], []
        yield from self._split(done, held, counts)

    def windows(self, text: bytes) -> Iterator[bytes]:
        words, m = words_of(text), self.model
        if words:
            joined, n = _joined(words), len(words)
            spaces = [0, *accumulate(len(w) + 1 for w in words)]
            for start in range(0, max(1, n - m.window + m.stride), m.stride):
                yield joined[spaces[start] : spaces[min(start + m.window, n)] + 1] + m.carrier

    def _split(self, done: list[np.ndarray], held: list[bytes], counts: list[int]) -> list[np.ndarray]:
        return np.split(np.concatenate([*done, self._gains(held)]), np.cumsum(counts)[:-1]) if counts else []

    def _gains(self, windows: list[bytes]) -> np.ndarray:
        """Equal windows are compressed once, and all with one dictionary before the other, as its tables fill the processor's caches."""
        found = dict.fromkeys(windows, 0)
        if found:
            distinct = list(found)
            chosen = [distinct[k] for k in np.flatnonzero(self.differences.of(distinct, len(self.model.carrier) + 1)).tolist()]
            ordinary, toxic = ([len(compress(w)) for w in chosen] for compress in self.compress)
            found.update((w, a - b) for w, a, b in zip(chosen, ordinary, toxic, strict=True))
        return np.fromiter(map(found.__getitem__, windows), np.int64, len(windows))

    def score(self, text: bytes) -> float:
        return next(self.scores([text]))

    def scores(self, texts: Iterable[bytes]) -> Iterator[float]:
        if not self.model.weights.any():
            yield from (self.model.prior for _ in texts)
            return
        for gains in self.all_gains(texts):
            z = float(features(gains, self.model.thresholds) @ self.model.weights)
            yield 1 / (1 + math.exp(-max(-30.0, min(30.0, z))))


def features(gains: np.ndarray, thresholds: tuple[int, ...]) -> np.ndarray:
    """1, the highest gain and the sum of the highest four, and, per sqrt(window), how many windows reach each threshold and the sum of gains up to 8."""
    n = len(gains)
    if not n:
        return np.array([1.0] + [0.0] * (len(thresholds) + 3))
    highest, scale = np.sort(gains)[-4:], math.sqrt(n)
    return np.array([1.0, highest[-1], highest.sum(), *((gains >= t).sum() / scale for t in thresholds), np.clip(gains, 0, 8).sum() / scale])


def _joined(words: list[bytes]) -> bytes:
    return b" " + b" ".join(words) + b" "


def _hashes(text: bytes, size: int) -> np.ndarray:
    """A 64-bit hash of each substring of this size."""
    x = np.frombuffer(text, np.uint8).astype(np.uint64)
    n = len(x) - size + 1
    out = np.zeros(max(0, n), dtype=np.uint64)
    for i in range(size if n > 0 else 0):
        out = (out ^ x[i : i + n]) * np.uint64(0x9E3779B97F4A7C15)
        out ^= out >> np.uint64(29)
    return out


def _pieces(text: bytes) -> np.ndarray:
    return _hashes(text, PIECE) >> np.uint64(32)


class Contexts:
    """In how many different contexts each substring stands in texts of one kind."""

    def __init__(self, texts: Iterable[bytes]) -> None:
        found = []
        for text in texts:
            context = _hashes(text, CONTEXT) >> np.uint64(32)
            found.append(_pieces(text)[: len(context)] << np.uint64(32) | context)
        every = np.concatenate(found) if found else np.empty(0, np.uint64)
        found.clear()
        every.sort()
        every = every[np.r_[True, every[1:] != every[:-1]]] if len(every) else every
        self.size = max(1, len(every))
        self.pieces, self.n = np.unique(every >> np.uint64(32), return_counts=True)

    def of(self, pieces: np.ndarray) -> np.ndarray:
        if not len(self.pieces):
            return np.zeros(len(pieces))
        at = np.minimum(np.searchsorted(self.pieces, pieces), len(self.pieces) - 1)
        return np.where(self.pieces[at] == pieces, self.n[at], 0).astype(np.float64)


def own_bytes(text: bytes, own: Contexts, other: Contexts, t: Training) -> np.ndarray:
    """Which bytes of a text are in substrings that are its kind's own."""
    pieces = _pieces(text)
    a, b = own.of(pieces), other.of(pieces)
    marks = np.zeros(len(text) + 1, dtype=np.int64)
    at = np.flatnonzero((a >= t.least_contexts) & (a / own.size > t.ratio * (b + 0.5) / other.size))
    marks[at] += 1
    marks[at + PIECE] -= 1
    return np.cumsum(marks)[:-1] > 0


def stretches(texts: list[bytes], own: Contexts, other: Contexts, t: Training) -> list[bytes]:
    """The stretches that are a kind's own, each once for what follows it."""
    found = set()
    for text in texts:
        edges = np.flatnonzero(np.diff(np.r_[0, own_bytes(text, own, other, t).astype(np.int8), 0]))
        found.update((text[a:b], text[b : b + PIECE]) for a, b in zip(edges[::2], edges[1::2], strict=True))
    return [s for s, _ in sorted(found)]


def trained(samples: list[bytes], size: int) -> bytes:
    """A dictionary by zstandard's trainer; where samples are too few for it, the samples themselves."""
    samples = list(samples)
    random.Random(1).shuffle(samples)
    try:
        return zstd.train_dictionary(size, samples, k=16, d=6).as_bytes()
    except zstd.ZstdError:
        return b"".join(samples)[:size]


def train_dictionaries(toxic: list[bytes], ordinary: list[bytes], t: Training) -> tuple[bytes, bytes, bytes]:
    """Contents of the ordinary and the toxic dictionary, and the carrier that ends both."""
    texts = [[_joined(w) for w in map(words_of, kind) if w] for kind in (ordinary, toxic)]
    plain, marked = (Contexts(kind) for kind in texts)
    own = [trained(stretches(texts[0], plain, marked, t), t.own_bytes), trained(stretches(texts[1], marked, plain, t), t.own_bytes)]
    pairs: set[tuple[bytes, bytes]] = set()
    for text in texts[0]:
        if len(pairs) >= t.base_pairs:
            break
        space = np.frombuffer(text, np.uint8) == 32
        taken = np.bincount(np.cumsum(space), weights=own_bytes(text, marked, plain, t) & ~space)
        words = text.split()
        pairs.update((a, b) for a, b, x, y in zip(words, words[1:], taken[1:], taken[2:], strict=False) if not x and not y)
    base_text = sorted(pairs)
    common = [w for w, _ in sorted(Counter(w for text in texts[0] for w in set(text.split())).items(), key=lambda x: (-x[1], x[0]))[: t.common_words]]
    carrier = b" ".join(common[:14])
    base = trained([_joined(list(p)) for p in base_text], t.base_bytes) + b" " + b" ".join(reversed(common)) + b" " + carrier
    width = max(map(len, own))
    return own[0].rjust(width, b"\0") + base, own[1].rjust(width, b"\0") + base, carrier


def thresholds(gains: np.ndarray, rates: tuple[float, ...]) -> tuple[int, ...]:
    """For each rate the least gain, 1 at least, that at most this share of gains reach."""
    ordered = np.sort(gains)[::-1]
    return tuple(max(1, int(ordered[int(len(gains) * r)]) + 1) if len(gains) else 1 for r in rates)


def fit(sample: list[tuple[bytes, int]], training: Training | None = None, prior: float = 0.1) -> Model:
    """A model from (text, toxic 0/1) pairs; the order decides which of them calibrate."""
    t = training or Training()
    kinds = [[x for x, y in sample if y == k] for k in (0, 1)]
    first, last = ([k[: (3 * len(k) + 3) // 4] for k in kinds], [k[(3 * len(k) + 3) // 4 :] for k in kinds])
    if not all(map(len, last)):
        return Model(b" ", b" ", b" ", t.window, t.stride, prior, (1,) * len(t.rates), np.zeros(len(t.rates) + 4))
    model = Model(*train_dictionaries(first[1], first[0], t), t.window, t.stride, prior, (1,) * len(t.rates), np.zeros(len(t.rates) + 4))
    windows = Windows(model)
    gains = [list(windows.all_gains(kind)) for kind in last]
    cuts = thresholds(np.concatenate(gains[0]), t.rates)
    x = np.array([features(g, cuts) for kind in gains for g in kind])
    n0, n1 = map(len, last)
    y = np.repeat([0.0, 1.0], [n0, n1])
    weights = logistic(x, y, np.where(y == 1, t.toxic_share / n1, (1 - t.toxic_share) / n0) * len(y))
    return Model(model.ordinary, model.toxic, model.carrier, t.window, t.stride, prior, cuts, weights)


def logistic(x: np.ndarray, y: np.ndarray, weight: np.ndarray, ridge: float = 0.1, rounds: int = 60) -> np.ndarray:
    """Weighted logistic regression with a ridge, by damped Newton steps."""
    w = np.zeros(x.shape[1])
    penalty = np.diag([1e-3] + [ridge] * (x.shape[1] - 1))
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (weight * p * (1 - p))[:, None]).T @ x + penalty, x.T @ (weight * (y - p)) - penalty @ w)
        w += step * min(1.0, 3 / (np.abs(step).max() + 1e-12))
        if np.abs(step).max() < 1e-8:
            break
    return w


def held_out(doc_id: Column) -> Column:
    """Whether a row is kept from learning: crc32 of its id as text leaves 1 when divided by 3."""
    return F.coalesce(F.crc32(doc_id.cast("string")) % 3 == 1, F.lit(False))


def learn(docs: DataFrame, labels: DataFrame, training: Training | None = None) -> Model:
    """Fit on a bounded sample of labelled rows, taken in the order of a hash of their id; only its ids are broadcast.

    The sample is bounded by documents and, once their lengths are known, by bytes: a text that does not fit into
    what is left of its kind's bytes is passed over, whatever its length.
    """
    t = training or Training()
    usable = labels.where("doc_id IS NOT NULL AND toxic IN (0, 1)").where(~held_out(F.col("doc_id"))).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    counts = {int(r["toxic"]): r["n"] for r in usable.groupBy("toxic").agg(F.count(F.lit(1)).alias("n")).collect()}
    prior = min(0.5, max(0.001, counts.get(1, 0) / max(1, sum(counts.values()))))
    order = F.xxhash64("doc_id")
    part = lambda kind, most: usable.where(F.col("toxic") == kind).orderBy(order, "doc_id").limit(most)
    chosen = part(1, t.toxic_docs).union(part(0, t.ordinary_docs)).withColumnRenamed("doc_id", "chosen_id")
    rows = docs.select("doc_id", utf8("text").alias("t")).join(F.broadcast(chosen), F.col("doc_id") == F.col("chosen_id"))
    small = rows.select("doc_id", "toxic", F.octet_length("t").alias("n")).collect()  # at most one for each chosen id
    small.sort(key=lambda r: (hashlib.md5(str(r["doc_id"]).encode()).digest(), r["n"]))
    left, taken = {0: t.ordinary_bytes, 1: t.toxic_bytes}, []
    for r in small:
        if r["n"] <= left[r["toxic"]]:
            left[r["toxic"]] -= r["n"]
            taken.append(r["doc_id"])
    if not taken:
        return fit([], t, prior)
    ids = docs.sparkSession.createDataFrame([(i,) for i in sorted(set(taken))], "taken_id long")
    texts = rows.join(F.broadcast(ids), F.col("doc_id") == F.col("taken_id")).select("doc_id", "t", "toxic").toArrow().to_pylist()
    texts.sort(key=lambda r: (hashlib.md5(str(r["doc_id"]).encode()).digest(), r["t"]))
    model = fit([(r["t"], int(r["toxic"])) for r in texts], t, prior)
    del texts
    give_back()
    return model


_ready: dict[str, Windows] = {}


def _windows(model: Model) -> Windows:
    if model.key not in _ready:
        _ready.clear()
        _ready[model.key] = Windows(model)
    return _ready[model.key]


def score(docs: DataFrame, model: Model, score_col: str = "score", text_col: str = "text") -> DataFrame:
    """docs with a score; one pass, row by row, nothing is shuffled."""
    text_at = docs.columns.index(text_col)
    packed = docs.sparkSession.sparkContext.broadcast(pickle.dumps(model))  # the dictionaries' sizes are bounded by Training
    names = [*docs.columns, score_col]

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        windows = _windows(pickle.loads(packed.value))
        for batch in batches:
            found = list(windows.scores((x.as_py() or "").encode() for x in batch.column(text_at)))
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(found, pa.float64())], names=names)

    return map_arrow(docs, kernel, with_field(docs, score_col, "double"))


def judge(docs: DataFrame, labels: DataFrame, threshold: float = 0.7, training: Training | None = None) -> DataFrame:
    """doc_id, held_out, score and predicted for every document."""
    slim = docs.select("doc_id", "text")
    scored = score(slim, learn(slim, labels, training)).drop("text")
    return scored.select("doc_id", held_out(F.col("doc_id")).alias("held_out"), "score", (F.col("score") >= threshold).cast("int").alias("predicted"))


def keep_ordinary(docs: DataFrame, labels: DataFrame, threshold: float = 0.7, training: Training | None = None) -> DataFrame:
    """The documents below the threshold, with the columns they came with."""
    name = free_name(docs, "score")
    return score(docs, learn(docs, labels, training), name).where(F.col(name) < threshold).select(*docs.columns)
