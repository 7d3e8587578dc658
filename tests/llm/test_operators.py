"""Operators against brute force on small tables with nulls, empty and long texts, copies and clashing names."""

import hashlib
import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F

from rowblock.llm import components, exact_dedup, line_dedup, lm_scoring, packing, piece_codec, quality_rules, simhash, token_counts, toxicity, url_filters

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
PIECES = public_tokenizers.path("piece_bpe_32k.model")
JSON, RANKS = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("byte_bpe_50k.tiktoken")


def texts(seed=1):
    rng = random.Random(seed)
    words = ["".join(rng.choice("abcdehilnorst") for _ in range(rng.randint(1, 9))) for _ in range(80)]
    line = lambda: " ".join(rng.choice(words) for _ in range(rng.randint(3, 14)))
    out = ["\n".join(line() for _ in range(rng.randint(1, 12))) for _ in range(60)]
    passage = "\n".join(line() for _ in range(9))
    out += [f"{line()}\n{passage}\n{line()}" for _ in range(6)]
    base = " ".join(line() for _ in range(60))
    out += [base, base.upper(), base + " more", base.replace(" ", "  ", 3), "x " + base]
    out += [None, None, "", "", " ", "\n\n", "É é", "a" * 3000, "long " * 6000, "日本語 ▁ text <s> <|endoftext|> 🙂", "\x00\x01", "one"]
    return out


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i * 7 % 1009, t, random.Random(i).choice(["en", "fr", None, "xx"]), None, None) for i, t in enumerate(texts())]
    rows.append((None, "no id", "en", None, None))
    return spark.createDataFrame(rows, SCHEMA).repartition(3).cache()


@pytest.fixture(scope="module")
def rows(docs):
    return [(r["doc_id"], r["text"] or "") for r in docs.collect()]


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.fixture(scope="module")
def labels(spark, rows):
    return spark.createDataFrame([(i, k % 3 > 0, k % 5 == 0) for k, (i, _) in enumerate(rows) if i is not None], "doc_id long, q boolean, t boolean").select("doc_id", F.col("q").cast("int").alias("quality"), F.col("t").cast("int").alias("toxic"))


def low(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text)


def test_exact_dedup(docs, rows):
    groups = defaultdict(list)
    for i, t in rows:
        groups[low(t)].append(i)
    got = {(r["doc_id"], r["text_sha256"]): r for r in exact_dedup.membership(docs).collect()}
    assert len(got) == len(rows)
    for t, ids in groups.items():
        keep = max((i for i in ids if i is not None), default=None)
        for i in ids:
            r = got[i, hashlib.sha256(t.encode()).hexdigest()]
            assert (r["keep_id"], r["group_size"], r["kept"]) == (keep, len(ids), i == keep)
    assert exact_dedup.survivors(docs).count() == len(groups)


@pytest.mark.parametrize("budget", [1, 2000, 1 << 20])
def test_grace_partitions_until_it_fits(docs, rows, budget):
    out = exact_dedup.survivors(docs, size_col="group_size", budget=budget)
    assert out.count() == len({low(t) for _, t in rows}) and out.agg(F.sum("group_size")).first()[0] == len(rows)


def test_survivors_with_clashing_names_and_repeated_rows(spark):
    df = spark.createDataFrame([(1, "A", 1, 2, 3), (1, "A", 1, 2, 3), (2, "b", 4, 5, 6), (1, "a", 7, 8, 9)], "doc_id long, text string, raw_text int, content_hash int, group_size int")
    out = exact_dedup.survivors(df)
    assert out.columns == df.columns and sorted(r["text"] for r in out.collect()) == ["a", "b"]


def brute_fingerprint(text):
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", low(text)) if w]
    if not words:
        return 0
    grams = [" ".join(words[i : i + 3]) for i in range(len(words) - 2)] or [" ".join(words)]
    hashes = [xxhash.xxh64_intdigest(s.encode(), 42) for s in grams]
    return sum(1 << b for b in range(64) if 2 * sum(h >> b & 1 for h in hashes) > len(hashes))


def classes(n, linked):
    root = list(range(n))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(n):
        for b in range(a):
            if linked(a, b):
                root[find(a)] = find(b)
    return [find(x) for x in range(n)]


def test_simhash(docs, rows):
    known = [(i, t) for i, t in rows if i is not None]
    fps = [brute_fingerprint(t) for _, t in known]
    root = classes(len(fps), lambda a, b: (fps[a] ^ fps[b]).bit_count() <= 3)
    least = defaultdict(lambda: 10**9)
    for (i, _), r in zip(known, root, strict=True):
        least[r] = min(least[r], i)
    got = {r["doc_id"]: (r["fingerprint"], r["component_id"]) for r in simhash.near_duplicates(docs.where("doc_id IS NOT NULL")).collect()}
    assert got == {i: (f"{f:016x}", least[r]) for (i, _), f, r in zip(known, fps, root, strict=True)}


def test_shingle_hash_is_sparks(spark):
    assert spark.sql("SELECT xxhash64('a b c')").first()[0] == np.uint64(xxhash.xxh64_intdigest(b"a b c", 42)).astype(np.int64)


@pytest.mark.parametrize("seed", range(4))
@pytest.mark.parametrize("dense", [8, 1 << 20])
def test_links_keep_all_components(monkeypatch, seed, dense):
    monkeypatch.setattr(simhash, "DENSE_RUN", dense)
    rng = np.random.default_rng(seed)
    centers = rng.integers(0, 1 << 63, 6, dtype=np.uint64)
    fps = set()
    for c in centers:
        now = int(c)
        for _ in range(40):
            now ^= sum(1 << int(b) for b in rng.choice(64, rng.integers(1, 5), replace=False))
            fps.add(now)
    fps = np.array(sorted(fps), dtype=np.uint64)
    keys, own = simhash.variants(fps)
    order = np.argsort(keys, kind="stable")
    found = set()
    for a, b in simhash.link_sorted(iter([(keys[order][i : i + 100], own[order][i : i + 100]) for i in range(0, len(keys), 100)])):
        found |= {(int(x), int(y)) for x, y in zip(a, b, strict=True)}
    assert all((a ^ b).bit_count() <= 3 for a, b in found)
    at = {int(f): i for i, f in enumerate(fps)}
    links = {(at[a], at[b]) for a, b in found} | {(at[b], at[a]) for a, b in found}
    want = classes(len(fps), lambda a, b: (int(fps[a]) ^ int(fps[b])).bit_count() <= 3)
    got = classes(len(fps), lambda a, b: (a, b) in links)
    assert [[x == y for y in want] for x in want] == [[x == y for y in got] for x in got]


def test_components_of_a_long_chain_and_a_hub(spark):
    edges = [(i, i + 1) for i in range(1, 40)] + [(1000, 1000 + i) for i in range(1, 50)] + [(5, 5)]
    got = {r["vertex"]: r["root"] for r in components.connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {**dict.fromkeys(range(1, 41), 1), **dict.fromkeys(range(1000, 1050), 1000)}


def test_tournament_is_first_fit_decreasing():
    rng = random.Random(2)
    for _ in range(30):
        sizes = sorted((rng.randint(1, 100) for _ in range(rng.randint(1, 60))), reverse=True)
        rooms, want = [], []
        for k, s in enumerate(sizes):
            at = next((i for i, r in enumerate(rooms) if r >= s), len(rooms))
            if at == len(rooms):
                rooms.append(100)
                want.append([])
            rooms[at] -= s
            want[at].append(k)
        assert packing.first_fit_decreasing(sizes, 100) == want


def test_packing(docs, rows):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(JSON)
    out = packing.pack(docs, JSON, RANKS, capacity=256, group_docs=20).collect()
    ids = {i: [*tok.encode(t, add_special_tokens=False).ids, 1] for i, t in rows}
    pieces, sequences = defaultdict(list), defaultdict(list)
    for r in out:
        part = np.array(ids[r["doc_id"]][r["start"] : r["start"] + r["length"]], dtype="<u4")
        assert len(part) == r["length"] > 0 and zlib.crc32(part.tobytes()) == r["ids_crc32"] and r["doc_tokens"] == len(ids[r["doc_id"]])
        pieces[r["doc_id"]].append((r["start"], r["length"]))
        sequences[r["sequence_id"]].append((r["offset"], r["length"]))
    for i, own in pieces.items():
        at = 0
        for start, length in sorted(own):
            assert start == at
            at += length
        assert at == len(ids[i])
    assert set(pieces) == set(ids)
    padding = 0
    for own in sequences.values():
        at = 0
        for offset, length in sorted(own):
            assert offset == at
            at += length
        assert at <= 256
        padding += 0 if at & (at - 1) == 0 else 256 - at
    assert padding <= 4 * len(sequences)


def test_fast_ids_are_the_librarys():
    from tokenizers import Tokenizer

    tok, fast = Tokenizer.from_file(JSON), packing._encoder(JSON, RANKS)
    rng = random.Random(5)
    hard = ["".join(rng.choice(" aé\n\t\r\u00a0\u2028\u3000x'sTt12.,!日🙂\x1c\x85") for _ in range(rng.randint(0, 40))) for _ in range(3000)]
    for t in [*hard, "a<|endoftext|>b", "<|endoftext|>", *(x or "" for x in texts())]:
        assert fast(t) == tok.encode(t, add_special_tokens=False).ids, repr(t)


def test_pieces_are_the_librarys(docs, rows):
    import sentencepiece

    sp = sentencepiece.SentencePieceProcessor(model_file=PIECES)
    want = {i: sp.encode(t) for i, t in rows}
    counts = {r["doc_id"]: r for r in token_counts.token_counts(docs, PIECES).collect()}
    coded = piece_codec.encode(docs, PIECES)
    got = {r["doc_id"]: r for r in piece_codec.decode(coded, PIECES, "back").collect()}
    for i, t in rows:
        assert counts[i]["n_tokens"] == len(want[i]) and counts[i]["n_bytes"] == len(t.encode()) and counts[i]["over_limit"] == (len(want[i]) > 4096)
        assert got[i]["ids"] == want[i] and got[i]["back"] == sp.decode(want[i])
    digests = {r["doc_id"]: r for r in piece_codec.coded_digests(docs, PIECES).collect()}
    assert all(digests[i]["ids_crc32"] == zlib.crc32(np.array(want[i], dtype="<u4").tobytes()) and digests[i]["round_trip"] for i, _ in rows)


def test_machine_against_the_library():
    import sentencepiece

    from rowblock.llm.piece_machine import StreamingEncoder, machine

    sp, m = sentencepiece.SentencePieceProcessor(model_file=PIECES), machine(PIECES)
    rng = random.Random(3)
    cases = ["".join(rng.choice(" aehllo  the▁\n\t.<s></s>é漢🙂01 ") for _ in range(rng.randint(0, 80))) for _ in range(800)] + ["a" * 3000, " " * 333, "0" * 777, "<unk>"]
    for t in cases:
        ids = sp.encode(t)
        assert m.encode(t) == ids and m.count(t) == len(ids) and m.count(t, 7) == len(ids) and m.decode(ids) == sp.decode(ids), repr(t)
    e, got, widest = StreamingEncoder(m), [], 0
    text = "▁" + "thequickbrownfox" * 400
    for char in text:
        got += e.feed(char)
        widest = max(widest, len(e.back))
    assert [*got, *e.finish()] == sp.encode(text[1:]) and widest <= 6 * m.v.longest


def brute_quality(t):
    words = [w for w in re.split(r"[\x20\x09-\x0D]+", t) if w]
    lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
    windows = [tuple(words[i : i + 8]) for i in range(len(words) - 7)]
    seen = Counter(windows)
    covered = {k for i, w in enumerate(windows) if seen[w] > 1 for k in range(i, i + 8)}
    return len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), len(covered)


def test_quality_counts(docs, rows, labels):
    got = {r["doc_id"]: r for r in quality_rules.judge(docs, labels).collect()}
    for i, t in rows:
        want = brute_quality(t)
        assert tuple(got[i][c] for c in quality_rules.BASE) == want, t[:60]
        failed = want[0] < 20 or 100 * want[4] > 30 * want[0]
        assert got[i]["base_failed"] == failed and not (failed and got[i]["kept"])


def test_binomial_tail_is_exact(spark):
    from math import comb

    df = spark.createDataFrame([(k, n) for n in (1, 20, 400) for k in range(0, min(n, 12))], "k long, n long")
    for r in df.select("k", "n", quality_rules.binomial_tail(F.col("k"), F.col("n"), 0.05).alias("p")).collect():
        exact = sum(comb(r["n"], i) * 0.05**i * 0.95 ** (r["n"] - i) for i in range(r["k"] + 1))
        assert r["p"] == pytest.approx(1.0 if r["k"] >= r["n"] * 0.05 else exact, rel=1e-9)


def test_cutoffs_are_certified(spark):
    good = [("en", True, 0.0, 0.0, 0.0, 0.0)] * 4000
    bad = [("en", False, 0.4, 0.0, 0.0, 0.0)] * 100
    few = [("fr", True, 0.0, 0.0, 0.0, 0.0)] * 50 + [("fr", False, 0.4, 0.0, 0.0, 0.0)] * 50
    df = spark.createDataFrame(good + bad + few, "stratum string, good boolean, symbol_rate double, upper_rate double, mark_rate double, dup_line_rate double")
    got = {(r["stratum"], r["rule"]): r["cutoff"] for r in quality_rules.choose_cutoffs(df, quality_rules.RiskControl()).collect()}
    assert got["en", "symbol_rate"] == 0.3 and got["en", "upper_rate"] is None and got["fr", "symbol_rate"] is None


def test_filters_keep_columns(docs, labels, empty):
    for df in (docs, empty):
        assert quality_rules.keep_good(df, labels).columns == df.columns
        assert toxicity.keep_ordinary(df, labels).columns == df.columns
        assert line_dedup.without_repeats(df).columns == df.columns
        assert simhash.one_of_each(df).columns == df.columns


def test_line_dedup(spark):
    passage = [f"line {i} of a passage that two documents share" for i in range(12)]
    df = spark.createDataFrame([(1, "\n".join(["own start here", *passage, "own end"]), "a", 1, 1), (2, "\n".join(["another start", "and more", *passage, "the other end"]), "a", 1, 1), (3, None, None, None, None), (4, "", None, None, None)], SCHEMA)
    out = {r["doc_id"]: r["text"] for r in line_dedup.without_repeats(df).collect()}
    assert out[1].split("\n")[1:13] == passage and out[3] is None and out[4] == ""
    left = out[2].split("\n")
    assert len(left) < 10 and left[0] == "another start" and left[-1] == "the other end"


def test_lm_scoring_prefers_the_target(spark):
    rng = random.Random(1)
    good = [" ".join(rng.choice(["clear", "plain", "prose", "reads", "well"]) for _ in range(60)) for _ in range(80)]
    junk = ["".join(rng.choice("#$%&@!0123456789") for _ in range(300)) for _ in range(80)]
    df = spark.createDataFrame([(i, t) for i, t in enumerate(good + junk)] + [(900, None), (901, "")], "doc_id long, text string")
    labels = spark.createDataFrame([(i, int(i < 80)) for i in range(160)], "doc_id long, quality int")
    got = {r["doc_id"]: r for r in lm_scoring.score(df, labels).collect()}
    assert min(got[i]["score"] for i in range(80)) > max(got[i]["score"] for i in range(80, 160))
    assert got[900]["score"] == got[901]["score"] == 0 and got[3]["n_tokens"] == len(good[3])


def test_lm_probabilities_against_a_slow_model():
    data = b"abracadabra abra"
    counts = lm_scoring.Counts()
    counts.add(data)
    counts.flush()
    model = lm_scoring.Model(counts.total)
    padded = b"\0\0\0" + data
    grams = [Counter(padded[i + 3 - k : i + 4] for i in range(len(data))) for k in range(4)]
    loss, n = 0.0, len(data)
    for i in range(n):
        p = (grams[0][padded[i + 3 : i + 4]] + lm_scoring.STRENGTH[0]) / (n + 256 * lm_scoring.STRENGTH[0])
        for k in (1, 2, 3):
            gram = padded[i + 3 - k : i + 4]
            p = (grams[k][gram] + lm_scoring.STRENGTH[k] * p) / (grams[k - 1][gram[:-1]] + lm_scoring.STRENGTH[k])
        loss -= np.log(p)
    assert model.loss(*lm_scoring.places(data)) == pytest.approx(loss, rel=1e-4)


def test_toxicity_on_held_out_documents(spark):
    d = spark.read.parquet("/root/testdata/sf0.1/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.1/labels.parquet")
    got = toxicity.judge(d, labels).join(labels, "doc_id").where("held_out").collect()
    tp = sum(r["predicted"] and r["toxic"] for r in got)
    assert tp / max(1, sum(r["predicted"] for r in got)) > 0.9 and tp / sum(r["toxic"] for r in got) > 0.6
    assert all(0 <= r["score"] <= 1 for r in got)


def test_url_filters(spark):
    urls = ["http://a.example.org/es/x", "https://example.org/en/12#y", "HTTP://A.ORG?x", "x://B.com/fr/1", "x://com/de/", "x://notcom/de/", None, "nothing", "p://h:80/a?b://c", "q://example.org/EN/1", "r://sub.example.org/en/1/de"]
    pages = spark.createDataFrame([(i, u, None) for i, u in enumerate(urls)], "page_id long, url string, html string")
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    got = {r["page_id"]: r for r in url_filters.judge(pages, labels).collect()}
    assert [got[i]["rule"] for i in range(11)] == ["example.org/es/", "example.org/en/1", None, "com/fr/", "com/de/", None, None, None, None, "org/", "example.org/en/1"]
    assert [(got[i]["host"], got[i]["path"]) for i in (2, 6, 7, 8)] == [("a.org", ""), ("", ""), ("", ""), ("h:80", "/a")]
    assert [got[i]["verdict"] for i in (0, 3, 4, 9)] == ["block", "allow", "block", "allow"]


def test_reputation_blocks_bad_hosts_and_shrinks_rare_ones(spark):
    hosts = spark.createDataFrame([("bad.a.net", 500, 490), ("good.a.net", 500, 5), ("rare.a.net", 1, 1), ("x.b.net", 400, 8), ("new.c.net", 0, 0)], "host string, n long, bad long")
    got = {r["host"]: r["by_host"] for r in url_filters.reputation(hosts).collect()}
    assert got == {"bad.a.net": "block", "good.a.net": "allow", "rare.a.net": "allow", "x.b.net": "allow", "new.c.net": "allow"}


def test_empty_tables(spark, empty):
    labels = spark.createDataFrame([], "doc_id long, quality int, toxic int")
    frames = [exact_dedup.membership(empty), simhash.near_duplicates(empty), packing.pack(empty, JSON, RANKS), token_counts.token_counts(empty, PIECES), piece_codec.coded_digests(empty, PIECES), quality_rules.judge(empty, labels), toxicity.judge(empty, labels), lm_scoring.score(empty, labels), line_dedup.digests(empty)]
    assert [f.count() for f in frames] == [0] * len(frames)
