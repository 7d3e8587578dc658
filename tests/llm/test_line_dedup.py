"""Line dedup against a plain version, on shared and null ids, clashing names and very long texts."""

import random

import pytest

from rowblock.llm import line_dedup

SCHEMA = "doc_id long, text string"


def brute(rows):
    """Every line in a later occurrence of two neighbouring lines goes; rows equal in id and text are one."""
    distinct = sorted({(i, t or "") for i, t in rows}, key=lambda r: (r[0] is not None, r[0] or 0))
    first = {}
    for k, (_, t) in enumerate(distinct):
        lines = t.split("\n")
        for at, pair in enumerate(zip(lines, lines[1:])):
            first.setdefault(pair, (k, at))
    out = {}
    for k, (i, t) in enumerate(distinct):
        lines = t.split("\n")
        gone = {x for at, pair in enumerate(zip(lines, lines[1:])) if any(pair) and first[pair] != (k, at) for x in (at, at + 1)}
        out[i, t] = "\n".join(x for n, x in enumerate(lines) if n not in gone)
    return out


def planted(seed):
    rng = random.Random(seed)
    line = lambda: " ".join(str(rng.randint(0, 10**6)) for _ in range(rng.randint(1, 30)))
    passages = [[line() for _ in range(n)] for n in (2, 2, 2, 3, 3, 4, 6, 12)]
    rows = []
    for i in range(60):
        lines = [line() for _ in range(rng.randint(0, 4))]
        for p in rng.sample(passages, rng.randint(0, 3)):
            lines += p + [line() for _ in range(rng.randint(0, 3))]
        rows.append((i, "\n".join(lines)))
    return rows, passages


@pytest.mark.parametrize("seed", range(3))
@pytest.mark.parametrize("bits", [1 << 28, 0])
def test_passages_vanish_whole_but_for_one(spark, seed, bits):
    rows, passages = planted(seed)
    df = spark.createDataFrame(rows, SCHEMA).repartition(4)
    got = {r["doc_id"]: r["text"] for r in line_dedup.without_repeats(df, line_dedup.Chunking(most_bits=bits)).collect()}
    want = brute(rows)
    assert got == {i: want[i, t] for i, t in rows}
    for p in passages:
        assert sum("\n".join(p) in t for t in got.values()) <= 1
        assert all(any(x in t.split("\n") for t in got.values()) for x in p) or not any("\n".join(p) in t for _, t in rows)


def test_shared_and_null_ids_are_rows_of_their_own(spark):
    p, v = "\n".join(f"passage line {k}" for k in range(9)), "\n".join(f"only here {k}" for k in range(9))
    rows = [(1, p), (5, p), (5, v), (None, p + "\nx"), (None, v + "\ny\nz"), (None, None), (7, "")]
    got = sorted(((r["doc_id"], r["text"]) for r in line_dedup.without_repeats(spark.createDataFrame(rows, SCHEMA)).collect()), key=repr)
    want = brute(rows)
    assert got == sorted(((i, t if t is None else want[i, t]) for i, t in rows), key=repr)
    for x in (p, v):
        assert all(any(line in (t or "").split("\n") for _, t in got) for line in x.split("\n"))


def test_equal_rows_are_one_document(spark):
    rows = [(3, "a\nb\nc"), (3, "a\nb\nc"), (4, "a\nb\nd")]
    assert sorted(r["text"] for r in line_dedup.without_repeats(spark.createDataFrame(rows, SCHEMA)).collect()) == ["a\nb\nc", "a\nb\nc", "d"]


def test_short_and_empty_lines(spark):
    rows = [(1, "}\n}\nend"), (2, "x\n}\n}"), (3, "\n\n\n"), (4, "u\n\n\nv"), (5, " "), (6, " \n\t\n")]
    got = {r["doc_id"]: r["text"] for r in line_dedup.without_repeats(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got == {1: "}\n}\nend", 2: "x", 3: "\n\n\n", 4: "u\n\n\nv", 5: " ", 6: " \n\t\n"}


def test_clashing_names(spark):
    names = ["row", "text_hash", "gone", "gone_doc", "gone_chunks", "lines", "given", "spans", "n_gone", "a.b"]
    df = spark.createDataFrame([(1, "a\nb", *names), (2, "a\nb\nc", *names)], SCHEMA + "".join(f", `{n}` string" for n in names))
    out = line_dedup.without_repeats(df)
    assert out.columns == df.columns and {tuple(r) for r in out.collect()} == {(1, "a\nb", *names), (2, "c", *names)}


def test_very_long_text(spark):
    rows = [(1, "\n".join(f"l{k % 4000}" for k in range(40_000))), (2, "w " * 200_000)]
    got = {r["doc_id"]: r["text"] for r in line_dedup.without_repeats(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert got[2] == rows[1][1] and got[1].split("\n") == brute(rows)[rows[0]].split("\n")


def test_boundaries_depend_on_the_order_of_lines(spark):
    df = spark.createDataFrame([(k, f"first {k}\nsecond {k}\nend") for k in range(200)] + [(k, f"second {k - 1000}\nfirst {k - 1000}\nend") for k in range(1000, 1200)], SCHEMA)
    spans = {r["doc"]: len(r["spans"]) for r in line_dedup.with_spans(line_dedup.with_lines(df, "doc_id", "text"), line_dedup.Chunking()).collect()}
    assert any(spans[k] != spans[k + 1000] for k in range(200)) and 30 < sum(spans[k] == 2 for k in range(200)) < 110
