"""Compression distance against a plain version, and the operator's defined results."""

import math
import random

import numpy as np
import pytest
import zstandard as zstd

from rowblock.llm import toxicity


def sample(seed=3, docs=160):
    """Texts of invented words; those marked 1 have one of two rude words in every twelfth place or so."""
    rng = random.Random(seed)
    parts = ["an", "ther", "ing", "st", "re", "ou", "wh", "ed", "ti", "on", "ea", "sh"]
    word = lambda: "".join(rng.choice(parts) for _ in range(rng.randint(1, 3)))
    out = []
    for k in range(docs):
        words = [word() for _ in range(rng.randint(60, 200))]
        if k % 4 == 0:
            for at in range(rng.randint(0, 9), len(words), 12):
                words[at] = rng.choice(["blockhead", "Numskull"])
        out.append((" ".join(words), int(k % 4 == 0)))
    return out


@pytest.fixture(scope="module")
def model():
    return toxicity.fit([(t.encode(), y) for t, y in sample()])


def slow_score(model, text):
    """The same score from one compressor call a window and plain sums."""
    words = "".join(c if c.isalpha() or ord(c) > 127 else " " for c in text.lower()).split()
    gains = []
    for start in range(0, max(1, len(words) - 3), 3) if words else []:
        window = (" " + " ".join(words[start : start + 6]) + " ").encode() + model.carrier
        sizes = []
        for content in (model.ordinary, model.toxic):
            params = zstd.ZstdCompressionParameters(window_log=18, hash_log=17, chain_log=18, search_log=6, min_match=4, target_length=64, strategy=zstd.STRATEGY_BTLAZY2, write_content_size=False, write_dict_id=False)
            given = zstd.ZstdCompressionDict(content, dict_type=zstd.DICT_TYPE_RAWCONTENT)
            given.precompute_compress(compression_params=params)
            sizes.append(len(zstd.ZstdCompressor(dict_data=given, compression_params=params).compress(window)))
        gains.append(sizes[0] - sizes[1])
    root = math.sqrt(len(gains)) or 1
    x = [1, max(gains, default=0), sum(sorted(gains)[-4:])] + [sum(g >= t for g in gains) / root for t in model.thresholds] + [sum(min(8, max(0, g)) for g in gains) / root]
    return 1 / (1 + math.exp(-max(-30, min(30, float(np.dot(x, model.weights))))))


def test_scores_against_the_slow_version(spark, model):
    texts = [t for t, _ in sample(9, 12)] + ["", None, "one", "a" * 30, "Numskull! numskull#blockhead", "é ü 日本 12"]
    df = spark.createDataFrame([(i, t, "x") for i, t in enumerate(texts)], "doc_id long, text string, score string")
    got = {r["doc_id"]: r["score_"] for r in toxicity.score(df, model, "score_").collect()}
    assert got == pytest.approx({i: slow_score(model, t or "") for i, t in enumerate(texts)})
    assert got[12] == got[13] and all(0 <= s <= 1 for s in got.values())


def test_new_texts_of_both_kinds_are_told_apart(model):
    windows = toxicity.Windows(model)
    new = sample(77, 80)
    assert all((windows.score(t.encode()) >= 0.7) == bool(y) for t, y in new)


def test_words_of_the_sample_alone_do_not_decide(model):
    """Ordinary words that only toxic training texts have say nothing; the stretches have to stand in many contexts."""
    assert model.toxic != model.ordinary and b"blockhead" in model.toxic and b"blockhead" not in model.ordinary


def test_long_texts_have_all_their_windows(model):
    windows = toxicity.Windows(model)
    calm = " ".join(t for t, y in sample(5, 200) if not y)
    assert len(windows.gains((calm * 3).encode())) == -(-(len((calm * 3).split()) - 3) // 3)
    assert len(windows.gains(b"x" * 100_000)) > 500


def test_judge_keeps_the_held_out_fold_out_and_survives_odd_labels(spark):
    rows = sample(2, 200)
    df = spark.createDataFrame([*((i, t, 0, "s") for i, (t, _) in enumerate(rows)), (500, None, 1, None), (500, None, 1, None), (None, "no id", 1, None)], "doc_id long, text string, toxic int, predicted string")
    labels = spark.createDataFrame([*((i, y) for i, (_, y) in enumerate(rows)), (1, None), (None, 1), (2, 7)], "doc_id long, toxic int")
    flipped = labels.selectExpr("doc_id", "CASE WHEN crc32(CAST(doc_id AS STRING)) % 3 = 1 THEN 1 - toxic ELSE toxic END AS toxic")
    one, two = (sorted(toxicity.judge(df, x).collect(), key=repr) for x in (labels, flipped))
    assert one == two and len(one) == 203
    got = {r["doc_id"]: r["predicted"] for r in one}
    assert sum(got[i] == y for i, (_, y) in enumerate(rows)) >= 195
    assert toxicity.keep_ordinary(df, labels).columns == df.columns


def test_the_sample_is_bounded_by_bytes_and_has_long_texts(spark):
    df = spark.createDataFrame([(i, "word " * (2000 if i < 3 else 10)) for i in range(40)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(40)], "doc_id long, toxic int")
    seen = []
    fit, toxicity.fit = toxicity.fit, lambda rows, *a: seen.append(rows) or fit(rows, *a)
    try:
        toxicity.learn(df, labels, toxicity.Training(toxic_bytes=10_200, ordinary_bytes=500))
    finally:
        toxicity.fit = fit
    sizes = [sum(len(t) for t, y in seen[0] if y == k) for k in (0, 1)]
    assert sizes[0] <= 500 and sizes[1] <= 10_200 and seen[0]


def test_thresholds_are_rates_of_ordinary_windows():
    gains = np.r_[np.zeros(996, int), 3, 5, 7, 9]
    assert toxicity.thresholds(gains, (1 / 250, 2 / 1000, 1 / 1000)) == (1, 6, 8)
    assert toxicity.thresholds(np.empty(0, int), (0.1,)) == (1,)
