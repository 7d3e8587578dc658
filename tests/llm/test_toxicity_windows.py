"""Windows that gain nothing are not compressed, and the gains are those of two compressions each."""

import numpy as np

from rowblock.llm import toxicity
from tests.llm.test_toxicity import sample


def test_most_windows_are_not_compressed_and_no_gain_changes():
    model = toxicity.fit([(t.encode(), y) for t, y in sample()])
    windows = toxicity.Windows(model)
    texts = [t.encode() for t, _ in sample(21, 60)] + [b"", b"one", b"numskull", "é ü 日本 12".encode(), b"x" * 5000, b"blockheads numskul lock head " * 2000]
    ordinary, toxic = windows.compress
    want = [np.array([len(ordinary(w)) - len(toxic(w)) for w in windows.windows(t)], dtype=np.int64) for t in texts]
    calls = []
    windows.compress = [lambda w, f=f: calls.append(1) or f(w) for f in windows.compress]
    got = list(windows.all_gains(texts))
    assert len(got) == len(want) and all(np.array_equal(a, b) for a, b in zip(got, want, strict=True))
    assert [g.tolist() for g in map(windows.gains, texts[:3])] == [w.tolist() for w in want[:3]]
    assert any(w.any() for w in want)
    calls.clear()
    calm = [t.encode() for t, y in sample(33, 60) if not y]
    n = sum(map(len, windows.all_gains(calm)))
    assert len(calls) < n  # two each before
