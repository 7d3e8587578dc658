"""Windows that stand several times in what is scored together are compressed once."""

from rowblock.llm import toxicity
from tests.llm.test_toxicity import sample


def test_equal_windows_are_compressed_once_and_gain_the_same():
    model = toxicity.fit([(t.encode(), y) for t, y in sample()])
    windows = toxicity.Windows(model)
    texts = [t.encode() for t, y in sample(21, 30) if y]
    alone = [windows.gains(t).tolist() for t in texts]
    calls = []
    windows.compress = [lambda w, f=f: calls.append(w) or f(w) for f in windows.compress]
    got = [g.tolist() for g in windows.all_gains(texts * 3)]
    assert got == alone * 3 and any(map(any, alone))
    assert len(calls) == 2 * len(set(calls))
