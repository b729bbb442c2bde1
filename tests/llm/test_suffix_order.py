"""The suffix sort of op1."""
import numpy as np

from signgraph.llm import suffix


def test_ranks_are_sorted_as_one_number(monkeypatch):
    r = np.random.default_rng(2)
    part = r.integers(97, 99, 60).astype(np.uint8)
    text = np.concatenate([part, [255], part[5:], [255], r.integers(97, 99, 400), [255], part, part, [255]]).astype(np.uint8)
    n, real = [], np.argsort
    monkeypatch.setattr(np, "argsort", lambda *a, **k: n.append(1) or real(*a, **k))
    sa, _ = suffix.suffix_order(text, 400)
    raw = text.tobytes()
    heads = [raw[i : i + 400] for i in sa.tolist() if i + 400 <= len(raw)]
    assert heads == sorted(heads) and sorted(sa.tolist()) == list(range(len(text)))
    assert len(n) == 1  # of the first eight bytes only
