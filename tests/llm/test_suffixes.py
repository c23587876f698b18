import random

import numpy as np
import pytest

from linkrank.llm import suffixes


def lcp(a, b):
    k = 0
    while k < min(len(a), len(b)) and a[k] == b[k]:
        k += 1
    return k


@pytest.mark.parametrize("letters,wide", [(1, 2048), (2, 2048), (2, 3), (4, 2048), (26, 5)])
def test_equals_sorting(monkeypatch, letters, wide):
    monkeypatch.setattr(suffixes, "_WIDE", wide)
    rng = random.Random(letters)
    for _ in range(150):
        s = [rng.randrange(letters) for _ in range(rng.randrange(60))]
        if rng.random() < 0.3:
            s = s[: len(s) // 4] * 4
        order = suffixes.suffix_array(np.array(s, np.int64), letters).tolist()
        want = sorted(range(len(s)), key=lambda k: s[k:])
        assert order == want, s
        shared = suffixes.common_prefixes(np.array(s, np.int64), np.array(order, np.int64))
        assert all(shared[order[k]] == lcp(s[order[k]:], s[order[k - 1]:]) for k in range(1, len(s)))


def test_long_runs():
    s = np.concatenate([np.full(3000, 5), np.arange(9), np.full(3000, 5), np.full(2000, 7)])
    order = suffixes.suffix_array(s, 9)
    t = s.tolist()
    assert sorted(order.tolist()) == list(range(len(t)))
    assert all(t[order[k - 1] :] < t[order[k] :] for k in range(1, len(t), 37))
