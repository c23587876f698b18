import random

import numpy as np
import pytest

from linkrank.llm import components as cc


def brute(links):
    parent = {}

    def find(x):
        parent.setdefault(x, x)
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = sorted((find(a), find(b)))
        parent[b] = a
    return {x: find(x) for x in parent}


SHAPES = {
    "random": lambda rng: [(rng.randrange(300), rng.randrange(300)) for _ in range(200)],
    "path": lambda rng: [(k, k + 1) for k in rng.sample(range(400), 400)],
    "star": lambda rng: [(500, k) for k in range(300)] + [(k, 501) for k in range(300, 400)],
    "two": lambda rng: [(1, 2), (2, 1), (2, 3), (7, 7), (-5, 9)],
}


@pytest.mark.parametrize("few", [0, 1 << 19])
@pytest.mark.parametrize("shape", SHAPES)
def test_components(spark, monkeypatch, shape, few):
    monkeypatch.setattr(cc, "FEW_LINKS", few)
    links = SHAPES[shape](random.Random(1))
    got = [tuple(r) for r in cc.components(spark.createDataFrame(links, "a long, b long").repartition(5)).collect()]
    want = {k: v for k, v in brute(links).items() if sum(w == v for w in brute(links).values()) > 1}
    assert len(got) == len(dict(got)) and dict(got) == want


def test_no_links(spark, monkeypatch):
    assert cc.components(spark.createDataFrame([], "a long, b long")).count() == 0
    monkeypatch.setattr(cc, "FEW_LINKS", -1)
    assert cc.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_runs_are_bounded(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(cc, "BATCH_LINKS", 8)
    rng = random.Random(0)
    links = [(rng.randrange(50), rng.randrange(50)) for _ in range(200)]
    batches = [pa.record_batch([np.array([a for a, _ in links[k : k + 3]]), np.array([b for _, b in links[k : k + 3]])], names=["a", "b"]) for k in range(0, 200, 3)]
    out = [(a, b) for batch in cc._contract(iter(batches)) for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist())]
    full = {k: v for k, v in brute(links).items() if k != v}
    assert {k: v for k, v in brute(out).items() if k != v} == full
