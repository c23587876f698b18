from dataclasses import replace

import numpy as np
import pytest

from linkrank.config import RankConfig
from linkrank.functions.measures import l1_norm
from linkrank.graph import Graph
from linkrank.operators.asynchronous import async_pull
from linkrank.operators.kernel import Block, sweep
from linkrank.operators.sequential import sequential
from linkrank.operators.synchronous import sync_pull


def edges(seed, n=400, m=3000):
    rng = np.random.default_rng(seed)
    return rng.integers(0, n, m), rng.integers(0, n, m)


def test_any_number_of_edges_in_many_batches(spark):
    assert RankConfig().max_edges is None  # was 5,000,000, beyond which queries ended with an error
    src, dst = edges(3)
    graph = Graph.from_edges(spark.createDataFrame([(int(a), int(b)) for a, b in zip(src, dst)], "src long, dst long"))
    cfg = RankConfig(tol=1e-13, blocks=3, check_every=5)
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "97")
    try:
        runs = [sequential(graph, cfg), async_pull(graph, cfg, "sweep")]
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)
    assert all(r.converged for r in runs)
    exact = sync_pull(graph, cfg).ranks
    assert all(l1_norm(r.ranks, exact) < 1e-10 for r in runs)
    with pytest.raises(ValueError):
        sequential(graph, replace(cfg, max_edges=100))


def test_edges_laid_by_level_give_the_same_sweep():
    src, dst = edges(4)
    made = lambda: Block.of_edges(np.arange(400), src, dst, np.random.default_rng(1).random(len(src)))
    plain, laid = made(), made()
    laid.lay_by_level()
    assert laid._laid is not None
    a, b = np.full(400, 1 / 400), np.full(400, 1 / 400)
    for _ in range(3):
        assert np.allclose(sweep(plain, a, 1e-3, 0.85), sweep(laid, b, 1e-3, 0.85), rtol=1e-12, atol=0) and np.allclose(a, b, rtol=1e-12, atol=0)
