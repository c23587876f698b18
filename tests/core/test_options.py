"""Every method with every option: the right ranks, or a refusal."""

import random
from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from linkrank.config import RankConfig
from linkrank.functions import measures
from linkrank.graph import csr_blocks, assign_blocks
from linkrank.operators.asynchronous import async_edge, async_pull
from linkrank.operators.fixpoint import surfer_walks, weak_components
from linkrank.operators.helped import sync_helped
from linkrank.operators.kernel import Block, sweep
from linkrank.operators.sequential import sequential, solve_exact
from linkrank.operators.synchronous import sync_edge, sync_pull
from tests.core.graphs import close, graph, random_edges, ranks

CFG = RankConfig(tol=1e-7, blocks=2, partitions=2, check_every=4, max_iter=200)
METHODS = {
    "sequential": sequential, "sync_pull": sync_pull, "sync_edge": sync_edge, "sweep": lambda g, c: async_pull(g, c, "sweep"), "adversarial": lambda g, c: async_pull(g, c, "adversarial"), "edge_sweep": lambda g, c: async_edge(g, c, "sweep"),
    "edge_zero_sweep": lambda g, c: async_edge(g, c, "sweep", seed="zero"), "rounds": lambda g, c: async_pull(g, replace(c, tol=1e-4)), "edge_rounds": lambda g, c: async_edge(g, replace(c, tol=1e-3)), "free": lambda g, c: async_pull(g, replace(c, tol=1e-3), "free"),
    "helped": lambda g, c: sync_helped(g, replace(c, tol=1e-3), workers=2),
}
FAST = ["sequential", "sync_pull", "sweep", "adversarial", "edge_sweep", "edge_zero_sweep"]
OPTIONS = {
    "spread": dict(dangling="redistribute"), "safe": dict(freeze=True, freeze_guard="safe"), "freeze": dict(freeze=True), "twins": dict(twins=True), "twins_freeze": dict(twins=True, freeze=True),
    "ordered": dict(sum_mode="ordered"), "decimal": dict(sum_mode="decimal"), "inner": dict(inner_sweeps=2), "stale": dict(staleness=2, schedule_seed=1),
}
REFUSED = {
    "spread": {"free"}, "safe": {"sweep", "adversarial", "edge_sweep", "edge_zero_sweep", "rounds", "edge_rounds", "free", "helped"}, "decimal": set(METHODS) - {"sync_pull", "sync_edge"},
    "inner": {"sequential", "sync_pull", "sync_edge", "helped"}, "stale": set(METHODS) - {"adversarial"},
}


@pytest.fixture(scope="module")
def leaking(spark):
    """A graph with vertices without out-links, and with twins."""
    edges = random_edges(random.Random(8), 24, 90)
    return graph(spark, [e for e in edges if e[0] % 6] + [(1, 40), (2, 40), (1, 41), (2, 41)])


@pytest.fixture(scope="module")
def exact(leaking):
    return {how: ranks(solve_exact(leaking, RankConfig(dangling=how))) for how in ("leak", "redistribute")}


@pytest.mark.parametrize("option", OPTIONS)
def test_ranks_or_refusal(leaking, exact, option):
    cfg = replace(CFG, **OPTIONS[option])
    refused = REFUSED.get(option, set())
    for name in METHODS:
        if name in refused:
            with pytest.raises(ValueError):
                METHODS[name](leaking, cfg)
        elif name in FAST or (option, name) in {("spread", "helped"), ("spread", "rounds"), ("twins", "helped"), ("freeze", "helped"), ("inner", "rounds")}:
            found = METHODS[name](leaking, cfg)
            near = 26 * 5.67 * 3 * (1e-3 if name in ("helped", "edge_rounds", "free") else 1e-4 if name == "rounds" else 1e-7)
            assert found.converged and close(ranks(found), exact[cfg.dangling], near), name
    assert abs(sum(exact["redistribute"].values()) - 1) < 1e-9


def test_twins_refuse_what_breaks_them(leaking, spark):
    for run in (sync_pull, sequential, lambda g, c: async_pull(g, c, "sweep"), lambda g, c: sync_helped(g, c, 2)):
        for extra in (dict(dangling="redistribute"), dict(init=spark.createDataFrame([(1, 0.5)], "id long, rank double"))):
            with pytest.raises(ValueError):
                run(leaking, replace(CFG, twins=True, **extra))


def test_sweeps_by_levels_equal_sweeps_by_vertices(monkeypatch):
    from linkrank.operators import kernel

    rng = np.random.default_rng(3)
    for n, m in ((50, 60), (400, 900), (300, 6000), (1, 0)):
        src, dst = rng.integers(0, n, m), rng.integers(0, n, m)
        found = []
        for deep in (0, 10**9):
            monkeypatch.setattr(kernel, "DEEP", deep)
            block = Block.of_edges(np.arange(n), src, dst, np.full(m, 0.01))
            rank, course = np.linspace(0, 1, n), []
            for active in (None, np.arange(n) % 3 > 0, None):
                course.append(sweep(block, rank, 0.1, 0.85, active).copy())
            found.append((rank, course))
        assert np.allclose(found[0][0], found[1][0], atol=1e-14) and np.allclose(found[0][1], found[1][1], atol=1e-14)


def test_components_of_a_long_path(spark):
    path = [(k, k + 1) for k in range(2000)] + [(5000, 5001), (5001, 5000)]
    random.Random(1).shuffle(path)
    names = random.Random(2).sample(range(10**6), 5002)
    got = ranks_of(weak_components(graph(spark, [(names[a], names[b]) for a, b in path])))
    least = min(names[:2001])
    assert all(got[names[k]] == least for k in range(2001)) and got[names[5000]] == got[names[5001]] == min(names[5000:5002])


def ranks_of(frame):
    return {r.id: r.value for r in frame.collect()}


def test_surfers_of_a_hub(spark):
    g = graph(spark, [(0, k) for k in range(1, 200)] + [(k, 0) for k in range(1, 200)])
    got, want = ranks(surfer_walks(g, 20, 30)), ranks(sequential(g, CFG))
    assert abs(got[0] - want[0]) < 0.05 and abs(sum(got.values()) - sum(want.values())) < 0.2


def test_block_arrays(spark):
    g = graph(spark, random_edges(random.Random(5), 30, 120))
    rows = csr_blocks(g, assign_blocks(g, 3, "range")).collect()
    assert sorted(i for r in rows for i in r.ids) == sorted(r.id for r in g.vertices.collect())
    assert all(r.in_ptr[0] == 0 and r.in_ptr[-1] == len(r.in_src) == len(r.in_coef) and len(r.in_ptr) == len(r.ids) + 1 for r in rows)


def test_progress_memory_and_shuffles(spark):
    assert [measures.progress(m) for m in ("async_pull", "async_pull:rounds", "async_pull:sweep", "async_edge:free", "sync_helped")] == ["blocking", "blocking", "blocking", "lock-free", "wait-free"]
    assert measures.rank_bytes("sync_pull", 10) == 160 and measures.rank_bytes("async_pull:free", 10) == 80
    g = graph(spark, random_edges(random.Random(5), 30, 120))
    few, _ = measures.shuffle_bytes(spark, lambda: sync_pull(g, replace(CFG, max_iter=1, tol=0.0)))
    assert few.iterations == 1 and measures.shuffle_bytes(spark, lambda: sync_pull(g, replace(CFG, max_iter=4, tol=0.0, check_every=1)))[1] > _ > 0


def test_hubs_lie_in_all_partitions(spark):
    from linkrank.operators.synchronous import _Loop
    from linkrank.plans.lineage import exchanges, loop_settings
    from linkrank.sources.rmat import rmat_edges

    from linkrank.graph import Graph

    skewed = Graph.from_edges(rmat_edges(spark, 3000).unionByName(spark.range(1, 900).selectExpr("0L AS src", "id AS dst")))
    want = ranks(sequential(skewed, RankConfig(max_iter=4, tol=0.0)))
    for run in (sync_pull, sync_edge):
        for extra in (dict(check_every=4), dict(freeze=True), dict(freeze=True, freeze_guard="safe")):
            cfg = RankConfig(max_iter=4, tol=0.0, partitions=4, hub_degree=100, **extra)
            assert close(ranks(run(skewed, cfg)), want, 1e-12)
    with loop_settings(spark, 4):
        loop = _Loop(skewed, RankConfig(partitions=4, hub_degree=100), "sync_pull")
        sizes = [r["count"] for r in loop.edges.unionByName(loop.hub_edges).groupBy(F.spark_partition_id()).count().collect()]
        assert loop.hub_edges.count() > 800 and max(sizes) < 900 and exchanges(loop.step(loop.start)) == 1
