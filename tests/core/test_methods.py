import random
from dataclasses import replace

import pytest

from linkrank.config import RankConfig
from linkrank.operators.asynchronous import async_edge, async_pull
from linkrank.operators.faults import FaultPlan
from linkrank.operators.helped import sync_helped
from linkrank.operators.sequential import sequential, solve_exact
from linkrank.operators.synchronous import sync_edge, sync_pull
from tests.core.graphs import RANKS, close, graph, random_edges, ranks

CFG = RankConfig(tol=1e-10, blocks=2, partitions=2, check_every=4)


@pytest.mark.parametrize("name", RANKS)
def test_closed_forms(spark, name):
    g = graph(spark, name)
    assert close(ranks(solve_exact(g)), RANKS[name])
    assert close(ranks(sequential(g, CFG)), RANKS[name])
    assert close(ranks(sync_pull(g, replace(CFG, check_every=8))), RANKS[name])
    assert close(ranks(async_pull(g, CFG, "sweep")), RANKS[name])


@pytest.fixture(scope="module")
def random_graph(spark):
    return graph(spark, random_edges(random.Random(4), 60, 400))


@pytest.fixture(scope="module")
def exact(random_graph):
    return ranks(solve_exact(random_graph))


METHODS = {
    "sync_pull": lambda g: sync_pull(g, CFG),
    "sync_edge": lambda g: sync_edge(g, CFG),
    "sync_edge_stored": lambda g: sync_edge(g, replace(CFG, fused=False, tol=1e-4)),
    "ordered": lambda g: sync_pull(g, replace(CFG, sum_mode="ordered")),
    "decimal": lambda g: sync_pull(g, replace(CFG, sum_mode="decimal")),
    "freeze_paper": lambda g: sync_pull(g, replace(CFG, freeze=True)),
    "freeze_safe": lambda g: sync_pull(g, replace(CFG, freeze=True, freeze_guard="safe")),
    "sync_edge_freeze": lambda g: sync_edge(g, replace(CFG, freeze=True)),
    "twins": lambda g: sync_pull(g, replace(CFG, twins=True)),
    "sync_edge_twins": lambda g: sync_edge(g, replace(CFG, twins=True)),
    "async_sweep": lambda g: async_pull(g, CFG, "sweep"),
    "async_inner": lambda g: async_pull(g, replace(CFG, inner_sweeps=3), "sweep"),
    "async_edge_sweep": lambda g: async_edge(g, CFG, "sweep"),
    "async_adversarial": lambda g: async_pull(g, replace(CFG, staleness=3, schedule_seed=7, blocks=5), "adversarial"),
    "async_twins_freeze": lambda g: async_pull(g, replace(CFG, twins=True, freeze=True), "sweep"),
}


@pytest.mark.parametrize("name", METHODS)
def test_methods_agree(random_graph, exact, name):
    found = METHODS[name](random_graph)
    within = 60 * 5.67 * (1e-4 if name == "sync_edge_stored" else 1e-10) * 3
    assert found.converged and close(ranks(found), exact, within), (found.stop_reason, found.iterations)


def test_rounds_and_free(random_graph, exact):
    cfg = replace(CFG, tol=1e-5)
    rounds = async_pull(random_graph, cfg)
    assert rounds.converged and close(ranks(rounds), exact, 60 * 5.67e-5) and set(rounds.block_iterations) == {0, 1}
    edge = async_edge(random_graph, replace(cfg, tol=1e-3))
    assert edge.converged and close(ranks(edge), exact, 60 * 5.67e-3)
    free = async_pull(random_graph, replace(cfg, tol=1e-3), "free")
    assert free.converged and close(ranks(free), exact, 60 * 5.67e-3 * 2)
    seen = [(h["iteration"], h["block"]) for h in free.history]
    assert len(seen) == len(set(seen))


def test_edge_form_says_when_it_does_not_converge(random_graph):
    found = async_edge(random_graph, replace(CFG, max_iter=2, tol=1e-16), "sweep")
    assert not found.converged and found.stop_reason == "not_converged"


def test_freezing_too_early(spark):
    g = graph(spark, "chain3")
    start = spark.createDataFrame([(0, 1 / 3), (1, 0.3333333), (2, 1 / 3)], "id long, rank double")
    cfg = RankConfig(tol=1e-2, freeze=True, freeze_factor=1e-5, init=start, partitions=2)
    early = sync_pull(g, cfg)
    assert sum(abs(a - b) for a, b in zip(sorted(ranks(early).values()), RANKS["chain3"])) > 0.4
    safe = sync_pull(g, replace(cfg, freeze_guard="safe"))
    assert close(ranks(safe), RANKS["chain3"], 1e-9)


def test_options(spark):
    g = graph(spark, "star_in5")
    spread = ranks(sync_pull(g, RankConfig(tol=1e-9, dangling="redistribute", partitions=2)))
    assert abs(sum(spread.values()) - 1) < 1e-6
    multi = [(0, 1), (0, 1), (0, 2), (1, 0), (2, 0)]
    assert close(ranks(sequential(graph(spark, multi, multiplicity=True), CFG)), [0.48648649, 0.32567568, 0.18783784])
    assert close(ranks(sequential(graph(spark, multi), CFG)), [0.48648649, 0.25675676, 0.25675676])
    loop = graph(spark, [(0, 0), (0, 1)], self_loops=True)
    r0 = 0.075 / (1 - 0.425)
    assert close(ranks(sequential(loop, CFG)), [r0, 0.075 + 0.425 * r0])
    alone = graph(spark, [(0, 1)], vertices=spark.createDataFrame([(2,)], "id long"))
    assert close(ranks(sequential(alone, CFG)), [0.05, 0.0925, 0.05])
    empty = graph(spark, "chain3")
    empty = graph(spark, [(5, 5)])
    assert sync_pull(empty, CFG).iterations == 0 and ranks(sync_pull(empty, CFG)) == {}


def test_warm_start_stops_at_once(random_graph, exact, spark):
    start = spark.createDataFrame(list(exact.items()), "id long, rank double")
    assert sync_pull(random_graph, replace(CFG, init=start, check_every=1)).iterations == 1


def test_helped(random_graph, exact):
    cfg = RankConfig(tol=1e-3, blocks=3, partitions=2)
    fine = sync_helped(random_graph, cfg, workers=3)
    assert fine.converged and close(ranks(fine), exact, 60 * 5.67e-3)
    assert ranks(fine).keys() == exact.keys()
    hurt = sync_helped(random_graph, cfg, workers=3, faults=FaultPlan(fail={(1, 0), (1, 2)}))
    assert hurt.converged and sorted(hurt.dead) == [0, 2] and close(ranks(hurt), ranks(fine), 1e-12)
    won = [(r["iteration"], r["block"]) for r in hurt.ledger if r["won"]]
    assert len(won) == len(set(won))
    stuck = sync_helped(random_graph, cfg, workers=3, faults=FaultPlan(fail={(1, 0)}, timeout=6), help_others=False)
    assert stuck.stop_reason == "blocked"
    none = sync_helped(random_graph, cfg, workers=2, faults=FaultPlan(fail={(1, 0), (1, 1)}, timeout=20))
    assert none.stop_reason == "failed"
