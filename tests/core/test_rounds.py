from dataclasses import replace

import numpy as np
import pytest

from linkrank.config import RankConfig
from linkrank.functions.measures import l1_norm
from linkrank.graph import Graph
from linkrank.operators import rounds
from linkrank.operators.asynchronous import async_edge, async_pull
from linkrank.operators.kernel import Block, sweep, sweep_shares
from linkrank.operators.synchronous import sync_pull
from linkrank.plans.lineage import exchanges, loop_settings


def edges(seed, n=400, m=3000):
    rng = np.random.default_rng(seed)
    return rng.integers(0, n, m), rng.integers(0, n, m)


@pytest.mark.parametrize("edge_form", [False, True])
def test_packed_sweeps_are_those_of_a_plain_block(edge_form):
    src, dst = edges(5)
    ids = np.flatnonzero(np.random.default_rng(2).random(400) < 0.5)
    own = np.isin(dst, ids)
    src, dst, coef = src[own], dst[own], np.random.default_rng(1).random(int(own.sum())) / 20
    plain = Block.of_edges(ids, src, dst, coef)
    rank = np.random.default_rng(3).random(len(plain.inputs))
    arrays, outside = rounds.packed(ids, src, dst, coef, edge_form)
    outer, mine = rank[np.searchsorted(plain.inputs, outside)], rank[plain.own]
    active = np.random.default_rng(4).random(len(ids)) < 0.7
    for _ in range(3):
        (sweep_shares if edge_form else sweep)(plain, rank, 1e-3, 0.85, active)
    rounds.passes(arrays, mine, outer, 1e-3, 0.85, 3, active)
    assert np.allclose(mine, rank[plain.own], rtol=1e-12, atol=0)


def test_a_round_moves_arrays_only(spark):
    src, dst = edges(3)
    graph = Graph.from_edges(spark.createDataFrame([(int(a), int(b)) for a, b in zip(src, dst)], "src long, dst long"))
    cfg = RankConfig(tol=1e-13, blocks=3, inner_sweeps=4)
    with loop_settings(spark):
        layout = rounds.PackedBlocks(graph, cfg, False)
        sent = layout.start()
        assert sent.count() <= 9  # a row for each two blocks; a row for each vertex and block that read it before
        assert exchanges(layout._swept(sent, None, 0.0, 4)) == 1  # blocks' arrays were moved in each round before
    plain = replace(cfg, inner_sweeps=1)
    want = sync_pull(graph, plain).ranks
    for how in ("hash", "range"):
        got = async_pull(graph, replace(cfg, block_how=how))
        assert got.converged and l1_norm(got.ranks, want) < 1e-10 and set(got.block_iterations) == {0, 1, 2}
    got = async_edge(graph, plain)
    assert got.converged and l1_norm(got.ranks, want) < 1e-10
    spread = replace(cfg, dangling="redistribute")
    assert l1_norm(async_pull(graph, replace(spread, inner_sweeps=1)).ranks, sync_pull(graph, replace(spread, inner_sweeps=1)).ranks) < 1e-10


def test_a_block_of_its_own_stops_alone(spark):
    """Two graphs apart, one a long way from rest: a block at rest is left out and its ranks stay."""
    chain = [(2 * k, 2 * k + 2) for k in range(60)]
    graph = Graph.from_edges(spark.createDataFrame(chain + [(1001, 1003)], "src long, dst long"))
    cfg = RankConfig(tol=1e-14, blocks=2, block_how="range")
    got = async_pull(graph, cfg)
    assert got.converged and l1_norm(got.ranks, sync_pull(graph, cfg).ranks) < 1e-12


@pytest.mark.parametrize("edge_form,run", [(False, 1 << 16), (True, 1 << 16), (False, 7)])
def test_edges_of_a_source_have_one_share_and_sweeps_end_at_rest(monkeypatch, edge_form, run):
    monkeypatch.setattr(rounds, "SUM", run)
    src, dst = edges(7)
    ids = np.flatnonzero(np.random.default_rng(2).random(400) < 0.5)
    own = np.isin(dst, ids)
    coef = 1.0 / np.bincount(src, minlength=400)[src][own]
    src, dst = src[own], dst[own]
    plain = Block.of_edges(ids, src, dst, coef)
    rank = np.random.default_rng(3).random(len(plain.inputs))
    arrays, outside = rounds.packed(ids, src, dst, coef, edge_form)
    assert not any(len(arrays[f"{k}_coef"]) for k in ("outer", "late", "early"))  # eight bytes an edge before
    assert len(arrays["share"]) == len(ids) and len(arrays["outer_share"]) == len(outside)
    outer, mine = rank[np.searchsorted(plain.inputs, outside)], rank[plain.own]
    rest = mine.copy()
    for _ in range(3):
        (sweep_shares if edge_form else sweep)(plain, rank, 1e-3, 0.85)
    rounds.passes(arrays, mine, outer, 1e-3, 0.85, 3)
    assert np.allclose(mine, rank[plain.own], rtol=1e-12, atol=0)
    if not edge_form:
        rounds.passes(arrays, rest, outer, 1e-3, 0.85, 10**9)  # did not end before
        again = rest.copy()
        rounds.passes(arrays, again, outer, 1e-3, 0.85, 1)
        assert np.array_equal(again, rest)
