import threading

from linkrank import queries
from linkrank.config import LEVELS, RankConfig
from linkrank.graph import Graph
from linkrank.operators import features
from linkrank.operators.faults import FaultPlan
from linkrank.operators.helped import sync_helped
from linkrank.plans.lineage import plan_text


def test_long_steps_are_no_waiting(spark):
    graph = Graph.from_edges(spark.range(300).selectExpr("id AS src", "(id * id + 1) % 300 AS dst"))
    found = sync_helped(graph, RankConfig(max_iter=6, tol=0.0, blocks=3), workers=3, faults=FaultPlan(fail={(1, 1)}, timeout=1.0))
    assert found.stop_reason == "max_iter" and found.iterations == 6  # ended as blocked after a second before


def test_levels_are_those_of_runs_over_a_table(spark, sf_dir, monkeypatch):
    read = []
    table = queries.workloads.table
    monkeypatch.setattr(queries.workloads, "table", lambda s, d, name: read.append(name) or table(s, d, name))
    found = queries.queries()["levels_of_methods"](spark, sf_dir).collect()
    assert "pages" in read
    assert {(r.kind, r.freeze): tuple(r.levels.split("+")) for r in found} == LEVELS


def test_shared_targets_move_hashes(spark, sf_dir):
    found = queries.queries()["shared_targets"](spark, sf_dir)
    assert "ShuffledHashJoin" not in plan_text(found)  # pairs are stored as two numbers before addresses are joined
    targets = {}
    for r in queries.workloads.page_links(spark, sf_dir).distinct().collect():
        targets.setdefault(r.src, set()).add(r.dst)
    pages = sorted(targets)
    want = {(a, b, len(targets[a] & targets[b])) for k, a in enumerate(pages) for b in pages[k + 1 :] if len(targets[a] & targets[b]) >= 2}
    assert {(r.a, r.b, r.shared) for r in found.collect()} == want and want


def test_pairs_of_shared_targets_are_not_moved(spark, sf_dir, monkeypatch):
    whole = queries.queries()["shared_targets"](spark, sf_dir)
    want = {(r.a, r.b, r.shared) for r in whole.collect()}
    monkeypatch.setattr(features, "PAGES", 8, raising=False)
    monkeypatch.setattr(features, "RUN", 16, raising=False)
    found = queries.queries()["shared_targets"](spark, sf_dir)
    rows = found.collect()
    assert len(rows) == len(want) and {(r.a, r.b, r.shared) for r in rows} == want
    assert "Join" not in plan_text(found)  # no address is joined to pairs


def test_runs_over_series_go_side_by_side(spark, sf_dir, monkeypatch):
    begun, met = threading.Event(), []
    first, second = queries.sequential, queries.async_pull
    monkeypatch.setattr(queries, "SERIES", (1, 2))
    monkeypatch.setattr(queries, "sequential", lambda *a: met.append(begun.wait(20)) or first(*a))
    monkeypatch.setattr(queries, "async_pull", lambda *a: begun.set() or second(*a))
    found = queries.iterations_of_series(spark, sf_dir).collect()
    assert sorted(r.graph for r in found) == [1, 2] and met == [True, True]
