import inspect
import random
from dataclasses import replace

import pytest
from pyspark.sql import functions as F

from linkrank.config import LEVELS, RankConfig
from linkrank.functions import measures, udf
from linkrank.graph import Graph, assign_blocks, csr_blocks
from linkrank.operators import fixpoint, relational
from linkrank.operators.sequential import sequential, solve_exact
from linkrank.operators.synchronous import _Loop, block_errors, global_error, sync_pull
from linkrank.operators.twins import twin_classes
from linkrank.plans.lineage import exchanges, loop_settings
from linkrank.sources import edges as readers
from linkrank.sources.rmat import rmat_edges, scale_for
from tests.core.graphs import close, graph, random_edges, ranks


def test_a_step_has_one_exchange(spark):
    g = graph(spark, random_edges(random.Random(1), 50, 300))
    with loop_settings(spark):
        loop = _Loop(g, RankConfig(), "sync_pull")
        assert exchanges(loop.step(loop.start)) == 1
        loop = _Loop(g, RankConfig(), "sync_edge")
        assert exchanges(loop.step(loop.start)) == 1


def test_bucketed_tables_need_one_exchange(spark):
    g = graph(spark, random_edges(random.Random(1), 50, 300))
    e = readers.save_bucketed(g.edges, "bucketed_edges", "src", 4)
    s = readers.save_bucketed(g.vertices.withColumn("rank", F.lit(0.02)), "bucketed_state", "id", 4)
    with loop_settings(spark):
        sums = e.join(s, F.col("src") == F.col("id")).groupBy("dst").agg(F.sum(F.col("rank") * F.col("coef")).alias("t"))
        assert exchanges(s.join(sums, F.col("id") == F.col("dst"), "left")) == 1


def test_contraction_and_mass(spark):
    g = graph(spark, random_edges(random.Random(2), 40, 200))
    found = sync_pull(g, RankConfig(max_iter=4, tol=0.0, partitions=2))
    l1 = [h["l1_delta"] for h in found.history]
    assert all(b <= 0.85 * a + 1e-12 for a, b in zip(l1, l1[1:]))
    r = ranks(found)
    assert sum(r.values()) <= 1 + 1e-12 and min(r.values()) >= 0.15 / len(r) - 1e-15


def test_blocks_tile_the_vertices(spark):
    g = graph(spark, random_edges(random.Random(3), 90, 500))
    n = g.count()
    for how in ("hash", "range", "edges"):
        of = assign_blocks(g, 4, how).collect()
        assert sorted(r.id for r in of) == sorted(r.id for r in g.vertices.collect()) and {r.block for r in of} == set(range(4))
        if how == "range":
            sizes = [sum(r.block == b for r in of) for b in range(4)]
            assert max(sizes) - min(sizes) <= 1
            assert sorted(of, key=lambda r: r.id) == sorted(of, key=lambda r: (r.block, r.id))
    arrays = csr_blocks(g, assign_blocks(g, 3)).collect()
    assert sum(len(r.ids) for r in arrays) == n and sum(len(r.in_src) for r in arrays) == g.edges.count()
    assert all(r.in_ptr[0] == 0 and r.in_ptr[-1] == len(r.in_src) for r in arrays)


def test_errors_by_block(spark):
    g = graph(spark, "star_in5")
    before = g.vertices.select("id", F.lit(0.2).alias("rank"))
    after = sync_pull(g, RankConfig(max_iter=1, partitions=2)).ranks
    errors = block_errors(before, after, assign_blocks(g, 2, "range"))
    assert abs(global_error(errors) - 0.51) < 1e-12


def test_twins(spark):
    of = {r.id: r["class"] for r in twin_classes(graph(spark, "twins5")).collect()}
    assert of == {0: 0, 1: 1, 2: 2, 3: 2, 4: 4}
    none = {r.id: r["class"] for r in twin_classes(graph(spark, "star_in5")).collect()}
    assert none == {0: 0, 1: 1, 2: 1, 3: 1, 4: 1}


def test_levels():
    assert LEVELS["async", True] == ("node", "block") and LEVELS["sync", False] == ("global",)
    assert measures.step_bound(1e-16) == 232
    assert [measures.progress(m) for m in ("sync_pull", "async_pull:free", "sync_helped")] == ["blocking", "lock-free", "wait-free"]


def test_measures(spark):
    g = graph(spark, random_edges(random.Random(5), 40, 200))
    cfg = RankConfig(tol=1e-9)
    base = sequential(g, cfg)
    exact = solve_exact(g)
    report = measures.convergence_report(base, exact, g.count(), cfg)
    assert report["within_bound"] and measures.top_overlap(base.ranks, exact, 10) == 1.0 and measures.order_agreement(base.ranks, exact, 2) > 0.99
    assert measures.l1_norm(base.ranks, base.ranks) == 0.0
    frame = measures.compare(g, "g", {"sequential": lambda x: sequential(x, cfg), "again": lambda x: sequential(x, cfg)}, repeats=1)
    assert {r.method: r.l1 for r in frame.collect()} == {"sequential": 0.0, "again": 0.0}
    assert all(r.speedup > 0 for r in measures.speedup(frame).collect()) and measures.scaling(frame.fillna(1, ["workers"])).count() == 2
    assert base.history_frame().count() == base.iterations and measures.iterations(base).first().iterations == base.iterations


def test_other_fixed_points(spark):
    g = graph(spark, [(1, 2), (2, 3), (7, 8)])
    assert {r.id: r.value for r in fixpoint.weak_components(g).collect()} == {1: 1, 2: 1, 3: 1, 7: 7, 8: 7}
    assert {r.id: r.value for r in fixpoint.hops(g, 1).collect()} == {1: 0, 2: 1, 3: 2, 7: None, 8: None}
    ring = graph(spark, "complete4")
    assert close(ranks(fixpoint.perforated(ring, 3, 0.3)), [0.25] * 4, 1e-9)
    walked = ranks(fixpoint.surfer_walks(graph(spark, "twins5"), 1500, steps=12))
    assert abs(walked[0] / (1 - 0.85**13) - 0.30391642) < 0.01  # walks are cut after 12 steps
    assert abs(walked[1] - 0.03) < 0.001


def test_generators_agree(spark):
    udf.register(spark)
    want = sorted(map(tuple, rmat_edges(spark, 500).collect()))
    assert sorted(map(tuple, spark.read.format("rankgraph").option("edges", "500").load().collect())) == want
    assert sorted(map(tuple, spark.sql("SELECT * FROM rmat_edges(500, 1)").collect())) == want
    g = Graph.from_edges(rmat_edges(spark, 20_000))
    n, m = g.count(), g.edges.count()
    assert 0.25 < n / m < 0.75 and scale_for(20_000) >= 14
    assert spark.sql("SELECT step_bound(1e-16D) AS b").first().b == 232
    assert spark.sql("SELECT ordered_sum(v, s) AS t FROM VALUES (0.1D, 2L), (0.2D, 1L) AS x(v, s)").first().t == 0.2 + 0.1
    assert [tuple(r) for r in spark.sql("SELECT * FROM adjacency('3: 4, 5')").collect()] == [(3, 4), (3, 5)]


@pytest.mark.parametrize("fmt", ["tsv", "csv", "json", "orc", "parquet"])
def test_edge_files(spark, tmp_path, fmt):
    rows = [(1, 2), (2, 3), (1, 3)]
    readers.write_edges(spark.createDataFrame(rows, "src long, dst long"), f"{tmp_path}/e", fmt)
    assert sorted(map(tuple, readers.read_edges(spark, f"{tmp_path}/e", fmt).collect())) == sorted(rows)


def test_adjacency_and_comments(spark, tmp_path):
    rows = [(1, 2), (2, 3), (1, 3)]
    readers.write_edges(spark.createDataFrame(rows, "src long, dst long"), f"{tmp_path}/a", "adjacency")
    assert sorted(map(tuple, readers.read_adjacency(spark, f"{tmp_path}/a").collect())) == sorted(rows)
    (tmp_path / "t.txt").write_text("# a\n1\t2\n\n3 4\nbad line\n")
    assert sorted(map(tuple, readers.read_edges(spark, f"{tmp_path}/t.txt").collect())) == [(1, 2), (3, 4)]


def test_relational(spark):
    g = graph(spark, "twins5")
    r = sequential(g, RankConfig(tol=1e-9)).ranks
    assert {b.id: b.band for b in relational.rank_bands(r, 3).collect()}[4] == 0
    rows = spark.createDataFrame([(4, "x"), (99, "y")], "k long, name string")
    got = {x.name: x.rank_ratio for x in relational.rank_features(r, rows, "k").collect()}
    assert got["x"] > 1 and got["y"] is None
    delta = relational.edge_delta(graph(spark, "chain3").edges, graph(spark, [(0, 1), (1, 5)]).edges)
    assert sorted(map(tuple, delta.collect())) == [(1, 2, -1), (1, 5, 1)]


def test_tolerance_modes():
    cfg = RankConfig(tol=1e-6)
    assert cfg.bound(100) == 1e-6 and replace(cfg, tol_mode="uniform_relative").bound(100) == 1e-8


def test_fixpoint_never_stops_unfinished(spark):
    g = graph(spark, [(1, 2), (2, 3), (3, 4), (4, 5)])
    start = g.vertices.select("id", F.when(F.col("id") == 1, F.lit(0).cast("long")).alias("value"))
    step = (g, start, lambda v, c: v + 1, F.min, lambda v, m: F.least(v, m))
    with pytest.raises(RuntimeError, match="after 3 steps"):
        fixpoint.fixpoint(*step, max_iter=3)
    state, steps = fixpoint.fixpoint(*step, max_iter=5)
    assert steps == 5 and {r.id: r.value for r in state.collect()} == {1: 0, 2: 1, 3: 2, 4: 3, 5: 4}
    assert inspect.signature(fixpoint.fixpoint).parameters["max_iter"].default is None
