"""Queries over the given tables, and the SQL they are compared with.

Ranks come as whole billionths, on graphs of a few thousand vertices and after a fixed
number of steps or at convergence, so that two engines' sums agree.
"""

from __future__ import annotations

from collections.abc import Callable
from concurrent.futures import ThreadPoolExecutor
from dataclasses import replace

from pyspark import inheritable_thread_target
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkrank.config import RankConfig, RankResult
from linkrank.functions import measures
from linkrank.graph import Graph, assign_blocks, edge_stats, graph_stats
from linkrank.operators import features, relational
from linkrank.operators.asynchronous import async_edge, async_pull
from linkrank.operators.faults import FaultPlan
from linkrank.operators.fixpoint import hops, surfer_walks, weak_components
from linkrank.operators.helped import sync_helped
from linkrank.operators.sequential import sequential
from linkrank.operators.synchronous import block_errors, global_error, sync_edge, sync_pull
from linkrank.operators.twins import twin_classes
from linkrank.sources import workloads
from linkrank.sources.rmat import rmat_edges, rmat_sql

STEPS = 20
FIXED = RankConfig(max_iter=STEPS, tol=0.0, check_every=5)
SETTLED = RankConfig(tol=1e-15, blocks=4, check_every=10, max_iter=400)
ROUNDS = replace(SETTLED, tol=1e-14, blocks=2, inner_sweeps=16)


def scaled(ranks: DataFrame) -> DataFrame:
    return ranks.select("id", F.round(F.col("rank") * 1e9).cast("long").alias("rank_e9"))


def _labeled(graph: Graph, ranks: DataFrame) -> DataFrame:
    return scaled(ranks).join(graph.labels, "id").select("label", "rank_e9")


def _edges(name: str):
    def query(spark, sf_dir):
        edges = workloads.BUILDERS[name](spark, sf_dir).where("src <> dst")
        if name in workloads.WEIGHTED:
            return edges.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("mult"))
        return edges.distinct()

    return query


def _edges_sql(name: str) -> str:
    if name in workloads.WEIGHTED:
        return f"SELECT src, dst, count(*) AS mult FROM ({workloads.SQL[name]}) WHERE src <> dst AND dst IS NOT NULL GROUP BY src, dst"
    return f"SELECT DISTINCT src, dst FROM ({workloads.SQL[name]}) WHERE src <> dst AND dst IS NOT NULL"


def _ranked(name: str, run: Callable[[Graph], RankResult]):
    def query(spark, sf_dir):
        graph = workloads.load(spark, sf_dir, name)
        ranks = run(graph).ranks
        return _labeled(graph, ranks) if name in workloads.LABELED else scaled(ranks)

    return query


def _graph_ctes(edges_sql: str, weighted: bool = False) -> str:
    return f"""e AS MATERIALIZED (SELECT src, dst, {'mult' if weighted else '1'} AS mult FROM ({edges_sql})),
v AS MATERIALIZED (SELECT DISTINCT id FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e)),
g AS (SELECT src, sum(mult) AS n FROM e GROUP BY src),
n AS (SELECT count(*) AS n FROM v),
c AS MATERIALIZED (SELECT e.src, e.dst, CAST(e.mult AS DOUBLE) / g.n AS w FROM e JOIN g USING (src) UNION ALL SELECT id, id, 0.0 FROM v)"""


def rank_sql(name: str, steps: int = STEPS, label: bool | None = None) -> str:
    """Ranks after a number of synchronous steps."""
    label = name in workloads.LABELED if label is None else label
    return f"""WITH RECURSIVE {_graph_ctes(_edges_sql(name), name in workloads.WEIGHTED)},
r(step, id, rank) AS (
  SELECT 0, id, 1.0 / n.n FROM v, n
  UNION ALL
  SELECT r.step + 1, c.dst, 0.15 / max(n.n) + 0.85 * sum(r.rank * c.w) FROM r JOIN c ON c.src = r.id, n WHERE r.step < {steps} GROUP BY r.step, c.dst
)
SELECT id{' AS label' if label else ''}, CAST(round(rank * 1e9) AS BIGINT) AS rank_e9 FROM r WHERE step = {steps}"""


def _curve_sql(name: str, steps: int) -> str:
    return f"""WITH RECURSIVE {_graph_ctes(_edges_sql(name))},
r(step, id, rank) AS (
  SELECT 0, id, 1.0 / n.n FROM v, n
  UNION ALL
  SELECT r.step + 1, c.dst, 0.15 / max(n.n) + 0.85 * sum(r.rank * c.w) FROM r JOIN c ON c.src = r.id, n WHERE r.step < {steps} GROUP BY r.step, c.dst
), d AS (SELECT b.step AS iteration, max(abs(b.rank - a.rank)) AS m FROM r a JOIN r b ON b.id = a.id AND b.step = a.step + 1 GROUP BY b.step)"""


def error_curve(spark, sf_dir):
    result = sync_pull(workloads.load(spark, sf_dir, "part_succession"), replace(FIXED, max_iter=8, check_every=1))
    return result.history_frame().select("iteration", F.round(F.col("max_delta") * 1e12).cast("long").alias("max_delta_e12"))


def iterations_tol(spark, sf_dir):
    result = sync_pull(workloads.load(spark, sf_dir, "part_succession"), RankConfig(tol=1e-8))
    return spark.createDataFrame([(result.iterations,)], "iterations int")


def redistributed(spark, sf_dir):
    graph = workloads.load(spark, sf_dir, "page_links")
    return _labeled(graph, sync_pull(graph, RankConfig(max_iter=6, tol=0.0, dangling="redistribute")).ranks)


def twins_of_pages(spark, sf_dir):
    graph = workloads.load(spark, sf_dir, "page_links")
    of = twin_classes(graph).join(graph.labels, "id")
    heads = of.groupBy("class").agg(F.min("label").alias("class_label"), F.count(F.lit(1)).alias("members"))
    return of.join(heads, "class").select("label", "class_label", "members")


def distance_of_methods(spark, sf_dir):
    """Methods whose distance to the sequential ranks is within the bound for any graph."""
    graph = workloads.load(spark, sf_dir, "user_succession")
    base = sequential(graph, SETTLED).ranks
    n = graph.count()
    runs = {"sync_pull": sync_pull(graph, SETTLED), "sync_edge": sync_edge(graph, SETTLED), "async_pull": async_pull(graph, SETTLED, "sweep")}
    rows = [(k, bool(r.converged), bool(measures.l1_norm(r.ranks, base) <= 2 * measures.distance_bound(n, SETTLED.tol))) for k, r in runs.items()]
    return spark.createDataFrame(rows, "method string, converged boolean, within_bound boolean")


def helped_with_failures(spark, sf_dir):
    graph = workloads.load(spark, sf_dir, "user_succession")
    return scaled(sync_helped(graph, RankConfig(max_iter=5, tol=0.0, blocks=3), workers=3, faults=FaultPlan(fail={(1, 1)})).ranks)


def frozen_parts(spark, sf_dir):
    """Ranks of a perforated run with a coarse limit, after eight steps."""
    graph = workloads.load(spark, sf_dir, "part_succession")
    return scaled(sync_pull(graph, RankConfig(max_iter=8, tol=1e-12, freeze=True, freeze_factor=1e6)).ranks)


def _depth_one_sql(name: str) -> str:
    """Ranks of a graph whose edges all start where none end, without recursion."""
    return f"""WITH {_graph_ctes(_edges_sql(name))}
SELECT v.id AS label, CAST(round(1e9 * (0.15 / max(n.n) + 0.85 * coalesce(sum(0.15 / n.n / g.n), 0))) AS BIGINT) AS rank_e9
FROM v CROSS JOIN n LEFT JOIN e ON e.dst = v.id LEFT JOIN g ON g.src = e.src GROUP BY v.id"""


def _frozen_sql(steps: int, limit: float, name: str = "part_succession") -> str:
    return f"""WITH RECURSIVE {_graph_ctes(_edges_sql(name))},
r(step, id, rank, frozen) AS (
  SELECT 0, id, 1.0 / n.n, false FROM v, n
  UNION ALL
  SELECT step + 1, dst, CASE WHEN was THEN old ELSE new END, was OR (abs(new - old) < {limit!r} AND new <> old)
  FROM (SELECT r.step, c.dst, 0.15 / max(n.n) + 0.85 * sum(r.rank * c.w) AS new, max(CASE WHEN c.src = c.dst THEN r.rank END) AS old, bool_or(c.src = c.dst AND r.frozen) AS was
        FROM r JOIN c ON c.src = r.id, n WHERE r.step < {steps} GROUP BY r.step, c.dst)
)
SELECT id, CAST(round(rank * 1e9) AS BIGINT) AS rank_e9 FROM r WHERE step = {steps}"""


RMAT_LEVELS = 16
_NUMBERS = "(SELECT row_number() OVER () - 1 AS range FROM lineitem)"


def generated(spark, sf_dir):
    """A generated graph of as many draws as there are order lines."""
    return rmat_edges(spark, workloads.table(spark, sf_dir, "lineitem").count(), RMAT_LEVELS)


def ranked_generated(spark, sf_dir):
    return scaled(sync_pull(Graph.from_edges(generated(spark, sf_dir)), replace(FIXED, max_iter=10)).ranks)


SERIES = (1, 2, 3, 4, 5, 6, 7)  # generated graphs of that many times the smallest's draws
RUNS = 4  # of one task each that go side by side, as each holds a graph


def _series(spark, sf_dir):
    """The seven generated graphs; the smallest has a sixth as many draws as there are order lines."""
    size = max(1, workloads.table(spark, sf_dir, "lineitem").count() // 6)
    for k in SERIES:
        yield k, Graph.from_edges(rmat_edges(spark, k * size))


def iterations_of_series(spark, sf_dir):
    """Whether fewer iterations are taken without barriers on each generated graph, as in the iteration study, and how far the ranks are."""
    cfg = RankConfig(tol=1e-12, blocks=8, max_iter=400)

    def compared(k: int, graph: Graph, runs: ThreadPoolExecutor) -> tuple:
        base, free = (run.result() for run in [runs.submit(inheritable_thread_target(spark)(sequential), graph, cfg), runs.submit(inheritable_thread_target(spark)(async_pull), graph, cfg, "sweep")])
        l1 = measures.l1_norm(base.ranks, free.ranks)
        return k, bool(base.converged and free.converged), bool(free.iterations < base.iterations), bool(l1 <= 2 * measures.distance_bound(graph.count(), cfg.tol))

    # a run is one task: those of the graphs that are built go side by side, while the next graph is built
    with ThreadPoolExecutor(len(SERIES)) as graphs, ThreadPoolExecutor(RUNS) as runs:
        out = [g.result() for g in [graphs.submit(inheritable_thread_target(spark)(compared), k, graph, runs) for k, graph in _series(spark, sf_dir)]]
    return spark.createDataFrame(out, "graph int, converged boolean, fewer boolean, near boolean")


def perforation_on_lattice(spark, sf_dir):
    """What a coarse freeze does on the road-like graph: work falls, the distance rises, the safe guard stays near."""
    graph = workloads.load(spark, sf_dir, "event_lattice")
    cfg = RankConfig(tol=1e-9, blocks=4, max_iter=400)
    base = sequential(graph, cfg)
    rows = []
    for name, run in {"sequential": lambda c: sequential(graph, c), "async_pull": lambda c: async_pull(graph, c, "sweep"), "async_edge": lambda c: async_edge(graph, c, "sweep")}.items():
        plain, frozen = run(cfg), run(replace(cfg, freeze=True, freeze_factor=1e2))
        work = [sum(h["active"] for h in r.history) for r in (plain, frozen)]
        l1 = [measures.l1_norm(r.ranks, base.ranks) for r in (plain, frozen)]
        rows.append((name, bool(work[1] < work[0]), bool(l1[1] > l1[0]), bool(l1[1] > cfg.tol / 10)))
    safe = sequential(graph, replace(cfg, freeze=True, freeze_factor=1e-1, freeze_guard="safe"))
    rows.append(("safe", True, True, bool(measures.l1_norm(safe.ranks, base.ranks) > graph.count() * cfg.tol * 10)))
    return spark.createDataFrame(rows, "method string, less_work boolean, farther boolean, far boolean")


def tenth_of_tolerance(spark, sf_dir):
    """Whether the distance to the sequential ranks is below a tenth of the tolerance, beside the bound that holds on any graph.

    It is on graphs of depth one, whose ranks settle exactly; on others the distance is of
    the order of the tolerance times the number of vertices.
    """
    rows = []
    for name in ("page_links", "part_succession"):
        graph, cfg = workloads.load(spark, sf_dir, name), RankConfig(tol=1e-8, blocks=4)
        exact = sequential(graph, replace(cfg, tol=1e-15)).ranks
        for method, run in {"sync_pull": lambda: sync_pull(graph, cfg), "async_pull": lambda: async_pull(graph, cfg, "sweep")}.items():
            found = measures.convergence_report(run(), exact, graph.count(), cfg)
            rows.append((name, method, bool(found["below_tenth"]), bool(found["within_bound"])))
    return spark.createDataFrame(rows, "graph string, method string, below_tenth boolean, within_bound boolean")


def sync_beside_async(spark, sf_dir):
    graph = workloads.load(spark, sf_dir, "part_succession")
    return spark.createDataFrame([(bool(measures.l1_norm(sync_pull(graph, SETTLED).ranks, async_pull(graph, SETTLED, "sweep").ranks) < 1e-9),)], "within boolean")


def outcomes_under_failures(spark, sf_dir):
    """What becomes of a run when workers die after the first step: the helper ends while one lives, others are blocked."""
    graph, cfg, rows = workloads.load(spark, sf_dir, "user_succession"), RankConfig(max_iter=3, tol=0.0, blocks=3), []
    for failed in (0, 1, 2):
        plan = lambda patience: FaultPlan(fail={(1, w) for w in range(failed)}, timeout=patience)
        rows.append(("sync_helped", failed, sync_helped(graph, cfg, 3, plan(300)).stop_reason))
        rows.append(("barrier", failed, sync_helped(graph, cfg, 3, plan(8 if failed else 300), help_others=False).stop_reason))
        rows.append(("async_pull", failed, async_pull(graph, cfg, "free", plan(8 if failed else 300)).stop_reason))
    return spark.createDataFrame(rows, "method string, failed int, outcome string")


def in_neighbour_classes(spark, sf_dir):
    """The number of classes of equal in-neighbours, with the vertices, of three graphs."""
    rows = [(name, graph.count(), twin_classes(graph).select("class").distinct().count()) for name in ("page_links", "order_parts", "part_succession") for graph in (workloads.load(spark, sf_dir, name),)]
    return spark.createDataFrame(rows, "graph string, vertices long, classes long")


def balanced_blocks(spark, sf_dir):
    """Vertices and in-edges of the largest and the smallest block, for shares by range and by in-edges: whether they are balanced."""
    graph = workloads.load(spark, sf_dir, "part_succession")
    rows = []
    for how, column in (("range", "vertices"), ("edges", "in_edges")):
        sizes = assign_blocks(graph, 8, how).join(graph.in_degrees(), "id").groupBy("block").agg(F.count(F.lit(1)).alias("vertices"), F.sum("in_degree").alias("in_edges"))
        r = sizes.agg(F.count(F.lit(1)).alias("n"), F.max(column).alias("hi"), F.min(column).alias("lo")).first()
        most = graph.in_degrees().agg(F.max("in_degree")).first()[0] if how == "edges" else 1
        rows.append((how, r.n, bool(r.hi - r.lo <= 2 * most)))
    return spark.createDataFrame(rows, "how string, blocks long, balanced boolean")


def surfers_on_pages(spark, sf_dir):
    """Whether random surfers' visits come near the ranks of the page graph."""
    graph = workloads.load(spark, sf_dir, "page_links")
    exact = sequential(graph, SETTLED).ranks
    l1 = measures.l1_norm(surfer_walks(graph, 64, 8), exact)
    return spark.createDataFrame([(bool(l1 < 0.05 * exact.agg(F.sum("rank")).first()[0]),)], "near boolean")


def levels_of_methods(spark, sf_dir):
    """At which levels runs over the page graph stop: each vertex (its work ends before the run's), each block alone, or all at once."""
    graph, rows = workloads.load(spark, sf_dir, "page_links"), []
    n = graph.count()
    for kind, run in {"sync": sync_pull, "async": lambda g, c: async_pull(g, c, "sweep")}.items():
        for frozen in (False, True):
            result = run(graph, RankConfig(tol=1e-15, max_iter=20, blocks=4, freeze=frozen, freeze_factor=1e15))
            active: dict[int, int] = {}
            for h in result.history:
                active[h["iteration"]] = active.get(h["iteration"], 0) + h["active"]
            found = (*(["node"] if min(active.values(), default=n) < n else []), "block" if result.block_iterations else "global")
            rows.append((kind, frozen, "+".join(found)))
    return spark.createDataFrame(rows, "kind string, freeze boolean, levels string")


def block_errors_of_step(spark, sf_dir):
    """Largest change of the first step in each block, and over all."""
    graph = workloads.load(spark, sf_dir, "part_succession")
    after = sync_pull(graph, RankConfig(max_iter=1, tol=0.0)).ranks
    blocks = graph.vertices.select("id", (F.col("id") % 4).cast("int").alias("block"))
    errors = block_errors(graph.vertices.select("id", F.lit(1.0 / graph.count()).alias("rank")), after, blocks)
    return errors.select("block", F.round(F.col("max_delta") * 1e12).cast("long").alias("delta_e12"), F.lit(round(global_error(errors) * 1e12)).cast("long").alias("all_e12"))


def memory_of_methods(spark, sf_dir):
    """Ranks held between steps, by method: two arrays with barriers, one without."""
    n = workloads.load(spark, sf_dir, "part_succession").count()
    return spark.createDataFrame([(m, measures.rank_bytes(m, n)) for m in ("sync_pull", "sync_edge", "async_pull", "async_edge")], "method string, bytes long")


_STATS_SQL = """, o AS (SELECT src AS id, sum(mult) AS k FROM e GROUP BY 1), i AS (SELECT dst AS id, count(*) AS k FROM e GROUP BY 1)
SELECT count(*) AS vertices, CAST(sum(coalesce(i.k, 0)) AS BIGINT) AS edges, CAST(sum(coalesce(o.k, 0)) AS BIGINT) AS links, count(*) FILTER (o.k IS NULL) AS dangling, count(*) FILTER (i.k IS NULL) AS no_in_link,
       CAST(max(coalesce(i.k, 0)) AS BIGINT) AS max_in, CAST(max(coalesce(o.k, 0)) AS BIGINT) AS max_out
FROM v LEFT JOIN o ON o.id = v.id LEFT JOIN i ON i.id = v.id"""

STATS = tuple(workloads.BUILDERS)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    found: dict[str, Callable] = {}
    for name in workloads.BUILDERS:
        found[f"edges_{name}"] = _edges(name)
    for name in STATS:
        found[f"graph_stats_{name}"] = lambda spark, sf_dir, name=name: graph_stats(workloads.load(spark, sf_dir, name))
    found["graph_stats_similarity_knn"] = lambda spark, sf_dir: edge_stats(workloads.similarity_knn(spark, sf_dir))  # its edges cost most: no graph is stored of them
    found |= {
        "rank_sync_pull_part": _ranked("part_succession", lambda g: sync_pull(g, FIXED)),
        "rank_sync_pull_trade": _ranked("trade_mutual", lambda g: sync_pull(g, FIXED)),
        "rank_sync_pull_user": _ranked("user_succession", lambda g: sync_pull(g, FIXED)),
        "rank_sync_pull_page": _ranked("page_links", lambda g: sync_pull(g, replace(FIXED, max_iter=4, check_every=4))),
        "rank_sync_pull_host": _ranked("host_links", lambda g: sync_pull(g, replace(FIXED, max_iter=4, check_every=4))),
        "rank_sync_edge_part": _ranked("part_succession", lambda g: sync_edge(g, FIXED)),
        "rank_sync_edge_stored_user": _ranked("user_succession", lambda g: sync_edge(g, replace(FIXED, fused=False, max_iter=5, check_every=1))),
        "rank_ordered_sums_user": _ranked("user_succession", lambda g: sync_pull(g, replace(FIXED, sum_mode="ordered", max_iter=6))),
        "rank_decimal_sums_user": _ranked("user_succession", lambda g: sync_pull(g, replace(FIXED, sum_mode="decimal", max_iter=6))),
        "rank_sequential_part": _ranked("part_succession", lambda g: sequential(g, replace(FIXED, max_iter=80))),
        "rank_async_pull_part": _ranked("part_succession", lambda g: async_pull(g, SETTLED, "sweep")),
        "rank_async_rounds_user": _ranked("user_succession", lambda g: async_pull(g, ROUNDS)),
        "rank_async_rounds_part": _ranked("part_succession", lambda g: async_pull(g, ROUNDS)),
        "rank_async_rounds_trade": _ranked("trade_mutual", lambda g: async_pull(g, ROUNDS)),
        "rank_async_free_page": _ranked("page_links", lambda g: async_pull(g, replace(SETTLED, blocks=3), "free")),
        "rank_settled_trade": _ranked("trade_mutual", lambda g: sequential(g, SETTLED)),
        "rank_page_links": _ranked("page_links", lambda g: sync_pull(g, SETTLED)),
        "rank_async_redistribute_page": _ranked("page_links", lambda g: async_pull(g, replace(SETTLED, dangling="redistribute"), "sweep")),
        "rank_sequential_twins_page": _ranked("page_links", lambda g: sequential(g, replace(SETTLED, twins=True))),
        "rank_helped_twins_page": _ranked("page_links", lambda g: sync_helped(g, replace(SETTLED, twins=True, blocks=2, max_iter=6), workers=2)),
        "rank_helped_freeze_user": _ranked("user_succession", lambda g: sync_helped(g, RankConfig(max_iter=5, tol=1e-12, blocks=3, freeze=True, freeze_factor=1e7), workers=3)),
        "rank_async_delayed_user": _ranked("user_succession", lambda g: async_pull(g, replace(SETTLED, staleness=2, schedule_seed=3), "adversarial")),
        "rank_async_edge_part": _ranked("part_succession", lambda g: async_edge(g, SETTLED, "sweep")),
        "rank_async_edge_rounds_user": _ranked("user_succession", lambda g: async_edge(g, replace(SETTLED, max_iter=5, tol=1e-16))),
        "rank_async_opt_twins_page": _ranked("page_links", lambda g: async_pull(g, replace(SETTLED, freeze=True, twins=True), "sweep")),
        "rank_async_freeze_part": _ranked("part_succession", lambda g: async_pull(g, replace(SETTLED, freeze=True, freeze_factor=1.0), "sweep")),
        "rank_order_parts": _ranked("order_parts", lambda g: sync_pull(g, replace(FIXED, max_iter=3, check_every=3))),
        "rank_nation_uniform": _ranked("nation_trade", lambda g: sync_pull(g, replace(FIXED, max_iter=2, check_every=2))),
        "rank_lattice": _ranked("event_lattice", lambda g: sync_pull(g, replace(FIXED, max_iter=10))),
        "rank_turn_chain": _ranked("turn_chain", lambda g: sync_pull(g, replace(FIXED, max_iter=12, check_every=4))),
        "rank_twins_page": _ranked("page_links", lambda g: sync_pull(g, replace(FIXED, max_iter=4, check_every=4, twins=True))),
        "rank_safe_freeze_page": _ranked("page_links", lambda g: sync_pull(g, replace(SETTLED, tol=1e-13, freeze=True, freeze_guard="safe", check_every=1))),
        "rank_freeze_part": frozen_parts,
        "rank_redistribute_page": redistributed,
        "rank_rmat": ranked_generated,
        "rmat_edges": generated,
        "error_curve_part": error_curve,
        "iterations_tol8_part": iterations_tol,
        "twin_classes_page": twins_of_pages,
        "l1_within_bound": distance_of_methods,
        "helped_equals_barrier": helped_with_failures,
        "iterations_of_series": iterations_of_series, "perforation_on_lattice": perforation_on_lattice, "tenth_of_tolerance": tenth_of_tolerance, "l1_sync_vs_async": sync_beside_async, "outcomes_under_failures": outcomes_under_failures,
        "in_neighbour_classes": in_neighbour_classes, "balanced_blocks": balanced_blocks, "surfers_on_pages": surfers_on_pages, "levels_of_methods": levels_of_methods, "block_errors_of_step": block_errors_of_step, "memory_of_methods": memory_of_methods,
        "components_turns": lambda spark, sf_dir: weak_components(workloads.load(spark, sf_dir, "turn_chain")).select("id", F.col("value").alias("component")),
        "components_passages": lambda spark, sf_dir: weak_components(workloads.load(spark, sf_dir, "passage_links")).select("id", F.col("value").alias("component")),
        "hops_turns": lambda spark, sf_dir: hops(workloads.load(spark, sf_dir, "turn_chain"), 0).select("id", F.col("value").alias("hops")),
    }
    return found | relational.QUERIES | features.QUERIES


def _redistributed_sql(steps: int) -> str:
    return f"""WITH RECURSIVE {_graph_ctes(_edges_sql("page_links"))},
x AS MATERIALIZED (SELECT src, dst, w FROM c UNION ALL SELECT v.id, u.id, 1.0 / n.n FROM v, v u, n WHERE v.id NOT IN (SELECT src FROM e)),
r(step, id, rank) AS (
  SELECT 0, id, 1.0 / n.n FROM v, n
  UNION ALL
  SELECT r.step + 1, x.dst, 0.15 / max(n.n) + 0.85 * sum(r.rank * x.w) FROM r JOIN x ON x.src = r.id, n WHERE r.step < {steps} GROUP BY r.step, x.dst
)
SELECT id AS label, CAST(round(rank * 1e9) AS BIGINT) AS rank_e9 FROM r WHERE step = {steps}"""


def oracle_sql() -> dict[str, str]:
    found = {f"edges_{name}": _edges_sql(name) for name in workloads.BUILDERS}
    found |= {f"graph_stats_{name}": f"WITH {_graph_ctes(_edges_sql(name), name in workloads.WEIGHTED)}{_STATS_SQL}" for name in STATS}
    part, user = rank_sql("part_succession"), rank_sql("user_succession")
    settled_part, settled_user, settled_page, settled_trade = rank_sql("part_succession", 80), rank_sql("user_succession", 80), rank_sql("page_links", 6), rank_sql("trade_mutual", 230)
    generated_sql = rmat_sql(0, RMAT_LEVELS, rows=_NUMBERS)
    generated_graph = _graph_ctes(f"SELECT DISTINCT src, dst FROM ({generated_sql}) WHERE src <> dst")
    found |= {
        "rank_sync_pull_part": part, "rank_sync_edge_part": part, "rank_sync_pull_trade": rank_sql("trade_mutual"), "rank_sync_pull_user": user,
        "rank_sync_pull_page": rank_sql("page_links", 4), "rank_sync_pull_host": rank_sql("host_links", 4), "rank_twins_page": rank_sql("page_links", 4), "rank_safe_freeze_page": rank_sql("page_links", 6),
        "rank_sync_edge_stored_user": rank_sql("user_succession", 5), "rank_async_edge_rounds_user": rank_sql("user_succession", 5), "helped_equals_barrier": rank_sql("user_succession", 5),
        "rank_ordered_sums_user": rank_sql("user_succession", 6), "rank_decimal_sums_user": rank_sql("user_succession", 6),
        "rank_sequential_part": settled_part, "rank_async_pull_part": settled_part, "rank_async_edge_part": settled_part, "rank_async_rounds_part": settled_part, "rank_async_freeze_part": settled_part, "rank_async_rounds_user": settled_user, "rank_async_rounds_trade": settled_trade, "rank_settled_trade": settled_trade,
        "rank_async_free_page": settled_page, "rank_page_links": _depth_one_sql("page_links"), "rank_sequential_twins_page": settled_page, "rank_helped_twins_page": settled_page, "rank_async_opt_twins_page": settled_page,
        "rank_helped_freeze_user": _frozen_sql(5, 1e-5, "user_succession"), "rank_async_delayed_user": settled_user,
        "rank_order_parts": rank_sql("order_parts", 3), "rank_nation_uniform": rank_sql("nation_trade", 2), "rank_lattice": rank_sql("event_lattice", 10), "rank_turn_chain": rank_sql("turn_chain", 12),
        "rank_freeze_part": _frozen_sql(8, 1e-6),
        "rmat_edges": generated_sql,
        "rank_rmat": rank_sql("part_succession", 10).replace(_graph_ctes(_edges_sql("part_succession")), generated_graph),
        "rank_async_redistribute_page": _redistributed_sql(120), "rank_redistribute_page": _redistributed_sql(6),
        "iterations_of_series": "SELECT CAST(unnest([1, 2, 3, 4, 5, 6, 7]) AS INTEGER) AS graph, true AS converged, true AS fewer, true AS near",
        "perforation_on_lattice": "SELECT unnest(['sequential', 'async_pull', 'async_edge', 'safe']) AS method, true AS less_work, true AS farther, unnest([true, true, true, false]) AS far",
        "tenth_of_tolerance": "SELECT graph, method, graph = 'page_links' AS below_tenth, true AS within_bound FROM (SELECT unnest(['page_links', 'part_succession']) AS graph), (SELECT unnest(['sync_pull', 'async_pull']) AS method)",
        "l1_sync_vs_async": "SELECT true AS within",
        "outcomes_under_failures": "SELECT method, CAST(failed AS INTEGER) AS failed, CASE WHEN method = 'sync_helped' OR failed = 0 THEN 'max_iter' ELSE 'blocked' END AS outcome FROM (SELECT unnest(['sync_helped', 'barrier', 'async_pull']) AS method), (SELECT unnest([0, 1, 2]) AS failed)",
        "in_neighbour_classes": " UNION ALL ".join(f"SELECT * FROM (WITH {_graph_ctes(_edges_sql(name))}, s AS (SELECT v.id, coalesce(string_agg(CAST(e.src AS VARCHAR), ' ' ORDER BY e.src), '') AS ins FROM v LEFT JOIN e ON e.dst = v.id GROUP BY v.id) SELECT '{name}' AS graph, count(*) AS vertices, count(DISTINCT ins) AS classes FROM s)" for name in ("page_links", "order_parts", "part_succession")),
        "balanced_blocks": "SELECT unnest(['range', 'edges']) AS how, CAST(8 AS BIGINT) AS blocks, true AS balanced",
        "surfers_on_pages": "SELECT true AS near",
        "levels_of_methods": "SELECT unnest(['sync', 'sync', 'async', 'async']) AS kind, unnest([false, true, false, true]) AS freeze, unnest(['global', 'node+global', 'block', 'node+block']) AS levels",
        "block_errors_of_step": f"""WITH {_graph_ctes(_edges_sql("part_succession"))}, r AS (SELECT c.dst AS id, 0.15 / max(n.n) + 0.85 * sum(c.w / n.n) AS rank FROM c, n GROUP BY 1), d AS (SELECT id % 4 AS block, max(abs(rank - 1.0 / n.n)) AS m FROM r, n GROUP BY 1)
SELECT CAST(block AS INTEGER) AS block, CAST(round(m * 1e12) AS BIGINT) AS delta_e12, CAST(round(max(m) OVER () * 1e12) AS BIGINT) AS all_e12 FROM d""",
        "memory_of_methods": "SELECT method, CAST(8 * arrays * (SELECT count(DISTINCT l_partkey) FROM lineitem) AS BIGINT) AS bytes FROM (SELECT unnest(['sync_pull', 'sync_edge', 'async_pull', 'async_edge']) AS method, unnest([2, 2, 1, 1]) AS arrays)",
        "components_turns": f"""WITH RECURSIVE e AS (SELECT src AS a, dst AS b FROM ({_edges_sql("turn_chain")}) UNION SELECT dst, src FROM ({_edges_sql("turn_chain")})),
r(a, b) AS (SELECT a, a FROM e UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a) SELECT a AS id, min(b) AS component FROM r GROUP BY a""",
        "error_curve_part": _curve_sql("part_succession", 8) + "\nSELECT iteration, CAST(round(m * 1e12) AS BIGINT) AS max_delta_e12 FROM d",
        "iterations_tol8_part": _curve_sql("part_succession", 15) + "\nSELECT CAST(min(iteration) AS INTEGER) AS iterations FROM d WHERE m <= 1e-8",
        "twin_classes_page": f"""WITH {_graph_ctes(_edges_sql("page_links"))}, s AS (SELECT v.id, list(x.src || '/' || x.k ORDER BY x.src) AS ins FROM v LEFT JOIN (SELECT e.dst, e.src, g.n AS k FROM e JOIN g USING (src)) x ON x.dst = v.id GROUP BY v.id)
SELECT id AS label, min(id) OVER (PARTITION BY CASE WHEN ins = [NULL] THEN [] ELSE ins END) AS class_label, count(*) OVER (PARTITION BY CASE WHEN ins = [NULL] THEN [] ELSE ins END) AS members FROM s""",
        "l1_within_bound": "SELECT unnest(['sync_pull', 'sync_edge', 'async_pull']) AS method, true AS converged, true AS within_bound",
        "components_passages": f"""WITH RECURSIVE e AS (SELECT src AS a, dst AS b FROM ({_edges_sql("passage_links")}) UNION SELECT dst, src FROM ({_edges_sql("passage_links")})),
r(a, b) AS (SELECT a, a FROM e UNION SELECT r.a, e.b FROM r JOIN e ON r.b = e.a) SELECT a AS id, min(b) AS component FROM r GROUP BY a""",
        "hops_turns": f"""WITH RECURSIVE {_graph_ctes(_edges_sql("turn_chain"))}, h(id, hops) AS (SELECT CAST(0 AS BIGINT), CAST(0 AS BIGINT) UNION SELECT e.dst, h.hops + 1 FROM h JOIN e ON e.src = h.id)
SELECT v.id, min(h.hops) AS hops FROM v LEFT JOIN h USING (id) GROUP BY v.id""",
    }
    return found | relational.oracle_sql(rank_sql) | features.oracle_sql(rank_sql)

