"""Synchronous ranking: all vertices from the previous step's ranks.

A step joins the ranks to the edges where both lie by source, adds up the shares by
target after adding up within tasks (the step's only exchange), and joins the sums to
the vertices where they lie. The out-links of hubs lie by target instead, in all
partitions, and meet the hubs' ranks in a broadcast: hubs are few, as each has more than
``hub_degree`` of the edges. The change, its maximum and the work are observed while
the state is stored, so they cost no second job. Nothing but numbers reaches the
driver.
"""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from linkrank.config import RankConfig, RankResult
from linkrank.graph import Graph
from linkrank.operators.twins import on_classes
from linkrank.plans.lineage import cut, loop_settings


def sync_pull(graph: Graph, cfg: RankConfig = RankConfig()) -> RankResult:
    """Each vertex adds up its in-neighbours' shares of the previous ranks."""
    return _run(graph, cfg, "sync_pull")


def sync_edge(graph: Graph, cfg: RankConfig = RankConfig()) -> RankResult:
    """Each vertex with out-links writes its share on all of them; each vertex adds up what its in-links hold.

    With ``fused=False`` the written shares are stored before they are added up.
    """
    return _run(graph, cfg, "sync_edge")


def initial_ranks(graph: Graph, cfg: RankConfig, n: int) -> DataFrame:
    """(id, rank): uniform, or those given, with the uniform value for vertices not given."""
    start = F.lit(1.0 / max(n, 1))
    if isinstance(cfg.init, str):
        return graph.vertices.select("id", "out_degree", start.alias("rank"))
    given = cfg.init.select(F.col("id"), F.col("rank").cast("double").alias("rank"))
    return graph.vertices.join(given, "id", "left").select("id", "out_degree", F.coalesce("rank", start).alias("rank"))


def _total(cfg: RankConfig, value, order) -> F.Column:
    if cfg.sum_mode == "ordered":
        pairs = F.sort_array(F.collect_list(F.struct(order.alias("o"), value.alias("v"))))
        return F.aggregate(pairs, F.lit(0.0), lambda acc, x: acc + x["v"])
    if cfg.sum_mode == "decimal":
        return F.sum(value.cast("decimal(38,24)")).cast("double")
    return F.sum(value)


BROADCAST_ROWS = 500_000
CHAIN = 5  # steps in one plan


class _Loop:
    """A graph laid out for steps: edges by source, state by id, both sorted once, so that a step sorts only its sums."""

    def __init__(self, graph: Graph, cfg: RankConfig, method: str):
        self.cfg, self.method, self.graph = cfg, method, graph
        self.n = graph.count()
        self.frozen = 0
        self.parts = cfg.partitions or max(1, int(graph.spark.conf.get("spark.sql.shuffle.partitions")))
        edges = graph.edges.select("src", "dst", "coef", F.col("mult").cast("double").alias("mult"))
        hubs = cut(graph.vertices.where(F.col("out_degree") > cfg.hub_degree).select(F.col("id").alias("hub")))
        self.hubs = hubs if 0 < hubs.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else None
        if self.hubs is not None:
            is_hub = F.col("src") == F.col("hub")
            self.hub_edges = cut(edges.join(F.broadcast(hubs), is_hub, "left_semi").repartition(self.parts, "dst"))
            edges = edges.join(F.broadcast(hubs), is_hub, "left_anti")
        self.edges = cut(edges.repartition(self.parts, "src").sortWithinPartitions("src"))
        base = initial_ranks(graph, cfg, self.n)
        ins = graph.in_degrees()
        self.fixed = cut(base.join(ins, "id").repartition(self.parts, "id").sortWithinPartitions("id").select("id", F.col("out_degree").cast("double").alias("out_degree"), "in_degree", "rank"))
        self.size = self.fixed.count()
        self.start = self.fixed.select("id", "out_degree", "in_degree", "rank", F.lit(False).alias("frozen"), F.lit(False).alias("quiet"))

    def sums(self, state: DataFrame) -> DataFrame:
        """(dst, total): the shares that reach each vertex."""
        cfg = self.cfg
        slots = self.slots(self.edges, state)
        if self.hubs is not None:
            of_hubs = F.broadcast(state.join(F.broadcast(self.hubs), F.col("id") == F.col("hub"), "left_semi"))
            slots = slots.unionByName(self.slots(self.hub_edges, of_hubs, state))
        if self.method == "sync_edge" and not cfg.fused:
            slots = cut(slots)
        aggregates = [_total(cfg, F.col("value"), F.col("src")).alias("total")]
        if cfg.freeze:
            aggregates.append(F.max("moved").alias("stirred"))
        return slots.groupBy("dst").agg(*aggregates)

    def slots(self, edges: DataFrame, state: DataFrame, every: DataFrame | None = None) -> DataFrame:
        """(src, dst, value): the share on each of the edges whose sources are in ``state``; ``every`` is the state of all."""
        cfg = self.cfg
        more = ["moved"] if cfg.freeze else []
        if 0 < self.frozen <= BROADCAST_ROWS and cfg.freeze_guard == "paper":
            # settled vertices need no sum: their in-edges are left out before anything is moved;
            # beyond the bound the sums are taken and not used, as the edges lie by source
            edges = edges.join(F.broadcast((state if every is None else every).where("frozen").select(F.col("id").alias("dst"))), "dst", "left_anti")
        if self.method == "sync_edge":
            shares = state.where("out_degree > 0").select("id", (F.col("rank") / F.col("out_degree")).alias("share"), *more)
            value = F.col("share") * F.col("mult")
        else:
            shares = state.select("id", "rank", *more)
            value = F.col("rank") * F.col("coef")
        if every is not None:
            shares = F.broadcast(shares)  # hubs only
        return edges.join(shares, F.col("src") == F.col("id")).select("src", "dst", value.alias("value"), *more)

    def blind_step(self, state: DataFrame, lost: float = 0.0) -> DataFrame:
        """The next state without a look at the change: it reads the state once, so such steps can be chained in a plan."""
        cfg = self.cfg
        base = (1 - cfg.damping) / max(self.n, 1) + cfg.damping * lost / max(self.n, 1)
        joined = self.fixed.drop("rank").join(self.sums(state), F.col("id") == F.col("dst"), "left")
        return joined.select("id", "out_degree", "in_degree", (F.lit(base) + F.lit(cfg.damping) * F.coalesce("total", F.lit(0.0))).alias("rank"), F.lit(False).alias("frozen"), F.lit(False).alias("quiet"))

    def step(self, state: DataFrame, lost: float = 0.0) -> DataFrame:
        """The next state with delta, the absolute change."""
        cfg = self.cfg
        base = (1 - cfg.damping) / max(self.n, 1) + cfg.damping * lost / max(self.n, 1)
        if cfg.freeze:
            state = state.withColumn("moved", F.col("quiet") == F.lit(False))
        joined = state.join(self.sums(state), F.col("id") == F.col("dst"), "left")
        fresh = F.lit(base) + F.lit(cfg.damping) * F.coalesce("total", F.lit(0.0))
        if not cfg.freeze:
            return joined.select("id", "out_degree", "in_degree", fresh.alias("new"), "rank", "frozen", "quiet").select(
                "id", "out_degree", "in_degree", F.col("new").alias("rank"), F.abs(F.col("new") - F.col("rank")).alias("delta"), "frozen", "quiet", F.lit(True).alias("worked")
            )
        limit = F.lit(cfg.freeze_factor * cfg.bound(self.n))
        if cfg.freeze_guard == "paper":
            worked = ~F.col("frozen")
            new = F.when(worked, fresh).otherwise(F.col("rank"))
            change = F.abs(new - F.col("rank"))
            small = (change < limit) & (change != 0)
            frozen = F.col("frozen") | small
            quiet = F.lit(False)
        else:
            # settled only after two quiet steps, and awake again when an input moves
            worked = ~F.col("frozen") | F.coalesce("stirred", F.lit(False))
            new = F.when(worked, fresh).otherwise(F.col("rank"))
            change = F.abs(new - F.col("rank"))
            small = change < limit
            frozen = small & (F.col("quiet") | F.col("frozen")) & ~F.coalesce("stirred", F.lit(False))
            quiet = small
        return joined.select("id", "out_degree", "in_degree", new.alias("rank"), change.alias("delta"), frozen.alias("frozen"), quiet.alias("quiet"), worked.alias("worked"))


def _run(graph: Graph, cfg: RankConfig, method: str) -> RankResult:
    cfg.only(method, inner_sweeps=[1], staleness=[0], dangling=["leak", "redistribute"], freeze_guard=["paper", "safe"], sum_mode=["double", "ordered", "decimal"])
    if cfg.twins:
        return on_classes(graph, cfg, lambda g, c: _run(g, c, method))
    with loop_settings(graph.spark, cfg.partitions):
        loop = _Loop(graph, cfg, method)
        state, history, reason, at = loop.start, [], "max_iter", 0
        bound = cfg.bound(loop.n)
        if not loop.n:
            return RankResult(graph.vertices.select("id", F.lit(0.0).alias("rank")), method, 0, True, "empty")
        best, stalled = float("inf"), 0
        while at < cfg.max_iter:
            began = time.time()
            run = min(cfg.check_every, cfg.max_iter - at)
            for k in range(run):
                lost = 0.0
                if cfg.dangling == "redistribute":
                    state = cut(state) if k else state
                    lost = state.where("out_degree = 0").agg(F.sum("rank")).first()[0] or 0.0
                last = k == run - 1
                if last and k and not cfg.freeze:
                    state = cut(state)  # a step that looks at the change reads it twice
                state = loop.step(state, lost) if last or cfg.freeze else loop.blind_step(state, lost)
                if not last and (cfg.freeze or k % CHAIN == CHAIN - 1):
                    state = cut(state)
            seen = Observation()
            worked = F.col("worked")
            state = state.observe(seen, F.max("delta").alias("max_delta"), F.sum("delta").alias("l1_delta"), F.count_if(worked).alias("active"), F.sum(F.when(worked, F.col("in_degree")).otherwise(0)).alias("edges_touched"))
            state = cut(state).select("id", "out_degree", "in_degree", "rank", "frozen", "quiet")
            at += run
            found = seen.get
            loop.frozen = loop.size - found["active"] if cfg.freeze else 0
            history.append({"iteration": at, "block": None, **found, "seconds": time.time() - began})
            if found["max_delta"] <= bound:
                reason = "converged"
                break
            stalled = stalled + 1 if found["max_delta"] >= best else 0
            best = min(best, found["max_delta"])
            if stalled >= 25:
                reason = "stalled"
                break
        return RankResult(state.select("id", "rank"), method, at, reason == "converged", reason, history)


def block_errors(before: DataFrame, after: DataFrame, block_of: DataFrame) -> DataFrame:
    """(block, max_delta): each block's largest change between two rank frames."""
    joined = after.select("id", F.col("rank").alias("_new")).join(before.select("id", F.col("rank").alias("_old")), "id").join(block_of, "id")
    return joined.groupBy("block").agg(F.max(F.abs(F.col("_new") - F.col("_old"))).alias("max_delta"))


def global_error(errors: DataFrame) -> float:
    return errors.agg(F.max("max_delta")).first()[0] or 0.0


__all__ = ["sync_pull", "sync_edge", "initial_ranks", "block_errors", "global_error"]
