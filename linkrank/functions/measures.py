"""Accuracy, work and time of ranking runs."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkrank.config import RankConfig, RankResult
from linkrank.graph import Graph


def distances(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: l1, linf and relative_l1 between two rank frames; a vertex missing on one side counts with rank 0."""
    joined = a.select("id", F.col("rank").alias("_a")).join(b.select("id", F.col("rank").alias("_b")), "id", "full")
    gap = F.abs(F.coalesce("_a", F.lit(0.0)) - F.coalesce("_b", F.lit(0.0)))
    return joined.agg(F.coalesce(F.sum(gap), F.lit(0.0)).alias("l1"), F.coalesce(F.max(gap), F.lit(0.0)).alias("linf"), F.coalesce(F.sum(gap) / F.sum(F.abs(F.coalesce("_b", F.lit(0.0)))), F.lit(0.0)).alias("relative_l1"))


def l1_norm(a: DataFrame, b: DataFrame) -> float:
    return float(distances(a, b).first()["l1"])


def top_overlap(a: DataFrame, b: DataFrame, k: int) -> float:
    """Share of the k highest ranked vertices that two frames have in common."""
    top = lambda r: r.orderBy(F.desc("rank"), "id").limit(k).select("id")
    return top(a).intersect(top(b)).count() / max(1, min(k, a.limit(k).count()))


def order_agreement(a: DataFrame, b: DataFrame, pairs: int = 16) -> float:
    """Share of vertex pairs that both frames put in one order, over ``pairs`` hash-chosen partners of each vertex."""
    joined = a.select("id", F.col("rank").alias("_a")).join(b.select("id", F.col("rank").alias("_b")), "id")
    agree = []
    for k in range(pairs):
        slot = F.pmod(F.xxhash64("id", F.lit(k)), F.lit(1 << 30))
        w = Window.partitionBy(F.pmod(F.xxhash64("id", F.lit(k + 1000)), F.lit(256))).orderBy(slot, "id")
        following = joined.select("_a", "_b", F.lead("_a").over(w).alias("_a2"), F.lead("_b").over(w).alias("_b2")).where("_a2 IS NOT NULL")
        agree.append(following.agg(F.avg((F.signum(F.round((F.col("_a") - F.col("_a2")), 12)) == F.signum(F.round((F.col("_b") - F.col("_b2")), 12))).cast("double"))).first()[0])
    found = [x for x in agree if x is not None]
    return sum(found) / len(found) if found else 1.0


def iterations(result: RankResult) -> DataFrame:
    """(block, iterations): of each block where blocks stop alone, else one row with a null block."""
    rows = sorted(result.block_iterations.items()) or [(None, result.iterations)]
    return result.ranks.sparkSession.createDataFrame(rows, "block int, iterations int")


def step_bound(tol: float, damping: float = 0.85) -> int:
    """Synchronous steps after which the largest change is at most tol, on any graph."""
    return 1 + math.ceil(math.log(tol / 2) / math.log(damping))


def distance_bound(n: int, tol: float, damping: float = 0.85, staleness: int = 1) -> float:
    """L1 distance to the fixed point of a run over n vertices that stopped at tol."""
    return damping / (1 - damping) * n * tol * max(1, staleness)


def convergence_report(result: RankResult, reference: DataFrame, n: int, cfg: RankConfig) -> dict:
    """A run's distance to a reference beside a tenth of the tolerance and the bound that holds for any graph."""
    l1 = l1_norm(result.ranks, reference)
    bound = distance_bound(n, cfg.bound(n), cfg.damping)
    return {"method": result.method, "l1": l1, "below_tenth": l1 < cfg.tol / 10, "bound": bound, "within_bound": l1 <= 2 * bound}


def timed(run: Callable[[], RankResult]) -> tuple[RankResult, float]:
    began = time.perf_counter()
    result = run()
    result.ranks.agg(F.sum("rank")).first()
    return result, time.perf_counter() - began


def runs_frame(spark: SparkSession, rows: list[dict]) -> DataFrame:
    """(graph, method, workers, seconds, iterations, l1, outcome) of measured runs."""
    names = ["graph", "method", "workers", "seconds", "iterations", "l1", "outcome"]
    return spark.createDataFrame([tuple(r.get(n) for n in names) for r in rows], "graph string, method string, workers int, seconds double, iterations int, l1 double, outcome string")


def speedup(runs: DataFrame, base: str = "sequential") -> DataFrame:
    """Runs with speedup: the base method's seconds over theirs, on the same graph."""
    bases = runs.where(F.col("method") == base).groupBy("graph").agg(F.min("seconds").alias("_base"))
    return runs.join(bases, "graph").select("graph", "method", "workers", "seconds", (F.col("_base") / F.col("seconds")).alias("speedup"))


def scaling(runs: DataFrame) -> DataFrame:
    """Runs with the ratio of the same method's seconds at its fewest workers."""
    w = Window.partitionBy("graph", "method")
    first = F.min(F.struct("workers", "seconds")).over(w)
    return runs.select("graph", "method", "workers", "seconds", (first["seconds"] / F.col("seconds")).alias("scaling"))


def compare(graph: Graph, name: str, methods: dict[str, Callable[[Graph], RankResult]], base: str = "sequential", repeats: int = 3) -> DataFrame:
    """Runs of several methods over one graph: median seconds, iterations, and L1 to the base method's ranks."""
    rows, reference = [], None
    for method in [base, *(m for m in methods if m != base)]:
        seconds = []
        for _ in range(repeats):
            result, took = timed(lambda: methods[method](graph))
            seconds.append(took)
        reference = result.ranks if method == base else reference
        rows.append({"graph": name, "method": method, "workers": None, "seconds": sorted(seconds)[len(seconds) // 2], "iterations": result.iterations, "l1": l1_norm(result.ranks, reference), "outcome": result.stop_reason})
    return runs_frame(graph.spark, rows)


ARRAYS = {"sync_pull": 2, "sync_edge": 2, "sync_helped": 2, "sequential": 2, "async_pull": 1, "async_edge": 1}


def rank_bytes(method: str, n: int) -> int:
    """Bytes of the ranks that a method keeps between steps: two arrays with barriers, one without."""
    return 8 * n * ARRAYS[method.partition(":")[0]]


def shuffle_bytes(spark: SparkSession, run: Callable[[], RankResult]) -> tuple[RankResult, int]:
    """A run and the bytes its stages wrote to shuffles, by the session's own record of stages."""
    store = spark.sparkContext._jsc.sc().statusStore()

    def total() -> int:
        spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty()
        none = spark.sparkContext._jvm.java.util.ArrayList()
        stages = store.stageList(none, False, False, spark.sparkContext._gateway.new_array(spark.sparkContext._jvm.double, 0), none)
        return sum(stages.apply(k).shuffleWriteBytes() for k in range(stages.size()))

    before = total()
    result = run()
    result.ranks.agg(F.sum("rank")).first()
    return result, total() - before


def progress(method: str) -> str:
    """Which workers must finish when others stall: blocking, lock-free or wait-free.

    Of the barrier-free methods (name:schedule) only the free schedule lets other blocks go
    on; a round, the default, waits for all its tasks, and the replays are one task.
    """
    name, _, schedule = method.partition(":")
    if name == "sync_helped":
        return "wait-free"
    return "lock-free" if name in ("async_pull", "async_edge") and schedule == "free" else "blocking"
