"""Synchronous ranking in which idle workers finish others' blocks.

Workers are driver threads that submit a job for one block of one step. A worker first
takes its own block, then any block of the step that is not committed yet, the one that
was begun longest ago first, also if another worker is at it. A block's result is
committed only if the block still carries the step's stamp, so the first writer wins
and later results are dropped. Any worker that finds all blocks committed closes the
step. A run ends as long as one worker lives.
"""

from __future__ import annotations

import threading
import time

from pyspark import InheritableThread
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from linkrank.config import RankConfig, RankResult
from linkrank.graph import Graph
from linkrank.operators.asynchronous import STATE, _Layout
from linkrank.operators.faults import FaultPlan, WorkerFailed
from linkrank.operators.twins import on_classes
from linkrank.plans.lineage import cut, loop_settings


class Ledger:
    """Stamps of blocks and the committed results of the current step."""

    def __init__(self, blocks, bound: float, max_iter: int):
        self.lock = threading.Lock()
        self.blocks, self.bound, self.max_iter = sorted(blocks), bound, max_iter
        self.iteration = 1
        self.stamp = {b: 1 for b in self.blocks}  # the step a block's next result is for
        self.begun: dict[int, float] = {}
        self.results: dict[int, tuple[DataFrame, float]] = {}
        self.rows: list[dict] = []
        self.previous: DataFrame | None = None
        self.error = float("inf")

    def next_task(self, worker: int) -> tuple[int, int] | None:
        """(iteration, block) to work on: the worker's own, else the longest begun of those not committed."""
        with self.lock:
            left = [b for b in self.blocks if b not in self.results]
            if not left:
                return None
            own = self.blocks[worker % len(self.blocks)]
            pick = own if own in left and own not in self.begun else min(left, key=lambda b: self.begun.get(b, 0.0))
            self.begun.setdefault(pick, time.time())
            return self.iteration, pick

    def commit(self, iteration: int, block: int, worker: int, result: DataFrame, error: float) -> bool:
        """Takes a result if the block still has the step's stamp; says whether it did."""
        with self.lock:
            won = self.stamp[block] == iteration and self.iteration == iteration
            self.rows.append({"iteration": iteration, "block": block, "worker": worker, "max_delta": error, "won": won})
            if won:
                self.stamp[block] = iteration + 1
                self.results[block] = (result, error)
            return won

    def close(self, iteration: int) -> bool:
        """Ends the step if all blocks are committed; harmless if another worker has done so."""
        with self.lock:
            if self.iteration != iteration or len(self.results) < len(self.blocks):
                return False
            state = None
            for b in self.blocks:
                state = self.results[b][0] if state is None else state.unionByName(self.results[b][0])
            self.error = max(e for _, e in self.results.values())
            self.previous, self.results, self.begun = state, {}, {}
            self.iteration += 1
            return True

    @property
    def done(self) -> bool:
        return self.error <= self.bound or self.iteration > self.max_iter


def sync_helped(graph: Graph, cfg: RankConfig = RankConfig(), workers: int = 4, faults: FaultPlan | None = None, help_others: bool = True) -> RankResult:
    """Ranks by ``workers`` that share the blocks of a step.

    ``help_others=False``: each worker does its own blocks only and waits for the rest,
    as with a barrier; then a dead worker blocks the run, which the timeout reports.
    """
    cfg.only("sync_helped", inner_sweeps=[1], staleness=[0], sum_mode=["double", "ordered"], freeze_guard=["paper"], dangling=["leak", "redistribute"])
    if cfg.twins:
        return on_classes(graph, cfg, lambda g, c: sync_helped(g, c, workers, faults, help_others))
    faults = faults or FaultPlan()
    with loop_settings(graph.spark, cfg.partitions):
        layout = _Layout(graph, cfg)
        if not layout.n:
            return RankResult(graph.vertices.select("id", F.lit(0.0).alias("rank")), "sync_helped", 0, True, "empty")
        ledger = Ledger(layout.size, cfg.bound(layout.n), cfg.max_iter)
        ledger.previous = layout.start()
        stop = threading.Event()
        dead: list[int] = []
        busy: set[int] = set()
        seconds: list[float] = [time.time()]

        def compute(block: int) -> tuple[DataFrame, float]:
            seen, before = Observation(), ledger.previous
            result = cut(layout.swept(before, [block], True, layout.lost(before)).observe(seen, F.max("delta").alias("m")))
            return result, float(seen.get["m"] or 0.0)

        def worker(w: int) -> None:
            slept: set[int] = set()
            try:
                while not ledger.done and not stop.is_set():
                    at = ledger.iteration
                    if at not in slept:
                        slept.add(at)
                        faults.before(at, w)
                    if help_others:
                        task = ledger.next_task(w)
                    else:
                        own = [b for k, b in enumerate(ledger.blocks) if k % workers == w and b not in ledger.results]
                        task = (ledger.iteration, own[0]) if own else None
                    if task is None:
                        if ledger.close(at):
                            seconds.append(time.time())
                        else:
                            time.sleep(0.01)
                        continue
                    iteration, block = task
                    if iteration == ledger.iteration:
                        busy.add(w)
                        try:
                            result, error = compute(block)
                        finally:
                            busy.discard(w)
                        ledger.commit(iteration, block, w, result, error)
                    if ledger.close(iteration):
                        seconds.append(time.time())
            except WorkerFailed:
                dead.append(w)

        threads = [InheritableThread(target=worker, args=(w,), daemon=True) for w in range(workers)]
        for t in threads:
            t.start()
        worked = time.time()  # a run is blocked when nobody has worked for the timeout, however long its steps take
        while any(t.is_alive() for t in threads) and not ledger.done and (faults.timeout is None or time.time() < worked + faults.timeout):
            if busy:
                worked = time.time()
            time.sleep(0.02)
        stop.set()
        # sleepers may still sleep: nobody waits for them once the last step is closed
        reason = "converged" if ledger.error <= ledger.bound else "max_iter" if ledger.iteration > cfg.max_iter else "failed" if len(dead) == workers else "blocked"
        history = []
        for k in range(1, ledger.iteration):
            own = [r for r in ledger.rows if r["iteration"] == k and r["won"]]
            history.append({"iteration": k, "block": None, "max_delta": max(r["max_delta"] for r in own), "active": layout.n, "edges_touched": sum(layout.edges.values()), "seconds": seconds[k] - seconds[k - 1] if k < len(seconds) else None})
        found = RankResult(ledger.previous.select("id", "rank"), "sync_helped", ledger.iteration - 1, reason == "converged", reason, history)
        found.ledger = ledger.rows
        found.dead = dead
        return found


__all__ = ["Ledger", "sync_helped", "STATE"]
