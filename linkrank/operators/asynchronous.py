"""Barrier-free ranking by blocks that sweep their vertices in place.

Schedules:

rounds: all blocks sweep side by side against the values of the last exchange; the one
    that scales, as a round is one job of block tasks and moves arrays only (module rounds).
sweep, adversarial: replayed in one task, for small graphs.
free: a driver thread for each block submits its own jobs and publishes versions; no
    thread waits for another. Not deterministic.

A block's error is the change of what it publishes. A block is left out of a round once
its own error and its inputs' are small, and comes back when an input moves.
"""

from __future__ import annotations

import threading
import time
from dataclasses import replace

import numpy as np
import pyarrow as pa
from pyspark import InheritableThread
from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from linkrank.config import RankConfig, RankResult
from linkrank.graph import Graph, assign_blocks, csr_blocks, mirrors
from linkrank.operators.kernel import Block, sweep, sweep_shares
from linkrank.operators.rounds import PackedBlocks
from linkrank.operators.sequential import replayed
from linkrank.operators.synchronous import initial_ranks
from linkrank.operators.twins import on_classes
from linkrank.plans.lineage import cut, loop_settings

STATE = "block int, id long, rank double, frozen boolean, delta double"


def async_pull(graph: Graph, cfg: RankConfig = RankConfig(), schedule: str = "rounds", faults=None) -> RankResult:
    """In-place sweeps: a vertex reads what its block's earlier vertices have just written."""
    return _run(graph, cfg, schedule, False, "uniform", faults)


def async_edge(graph: Graph, cfg: RankConfig = RankConfig(), schedule: str = "rounds", seed: str = "uniform", faults=None) -> RankResult:
    """Sweeps over shares held since the block's last pass; may fail to converge within max_iter, and then says so.

    ``seed="zero"``: the first pass reads shares of 0, as if none was written yet.
    """
    return _run(graph, cfg, schedule, True, seed, faults)


def block_kernel(cfg: RankConfig, n: int, edge_form: bool, lost: float = 0.0):
    """Sweeps one block: its arrays on the left, the ranks it reads on the right; ``lost`` is the rank without out-links to spread."""
    base, limit = (1 - cfg.damping) / max(n, 1) + cfg.damping * lost / max(n, 1), cfg.freeze_factor * cfg.bound(n)
    work = sweep_shares if edge_form else sweep
    cfg = replace(cfg, init="uniform")  # a frame to start from stays with the driver

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return pa.table({"block": pa.array([], pa.int32()), "id": pa.array([], pa.int64()), "rank": pa.array([], pa.float64()), "frozen": pa.array([], pa.bool_()), "delta": pa.array([], pa.float64())})
        arrays = [left.column(k)[0].values.to_numpy() for k in ("ids", "in_ptr", "in_src", "in_coef")]
        block = Block.of(*arrays)
        at = np.searchsorted(block.inputs, right.column("read_id").to_numpy())
        rank, frozen = np.zeros(len(block.inputs)), np.zeros(len(block.inputs), bool)
        rank[at] = right.column("read_rank").to_numpy()
        frozen[at] = right.column("read_frozen").to_numpy(zero_copy_only=False)
        frozen = frozen[block.own]
        before = rank[block.own]
        active = ~frozen if cfg.freeze else None
        for _ in range(cfg.inner_sweeps):
            work(block, rank, base, cfg.damping, active)
        change = np.abs(rank[block.own] - before)
        if cfg.freeze:
            frozen |= (change > 0) & (change < limit)
        return pa.table({"block": pa.array(np.full(len(block.ids), left.column("block")[0].as_py()), pa.int32()), "id": block.ids, "rank": rank[block.own], "frozen": pa.array(frozen), "delta": change})

    return run


class _Layout:
    """Blocks, their arrays, what each reads, and which blocks feed which."""

    def __init__(self, graph: Graph, cfg: RankConfig):
        self.graph, self.cfg, self.n = graph, cfg, graph.count()
        self.block_of = cut(assign_blocks(graph, cfg.blocks, cfg.block_how))
        self.csr = cut(csr_blocks(graph, self.block_of))
        seen = mirrors(graph, self.block_of)
        own = self.block_of.select(F.col("id").alias("src"), F.col("block").alias("dst_block"))
        self.reads = cut(seen.unionByName(own).distinct())
        feeds = self.reads.join(self.block_of.select(F.col("id").alias("src"), F.col("block").alias("src_block")), "src").select("src_block", "dst_block").distinct()
        self.feeds = cut(feeds)  # up to blocks ** 2 rows
        self.size = {r["block"]: r["count"] for r in self.block_of.groupBy("block").count().collect()}
        self.edges = {r["block"]: r["m"] for r in self.csr.select("block", F.size("in_src").alias("m")).collect()}

    def start(self) -> DataFrame:
        ranks = initial_ranks(self.graph, self.cfg, self.n)
        return cut(ranks.join(self.block_of, "id").select("block", "id", "rank", F.lit(False).alias("frozen"), F.lit(0.0).alias("delta")))

    def of_blocks(self, frame: DataFrame, key: str, blocks, how: str = "left_semi") -> DataFrame:
        """The rows of some blocks; ``blocks`` None: all."""
        if blocks is None:
            return frame if how == "left_semi" else frame.limit(0)
        own = self.graph.spark.createDataFrame([(b,) for b in sorted(blocks)], "_block int")
        return frame.join(F.broadcast(own), F.col(key) == F.col("_block"), how)  # at most a row for each block

    def swept(self, state: DataFrame, blocks, edge_form: bool, lost: float = 0.0) -> DataFrame:
        """The new state of the given blocks; of all if None."""
        values = state.select(F.col("id").alias("read_id"), F.col("rank").alias("read_rank"), F.col("frozen").alias("read_frozen"))
        inputs = self.of_blocks(self.reads, "dst_block", blocks).join(values, F.col("src") == F.col("read_id")).select("dst_block", "read_id", "read_rank", "read_frozen")
        arrays = self.of_blocks(self.csr, "block", blocks)
        return arrays.groupBy("block").cogroup(inputs.groupBy("dst_block")).applyInArrow(block_kernel(self.cfg, self.n, edge_form, lost), STATE)

    def lost(self, state: DataFrame) -> float:
        """The rank of vertices without out-links, where it is to be spread."""
        if self.cfg.dangling == "leak":
            return 0.0
        without = self.graph.vertices.where("out_degree = 0").select("id")
        return state.join(without, "id", "left_semi").agg(F.sum("rank")).first()[0] or 0.0

    def read_by(self) -> dict[int, set[int]]:
        """Of each block those it reads; for schedules with a driver thread for each block."""
        found: dict[int, set[int]] = {}
        for r in self.feeds.collect():
            found.setdefault(r.dst_block, set()).add(r.src_block)
        return found


def _run(graph: Graph, cfg: RankConfig, schedule: str, edge_form: bool, seed: str, faults) -> RankResult:
    if schedule not in ("rounds", "free", "sweep", "adversarial"):
        raise ValueError(schedule)
    spread = ["leak"] if schedule == "free" else ["leak", "redistribute"]  # no two blocks of a free run see one sum of all
    cfg.only(f"async:{schedule}", sum_mode=["double", "ordered"], freeze_guard=["paper"], dangling=spread, staleness=[cfg.staleness if schedule == "adversarial" else 0])
    if cfg.twins:
        return on_classes(graph, cfg, lambda g, c: _run(g, c, schedule, edge_form, seed, faults))
    if edge_form and seed == "zero":
        # what a block that reads nothing but zeros writes first
        cfg = replace(cfg, init=graph.vertices.select("id", F.lit((1 - cfg.damping) / max(graph.count(), 1)).alias("rank")))
    if schedule in ("sweep", "adversarial"):
        return replayed(graph, cfg, schedule, edge_form)
    name = f"async_{'edge' if edge_form else 'pull'}:{schedule}"
    few = max(8, 4 * cfg.blocks)  # a round's rows are blocks and what they send
    with loop_settings(graph.spark, cfg.partitions or (min(few, int(graph.spark.conf.get("spark.sql.shuffle.partitions"))) if schedule == "rounds" else None)):
        if not graph.count():
            return RankResult(graph.vertices.select("id", F.lit(0.0).alias("rank")), name, 0, True, "empty")
        if schedule == "rounds":
            return _rounds(PackedBlocks(graph, cfg, edge_form), cfg, edge_form, name, faults)
        return _free(_Layout(graph, cfg), cfg, edge_form, name, faults)


def _rounds(layout: PackedBlocks, cfg: RankConfig, edge_form: bool, name: str, faults) -> RankResult:
    sent, history, own = layout.start(), [], {b: 0 for b in layout.size}
    errors = {b: float("inf") for b in layout.size}
    bound, active, at, reason = cfg.bound(layout.n), set(layout.size), 0, "not_converged" if edge_form else "max_iter"
    seen = layout.seen(sent)
    while at < cfg.max_iter:
        began = time.time()
        if faults:
            faults.sleep_all(at + 1)
        idle = set(layout.size) - active
        lost = sum(r.lost for r in sorted(seen)) if cfg.dangling == "redistribute" else 0.0
        sent = layout.round(sent, active if idle else None, lost)
        seen = layout.seen(sent)
        at += 1
        for r in seen:
            if r.src in idle:
                continue
            errors[r.src] = r.m
            own[r.src] += 1
            history.append({"iteration": at, "block": r.src, "max_delta": r.m, "l1_delta": r.s, "active": r.a, "edges_touched": layout.edges.get(r.src, 0), "seconds": time.time() - began})
        for b in idle:
            errors[b] = 0.0
        active = layout.fed_by({b for b in layout.size if errors[b] > bound})
        if not active:
            reason = "converged"
            break
    return RankResult(layout.ranks(sent), name, at, reason == "converged", reason, history, own)


def _free(layout: _Layout, cfg: RankConfig, edge_form: bool, name: str, faults) -> RankResult:
    lock = threading.Lock()
    start = layout.start()
    versions = {b: start.where(F.col("block") == b) for b in layout.size}
    errors = {b: float("inf") for b in layout.size}
    stamp = {b: 0 for b in layout.size}
    own, history, failed = {b: 0 for b in layout.size}, [], []
    bound, reads = cfg.bound(layout.n), layout.read_by()

    def worker(b: int) -> None:
        try:
            read: dict[int, int] = {}
            while own[b] < cfg.max_iter:
                began = time.time()
                if faults:
                    faults.before(own[b] + 1, b)
                with lock:
                    newest = {c: stamp[c] for c in reads.get(b, {b}) | {b}}
                    state = None
                    for c in sorted(newest):
                        state = versions[c] if state is None else state.unionByName(versions[c])
                if newest == read and errors[b] <= bound:
                    with lock:
                        if all(e <= bound for e in errors.values()):
                            return
                    time.sleep(0.05)  # nothing new to read
                    continue
                seen = Observation()
                fresh = cut(layout.swept(state, [b], edge_form).observe(seen, F.max("delta").alias("m")))
                with lock:
                    versions[b], errors[b] = fresh, float(seen.get["m"] or 0.0)
                    stamp[b] += errors[b] > bound  # smaller changes are published, but wake no reader
                    read = newest | {b: stamp[b]}
                    own[b] += 1
                    history.append({"iteration": own[b], "block": b, "max_delta": errors[b], "active": layout.size[b], "edges_touched": layout.edges.get(b, 0), "seconds": time.time() - began})
        except Exception as error:  # noqa: BLE001  a dead worker must be reported, not hang the others
            failed.append((b, error))
            with lock:
                errors[b] = float("inf")

    threads = [InheritableThread(target=worker, args=(b,), daemon=True) for b in layout.size]
    for t in threads:
        t.start()
    deadline = None if faults is None or faults.timeout is None else time.time() + faults.timeout
    for t in threads:
        t.join(None if deadline is None else max(0.0, deadline - time.time()))
    blocked = any(t.is_alive() for t in threads)
    with lock:
        for b in layout.size:
            own[b] = max(own[b], cfg.max_iter) if blocked else own[b]  # lets waiting workers end
        state = None
        for b in sorted(versions):
            state = versions[b] if state is None else state.unionByName(versions[b])
        small = all(e <= bound for e in errors.values())
    reason = "blocked" if blocked or failed else "converged" if small else "not_converged" if edge_form else "max_iter"
    return RankResult(cut(state).select("id", "rank"), name, max((h["iteration"] for h in history), default=0), reason == "converged", reason, history, {b: sum(h["block"] == b for h in history) for b in layout.size})
