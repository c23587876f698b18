"""Rounds of block sweeps: all blocks side by side, each against what others sent after the round before.

A block is packed once: its in-edges by what their source is to a sweep. ``outer`` sources
lie in other blocks and keep their ranks for a round, ``late`` ones are read before they
are written, ``early`` ones after. Rounds move no vertex as a row: a block sends each
block that reads it the ranks read there, as one array, and itself all of its own.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkrank.config import RankConfig
from linkrank.graph import Graph, assign_blocks
from linkrank.operators.kernel import _ranges
from linkrank.operators.synchronous import initial_ranks
from linkrank.plans.lineage import cut

RUN = 1 << 20  # edges that a task puts together before it hands them on
SUM = 1 << 16  # edges that are summed at a time, so that their values stay near the processor
ARRAYS = {
    "ids": "<i8", "sinks": "<i4", "outer_rows": "<i4", "outer_starts": "<i8", "outer_src": "<i4", "outer_coef": "<f8", "late_rows": "<i4", "late_starts": "<i8", "late_src": "<i4", "late_coef": "<f8",
    "early_rows": "<i4", "early_starts": "<i8", "early_src": "<i4", "early_coef": "<f8", "levels": "<i8", "share": "<f8", "outer_share": "<f8",
}
PACKED = "block int, n int, m long, start binary, outside array<long>, " + ", ".join(f"{k} binary" for k in ARRAYS)
SENT = "dst int, src int, at binary, rank binary, frozen binary, m double, s double, a long, lost double"


def _joined(column: pa.ChunkedArray, kind: str) -> np.ndarray:
    return np.concatenate([np.zeros(0, kind), *(np.frombuffer(v.as_buffer(), kind) for v in column if v.is_valid)])


def _gather(kinds: dict[str, str]):
    """Rows to arrays: a row for each block of some RUN rows of a task."""

    def flush(held: list[pa.RecordBatch]):
        table = pa.Table.from_batches(held)
        block = table.column("block").to_numpy()
        order = np.argsort(block, kind="stable")
        cuts = np.flatnonzero(np.diff(block[order])) + 1
        columns = {k: table.column(k).to_numpy()[order].astype(kind) for k, kind in kinds.items()}
        firsts = block[order][np.append(0, cuts)].astype(np.int32)
        yield pa.record_batch([pa.array(firsts), *(pa.array([part.tobytes() for part in np.split(v, cuts)], pa.binary()) for v in columns.values())], names=["block", *kinds])

    def gather(batches):
        held, size = [], 0
        for batch in batches:
            if len(batch):
                held.append(batch)
                size += len(batch)
            if size >= RUN:
                yield from flush(held)
                held, size = [], 0
        if held:
            yield from flush(held)

    return gather


def _levels(n: int, src: np.ndarray, dst: np.ndarray) -> np.ndarray:
    """Of each vertex: 0 if it reads none of these edges, else one more than the largest level it reads."""
    level, waits = np.zeros(n, np.int32), np.bincount(dst, minlength=n)
    order = np.argsort(src, kind="stable")
    first, readers = np.searchsorted(src[order], np.arange(n + 1)), dst[order]
    group, at = np.flatnonzero(waits == 0), 0
    while len(group):
        level[group] = at
        at += 1
        freed, times = np.unique(readers[_ranges(first[group], first[group + 1])], return_counts=True)
        waits[freed] -= times
        group = freed[waits[freed] == 0]
    return level


def _by_row(name: str, row: np.ndarray, src: np.ndarray, coef: np.ndarray) -> dict[str, np.ndarray]:
    starts = np.flatnonzero(np.diff(row, prepend=-1))
    return {f"{name}_rows": row[starts], f"{name}_starts": starts, f"{name}_src": src, f"{name}_coef": coef}


def packed(ids: np.ndarray, src: np.ndarray, dst: np.ndarray, coef: np.ndarray, edge_form: bool) -> tuple[dict[str, np.ndarray], np.ndarray]:
    """A block's arrays from its sorted vertices and their in-edges, and the vertices of others that it reads."""
    row, at = np.searchsorted(ids, dst), np.minimum(np.searchsorted(ids, src), len(ids) - 1)
    inside = ids[at] == src
    outside, place = np.unique(src[~inside], return_inverse=True)
    order = np.argsort(row[~inside] * max(len(outside), 1) + place, kind="stable")
    found = _by_row("outer", row[~inside][order], place[order], coef[~inside][order])
    order = np.flatnonzero(inside)
    order = order[np.argsort(row[order] * len(ids) + at[order], kind="stable")]
    row, at, coef = row[order], at[order], coef[order]
    early = np.zeros(len(row), bool) if edge_form else at < row  # the edge form reads nothing of the pass itself
    found |= _by_row("late", row[~early], at[~early], coef[~early])
    row, at, coef = row[early], at[early], coef[early]
    level = _levels(len(ids), at, row)
    order = np.argsort(level[row], kind="stable")
    found |= _by_row("early", row[order], at[order], coef[order])
    levels = np.searchsorted(level[found["early_rows"]], np.arange(1, int(level.max(initial=0)) + 2))
    found |= _by_source(found, len(ids), len(outside))
    return found | {"ids": ids, "levels": levels}, outside


def _by_source(found: dict[str, np.ndarray], n: int, others: int) -> dict[str, np.ndarray]:
    """``share`` of each vertex and ``outer_share`` of each of others, in place of an edge's, where all of a source's edges have one; else none."""
    share, outer_share = np.zeros(n), np.zeros(others)
    of = (("outer", outer_share), ("late", share), ("early", share))
    for name, to in of:
        to[found[f"{name}_src"]] = found[f"{name}_coef"]
    none = np.zeros(0)
    if any(not np.array_equal(to[found[f"{name}_src"]], found[f"{name}_coef"]) for name, to in of):
        return {"share": none, "outer_share": none}
    return {"share": share, "outer_share": outer_share} | {f"{name}_coef": none for name, _ in of}


def _pack(edge_form: bool):
    def pack(group: pa.Table) -> pa.Table:
        ids, start, sink = _joined(group.column("id"), "<i8"), _joined(group.column("start"), "<f8"), _joined(group.column("sink"), "?")
        order = np.argsort(ids)
        edges = [_joined(group.column(k), kind) for k, kind in (("src", "<i8"), ("dst", "<i8"), ("coef", "<f8"))]
        arrays, outside = packed(ids[order], *edges, edge_form)
        arrays["sinks"] = np.flatnonzero(sink[order])
        one = {"block": pa.array([group.column("block")[0].as_py()], pa.int32()), "n": pa.array([len(ids)], pa.int32()), "m": pa.array([len(edges[0])], pa.int64()), "start": pa.array([start[order].tobytes()], pa.binary())}
        one["outside"] = pa.ListArray.from_arrays(pa.array([0, len(outside)], pa.int32()), pa.array(outside, pa.int64()))
        return pa.table(one | {k: pa.array([arrays[k].astype(kind).tobytes()], pa.binary()) for k, kind in ARRAYS.items()})

    return pack


def _address(own: pa.Table, needs: pa.Table) -> pa.Table:
    """(block, reader, mine, place): which of its ranks a block sends to each reader, and where they belong there."""
    rows = []
    if needs.num_rows:
        ids = np.frombuffer(own.column("ids")[0].as_buffer(), "<i8")
        reader, place = needs.column("reader").to_numpy(), needs.column("place").to_numpy()
        mine = np.searchsorted(ids, needs.column("id").to_numpy())
        order = np.argsort(reader, kind="stable")
        for part in np.split(order, np.flatnonzero(np.diff(reader[order])) + 1):
            rows.append((own.column("block")[0].as_py(), int(reader[part[0]]), mine[part].astype("<i4").tobytes(), place[part].astype("<i4").tobytes()))
    kinds = {"block": pa.int32(), "reader": pa.int32(), "mine": pa.binary(), "place": pa.binary()}
    return pa.table({k: pa.array([r[i] for r in rows], kind) for i, (k, kind) in enumerate(kinds.items())})


def _runs(starts: np.ndarray, lo: int, hi: int) -> list[tuple[int, int]]:
    """Ranges of the rows ``lo`` up to ``hi`` of some SUM edges each, at least a row."""
    if lo == hi:
        return []
    cuts = np.searchsorted(starts[lo:hi], np.arange(starts[lo], starts[hi], SUM), "right") - 1 + lo
    cuts = np.unique(np.append(cuts, (lo, hi)))
    return list(zip(cuts[:-1].tolist(), cuts[1:].tolist()))


class _Sums:
    """Sums over the in-edges of one kind of a packed block."""

    def __init__(self, name: str, block: dict):
        self.rows, self.src, self.coef = (block[f"{name}_{k}"] for k in ("rows", "src", "coef"))
        self.starts = np.append(block[f"{name}_starts"], len(self.src))
        self.all = _runs(self.starts, 0, len(self.rows))

    def of(self, lo: int, hi: int, values: np.ndarray) -> np.ndarray:
        """The sums of the rows ``lo`` up to ``hi``; values are ranks, or shares of ranks where no edge has its own."""
        a, b = self.starts[lo], self.starts[hi]
        read = values[self.src[a:b]]
        if len(self.coef):
            read *= self.coef[a:b]
        return np.add.reduceat(read, self.starts[lo:hi] - a)

    def add(self, values: np.ndarray, out: np.ndarray) -> None:
        for lo, hi in self.all:
            out[self.rows[lo:hi]] += self.of(lo, hi, values)


def passes(block: dict, rank: np.ndarray, outer: np.ndarray, base: float, damping: float, sweeps: int, active: np.ndarray | None = None) -> None:
    """Sweeps over a packed block, in place: vertices in id order read what those before them have just written.

    A sweep that changes no bit ends them, as all later ones would be the same.
    """
    by_source, share = len(block["share"]) > 0, block["share"]
    given = np.zeros(len(rank))
    _Sums("outer", block).add(outer * block["outer_share"] if by_source else outer, given)
    late, early, levels = _Sums("late", block), _Sums("early", block), np.append(0, block["levels"]).tolist()
    runs = [_runs(early.starts, lo, hi) for lo, hi in zip(levels[:-1], levels[1:])]
    first = np.ones(len(rank), bool)
    first[early.rows] = False
    if active is not None:
        first &= active
    read = rank * share if by_source else rank  # what an edge reads of its source
    for _ in range(sweeps):
        before, sums = rank.copy(), given.copy()
        late.add(read, sums)
        rank[first] = base + damping * sums[first]
        if by_source:
            read[first] = rank[first] * share[first]
        for level in runs:  # none of a level reads another
            for lo, hi in level:
                group = early.rows[lo:hi]
                new = base + damping * (sums[group] + early.of(lo, hi, read))
                rank[group] = new if active is None else np.where(active[group], new, rank[group])
                if by_source:
                    read[group] = rank[group] * share[group]
        if np.array_equal(rank, before):
            break


def _kernel(cfg: RankConfig, n: int, lost: float, sweeps: int):
    """A block's round: its arrays and addresses on the left, what was sent to it on the right."""
    base, limit, damping, freeze = (1 - cfg.damping) / max(n, 1) + cfg.damping * lost / max(n, 1), cfg.freeze_factor * cfg.bound(n), cfg.damping, cfg.freeze
    schema = pa.schema([("dst", pa.int32()), ("src", pa.int32()), ("at", pa.binary()), ("rank", pa.binary()), ("frozen", pa.binary()), ("m", pa.float64()), ("s", pa.float64()), ("a", pa.int64()), ("lost", pa.float64())])

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        if not left.num_rows:
            return schema.empty_table()
        reader = left.column("reader").to_pylist()
        place = reader.index(None)
        block = {k: np.frombuffer(left.column(k)[place].as_buffer(), kind) for k, kind in ARRAYS.items()}
        number, outer = left.column("block")[0].as_py(), np.zeros(left.column("outer")[place].as_py())
        for k, source in enumerate(right.column("src").to_pylist()):
            values = np.frombuffer(right.column("rank")[k].as_buffer(), "<f8")
            if source == number:
                rank, before, frozen = values.copy(), values, np.frombuffer(right.column("frozen")[k].as_buffer(), "?").copy()
            else:
                outer[np.frombuffer(right.column("at")[k].as_buffer(), "<i4")] = values
        passes(block, rank, outer, base, damping, sweeps, ~frozen if freeze else None)
        change = np.abs(rank - before)
        if freeze:
            frozen |= (change > 0) & (change < limit)
        rows = [(number, number, None, rank.tobytes(), frozen.tobytes(), float(change.max()), float(change.sum()), int((~frozen).sum()), float(rank[block["sinks"]].sum()))]
        for k, to in enumerate(reader):
            if to is not None:
                rows.append((to, number, left.column("place")[k].as_py(), rank[np.frombuffer(left.column("mine")[k].as_buffer(), "<i4")].tobytes(), None, None, None, None, None))
        return pa.table({f.name: pa.array([r[i] for r in rows], f.type) for i, f in enumerate(schema)}, schema=schema)

    return run


def _unpack(batches):
    for batch in batches:
        for ids, rank in zip(batch.column(0), batch.column(1)):
            ids, rank = np.frombuffer(ids.as_buffer(), "<i8"), np.frombuffer(rank.as_buffer(), "<f8")
            for lo in range(0, len(ids), 1 << 16):
                yield pa.record_batch([pa.array(ids[lo : lo + (1 << 16)]), pa.array(rank[lo : lo + (1 << 16)])], names=["id", "rank"])


class PackedBlocks:
    """Blocks packed for rounds, lying by block so that a round moves only what blocks send."""

    def __init__(self, graph: Graph, cfg: RankConfig, edge_form: bool):
        self.graph, self.cfg, self.n = graph, cfg, graph.count()
        if cfg.block_how == "hash":
            by_id = lambda frame, key: frame.withColumn("block", F.pmod(F.xxhash64(key), F.lit(cfg.blocks)).cast("int"))  # noqa: E731  as assign_blocks does
        else:
            block_of = cut(assign_blocks(graph, cfg.blocks, cfg.block_how))
            by_id = lambda frame, key: frame.join(block_of.withColumnRenamed("id", key), key)
        own = by_id(initial_ranks(graph, cfg, self.n), "id").select("block", "id", F.col("rank").alias("start"), (F.col("out_degree") == 0).alias("sink"))
        edges = by_id(graph.edges.select("src", "dst", "coef"), "dst").select("block", "src", "dst", "coef")
        own = own.mapInArrow(_gather({"id": "<i8", "start": "<f8", "sink": "?"}), "block int, id binary, start binary, sink binary")
        edges = edges.mapInArrow(_gather({"src": "<i8", "dst": "<i8", "coef": "<f8"}), "block int, src binary, dst binary, coef binary")
        self.packed = cut(own.unionByName(edges, allowMissingColumns=True).groupBy("block").applyInArrow(_pack(edge_form), PACKED))
        needs = self.packed.select(F.col("block").alias("reader"), F.posexplode("outside").alias("place", "id"))
        needs = by_id(needs, "id").select("block", "reader", "place", "id")
        sends = cut(self.packed.select("block", "ids").groupBy("block").cogroup(needs.groupBy("block")).applyInArrow(_address, "block int, reader int, mine binary, place binary"))
        self.feeds = cut(sends.select(F.col("block").alias("src_block"), F.col("reader").alias("dst_block")))  # up to blocks ** 2 rows: never collected
        rows = self.packed.select("block", F.size("outside").alias("outer"), *ARRAYS).unionByName(sends, allowMissingColumns=True)
        self.fixed = cut(rows.repartition("block").sortWithinPartitions("block"))
        found = self.packed.select("block", "n", "m").collect()  # a row for each block
        self.size, self.edges = {r.block: r.n for r in found}, {r.block: r.m for r in found}

    def of_blocks(self, frame: DataFrame, key: str, blocks, how: str = "left_semi") -> DataFrame:
        """The rows of some blocks; ``blocks`` None: all."""
        if blocks is None:
            return frame
        own = self.graph.spark.createDataFrame([(b,) for b in sorted(blocks)], "_block int")
        return frame.join(F.broadcast(own), F.col(key) == F.col("_block"), how)  # at most a row for each block

    def _swept(self, sent: DataFrame, blocks, lost: float, sweeps: int) -> DataFrame:
        left, right = self.of_blocks(self.fixed, "block", blocks), self.of_blocks(sent, "dst", blocks)
        return left.groupBy("block").cogroup(right.groupBy("dst")).applyInArrow(_kernel(self.cfg, self.n, lost, sweeps), SENT)

    def start(self) -> DataFrame:
        """What blocks send before the first round."""
        nothing = F.lit(b"")
        own = self.packed.select(F.col("block").alias("dst"), F.col("block").alias("src"), nothing.alias("at"), F.col("start").alias("rank"), F.unhex(F.repeat(F.lit("00"), F.col("n"))).alias("frozen"))
        return cut(self._swept(own, None, 0.0, 0))

    def round(self, sent: DataFrame, active, lost: float) -> DataFrame:
        """What blocks have sent after a round of the given blocks; of all if None."""
        fresh = self._swept(sent, active, lost, self.cfg.inner_sweeps)
        if active is not None:
            fresh = fresh.unionByName(self.of_blocks(sent, "src", active, "left_anti"))
        return cut(fresh)

    def seen(self, sent: DataFrame) -> list:
        """(src, m, s, a, lost) of each block: its largest change and their sum, vertices not frozen, rank without out-links."""
        return sent.where("dst = src").select("src", "m", "s", "a", "lost").collect()  # a row for each block

    def fed_by(self, loud: set[int]) -> set[int]:
        """The blocks that read one of the given blocks, these included."""
        if not loud or len(loud) == len(self.size):
            return loud
        return loud | {r[0] for r in self.of_blocks(self.feeds, "src_block", loud).select("dst_block").distinct().collect()}  # at most a row for each block

    def ranks(self, sent: DataFrame) -> DataFrame:
        own = sent.where("dst = src").select(F.col("src").alias("block"), "rank")
        return cut(self.packed.select("block", "ids").join(own, "block").select("ids", "rank").mapInArrow(_unpack, "id long, rank double"))
