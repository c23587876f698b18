"""Exact Jaccard join of documents on word shingles.

A document is a row of a sparse 0/1 matrix whose columns are 5-word shingles; two
documents link if their rows' product is at least 0.8 of their union. The product is
never taken in full:

* Documents of equal sets are one vertex, known by the set's hash.
* Shingles have one order for all: those that counters of a fixed number found
  common in the corpus come last. By the sizes' bounds, two linked sets have at least min(l_a, l_b)
  of the first n - ceil(0.8 n) + l shingles in that order in common, with l about
  ``EXTRA`` of n, so only these entries of the matrix are moved.
* They are cut into blocks of columns. A column of up to ``SHORT`` vertices yields all
  their pairs, a longer one its pairs with one pivot. Pairs of fitting sizes are
  counted over all blocks; those that reach min(l_a, l_b) are verified on the whole
  sets.
* A linked pair not found so far has long columns in common. Columns whose vertices lie
  in one component by now are done. Of the others, vertices with too few long columns
  to reach the bound are left out, the rest is cut into clusters that share columns,
  and of each two chunks of a cluster the whole rows are multiplied in one task, which
  gives back only links.

So no link between components is missed, and no column yields all its pairs unless
they lie in different components. Words are `[^\\x20\\x09-\\x0D]+` with A-Z in lower
case; fewer than five are one shingle. Null, empty and blank texts have no shingle and
link with nothing. Repeated rows are copies of each other; a null id gets the
component of its copies, and is smallest nowhere.
"""

from __future__ import annotations

import math
import zlib

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkrank.llm.components import components, roots
from linkrank.llm.tables import cut, free, if_small, release, table
from linkrank.llm.text import LOWER, SLICE, mix, shingles, slices, utf8, word_hashes

QUERY = "op5_jaccard"

WORDS = 5
PART, WHOLE = 80, 100  # links: WHOLE * intersection >= PART * union
EXTRA = 0.05
SHORT = 48
COUNTERS = 1 << 22
SLICES = 32
RUN = 1 << 18  # shingles that are counted at a time
FAN = 64  # tasks whose counters are added up at a time
BLOCK_ENTRIES = 200_000
FLUSH = 1 << 17
PAIRS = 1 << 18  # pairs of a block that are held before equal ones are added up
RECENT = 1 << 17  # sets a task remembers, to pass over copies
CHUNK = 1024  # members of a cluster's chunk at most
CHUNK_SHINGLES = 1 << 18  # shingles of a chunk, about
TILE = 256  # rows that are multiplied at a time
PASSES = 3  # over the blocks of columns, and over the clusters of pairs, at most: what one moves is gone before the next
FEW_IDS = 200_000  # that are broadcast
PASS_SHINGLES = 1 << 23  # of the corpus for each pass, about

_ENTRY = np.dtype([("column", "<u4"), ("node", "<i8"), ("size", "<u4")])


def sets(column, keep=None):
    """(row, sorted distinct shingles) of each row with words."""
    data, offsets = utf8(column)
    for lo, hi in slices(offsets):
        if keep is not None and not keep[lo:hi].any():
            continue
        words, bounds = word_hashes(LOWER[data[offsets[lo] : offsets[hi]]], offsets[lo : hi + 1] - offsets[lo])
        for k in range(hi - lo):
            if bounds[k + 1] > bounds[k] and (keep is None or keep[lo + k]):
                found = np.sort(shingles(words[bounds[k] : bounds[k + 1]], WORDS))
                yield lo + k, found[np.concatenate(([True], found[1:] != found[:-1]))]


def set_hash(found: np.ndarray) -> int:
    return int(mix(found.sum(keepdims=True) + np.uint64(len(found))).view(np.int64)[0])


def extra(size):
    return np.maximum(1, np.floor(np.asarray(size) * EXTRA)).astype(np.int64)


def prefix_size(size: int) -> int:
    return min(size, size - -(-PART * size // WHOLE) + int(extra(size)))


def _count(counts: np.ndarray, pending: list[np.ndarray]) -> None:
    at, n = np.unique(np.concatenate(pending) & np.uint64(COUNTERS - 1), return_counts=True)
    counts[at] += n.astype(np.uint32)


def _summaries(batches):
    """A row for each document; at the end the task's counters of shingles, in slices (n_shingles: task, node: slice)."""
    counts = np.zeros(COUNTERS, np.uint32)
    names = ["doc_id", "n_shingles", "node", "counts"]
    for batch in batches:
        n, node = np.zeros(len(batch), np.int64), np.zeros(len(batch), np.int64)
        pending, held = [], 0
        for k, found in sets(batch.column(1)):
            n[k], node[k] = len(found), set_hash(found)
            pending.append(found)
            held += len(found)
            if held > RUN:
                _count(counts, pending)
                pending, held = [], 0
        if pending:
            _count(counts, pending)
        yield pa.record_batch([batch.column(0), n, node, pa.nulls(len(batch), pa.binary())], names=names)
    parts = [zlib.compress(x.astype(np.int64).tobytes(), 1) if x.any() else None for x in np.split(counts, SLICES)]
    some = [k for k, x in enumerate(parts) if x]
    task = TaskContext.get().partitionId() if TaskContext.get() else 0
    yield pa.record_batch([pa.nulls(len(some), pa.int64()), np.full(len(some), task), np.array(some, np.int64), pa.array([parts[k] for k in some], pa.binary())], names=names)


def _merge(group: pa.Table) -> pa.Table:
    total = np.zeros(COUNTERS // SLICES, np.int64)
    for raw in group.column("counts"):
        total += np.frombuffer(zlib.decompress(raw.as_py()), np.int64)
    return pa.table({"task": [group.column("task")[0].as_py() // FAN], "slice": [group.column("slice")[0].as_py()], "counts": pa.array([zlib.compress(total.tobytes(), 1)], pa.binary())})


def common(counts: np.ndarray) -> np.ndarray:
    """How far each counter lies above what the number of different shingles explains; 0 for most."""
    mean = counts.mean()
    return np.clip(counts - np.int64(2 + mean + 6 * np.sqrt(mean)), 0, (1 << 32) - 1).astype(np.uint32)


def _entries(shared, blocks: int, turn: int = 0, turns: int = 1):
    """The matrix entries of each set's prefix, by blocks of columns: (block, entries); of one in ``turns`` blocks."""

    def pack(held):
        rows = np.concatenate(held)
        order = np.argsort(rows["block"], kind="stable")
        rows = rows[order]
        cuts = np.flatnonzero(np.concatenate(([True], np.diff(rows["block"]) > 0)))
        bare = np.empty(len(rows), _ENTRY)
        for name in _ENTRY.names:
            bare[name] = rows[name]
        parts = [bare[a:b].tobytes() for a, b in zip(cuts, np.append(cuts[1:], len(rows)))]
        return pa.record_batch([pa.array(rows["block"][cuts], pa.int32()), pa.array(parts, pa.binary())], names=["block", "entries"])

    kind = np.dtype([("block", "<i4"), *_ENTRY.descr])

    def emit(batches):
        hot = shared.value
        held, size, recent = [], 0, np.zeros(RECENT, np.int64)
        for batch in batches:
            for _, found in sets(batch.column(0)):
                node = set_hash(found)
                if recent[node % RECENT] == node:
                    continue
                recent[node % RECENT] = node
                above = hot[found & np.uint64(COUNTERS - 1)]
                if above.any():
                    found = found[np.argsort(above, kind="stable")]
                columns = mix(found[: prefix_size(len(found))] + np.uint64(0x51ED270B))
                block = (columns >> np.uint64(32)) % np.uint64(blocks)
                if turns > 1:
                    own = block % np.uint64(turns) == turn
                    columns, block = columns[own], block[own]
                rows = np.empty(len(columns), kind)
                rows["block"] = block
                rows["column"] = columns & np.uint64(0xFFFFFFFF)
                rows["node"], rows["size"] = node, len(found)
                held.append(rows)
                size += len(rows)
                if size >= FLUSH:
                    yield pack(held)
                    held, size = [], 0
        if held:
            yield pack(held)

    return emit


def fits(a, b):
    """Whether sets of these sizes can link."""
    a, b = np.asarray(a, np.int64), np.asarray(b, np.int64)
    return WHOLE * np.minimum(a, b) >= PART * np.maximum(a, b)


def _columns(raw: list[bytes]):
    """A block's distinct entries by column, and where each column begins."""
    rows = np.frombuffer(b"".join(raw), _ENTRY)
    rows = rows[np.lexsort((rows["node"], rows["column"]))]
    new = np.ones(len(rows), bool)
    new[1:] = (rows["column"][1:] != rows["column"][:-1]) | (rows["node"][1:] != rows["node"][:-1])
    rows = rows[new]
    starts = np.flatnonzero(np.concatenate(([True], rows["column"][1:] != rows["column"][:-1]))) if len(rows) else np.zeros(0, np.int64)
    return rows, starts, np.diff(np.append(starts, len(rows)))


_PAIR = np.dtype([("a", "<i8"), ("b", "<i8"), ("short", "<i8"), ("pivot", "<i8"), ("need", "<i8")])


def _added(rows: np.ndarray) -> np.ndarray:
    """Pairs with the counts of equal ones added up, in order."""
    if not len(rows):
        return rows
    rows = rows[np.lexsort((rows["b"], rows["a"]))]
    at = np.flatnonzero(np.concatenate(([True], (rows["a"][1:] != rows["a"][:-1]) | (rows["b"][1:] != rows["b"][:-1]))))
    out = rows[at].copy()
    for name in ("short", "pivot"):
        out[name] = np.add.reduceat(rows[name], at)
    return out


class _Pairs:
    """Pairs of a block's entries, added up whenever PAIRS of them are held."""

    def __init__(self, rows: np.ndarray):
        self.rows, self.total, self.held, self.size = rows, np.zeros(0, _PAIR), [], 0

    def add(self, left: np.ndarray, right: np.ndarray, kind: str) -> None:
        rows = self.rows
        ok = (rows["node"][left] != rows["node"][right]) & fits(rows["size"][left], rows["size"][right])
        left, right = left[ok], right[ok]
        found = np.zeros(len(left), _PAIR)
        a, b = rows["node"][left], rows["node"][right]
        found["a"], found["b"], found[kind] = np.minimum(a, b), np.maximum(a, b), 1
        found["need"] = np.minimum(extra(rows["size"][left]), extra(rows["size"][right]))
        self.held.append(found)
        self.size += len(found)
        if self.size > PAIRS:
            self.sums()

    def sums(self) -> np.ndarray:
        self.total, self.held, self.size = _added(np.concatenate([self.total, *self.held])), [], 0
        return self.total


def _candidates(group: pa.Table) -> pa.Table:
    """Pairs of a block's short columns and of its long columns' pivots, and the long columns' entries."""
    rows, starts, sizes = _columns(group.column("entries").to_pylist())
    pairs = _Pairs(rows)
    for n in np.unique(sizes[(sizes > 1) & (sizes <= SHORT)]):
        every = starts[sizes == n]
        for i in range(n):
            for j in range(i + 1, n):
                pairs.add(every + i, every + j, "short")
    block = int(group.column("block")[0].as_py())
    column, node, size = ([np.zeros(0, np.int64)] for _ in range(3))
    for k in np.flatnonzero(sizes > SHORT):
        own = np.arange(starts[k], starts[k] + sizes[k])
        pivot = own[mix(rows["node"][own].astype(np.uint64)).argmin()]
        pairs.add(np.full(len(own), pivot), own, "pivot")
        column.append(np.full(len(own), (block << 32) | int(rows["column"][starts[k]]), np.int64))
        node.append(rows["node"][own])
        size.append(rows["size"][own].astype(np.int64))
    found = pairs.sums()
    column, node, size = (np.concatenate(x) for x in (column, node, size))
    none, zero = np.zeros(len(found), np.int64), np.zeros(len(node), np.int64)
    both = lambda x, y: np.concatenate([x, y])
    return pa.table({"a": both(found["a"], node), "b": both(found["b"], zero), "size": both(none, size), "column": pa.array(both(none, column), mask=np.arange(len(found) + len(node)) < len(found)), "short": both(found["short"], zero), "pivot": both(found["pivot"], zero), "need": both(found["need"], zero)})


def _pick(shared):
    """(node, found) of the documents that may be wanted: those whose id's bit is set; a slice of texts at a time."""

    def pick(batches):
        bits = shared.value
        for batch in batches:
            ids = batch.column(0).fill_null(-1).to_numpy().astype(np.int64).view(np.uint64)
            keep = _has_bit(bits, ids)
            nodes, raw, size = [], [], 0
            for _, found in sets(batch.column(1), keep):
                nodes.append(set_hash(found))
                raw.append(found.tobytes())
                size += len(raw[-1])
                if size > SLICE:
                    yield pa.record_batch([pa.array(nodes, pa.int64()), pa.array(raw, pa.binary())], names=["node", "found"])
                    nodes, raw, size = [], [], 0
            yield pa.record_batch([pa.array(nodes, pa.int64()), pa.array(raw, pa.binary())], names=["node", "found"])

    return pick


MOST_BITS = 28  # places of the bitmap of wanted ids, as a power of 2: 32 MB; beyond some 2**24 ids it lets most rows pass, and the join drops them


def _bits_for(n: int) -> int:
    """Power of 2 of the places for ``n`` ids: 64 each or more."""
    return min(MOST_BITS, max(16, (64 * n).bit_length()))


def _has_bit(bits: np.ndarray, ids: np.ndarray) -> np.ndarray:
    at = mix(ids) & np.uint64(64 * len(bits) - 1)
    return (bits[at >> np.uint64(6)] >> (at & np.uint64(63))) & np.uint64(1) > 0


def _bits(power: int):
    """The wanted ids' places in the bitmap: (word, bits), summed up within a batch."""

    def places(batches):
        for batch in batches:
            at = mix(batch.column(0).to_numpy().astype(np.int64).view(np.uint64)) & np.uint64((1 << power) - 1)
            words, where = np.unique(at >> np.uint64(6), return_inverse=True)
            value = np.zeros(len(words), np.uint64)
            np.bitwise_or.at(value, where, np.uint64(1) << (at & np.uint64(63)))
            yield pa.record_batch([words.astype(np.int64), value.view(np.int64)], names=["word", "bits"])

    return places


def _verify(batches):
    for batch in batches:
        keep = []
        for x, y in zip(batch.column(2), batch.column(3)):
            x, y = np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)
            if len(x) > len(y):
                x, y = y, x
            at = np.minimum(np.searchsorted(y, x), len(y) - 1)
            both = int((y[at] == x).sum())
            keep.append(WHOLE * both >= PART * (len(x) + len(y) - both))
        yield pa.record_batch(batch.columns[:2], names=["a", "b"]).filter(pa.array(keep, pa.bool_()))


class Join:
    """The join's stages over one table of documents (doc_id, text)."""

    def __init__(self, docs: DataFrame):
        self.spark = docs.sparkSession
        self.docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
        seen = cut(self.docs.mapInArrow(_summaries, "doc_id long, n_shingles long, node long, counts binary"))
        self.rows = cut(seen.where("counts IS NULL").select("doc_id", "n_shingles", "node"))
        parts = seen.where("counts IS NOT NULL").select(F.col("n_shingles").alias("task"), F.col("node").alias("slice"), "counts")
        tasks = seen.rdd.getNumPartitions()
        while tasks:
            tasks //= FAN
            parts = parts.groupBy("slice", F.expr(f"task div {FAN}")).applyInArrow(_merge, "task long, slice long, counts binary")
        counts = np.zeros((SLICES, COUNTERS // SLICES), np.int64)
        for r in parts.collect():  # SLICES rows: COUNTERS numbers, whatever the corpus
            counts[r.slice] = np.frombuffer(zlib.decompress(r.counts), np.int64)
        del seen, parts
        release(self.spark)  # the tasks' counters
        self.hot = common(counts.ravel())
        total = self.rows.agg(F.sum("n_shingles")).first()[0] or 0
        self.blocks = min(1 << 30, max(128, math.ceil(total * (1 - PART / WHOLE + EXTRA) / BLOCK_ENTRIES)))
        self.turns = min(PASSES, max(1, math.ceil(total / PASS_SHINGLES)))

    def entries(self, shared, turn: int) -> DataFrame:
        return self.docs.select("text").mapInArrow(_entries(shared, self.blocks, turn, self.turns), "block int, entries binary")

    def wanted(self, nodes: DataFrame) -> DataFrame:
        """(node, found): the whole sets of the given nodes, read again from their first documents."""
        least = self.rows.groupBy("node").agg(F.min(F.coalesce("doc_id", F.lit(-1).cast("long"))).alias("doc_id"))  # before anything is joined: a set may have any number of copies
        first = cut(least.join(nodes, "node", "left_semi"))
        n = first.count()
        power = _bits_for(n)
        words = first.select("doc_id").mapInArrow(_bits(power), "word long, bits long").groupBy("word").agg(F.bit_or("bits").alias("bits")).toArrow()  # at most 2**MOST_BITS / 64 rows
        bits = np.zeros(1 << (power - 6), np.uint64)
        bits[words.column("word").to_numpy()] = words.column("bits").to_numpy().view(np.uint64)
        shared = self.spark.sparkContext.broadcast(bits)
        try:
            docs = self.docs
            if n <= FEW_IDS:  # no other row goes to Python
                docs = docs.join(F.broadcast(first.select(F.col("doc_id").alias("_id"))), F.coalesce("doc_id", F.lit(-1).cast("long")) == F.col("_id"), "left_semi")
            picked = docs.mapInArrow(_pick(shared), "node long, found binary")
            return cut(picked.join(nodes, "node", "left_semi").groupBy("node").agg(F.first("found").alias("found")))
        finally:
            shared.destroy()

    def links(self) -> DataFrame:
        """Verified links (a, b) between nodes; all that components need."""
        shared, found = self.spark.sparkContext.broadcast(self.hot), None
        try:
            for turn in range(self.turns):
                some = cut(self.entries(shared, turn).groupBy("block").applyInArrow(_candidates, "a long, b long, size long, column long, short long, pivot long, need long"))
                found = some if found is None else found.unionByName(some)
                release(self.spark)  # the turn's entries
        finally:
            shared.destroy()
        counted = found.where("column IS NULL").groupBy("a", "b").agg(F.sum("short").alias("short"), F.sum("pivot").alias("pivot"), F.max("need").alias("need"))
        pairs = cut(counted)
        strong = cut(pairs.where("short + pivot >= need").select("a", "b"))
        dense = cut(self.dense(found.where("column IS NOT NULL").select(F.col("a").alias("node"), "size", "column"), pairs))
        del counted, found, some, pairs
        release(self.spark)  # the candidates
        links = self.linked(strong)
        del strong
        across = self.across(dense, links)
        return links if across is None else links.unionByName(across)

    def linked(self, strong: DataFrame) -> DataFrame:
        """The pairs (a, b) that link. The sets are gathered for a part of the pairs' clusters at a time, so that few lie on disk at once."""
        turn, placed = F.lit(0), strong
        if self.turns > 1:
            known = components(strong).withColumnRenamed("node", "_node")
            turn, placed = F.pmod(F.xxhash64("component"), F.lit(self.turns)), strong.join(known, F.col("a") == F.col("_node"))
        placed, links = cut(placed.select("a", "b", turn.alias("turn"))), None
        for k in range(self.turns):
            own = placed.where(F.col("turn") == k).select("a", "b")
            sets = self.wanted(cut(own.select(F.explode(F.array("a", "b")).alias("node")).distinct()))
            release(self.spark)  # the sets' shuffle
            some = cut(self.verified(own, sets))
            links = some if links is None else links.unionByName(some)
            del sets
            release(self.spark)  # the turn's sets and their pairs
        return links

    def dense(self, columns: DataFrame, pairs: DataFrame) -> DataFrame:
        """(node, column) of the long columns, of vertices that can reach the bound with them.

        A partner has at least PART / WHOLE of the vertex's size, which bounds what is
        needed; of a vertex's short columns at most those shared with one partner count.
        """
        own = columns.groupBy("node").agg(F.count(F.lit(1)).alias("n"), F.max("size").alias("size"))
        ends = pairs.where("short > 0").select(F.explode(F.array("a", "b")).alias("_node"), "short").groupBy("_node").agg(F.max("short").alias("most"))
        least = F.greatest(F.lit(1), F.floor(F.ceil(F.col("size") * PART / WHOLE) * EXTRA))
        able = own.join(ends, F.col("node") == F.col("_node"), "left").where(F.col("n") + F.coalesce("most", F.lit(0)) >= least).select("node")
        return columns.select("node", "column").join(cut(able), "node", "left_semi")

    def across(self, dense: DataFrame, links: DataFrame) -> DataFrame | None:
        """Links between different components that have long columns in common."""
        if dense.limit(1).count() == 0:
            return None
        known = cut(components(links).withColumnRenamed("node", "_node"))
        placed = cut(dense.join(known, F.col("node") == F.col("_node"), "left").select("column", "node", F.coalesce("component", "node").alias("component")))
        mixed = placed.groupBy("column").agg((F.min("component") != F.max("component")).alias("mixed")).where("mixed").select("column")
        apart = cut(placed.join(if_small(cut(mixed)), "column", "left_semi"))
        if apart.limit(1).count() == 0:
            return None
        clusters = components(apart.select(F.col("node").alias("a"), F.col("column").alias("b"))).withColumnRenamed("component", "cluster").withColumnRenamed("node", "_node")
        members = apart.select("node", "component").distinct().join(cut(clusters), F.col("node") == F.col("_node")).select("cluster", "node", "component")
        members = cut(members)
        return cut(_multiplied(members, self.wanted(cut(members.select("node").distinct()))))

    def verified(self, pairs: DataFrame, sets: DataFrame) -> DataFrame:
        with_b = pairs.join(sets.select(F.col("node").alias("b"), F.col("found").alias("y")), "b")
        both = with_b.join(sets.select(F.col("node").alias("a"), F.col("found").alias("x")), "a")
        return both.select("a", "b", "x", "y").mapInArrow(_verify, "a long, b long")


def overlaps(x: list[np.ndarray], y: list[np.ndarray]) -> np.ndarray:
    """Sizes of the intersections of two lists of sets: the product of their incidence matrices."""
    columns = np.intersect1d(np.unique(np.concatenate(x)), np.unique(np.concatenate(y)))
    out = np.zeros((len(x), len(y)), np.float32)
    for at in range(0, len(columns), 4096):
        own = columns[at : at + 4096]
        dense = []
        for side in (x, y):
            m = np.zeros((len(side), len(own)), np.float32)
            for k, s in enumerate(side):
                place = np.minimum(np.searchsorted(own, s), len(own) - 1)
                m[k, place[own[place] == s]] = 1
            dense.append(m)
        out += dense[0] @ dense[1].T
    return out.astype(np.int64)


def _multiplied(members: DataFrame, found: DataFrame) -> DataFrame:
    """(a, b): links between members (cluster, node, component) of one cluster and different components.

    Clusters are cut into chunks of bounded shingles, and a task multiplies two chunks a
    tile at a time, so what it holds does not follow the cluster's size. Each member's set
    goes to as many tasks as its cluster has chunks.
    """
    weighed = members.join(found.select(F.col("node").alias("_node"), (F.octet_length("found") / 8).alias("n")), F.col("node") == F.col("_node")).drop("_node")
    sizes = weighed.groupBy("cluster").agg(F.greatest(F.ceil(F.count(F.lit(1)) / CHUNK), F.ceil(F.sum("n") / CHUNK_SHINGLES)).alias("chunks"))
    spread = members.join(cut(sizes), "cluster").withColumn("i", F.pmod(F.xxhash64("node"), F.col("chunks"))).withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), F.col("chunks") - 1)))
    keyed = spread.join(found.withColumnRenamed("node", "_node"), F.col("node") == F.col("_node"))
    keyed = keyed.select(F.concat_ws(":", "cluster", F.least("i", "j"), F.greatest("i", "j")).alias("g"), (F.col("i") > F.col("j")).cast("int").alias("side"), "node", "component", "found")

    def multiply(group: pa.Table) -> pa.Table:
        side, node, comp = (group.column(k).to_numpy() for k in ("side", "node", "component"))
        x, y = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        same = not len(y)
        y = x if same else y
        near = [(np.zeros(0, np.int64),) * 2]
        if len(x) and len(np.unique(comp)) > 1:
            sets_ = [np.frombuffer(v.as_buffer(), np.uint64) for v in group.column("found")]
            size = np.array([len(v) for v in sets_])
            for lo in range(0, len(x), TILE):
                own = x[lo : lo + TILE]
                for at in range(lo if same else 0, len(y), TILE):
                    other = y[at : at + TILE]
                    both = overlaps([sets_[k] for k in own], [sets_[k] for k in other])
                    p, q = np.nonzero((WHOLE * both >= PART * (size[own][:, None] + size[other][None, :] - both)) & (comp[own][:, None] != comp[other][None, :]))
                    near.append(roots(node[own[p]], node[other[q]]))
        a, b = roots(*(np.concatenate(v) for v in zip(*near)))
        return pa.table({"a": a[a != b], "b": b[a != b]})

    return keyed.groupBy("g").applyInArrow(multiply, "a long, b long")


def _rooted(docs: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(doc_id, n_shingles, node, root) of the rows with shingles, and the others' (doc_id, n_shingles)."""
    join = Join(docs)
    known = cut(components(join.links()).withColumnRenamed("node", "_node"))
    join.docs = None
    release(docs.sparkSession)
    some = join.rows.where("n_shingles > 0").join(if_small(known), F.col("node") == F.col("_node"), "left").select("doc_id", "n_shingles", "node", F.coalesce("component", "node").alias("root"))
    return cut(some), join.rows.where("n_shingles = 0").select("doc_id", "n_shingles")


def jaccard_classes(docs: DataFrame) -> DataFrame:
    """(doc_id, n_shingles, component_id): a row for each document."""
    some, none = _rooted(docs)
    least = cut(some.groupBy("root").agg(F.min("doc_id").alias("component_id")))
    return some.join(least, "root").select("doc_id", "n_shingles", "component_id").unionByName(none.withColumn("component_id", F.col("doc_id")))


def _nodes(column):
    """The hash of each row's set; null without shingles."""
    out = [None] * len(column)
    for k, found in sets(column):
        out[k] = set_hash(found)
    return pa.array(out, pa.int64())


def first_of_each(docs: DataFrame) -> DataFrame:
    """One document of each group of near copies, with all its columns: that with the smallest id.

    Rows of one id count as documents of their own, told apart by their sets; rows without
    shingles and those of null id stay.
    """
    some, none = _rooted(docs)
    some = some.where("doc_id IS NOT NULL")
    later_, twice_, first_, set_, id_, node_ = free(docs.columns, "_later", "_twice", "_first", "_set", "_id", "_node")
    first = cut(some.groupBy("root").agg(F.min(F.struct("doc_id", "node")).alias("k")).select("root", F.col("k.doc_id").alias(first_), F.col("k.node").alias(set_)))
    twice = cut(some.select("doc_id").unionByName(none.select("doc_id").where("doc_id IS NOT NULL")).groupBy("doc_id").count().where("count > 1").select(F.col("doc_id").alias(twice_)))
    later = some.join(if_small(first), "root").where(F.col("doc_id") != F.col(first_)).select(F.col("doc_id").alias(later_)).distinct()
    later = cut(later.join(if_small(twice), F.col(later_) == F.col(twice_), "left_anti"))
    own = docs["doc_id"].cast("long")
    kept = docs.join(if_small(later), own == F.col(later_), "left_anti")
    if twice.limit(1).count() == 0:
        return kept
    shared = kept.join(if_small(twice), own == F.col(twice_), "left_semi")
    shared = shared.withColumn(id_, F.col("doc_id").cast("long")).withColumn(node_, F.arrow_udf(_nodes, "long")(F.col("text").cast("string")))
    some = shared.where(F.col(node_).isNotNull()).dropDuplicates([id_, node_]).join(if_small(first.select(first_, set_)), (F.col(id_) == F.col(first_)) & (F.col(node_) == F.col(set_)), "left_semi")
    return kept.join(if_small(twice), own == F.col(twice_), "left_anti").unionByName(some.unionByName(shared.where(F.col(node_).isNull())).drop(id_, node_))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_classes(table(spark, sf_dir, "documents"))


ORACLE = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS ws FROM documents
), s AS (
  SELECT DISTINCT doc_id, md5_number(array_to_string(ws[k : k + 4], ' ')) AS h
  FROM w, LATERAL (SELECT unnest(range(1, greatest(len(ws) - 4, CASE WHEN len(ws) > 0 THEN 1 ELSE 0 END) + 1)) AS k)
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
o AS (
  SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.h = b.h AND a.doc_id <> b.doc_id GROUP BY 1, 2
), l AS (
  SELECT a, b FROM o JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 80 * (x.n + y.n - c)
), r(a, b) AS (SELECT doc_id, doc_id FROM documents UNION SELECT r.a, l.b FROM r JOIN l ON r.b = l.a)
SELECT w.doc_id, CAST(coalesce(n.n, 0) AS BIGINT) AS n_shingles, c.component_id
FROM w LEFT JOIN n USING (doc_id) JOIN (SELECT a AS doc_id, min(b) AS component_id FROM r GROUP BY a) c USING (doc_id)
"""
