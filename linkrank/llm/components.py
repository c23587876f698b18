"""Connected components of a graph given as rows of links."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkrank.llm.tables import cut

BATCH_LINKS = 1 << 20
FEW_LINKS = 1 << 19  # up to which links are joined up in one task


def roots(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(node, smallest node of its component) of the links' nodes, by repeated hooking and jumping."""
    nodes, at = np.unique(np.concatenate([a, b]), return_inverse=True)
    x, y = at[: len(a)], at[len(a) :]
    parent = np.arange(len(nodes))
    while True:
        px, py = parent[x], parent[y]
        low, high = np.minimum(px, py), np.maximum(px, py)
        if (low == high).all():
            return nodes, nodes[parent]
        np.minimum.at(parent, high, low)
        while True:
            up = parent[parent]
            if (up == parent).all():
                break
            parent = up


def _contract(batches):
    """Replaces a task's links by one link from each of its nodes to the smallest it reaches, in runs."""
    def stars(run):
        a = np.concatenate([r.column(0).to_numpy() for r in run])
        b = np.concatenate([r.column(1).to_numpy() for r in run])
        node, root = roots(a, b)
        keep = node != root
        return pa.record_batch([node[keep], root[keep]], names=["a", "b"])

    run, size = [], 0
    for batch in batches:
        run.append(batch)
        size += len(batch)
        if size >= BATCH_LINKS:
            run = [stars(run)]
            if len(run[0]) > BATCH_LINKS // 2:
                yield run.pop()
            size = sum(map(len, run))
    if run:
        yield stars(run)


def components(links: DataFrame) -> DataFrame:
    """(node, component) of all nodes of ``links`` (a, b): the smallest node reachable.

    Each round contracts links within tasks, then hangs the larger of a node's
    neighbours, and the node, on the smallest of them. A node's smallest neighbour is
    an aggregate and its neighbours are streamed in a join, so a node with any number
    of links is never gathered. It ends when no link joins two non-roots, or when at
    most FEW_LINKS are left, which one task joins up.
    """
    edges = cut(links.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).where("a <> b").mapInArrow(_contract, "a long, b long"))
    while True:
        if edges.limit(FEW_LINKS + 1).count() <= FEW_LINKS:
            edges = cut(edges.coalesce(1).mapInArrow(_contract, "a long, b long"))
            break
        # every link is (node, smaller node): nodes with several smaller neighbours hook them together
        least = cut(edges.groupBy("a").agg(F.min("b").alias("m"), F.count(F.lit(1)).alias("n")))
        roots = least.select("a", "m")
        inner = edges.join(roots.withColumnRenamed("a", "_a"), F.col("b") == F.col("_a"), "left")
        moved = inner.select("a", "b", F.col("m").alias("up"))
        state = moved.agg(F.count("up").alias("deep")).first()["deep"]
        several = least.where("n > 1").limit(1).count()
        if not state and not several:
            break
        hooked = edges.join(roots, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b")
        lifted = moved.select("a", F.coalesce("up", "b").alias("b"))
        edges = cut(lifted.unionByName(hooked).distinct().mapInArrow(_contract, "a long, b long").distinct())
    leaves = edges.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return leaves.unionByName(edges.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
