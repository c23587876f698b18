"""Directed graphs as two frames, their blocks and their compressed form."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from linkrank.plans.lineage import cut


@dataclass
class Graph:
    """vertices (id, out_degree) and edges (src, dst, mult, coef); coef is the share of src's rank that dst gets."""

    vertices: DataFrame
    edges: DataFrame
    labels: DataFrame | None = None
    population: int | None = None  # of the rank equation, where the vertices stand for more than themselves

    @property
    def spark(self):
        return self.edges.sparkSession

    def count(self) -> int:
        return self.vertices.count() if self.population is None else self.population

    @staticmethod
    def from_edges(edges: DataFrame, vertices: DataFrame | None = None, multiplicity: bool = False, self_loops: bool = False) -> Graph:
        """A graph from rows (src, dst): nulls are dropped, repeated edges count once or by multiplicity.

        ``vertices`` (id) adds vertices without edges.
        """
        pairs = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).where("src IS NOT NULL AND dst IS NOT NULL")
        if not self_loops:
            pairs = pairs.where("src <> dst")
        merged = cut(pairs.groupBy("src", "dst").agg(F.count(F.lit(1)).alias("mult") if multiplicity else F.lit(1).cast("long").alias("mult")))
        degrees = merged.groupBy("src").agg(F.sum("mult").alias("out_degree"))
        ends = merged.select(F.explode(F.array("src", "dst")).alias("id"))
        if vertices is not None:
            ends = ends.unionByName(vertices.select(F.col("id").cast("long").alias("id")).where("id IS NOT NULL"))
        every = ends.distinct().join(degrees.withColumnRenamed("src", "id"), "id", "left").select("id", F.coalesce("out_degree", F.lit(0)).cast("long").alias("out_degree"))
        shares = merged.join(degrees, "src").select("src", "dst", "mult", (F.col("mult") / F.col("out_degree")).alias("coef"))
        return Graph(cut(every), cut(shares))

    @staticmethod
    def from_labels(edges: DataFrame, **options) -> Graph:
        """A graph from rows (src, dst) of text labels; ``labels`` (id, label) is kept.

        Ids are 64-bit hashes of the labels, checked for collisions, so that no global
        numbering is needed.
        """
        names = cut(edges.select(F.explode(F.array("src", "dst")).alias("label")).where("label IS NOT NULL").distinct().select(F.xxhash64("label").alias("id"), "label"))
        if names.groupBy("id").count().where("count > 1").limit(1).count():
            raise ValueError("two labels have one hash")
        graph = Graph.from_edges(edges.select(F.when(F.col("src").isNotNull(), F.xxhash64("src")).alias("src"), F.when(F.col("dst").isNotNull(), F.xxhash64("dst")).alias("dst")), **options)
        graph.labels = names
        return graph

    def in_degrees(self) -> DataFrame:
        found = self.edges.groupBy(F.col("dst").alias("id")).agg(F.count(F.lit(1)).alias("in_degree"))
        return self.vertices.select("id").join(found, "id", "left").select("id", F.coalesce("in_degree", F.lit(0)).cast("long").alias("in_degree"))


def assign_blocks(graph: Graph, blocks: int, how: str = "hash") -> DataFrame:
    """(id, block): static shares of the vertices.

    hash: by a hash of the id. range: equal numbers of vertices in id order. edges:
    shares in id order of about equal in-edges. The latter two number the ids by
    sorted partitions and their offsets, not by one task.
    """
    if how == "hash":
        return graph.vertices.select("id", F.pmod(F.xxhash64("id"), F.lit(blocks)).cast("int").alias("block"))
    weight = graph.in_degrees().withColumnRenamed("in_degree", "w") if how == "edges" else graph.vertices.select("id", F.lit(1).alias("w"))
    ordered = cut(weight.repartitionByRange("id").withColumn("_part", F.spark_partition_id()))
    sums = ordered.groupBy("_part").agg(F.sum("w").alias("w"))
    offsets = sums.select("_part", (F.sum("w").over(Window.orderBy("_part")) - F.col("w")).alias("_from"), F.sum("w").over(Window.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)).alias("_all"))
    within = F.sum("w").over(Window.partitionBy("_part").orderBy("id").rowsBetween(Window.unboundedPreceding, 0)) - F.col("w")
    place = ordered.withColumn("_in", within).join(F.broadcast(offsets), "_part")  # a row for each partition
    share = F.floor((F.col("_from") + F.col("_in")) * blocks / F.greatest(F.col("_all"), F.lit(1)))
    return place.select("id", F.least(share, F.lit(blocks - 1)).cast("int").alias("block"))


def mirrors(graph: Graph, block_of: DataFrame) -> DataFrame:
    """(src, dst_block): which blocks read which vertices' ranks."""
    return graph.edges.join(block_of.select(F.col("id").alias("dst"), F.col("block").alias("dst_block")), "dst").select("src", "dst_block").distinct()


def csr_blocks(graph: Graph, block_of: DataFrame) -> DataFrame:
    """(block, ids, in_ptr, in_src, in_coef): each block's vertices and in-edges as arrays.

    ids are sorted; vertex ids[k] has the in-edges in_ptr[k] up to in_ptr[k + 1]. A block
    has to fit in a worker: choose blocks so that each has some ten million edges at most.
    """
    rows = graph.edges.join(block_of.withColumnRenamed("id", "dst"), "dst").select("block", "src", "dst", "coef")
    rows = rows.unionByName(block_of.select("block", F.lit(None).cast("long").alias("src"), F.col("id").alias("dst"), F.lit(0.0).alias("coef")))

    def pack(table: pa.Table) -> pa.Table:
        edge = table.column("src").is_valid().to_numpy()
        src, dst, coef = table.column("src").fill_null(0).to_numpy()[edge], table.column("dst").to_numpy(), table.column("coef").to_numpy()[edge]
        ids = np.sort(dst[~edge])
        order = np.lexsort((src, dst[edge]))
        pointer = np.append(np.searchsorted(dst[edge][order], ids), len(order))
        one = lambda values, kind: pa.ListArray.from_arrays(pa.array([0, len(values)], pa.int32()), pa.array(values, kind))
        return pa.table({"block": pa.array([table.column("block")[0].as_py()], pa.int32()), "ids": one(ids, pa.int64()), "in_ptr": one(pointer, pa.int64()), "in_src": one(src[order], pa.int64()), "in_coef": one(coef[order], pa.float64())})

    return rows.groupBy("block").applyInArrow(pack, "block int, ids array<long>, in_ptr array<long>, in_src array<long>, in_coef array<double>")


def graph_stats(graph: Graph) -> DataFrame:
    """One row: vertices, edges, links (with multiplicity), dangling, no_in_link, max_in, max_out."""
    return _stats(graph.vertices.join(graph.in_degrees(), "id"))


def _stats(degrees: DataFrame) -> DataFrame:
    per = degrees.agg(
        F.count(F.lit(1)).alias("vertices"), F.sum("in_degree").cast("long").alias("edges"), F.sum("out_degree").cast("long").alias("links"),
        F.count_if(F.col("out_degree") == 0).alias("dangling"), F.count_if(F.col("in_degree") == 0).alias("no_in_link"), F.max("in_degree").alias("max_in"), F.max("out_degree").alias("max_out"),
    )
    return per.select("vertices", *(F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("edges", "links", "dangling", "no_in_link", "max_in", "max_out")))


def edge_stats(edges: DataFrame) -> DataFrame:
    """The row of ``graph_stats`` of the graph that rows (src, dst) give, each edge counted once, in one pass over them.

    No graph is stored and nothing is joined: an edge counts at both of its ends.
    """
    pairs = edges.select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst")).where("src <> dst").distinct()
    one, none = F.lit(1).cast("long"), F.lit(0).cast("long")
    end = lambda key, out, in_: F.struct(F.col(key).alias("id"), out.alias("out_degree"), in_.alias("in_degree"))
    ends = pairs.select(F.explode(F.array(end("src", one, none), end("dst", none, one))).alias("e")).select("e.*")
    return _stats(ends.groupBy("id").agg(F.sum("out_degree").alias("out_degree"), F.sum("in_degree").alias("in_degree")))
