"""Vertices with equal in-neighbours, computed once.

From a uniform start such vertices have equal ranks at every synchronous step, and at
the fixed point under any schedule. Candidates are found by fingerprints of the
in-neighbour sets; within a fingerprint the sets themselves are compared.
"""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from linkrank.config import RankConfig, RankResult
from linkrank.graph import Graph
from linkrank.plans.lineage import cut


def twin_classes(graph: Graph) -> DataFrame:
    """(id, class): the smallest id with the same in-neighbours and weights; one class for those without in-links."""
    prints = graph.edges.groupBy(F.col("dst").alias("id")).agg(
        F.count(F.lit(1)).alias("n"), F.sum(F.xxhash64("src", "coef").cast("decimal(38,0)")).alias("h1"), F.bit_xor(F.xxhash64("coef", "src", F.lit(1))).alias("h2")
    )
    prints = cut(prints)
    shared = prints.groupBy("n", "h1", "h2").agg(F.count(F.lit(1)).alias("m")).where("m > 1").drop("m")
    candidates = cut(prints.join(shared, ["n", "h1", "h2"]).select("id", "n", "h1", "h2"))
    lists = graph.edges.join(candidates, F.col("dst") == F.col("id")).groupBy("id", "n", "h1", "h2").agg(F.sort_array(F.collect_list(F.struct("src", "coef"))).alias("ins"))
    lists = cut(lists)
    least = lists.groupBy("n", "h1", "h2", "ins").agg(F.min("id").alias("class"))
    found = lists.join(least, ["n", "h1", "h2", "ins"]).select("id", "class")
    none = graph.vertices.select("id").join(prints.select("id"), "id", "left_anti")
    lowest = none.agg(F.min("id").alias("class"))
    without = none.crossJoin(F.broadcast(lowest))  # one row
    known = cut(found.unionByName(without))
    return graph.vertices.select("id").join(known, "id", "left").select("id", F.coalesce("class", "id").alias("class"))


def collapse(graph: Graph, classes: DataFrame) -> Graph:
    """The quotient: edges between classes' first members, with the summed shares of the source class.

    A class's rank is that of each member, so its out-degree is 1 and its edges' weight
    is their share.
    """
    of_src = classes.select(F.col("id").alias("src"), F.col("class").alias("c_src"))
    heads = classes.where("id = class").select(F.col("id").alias("dst"))
    merged = graph.edges.join(heads, "dst", "left_semi").join(of_src, "src").groupBy("c_src", "dst").agg(F.sum("coef").alias("coef"))
    edges = cut(merged.select(F.col("c_src").alias("src"), "dst", F.col("coef").alias("mult"), "coef"))
    out = edges.select(F.col("src").alias("id")).distinct().withColumn("out_degree", F.lit(1).cast("long"))
    vertices = heads.select(F.col("dst").alias("id")).join(out, "id", "left").select("id", F.coalesce("out_degree", F.lit(0)).cast("long").alias("out_degree"))
    return Graph(cut(vertices), edges, population=graph.count())


def expand(ranks: DataFrame, classes: DataFrame) -> DataFrame:
    """(id, rank) of all vertices from the classes' ranks."""
    return classes.join(ranks.withColumnRenamed("id", "class"), "class").select("id", "rank")


def on_classes(graph: Graph, cfg: RankConfig, run: Callable[[Graph, RankConfig], RankResult]) -> RankResult:
    """A run over classes of vertices with equal in-neighbours, spread over the vertices again."""
    if cfg.dangling != "leak" or not isinstance(cfg.init, str):
        raise ValueError("twins need the uniform start and dangling='leak'")
    classes = cut(twin_classes(graph))
    found = run(collapse(graph, classes), replace(cfg, twins=False))
    found.ranks = expand(found.ranks, classes)
    return found
