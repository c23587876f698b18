"""The synchronous loop for other updates, and random surfers."""

from __future__ import annotations

from collections.abc import Callable
from itertools import count

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from linkrank.graph import Graph
from linkrank.plans.lineage import cut, loop_settings

HUB_SHARES = 64


def fixpoint(graph: Graph, start: DataFrame, gather: Callable[[Column, Column], Column], combine: Callable[[Column], Column], apply: Callable[[Column, Column], Column], max_iter: int | None = None, both_ways: bool = False) -> tuple[DataFrame, int]:
    """(id, value) after steps that change nothing more, and their number.

    A step sends gather(value, coef) along each edge, combines what arrives at a vertex
    with an aggregate, and applies (value, combined) -> value. Without ``max_iter`` it runs
    until nothing changes; values that still change after ``max_iter`` steps are an error.
    """
    with loop_settings(graph.spark):
        edges = graph.edges.select("src", "dst", "coef")
        if both_ways:
            edges = edges.unionByName(edges.select(F.col("dst").alias("src"), F.col("src").alias("dst"), "coef")).distinct()
        parts = int(graph.spark.conf.get("spark.sql.shuffle.partitions"))
        edges = cut(edges.repartition(parts, "src"))
        state = cut(start.select("id", "value").repartition(parts, "id"))
        for k in count(1):
            sent = edges.join(state, F.col("src") == F.col("id")).select("dst", gather(F.col("value"), F.col("coef")).alias("m")).groupBy("dst").agg(combine(F.col("m")).alias("m"))
            joined = state.join(sent, F.col("id") == F.col("dst"), "left")
            fresh = cut(joined.select("id", apply(F.col("value"), F.col("m")).alias("value"), (~apply(F.col("value"), F.col("m")).eqNullSafe(F.col("value"))).alias("changed")))
            moved = fresh.where("changed").limit(1).count()
            state = fresh.select("id", "value")
            if not moved:
                return state, k
            if k == max_iter:
                raise RuntimeError(f"values still change after {max_iter} steps")


def weak_components(graph: Graph) -> DataFrame:
    """(id, value): the smallest id that can be reached without regard to direction.

    Each round hangs a vertex's larger neighbours, then the vertex and its smaller ones, on
    the smallest vertex among them, so long paths take some rounds only, not a round for
    each edge. It ends when a round changes no link.
    """
    links = cut(graph.edges.select(F.greatest("src", "dst").alias("a"), F.least("src", "dst").alias("b")).where("a > b").distinct())
    before = None
    while True:
        both = links.unionByName(links.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("_a"), F.least("a", "m").alias("m"))
        larger = both.join(least, F.col("a") == F.col("_a")).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a > b").distinct()
        larger = cut(larger)
        least = larger.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("_a"), "m")
        smaller = larger.join(least, F.col("a") == F.col("_a"))
        links = cut(smaller.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(least.select(F.col("_a").alias("a"), F.col("m").alias("b"))).where("a > b").distinct())
        state = tuple(links.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b")), F.sum(F.xxhash64("b", "a") % 1000003)).first())
        if state == before:
            break
        before = state
    return graph.vertices.select("id").join(links, F.col("id") == F.col("a"), "left").select("id", F.coalesce("b", "id").alias("value"))


def hops(graph: Graph, source: int) -> DataFrame:
    """(id, value): fewest edges from the source; null where it cannot be reached."""
    start = graph.vertices.select("id", F.when(F.col("id") == source, F.lit(0).cast("long")).alias("value"))
    return fixpoint(graph, start, lambda v, c: v + 1, F.min, lambda v, m: F.least(v, m))[0]


def perforated(graph: Graph, steps: int, rate: float, damping: float = 0.85) -> DataFrame:
    """(id, rank) after steps that each skip a hash-chosen share ``rate`` of the vertices."""
    n = graph.count()
    state = graph.vertices.select("id", F.lit(1.0 / max(n, 1)).alias("rank"))
    for k in range(steps):
        skip = F.pmod(F.xxhash64("id", F.lit(k)), F.lit(1_000_000)) < int(rate * 1_000_000)
        targets = state.where(~skip).select(F.col("id").alias("dst"))
        sums = graph.edges.join(targets, "dst", "left_semi").join(state, F.col("src") == F.col("id")).groupBy("dst").agg(F.sum(F.col("rank") * F.col("coef")).alias("total"))
        fresh = F.lit((1 - damping) / max(n, 1)) + damping * F.coalesce("total", F.lit(0.0))
        state = cut(state.join(sums, F.col("id") == F.col("dst"), "left").select("id", F.when(skip, F.col("rank")).otherwise(fresh).alias("rank")))
    return state


def surfer_walks(graph: Graph, walks: int, steps: int = 60, seed: int = 1, damping: float = 0.85) -> DataFrame:
    """(id, rank): shares of random surfers' visits, walks of them starting at each vertex.

    A surfer stops with probability 1 - damping at each vertex, or where no link leaves;
    the mean number of visits times (1 - damping) / n estimates the rank.
    """
    n = graph.count()
    # a vertex's out-links are numbered by the order of hashes, in shares of a hub's links, so none is gathered in one row
    share = F.pmod(F.xxhash64("dst"), F.lit(HUB_SHARES))
    placed = graph.edges.select("src", "dst", share.alias("share")).withColumn("k", F.row_number().over(Window.partitionBy("src", "share").orderBy("dst")))
    sizes = graph.edges.groupBy("src", share.alias("share")).agg(F.count(F.lit(1)).alias("m"))
    starts = sizes.withColumn("from", F.sum("m").over(Window.partitionBy("src").orderBy("share")) - F.col("m"))
    out = cut(placed.join(starts, ["src", "share"]).select(F.col("src").alias("_src"), (F.col("from") + F.col("k") - 1).alias("_k"), "dst"))
    degrees = cut(graph.edges.groupBy(F.col("src").alias("_src")).agg(F.count(F.lit(1)).alias("_m")))
    at = graph.vertices.select("id").withColumn("walk", F.explode(F.sequence(F.lit(1), F.lit(walks)))).select(F.col("id").alias("start"), "walk", "id")
    visits = at.groupBy("id").agg(F.count(F.lit(1)).alias("n"))
    for k in range(1, steps + 1):
        draw = lambda salt: F.pmod(F.xxhash64("start", "walk", F.lit(k), F.lit(seed), F.lit(salt)), F.lit(1 << 30))
        going = at.where(draw(0) < int(damping * (1 << 30))).join(degrees, F.col("id") == F.col("_src")).select("start", "walk", "id", (draw(1) % F.col("_m")).alias("_at"))
        at = cut(going.join(out, (F.col("id") == F.col("_src")) & (F.col("_at") == F.col("_k"))).select("start", "walk", F.col("dst").alias("id")))
        if not at.limit(1).count():
            break
        visits = cut(visits.unionByName(at.groupBy("id").agg(F.count(F.lit(1)).alias("n"))).groupBy("id").agg(F.sum("n").alias("n")))
    return visits.select("id", (F.col("n") * ((1 - damping) / (n * walks))).alias("rank"))
