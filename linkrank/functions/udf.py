"""SQL functions and table functions."""

from __future__ import annotations

import math

import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.functions import pandas_udf, udtf

from linkrank.sources.edges import EDGE
from linkrank.sources.rmat import FACTOR, PRIME, SHARES, scale_for


@pandas_udf(T.LongType())
def step_bound(tol: pd.Series) -> pd.Series:
    """Synchronous steps after which the largest change is at most tol, for damping 0.85."""
    return tol.map(lambda t: 1 + math.ceil(math.log(t / 2) / math.log(0.85)))


@pandas_udf(T.DoubleType())
def ordered_sum(value: pd.Series, src: pd.Series) -> float:
    """A sum whose order is that of ``src``: the same in every run."""
    total = 0.0
    for _, v in sorted(zip(src, value)):
        total += v
    return total


@udtf(returnType=EDGE)
class RmatEdges:
    """rmat_edges(edges, seed): generated edges; the rows of linkrank.sources.rmat."""

    def eval(self, edges: int, seed: int):
        limits = [math.floor(PRIME * sum(SHARES[: k + 1])) for k in range(3)]
        levels = scale_for(edges)
        for k in range(edges):
            s = (k * 2 + 1 + seed * 7919) % PRIME
            for _ in range(3):
                s = s * FACTOR % PRIME
            src = dst = 0
            for _ in range(levels):
                s = ((s * FACTOR % PRIME) ^ (s >> 13)) % PRIME
                src = src * 2 + (s >= limits[1])
                dst = dst * 2 + (s >= limits[2] or limits[0] <= s < limits[1])
            yield src, dst


@udtf(returnType=EDGE)
class Adjacency:
    """adjacency(line): the edges of one adjacency line."""

    def eval(self, line: str):
        parts = (line or "").replace(":", " ").replace(",", " ").split()
        for d in parts[1:]:
            yield int(parts[0]), int(d)


def register(spark: SparkSession) -> None:
    """Makes step_bound, ordered_sum, rmat_edges and adjacency known to SQL, and the rankgraph source to readers."""
    from linkrank.sources.datasource import RankGraphSource

    spark.udf.register("step_bound", step_bound)
    spark.udf.register("ordered_sum", ordered_sum)
    spark.udtf.register("rmat_edges", RmatEdges)
    spark.udtf.register("adjacency", Adjacency)
    spark.dataSource.register(RankGraphSource)


def rank_view(result, name: str, labels=None) -> None:
    """A temporary view (id, rank[, label]) of a run's ranks, for SQL users."""
    frame = result.ranks if labels is None else result.ranks.join(labels, "id", "left")
    frame.withColumn("rank", F.col("rank")).createOrReplaceTempView(name)
