"""A recursive-matrix generator: each edge picks a quadrant of the adjacency matrix at each level."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: Shares of the four quadrants.
SHARES = (0.57, 0.19, 0.19, 0.05)
# fixed values: a linear step modulo a prime that fits in 64-bit products, for any engine
PRIME = 2147483647
FACTOR = 48271


def scale_for(edges: int) -> int:
    """Levels at which about half as many vertices as edges get edges."""
    return max(4, math.ceil(math.log2(edges * 1.05)))


def rmat_edges(spark: SparkSession, edges: int, scale: int | None = None, seed: int = 1, shares: tuple[float, ...] = SHARES, partitions: int | None = None) -> DataFrame:
    """(src, dst): ``edges`` draws, repeats and loops included; each row depends on its number and the seed only."""
    scale = scale or scale_for(edges)
    limits = [math.floor(PRIME * sum(shares[: k + 1])) for k in range(3)]
    state = (F.col("id") * 2 + 1 + seed * 7919) % PRIME
    for _ in range(3):
        state = state * FACTOR % PRIME

    def descend(at, _):
        # the state is mixed with its own high part, so that nearby rows differ
        s = (at["s"] * FACTOR % PRIME).bitwiseXOR(F.shiftright(at["s"], 13)) % PRIME
        low, high = s >= limits[1], (s >= limits[2]) | ((s >= limits[0]) & (s < limits[1]))
        return F.struct(s.alias("s"), (at["src"] * 2 + low.cast("long")).alias("src"), (at["dst"] * 2 + high.cast("long")).alias("dst"))

    start = F.struct(state.alias("s"), F.lit(0).cast("long").alias("src"), F.lit(0).cast("long").alias("dst"))
    walked = spark.range(edges, numPartitions=partitions).select(F.aggregate(F.sequence(F.lit(1), F.lit(scale)), start, descend).alias("e"))
    return walked.select("e.src", "e.dst")


def rmat_sql(edges: int, scale: int | None = None, seed: int = 1, shares: tuple[float, ...] = SHARES, rows: str | None = None) -> str:
    """The same edges in SQL; ``rows``: a source of the numbers ``range`` from 0 on, else those up to ``edges``."""
    scale = scale or scale_for(edges)
    limits = [math.floor(PRIME * sum(shares[: k + 1])) for k in range(3)]
    sql = f"SELECT (range * 2 + 1 + {seed * 7919}) % {PRIME} AS s, CAST(0 AS BIGINT) AS src, CAST(0 AS BIGINT) AS dst FROM {rows or f'range({edges})'}"
    for _ in range(3):
        sql = f"SELECT s * {FACTOR} % {PRIME} AS s, src, dst FROM ({sql})"
    for _ in range(scale):
        sql = f"SELECT xor((s * {FACTOR}) % {PRIME}, s >> 13) % {PRIME} AS s, src, dst FROM ({sql})"
        sql = f"SELECT s, src * 2 + CASE WHEN s >= {limits[1]} THEN 1 ELSE 0 END AS src, dst * 2 + CASE WHEN s >= {limits[2]} OR (s >= {limits[0]} AND s < {limits[1]}) THEN 1 ELSE 0 END AS dst FROM ({sql})"
    return f"SELECT src, dst FROM ({sql})"
