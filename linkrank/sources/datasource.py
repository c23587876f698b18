"""A data source of generated graphs: spark.read.format("rankgraph").option("edges", ...).load()."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from linkrank.sources.rmat import FACTOR, PRIME, SHARES, scale_for


class _Range(InputPartition):
    def __init__(self, start: int, end: int):
        self.start, self.end = start, end


class RankGraphSource(DataSource):
    """Options: edges, scale, seed, partitions. The rows are those of ``rmat_edges``."""

    @classmethod
    def name(cls) -> str:
        return "rankgraph"

    def schema(self) -> str:
        return "src long, dst long"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.edges = int(options.get("edges", "1000"))
        self.scale = int(options.get("scale", str(scale_for(self.edges))))
        self.seed = int(options.get("seed", "1"))
        self.parts = int(options.get("partitions", "8"))

    def partitions(self):
        cuts = np.linspace(0, self.edges, self.parts + 1).astype(int)
        return [_Range(int(a), int(b)) for a, b in zip(cuts[:-1], cuts[1:]) if b > a]

    def read(self, partition):
        limits = [int(PRIME * sum(SHARES[: k + 1])) for k in range(3)]
        for a in range(partition.start, partition.end, 1 << 18):
            s = (np.arange(a, min(partition.end, a + (1 << 18)), dtype=np.int64) * 2 + 1 + self.seed * 7919) % PRIME
            for _ in range(3):
                s = s * FACTOR % PRIME
            src, dst = np.zeros_like(s), np.zeros_like(s)
            for _ in range(self.scale):
                s = (s * FACTOR % PRIME ^ (s >> 13)) % PRIME
                src = src * 2 + (s >= limits[1])
                dst = dst * 2 + ((s >= limits[2]) | ((s >= limits[0]) & (s < limits[1])))
            yield pa.record_batch([src, dst], names=["src", "dst"])
