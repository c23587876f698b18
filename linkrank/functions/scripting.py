"""Synchronous ranking as a SQL script, for sessions that hold no Python."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession


def ranks_script(edges: str, name: str, steps: int = 20, damping: float = 0.85) -> str:
    """A script that fills the table ``name`` (step, id, rank) with ``steps`` synchronous steps over the rows (src, dst) of ``edges``.

    The shares are stored by source once; each step reads the last one's ranks and appends its own.
    """
    return f"""BEGIN
  DECLARE at INT DEFAULT 0;
  DECLARE n BIGINT;
  CREATE TABLE {name}_shares USING parquet AS
    SELECT e.src, e.dst, 1.0D / count(*) OVER (PARTITION BY e.src) AS share FROM (SELECT DISTINCT src, dst FROM {edges} WHERE src <> dst) e;
  CREATE TABLE {name}_ids USING parquet AS SELECT src AS id FROM {name}_shares UNION SELECT dst FROM {name}_shares;
  SET n = (SELECT count(*) FROM {name}_ids);
  CREATE TABLE {name} USING parquet PARTITIONED BY (step) AS SELECT id, 1.0D / n AS rank, 0 AS step FROM {name}_ids;
  WHILE at < {steps} DO
    INSERT INTO {name} (id, rank, step)
      SELECT i.id, {1 - damping!r}D / n + {damping!r}D * coalesce(sum(s.share * r.rank), 0D), at + 1
      FROM {name}_ids i LEFT JOIN {name}_shares s ON s.dst = i.id LEFT JOIN (SELECT id, rank FROM {name} WHERE step = at) r ON r.id = s.src
      GROUP BY i.id;
    SET at = at + 1;
  END WHILE;
END"""


def script_ranks(spark: SparkSession, edges: str, name: str, steps: int = 20, damping: float = 0.85) -> DataFrame:
    """(id, rank) after the script's last step; its tables stay in the warehouse."""
    spark.sql(ranks_script(edges, name, steps, damping))
    return spark.table(name).where(f"step = {steps}").select("id", "rank")
