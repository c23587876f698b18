"""Readers and writers of edge lists and ranks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGE = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])


def read_edges(spark: SparkSession, path: str, fmt: str = "tsv") -> DataFrame:
    """(src, dst) from an edge list: tsv (tabs or blanks, # comments), csv (header), json, orc or parquet."""
    if fmt == "tsv":
        lines = spark.read.text(path).select(F.trim("value").alias("v")).where("v <> '' AND NOT startswith(v, '#')")
        parts = F.split("v", r"\s+")
        return lines.select(F.try_element_at(parts, F.lit(1)).try_cast("long").alias("src"), F.try_element_at(parts, F.lit(2)).try_cast("long").alias("dst")).where("src IS NOT NULL AND dst IS NOT NULL")
    if fmt == "csv":
        return spark.read.schema(EDGE).csv(path, header=True)
    if fmt == "json":
        return spark.read.schema(EDGE).json(path)
    return spark.read.format(fmt).load(path).select(F.col("src").cast("long").alias("src"), F.col("dst").cast("long").alias("dst"))


def read_adjacency(spark: SparkSession, path: str) -> DataFrame:
    """(src, dst) from adjacency lists: a vertex and its out-neighbours on a line."""
    lines = spark.read.text(path).select(F.trim("value").alias("v")).where("v <> '' AND NOT startswith(v, '#')")
    parts = lines.select(F.split("v", r"[\s:,]+").alias("p"))
    return parts.select(F.col("p")[0].try_cast("long").alias("src"), F.explode(F.slice("p", 2, F.greatest(F.size("p") - 1, F.lit(0)))).alias("d")).select("src", F.col("d").try_cast("long").alias("dst")).where("src IS NOT NULL AND dst IS NOT NULL")


def write_edges(edges: DataFrame, path: str, fmt: str = "tsv") -> None:
    if fmt == "tsv":
        edges.select(F.concat_ws("\t", "src", "dst").alias("value")).write.text(path)
    elif fmt == "adjacency":
        edges.groupBy("src").agg(F.sort_array(F.collect_list("dst")).alias("d")).select(F.concat_ws(" ", F.col("src").cast("string"), F.concat_ws(" ", F.transform("d", lambda x: x.cast("string")))).alias("value")).write.text(path)
    elif fmt == "csv":
        edges.write.csv(path, header=True)
    else:
        edges.write.format(fmt).save(path)


def save_bucketed(frame: DataFrame, name: str, key: str, buckets: int) -> DataFrame:
    """A table bucketed and sorted by ``key``: later joins on it move nothing, run-time re-planning on or off."""
    frame.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)
    return frame.sparkSession.table(name)


def write_blocks(csr: DataFrame, path: str) -> None:
    """Block arrays (block, ids, in_ptr, in_src, in_coef) to Parquet, a folder for each block, so that a task reads its own only."""
    csr.write.mode("overwrite").partitionBy("block").parquet(path)


def read_blocks(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.parquet(path)


def append_history(result, path: str) -> None:
    """A run's course, appended to those of others (method, iteration, block, changes, work, seconds)."""
    result.history_frame().coalesce(1).write.mode("append").parquet(path)


LEDGER = "iteration int, block int, worker int, max_delta double, won boolean"


def append_ledger(result, path: str) -> None:
    """What each worker of a helped run handed in for each block and step, and whether it was taken."""
    rows = [(r["iteration"], r["block"], r["worker"], float(r["max_delta"]), r["won"]) for r in result.ledger]
    result.ranks.sparkSession.createDataFrame(rows, LEDGER).coalesce(1).write.mode("append").parquet(path)
