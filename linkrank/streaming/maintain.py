"""Streams of events and edges: windows, joins, stateful edges, and ranks kept up to date."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import replace

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupStateTimeout

from linkrank.config import RankConfig, RankResult
from linkrank.graph import Graph
from linkrank.operators.synchronous import sync_pull
from linkrank.plans.lineage import new_folder

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def event_stream(spark: SparkSession, path: str, files_per_batch: int | None = None) -> DataFrame:
    """Events from a folder of Parquet files, repeats within an hour of the newest dropped."""
    reader = spark.readStream.schema(EVENTS)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    events = reader.parquet(path).withColumn("ts", F.col("ts").cast("timestamp"))
    return events.withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])


def windowed(events: DataFrame, length: str = "1 day", slide: str | None = None) -> DataFrame:
    """(start, event_type, events, value): counts and sums by tumbling or sliding windows."""
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    return events.groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("events"), F.sum("value").alias("value")).select(F.col("w.start").alias("start"), "event_type", "events", "value")


def sessions(events: DataFrame, gap: str = "30 minutes") -> DataFrame:
    """(user_id, start, end, events): a user's events without a longer gap."""
    grouped = events.groupBy(F.session_window("ts", gap).alias("s"), "user_id").agg(F.count(F.lit(1)).alias("events"))
    return grouped.select("user_id", F.col("s.start").alias("start"), F.col("s.end").alias("end"), "events")


def purchases_after_clicks(events: DataFrame, other: DataFrame, within: str = "1 hour") -> DataFrame:
    """(click_id, purchase_id): purchases by the same user at most ``within`` after a click; two streams."""
    clicks = events.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("click_user"), F.col("ts").alias("click_ts"))
    bought = other.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", F.col("ts").alias("bought_ts"))
    near = (F.col("click_user") == F.col("user_id")) & (F.col("bought_ts") > F.col("click_ts")) & (F.col("bought_ts") <= F.col("click_ts") + F.expr(f"INTERVAL {within}"))
    return clicks.join(bought, near).select("click_id", "purchase_id")


def _follow(key, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
    last = state.get[0] if state.exists else None
    rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
    users = rows["user_id"].tolist()
    pairs = [(a, b) for a, b in zip(([last] if last is not None else []) + users, users if last is not None else users[1:]) if a != b]
    if users:
        state.update((int(users[-1]),))
    yield pd.DataFrame(pairs, columns=["src", "dst"])


def succession_edges(events: DataFrame) -> DataFrame:
    """(src, dst): a user and the next user with the same event type, across batches by the last user kept."""
    return events.select("event_type", "ts", "event_id", "user_id").groupBy("event_type").applyInPandasWithState(_follow, "src long, dst long", "user long", "append", GroupStateTimeout.NoTimeout)


class RankKeeper:
    """Ranks of a growing graph: each batch of edges is merged in, and ranking restarts from the last ranks.

    Use ``update`` with foreachBatch. Edges are appended to Parquet in the shared folder
    by batch number, so a repeated batch overwrites itself.
    """

    def __init__(self, spark: SparkSession, cfg: RankConfig = RankConfig(tol=1e-9), folder: str | None = None):
        self.spark, self.cfg = spark, cfg
        self.folder = folder or new_folder(spark, "edges")
        self.result: RankResult | None = None
        self.steps: list[int] = []

    def update(self, edges: DataFrame, batch: int) -> None:
        edges.select("src", "dst").distinct().write.mode("overwrite").parquet(f"{self.folder}/batch={batch}")
        graph = Graph.from_edges(self.spark.read.parquet(self.folder).select("src", "dst"))
        start = "uniform" if self.result is None else self.result.ranks
        self.result = sync_pull(graph, replace(self.cfg, init=start))
        self.steps.append(self.result.iterations)


def late_rows(query) -> int:
    """Rows that a stream's stateful operators dropped because they were older than the watermark."""
    return sum(int(op["numRowsDroppedByWatermark"]) for p in query.recentProgress for op in p["stateOperators"])
