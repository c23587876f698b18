"""Settings for loops, and cutting lineage."""

from __future__ import annotations

import re
import tempfile
import uuid
from contextlib import contextmanager

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """The folder that all executors share: the session's checkpoint folder; a temporary one only where none is set."""
    context = spark.sparkContext
    if context.getCheckpointDir() is None:
        folder = spark.conf.get("spark.checkpoint.dir", None)
        if not folder:
            if not re.match(r"local(\[|$)", context.master):
                raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
            folder = tempfile.mkdtemp(prefix="checkpoints-")
        context.setCheckpointDir(folder)
    return context.getCheckpointDir()


def new_folder(spark: SparkSession, name: str) -> str:
    return f"{shared_folder(spark).rstrip('/')}/{name}-{uuid.uuid4().hex}"


def cut(df: DataFrame) -> DataFrame:
    """Stores ``df`` in the shared folder and reads it from there; its partitioning stays known."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


@contextmanager
def loop_settings(spark: SparkSession, partitions: int | None = None):
    """Fixed partitioning while a loop is built and run.

    With runtime re-planning, a stored state's partitioning is unknown and each step
    shuffles both sides of its joins again; without it a step has one exchange. Small
    sides are not broadcast either, as the state's size is the graph's.
    """
    wanted = {"spark.sql.adaptive.enabled": "false", "spark.sql.autoBroadcastJoinThreshold": "-1"}
    if partitions:
        wanted["spark.sql.shuffle.partitions"] = str(partitions)
    before = {k: spark.conf.get(k) for k in wanted}
    for k, v in wanted.items():
        spark.conf.set(k, v)
    try:
        yield
    finally:
        for k, v in before.items():
            spark.conf.set(k, v)


def plan_text(df: DataFrame) -> str:
    return df._jdf.queryExecution().executedPlan().toString()


def exchanges(df: DataFrame) -> int:
    """Hash exchanges in a frame's physical plan."""
    return len(re.findall(r"Exchange hashpartitioning", plan_text(df)))
