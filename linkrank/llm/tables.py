"""Reading, sampling and cutting lineage for the corpus operators."""

from __future__ import annotations

import gc
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkrank.llm.text import mix
from linkrank.plans.lineage import shared_folder


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def cut(df: DataFrame) -> DataFrame:
    """Writes ``df`` to the cluster's shared checkpoint folder and reads it from there."""
    shared_folder(df.sparkSession)
    return df.checkpoint()


def release(spark: SparkSession) -> None:
    """Lets Spark delete the shuffles and checkpoints that nothing refers to any more.

    It deletes them when the driver's JVM finds them unreachable, which a driver with little
    to do can put off until all stages have left theirs on disk. To be called between stages
    that move much, once the frames of the stage before are cut.
    """
    gc.collect()  # Python's frames keep the JVM's alive
    spark.sparkContext._jvm.System.gc()


def if_small(df: DataFrame, rows: int = 200_000, wide: str | None = None, most: int = 32 << 20) -> DataFrame:
    """``df`` with a broadcast hint if it has at most ``rows`` rows; else as it is.

    Columns are to be narrow, but for ``wide`` (text or binary), of which at most ``most``
    bytes are broadcast. Counts ``df``, so it should be cheap to compute: a table or what
    cut() gave.
    """
    few = df.limit(rows + 1)
    if wide is None:
        return F.broadcast(df) if few.count() <= rows else df
    found = few.agg(F.count(F.lit(1)).alias("n"), F.coalesce(F.sum(F.octet_length(wide)), F.lit(0)).alias("size")).first()
    return F.broadcast(df) if found["n"] <= rows and found["size"] <= most else df


def free(columns, *names: str) -> list[str]:
    """``names``, each with as many underscores behind it as tell it from ``columns`` (without case)."""
    taken, out = {c.lower() for c in columns}, []
    for name in names:
        while name.lower() in taken:
            name += "_"
        taken.add(name.lower())
        out.append(name)
    return out


def running(df: DataFrame, order: list, **values) -> DataFrame:
    """``df`` with, for each name of ``values``, the column's sum over the rows before a row in ``order``.

    Rows are sorted in ranges and summed within them; the ranges' totals, one row each, are
    added. No task sees all rows. ``order`` should leave no ties, the names be free.
    """
    keyed = df.withColumns({f"_by{k}": c for k, c in enumerate(order)} | {f"_of_{name}": c for name, c in values.items()})
    by = [f"_by{k}" for k in range(len(order))]
    parts = cut(keyed.repartitionByRange(*by).withColumn("_part", F.spark_partition_id()))
    sums = parts.groupBy("_part").agg(*(F.sum(f"_of_{name}").alias(f"_all_{name}") for name in values))
    up = Window.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)
    offsets = sums.select("_part", *(F.coalesce(F.sum(f"_all_{name}").over(up), F.lit(0)).alias(f"_from_{name}") for name in values))
    own = Window.partitionBy("_part").orderBy(*by).rowsBetween(Window.unboundedPreceding, -1)
    joined = parts.join(F.broadcast(offsets), "_part")  # a row for each range
    return joined.select(*df.columns, *((F.col(f"_from_{name}") + F.coalesce(F.sum(f"_of_{name}").over(own), F.lit(0))).alias(name) for name in values))


def remainder(column, modulus: int):
    """crc32 of the id's text, modulo ``modulus``; null for a null id."""
    return F.crc32(F.col(column).cast("string").cast("binary")) % modulus


def bounded_sample(rows: DataFrame, by: str, most: int, counts: dict, order: str = "doc_id") -> DataFrame:
    """About ``most`` rows of each value of ``by`` that ``counts`` lists, the same on each run.

    Taken are the rows whose hash of ``order`` lies in the share that gives ``most`` of the
    value's rows, so nothing is sorted and no value's rows meet in one task.
    """
    if not counts:
        return rows.limit(0)
    parts = 1 << 30
    below = F.create_map(*(F.lit(x) for value, n in counts.items() for x in (value, math.ceil(parts * min(1.0, most / max(n, 1))))))
    return rows.where(F.col(by).isin(list(counts)) & (F.pmod(F.xxhash64(F.col(order), F.lit(1)), F.lit(parts)) < below[F.col(by)]))


def bounded_pieces(rows: DataFrame, by: str, size: int, most: int) -> DataFrame:
    """(by, piece): at most ``most`` pieces of ``size`` characters of each value's texts, in a hash's order.

    Each row (doc_id, text, by) gives all pieces of its whole text; a row's second one comes
    after the first ones of all rows. A task hands on no more of a value than ``most``.
    """

    def pick(batches):
        kept: dict = {}
        for batch in batches:
            for value, text, key in zip(*(c.to_pylist() for c in batch.columns)):
                places = mix(np.arange(-(-len(text or "") // size), dtype=np.uint64) + np.uint64(key & (1 << 62) - 1)) >> np.uint64(1)
                for turn, at in enumerate(np.argsort(places, kind="stable")[:most].tolist()):
                    kept.setdefault(value, []).append((turn, int(places[at]), text[at * size : (at + 1) * size]))
            for value in kept:
                kept[value] = sorted(kept[value])[:most]
        flat = [(value, *piece) for value in kept for piece in kept[value]]
        columns = list(zip(*flat)) or [()] * 4
        yield pa.record_batch([pa.array(columns[0], pa.string()), pa.array(columns[1], pa.int64()), pa.array(columns[2], pa.int64()), pa.array(columns[3], pa.string())], names=["by", "turn", "place", "piece"])

    found = rows.select(F.col(by).cast("string"), F.col("text").cast("string"), F.xxhash64("doc_id", F.lit(3))).mapInArrow(pick, "by string, turn long, place long, piece string")
    ranked = found.withColumn("n", F.row_number().over(Window.partitionBy("by").orderBy("turn", "place", "piece")))
    return ranked.where(F.col("n") <= most).select(F.col("by").alias(by), "n", "piece")


def training_rows(docs: DataFrame, labels: DataFrame, label: str, most: int, where) -> tuple[DataFrame, float]:
    """(doc_id, text, label) of about ``most`` rows of each class, and the log-odds of class 1.

    ``where`` says which ids of ``labels`` may be learned from; labels other than 0
    and 1 are passed over, and an id with several labels counts once, with the
    largest; of several texts of an id the first in order counts. The log-odds are those
    of all labels learned from, not of the sample. The sample's ids are bounded, so they
    are broadcast to the documents.
    """
    ids = labels.where(F.col(label).isin(0, 1) & where).groupBy(F.col("doc_id").cast("long").alias("doc_id")).agg(F.max(label).cast("int").alias(label))
    n = dict(ids.groupBy(label).count().collect())
    sample = bounded_sample(ids, label, most, n)
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    rows = texts.join(F.broadcast(sample), "doc_id").groupBy("doc_id", label).agg(F.min("text").alias("text"))
    return rows.select("doc_id", "text", label), math.log((n.get(1, 0) + 1) / (n.get(0, 0) + 1))
