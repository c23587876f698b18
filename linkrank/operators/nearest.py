"""The nearest vectors of each vector within its label, by comparing all of them in blocks."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from linkrank.plans.lineage import cut

BLOCK = 4096  # vectors of a label that meet as many in a group
ROWS = 256  # vectors that are compared with a block at a time
FIRST, NONE, OUT = 3.0, -2.0, -9.0  # in place of cosines: not a number, unknown, not to be taken


def _unit(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """(rows of length 1, their number of components); shorter rows are filled with zeros, null ones are of no components."""
    vec = column.combine_chunks()
    size = vec.value_lengths().fill_null(0).to_numpy()
    x = np.zeros((len(size), max(1, int(size.max(initial=0)))))
    x[np.arange(x.shape[1]) < size[:, None]] = vec.flatten().to_numpy()
    with np.errstate(invalid="ignore", divide="ignore"):
        x /= np.abs(x).max(axis=1, keepdims=True)
        x /= np.linalg.norm(x, axis=1, keepdims=True)
    return x, size


def _best(x, size, ids, y, other_size, others, k: int, same: bool):
    """(src, dst, cosine) of the ``k`` largest cosines of each row, equal ones by id; ``same``: both sides hold the same vectors.

    Cosines count in billionths, and rounding keeps their order: only those within a billionth
    of a row's ``k``-th largest are rounded and put in order.
    """
    odd, other_odd = np.isnan(x).any(axis=1), np.isnan(y).any(axis=1)  # of length 0 or not finite
    x, y = np.where(odd[:, None], 0.0, x), np.where(other_odd[:, None], 0.0, y)
    width = min(x.shape[1], y.shape[1])
    y = np.ascontiguousarray(y[:, :width].T)
    lengths = np.unique(np.concatenate((size, other_size)))
    alike = len(lengths) == 1 and lengths[0] > 0
    for lo in range(0, len(x), ROWS):
        own = slice(lo, lo + ROWS)
        near = x[own, :width] @ y
        near[odd[own]] = FIRST
        near[:, other_odd] = FIRST
        if not alike:
            near[(size[own, None] != other_size) | (size[own, None] == 0)] = NONE
        if same:
            near[ids[own, None] == others] = OUT
        rows, held = np.arange(len(near)), []
        for _ in range(min(k, len(others))):
            at = near.argmax(axis=1)
            held.append((at, near[rows, at]))
            near[rows, at] = -np.inf
        for at, found in held:
            near[rows, at] = found
        least = held[-1][1] if held else np.zeros(len(near))
        row, at = np.nonzero(near >= (np.maximum(least, NONE) - 2e-9)[:, None])
        cos = np.round(near[row, at], 9)
        order = np.lexsort((others[at], -cos, row))
        row, at, cos = row[order], at[order], cos[order]
        first = np.searchsorted(row, rows)
        taken = np.arange(len(row)) - first[row] < k
        yield ids[own][row[taken]], others[at[taken]], cos[taken]


def _compare(k: int):
    def compare(group: pa.Table) -> pa.Table:
        side, ids = group.column("side").to_numpy(), group.column("vec_id").to_numpy()
        x, size = _unit(group.column("vec"))
        a, b = np.flatnonzero(side == 0), np.flatnonzero(side == 1)
        found = [(np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0))]
        for p, q in ((a, b), (b, a)) if group.column("lo")[0] != group.column("hi")[0] else ((a, a),):
            found += _best(x[p], size[p], ids[p], x[q], size[q], ids[q], k, p is q)
        src, dst, cos = (np.concatenate(v) for v in zip(*found))
        unknown = cos == NONE
        return pa.table({"src": src, "dst": dst, "cos": pa.array(np.where(cos == FIRST, np.nan, cos), mask=unknown)})

    return compare


def nearest(vectors: DataFrame, k: int) -> DataFrame:
    """(src, dst): the ``k`` others of each vector's label with the largest cosines in billionths, equal ones by id.

    Input is (vec_id, label, embedding). Cosines with a zero vector or one of a non-finite
    component are not a number and come first, those with a null or empty vector, one with a
    null component or one of another length are unknown and come last, as in SQL. A label
    is dealt to blocks, each pair of blocks is a group, and of a group only ``k`` rows a vector are kept.
    """
    whole = F.when(~F.exists("embedding", lambda x: x.isNull()), F.col("embedding").cast("array<double>")).alias("vec")
    rows = vectors.where("vec_id IS NOT NULL AND label IS NOT NULL").select(F.col("vec_id").cast("long").alias("vec_id"), "label", whole)
    labels = cut(rows.groupBy("label").agg(F.ceil(F.count(F.lit(1)) / BLOCK).alias("blocks")))
    groups = labels.agg(F.sum(F.col("blocks") * (F.col("blocks") + 1) / 2)).first()[0] or 1
    placed = rows.join(labels, "label").withColumn("i", F.pmod(F.xxhash64("vec_id"), "blocks")).withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    sided = placed.select("label", F.least("i", "j").alias("lo"), F.greatest("i", "j").alias("hi"), (F.col("i") > F.col("j")).cast("int").alias("side"), "vec_id", "vec")
    dealt = sided.repartition(int(min(max(groups, 8), 10_000)), "label", "lo", "hi")  # by number, as a group is little data and much work
    scored = dealt.groupBy("label", "lo", "hi").applyInArrow(_compare(k), "src long, dst long, cos double")
    ranked = scored.withColumn("r", F.row_number().over(Window.partitionBy("src").orderBy(F.desc("cos"), "dst")))
    return ranked.where(F.col("r") <= k).select("src", "dst")
