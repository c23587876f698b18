"""Near copies among vectors: a label's vectors in the order of their projections, in runs that are compared where they may link.

Vectors are projected on random directions and ordered, within their label, by the signs
of the projections, which close vectors mostly share. Runs of that order lie within balls.
Two vectors of the bound's cosine lie within a distance, so two runs whose balls are
farther apart hold no link; all others are compared by exact cosine. So no link is lost,
in a label of any size: the order only decides how many runs can be left out, which in a
crowded label may be none. The links are united
into components; within each component all vectors are then compared in blocks, so
that every vector knows all its links.

Equal vectors of a label are one vertex with a multiplicity, so that thousands of
copies cost no more than one. Only vectors with equal labels and lengths link. Those
that are null, zero, of null label or id, or hold null or non-finite components link
with nothing: no links, a component of their own, kept. Repeated ids count as separate
vectors. Empty input gives no rows.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkrank.llm.components import roots, components
from linkrank.llm.tables import cut, if_small, table

QUERY = "op3_vectors"

COSINE = 0.98
WORTH = 1000  # vectors of a run, BLOCK at least
PAIRS = 4096  # vectors of a block where all pairs of a component are compared
WINDOW = 16
BLOCK = 256  # vectors that are compared at a time
BUNDLE = 64  # vectors of small components that are compared in one go


def _unit(raw: list[bytes], kind: str) -> np.ndarray:
    x = np.frombuffer(b"".join(raw), kind).astype(np.float64).reshape(len(raw), -1)
    return x / np.linalg.norm(x, axis=1, keepdims=True)


def _pack(kind: str):
    """(vec_id, vec, size): the bytes of each usable vector; -0.0 counts as 0.0."""

    def pack(batches):
        for batch in batches:
            column = batch.column(1)
            flat = column.flatten().to_numpy(zero_copy_only=False).astype(kind)
            bounds = np.concatenate(([0], np.cumsum(column.value_lengths().fill_null(0).to_numpy())))
            good = np.concatenate(([0], np.cumsum(np.isfinite(flat)))) if len(flat) else np.zeros(1, int)
            some = np.concatenate(([0], np.cumsum(flat != 0))) if len(flat) else np.zeros(1, int)
            fine = (np.diff(bounds) > 0) & (good[bounds[1:]] - good[bounds[:-1]] == np.diff(bounds)) & (some[bounds[1:]] > some[bounds[:-1]])
            flat = flat + flat.dtype.type(0)
            vec = [flat[a:b].tobytes() if ok else None for a, b, ok in zip(bounds[:-1], bounds[1:], fine)]
            size = np.where(fine, np.diff(bounds), 0).astype(np.int32)
            yield pa.record_batch([batch.column(0), batch.column(2), pa.array(vec, pa.binary()), size], names=["vec_id", "label", "vec", "size"])

    return pack


def _project(kind: str, seed: int):
    """(rep, label, size, m, vec, code): the signs of a vector's projections on random directions, as a number in their order."""

    def project(batches):
        for batch in batches:
            size = batch.column(2).to_numpy()
            for d in np.unique(size):
                own = batch.filter(pa.array(size == d))
                signs = _unit(own.column(4).to_pylist(), kind) @ np.random.default_rng([seed, 0]).standard_normal((int(d), 64)) > 0
                code = np.packbits(signs, axis=1).view(">u8").ravel().astype(np.uint64) ^ np.uint64(1 << 63)
                yield pa.record_batch([*own.columns, code.view(np.int64)], names=["rep", "label", "size", "m", "vec", "code"])

    return project


def _keys(label, *numbers: np.ndarray) -> np.ndarray:
    """One number for each different row of a label column and arrays."""
    if isinstance(label, pa.ChunkedArray):
        label = label.combine_chunks()
    key = label.dictionary_encode().indices.to_numpy(zero_copy_only=False).astype(np.int64)
    for x in numbers:
        key = key * (int(x.max(initial=0)) + 1) + x
    return key


def _pairs(kind: str, cosine: float):
    """Links among the vectors of each label of a group, or between two runs of one."""

    def compare(group: pa.Table) -> pa.Table:
        side, rep, vec = group.column("side").to_numpy(), group.column("rep").to_numpy(), group.column("vec").to_pylist()
        key = _keys(group.column("label"), group.column("size").to_numpy())
        order = np.argsort(key, kind="stable")
        found = [(np.zeros(0, np.int64),) * 2]
        for own in np.split(order, np.flatnonzero(np.diff(key[order])) + 1):
            a, b = own[side[own] == 0], own[side[own] == 1]
            if not len(a):
                continue
            x = _unit([vec[k] for k in a], kind)
            y, b = (_unit([vec[k] for k in b], kind), b) if len(b) else (x, a)
            for lo in range(0, len(a), BLOCK):
                i, j = np.nonzero(x[lo : lo + BLOCK] @ y.T >= cosine)
                node, root = roots(rep[a[lo + i]], rep[b[j]])
                found.append((node[node != root], root[node != root]))
        return pa.table(dict(zip("ab", (np.concatenate(v) for v in zip(*found)))))

    return compare


def _count(kind: str, cosine: float):
    """Links of the vectors of a group: within each of its components, or between two blocks of one."""

    def count(group: pa.Table) -> pa.Table:
        comp, side, rep, n = (group.column(k).to_numpy() for k in ("component", "side", "rep", "n"))
        links = np.zeros(len(rep), np.int64)
        order = np.argsort(comp, kind="stable")
        cuts = np.flatnonzero(np.diff(comp[order])) + 1
        vec = group.column("vec").to_pylist()
        for own in np.split(order, cuts):
            a, b = own[side[own] == 0], own[side[own] == 1]
            if not len(a):
                continue
            x = _unit([vec[k] for k in a], kind)
            y = _unit([vec[k] for k in b], kind) if len(b) else x
            for lo in range(0, len(a), BLOCK):
                near = x[lo : lo + BLOCK] @ y.T >= cosine
                if len(b):
                    links[a[lo : lo + BLOCK]] += near @ n[b]
                    links[b] += near.T @ n[a[lo : lo + BLOCK]]
                else:
                    near[np.arange(len(near)), lo + np.arange(len(near))] = False
                    links[a[lo : lo + BLOCK]] += near @ n[a]
        return pa.table({"rep": rep, "links": links})

    return count


def near_copies(vectors: DataFrame, cosine: float = COSINE, seed: int = 11) -> DataFrame:
    """(vec_id, n_links, component_id, kept) from (vec_id, embedding, label)."""
    kind = "<f4" if "float" in vectors.schema["embedding"].dataType.simpleString() else "<f8"
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding"), F.col("label").cast("string").alias("label"))
    packed = rows.mapInArrow(_pack(kind), "vec_id long, label string, vec binary, size int")
    usable = (F.col("size") > 0) & F.col("label").isNotNull() & F.col("vec_id").isNotNull()
    packed = packed.withColumn("key", F.when(usable, F.md5(F.concat(F.col("label").cast("binary"), F.lit(b"\0"), F.col("vec")))))
    grouped = packed.where(usable).groupBy("key").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("n"), F.first("label").alias("label"), F.first("size").alias("size"), F.first("vec").alias("vec"))
    classes = cut(grouped)
    found = cut(components(_near(classes, kind, cosine, seed)))
    return _summary(packed, classes, found, _links(classes, found, kind, cosine))


def _ball(kind: str):
    """(centre, radius) around all vectors of a run, for their lengths of 1."""

    def ball(group: pa.Table) -> pa.Table:
        x = _unit(group.column("vec").to_pylist(), kind)
        centre = x.mean(axis=0)
        radius = float(np.linalg.norm(x - centre, axis=1).max())
        return group.select(["label", "size", "run"]).slice(0, 1).append_column("centre", pa.array([centre.tobytes()], pa.binary())).append_column("radius", pa.array([radius]))

    return ball


def _may_link(cosine: float):
    """Pairs of runs that may hold a link: two unit vectors of that cosine lie within a distance, so their runs' balls do."""
    reach = np.sqrt(2 - 2 * cosine) + 1e-9

    def may_link(batches):
        for batch in batches:
            gap = np.array([np.linalg.norm(np.frombuffer(a.as_buffer()) - np.frombuffer(b.as_buffer())) for a, b in zip(batch.column(4), batch.column(6))])
            near = gap <= batch.column(5).to_numpy() + batch.column(7).to_numpy() + reach
            yield batch.filter(pa.array(near)).select(["label", "size", "a", "b"])

    return may_link


def _runs(classes: DataFrame, labels: DataFrame, kind: str, seed: int) -> DataFrame:
    """(rep, label, size, m, vec, run): the vectors of a label in the order of their projections' signs, in runs of max(WORTH, BLOCK)."""
    rows = classes.join(if_small(labels), ["label", "size"]).select("rep", "label", "size", "m", "vec")
    coded = rows.mapInArrow(_project(kind, seed), "rep long, label string, size int, m long, vec binary, code long")
    ordered = coded.repartitionByRange("label", "size", "code", "rep").sortWithinPartitions("label", "size", "code", "rep")
    parts = cut(ordered.drop("code").withColumns({"_part": F.spark_partition_id(), "_at": F.monotonically_increasing_id()}))
    counts = parts.groupBy("label", "size", "_part").agg(F.count(F.lit(1)).alias("_n"), F.min("_at").alias("_first"))  # a row for each partition of a label
    before = F.sum("_n").over(Window.partitionBy("label", "size").orderBy("_part")) - F.col("_n")
    offsets = cut(counts.select("label", "size", "_part", (before - F.col("_first")).alias("_from")))
    place = parts.join(if_small(offsets), ["label", "size", "_part"]).withColumn("run", F.floor((F.col("_from") + F.col("_at")) / max(WORTH, BLOCK)).cast("long"))
    return cut(place.select("rep", "label", "size", "m", "vec", "run"))


def _near(classes: DataFrame, kind: str, cosine: float, seed: int) -> DataFrame:
    """(a, b): links that join up all near copies among the vertices, by the order of their projections as the module says."""
    labels = cut(classes.groupBy("label", "size").agg(F.count(F.lit(1)).alias("m")).where("m > 1"))
    rows = _runs(classes, labels, kind, seed)
    bundles = max(1, (labels.where(F.col("m") <= BLOCK).agg(F.sum("m")).first()[0] or 0) // BUNDLE)
    common = ["label", "size", "rep", "vec"]
    own = F.xxhash64("label", "size")
    small = rows.where(F.col("m") <= BLOCK).select(F.concat(F.lit("s"), F.pmod(own, F.lit(bundles)).cast("string")).alias("g"), F.lit(0).alias("side"), *common)
    rows = rows.where(F.col("m") > BLOCK)
    balls = cut(rows.groupBy("label", "size", "run").applyInArrow(_ball(kind), "label string, size int, run long, centre binary, radius double"))
    a = balls.select("label", "size", F.col("run").alias("a"), F.col("centre").alias("_ca"), F.col("radius").alias("_ra"))
    b = balls.select("label", "size", F.col("run").alias("b"), F.col("centre").alias("_cb"), F.col("radius").alias("_rb"))
    met = a.join(b, ["label", "size"]).where("a <= b").select("label", "size", "a", "b", "_ca", "_ra", "_cb", "_rb")
    pairs = cut(met.mapInArrow(_may_link(cosine), "label string, size int, a long, b long"))
    sides = pairs.select("label", "size", "a", "b", F.explode(F.when(F.col("a") == F.col("b"), F.array(F.lit(0))).otherwise(F.array(F.lit(0), F.lit(1)))).alias("side"))
    sides = sides.withColumn("run", F.when(F.col("side") == 0, F.col("a")).otherwise(F.col("b")))
    large = rows.join(if_small(sides), ["label", "size", "run"]).select(F.concat_ws(":", own.cast("string"), F.col("a").cast("string"), F.col("b").cast("string")).alias("g"), "side", *common)
    return small.unionByName(large).groupBy("g").applyInArrow(_pairs(kind, cosine), "a long, b long")


def _links(classes: DataFrame, found: DataFrame, kind: str, cosine: float) -> DataFrame:
    """(rep, links): the weight of the vectors linked to each vertex of a component."""
    sizes = cut(found.groupBy("component").agg(F.count(F.lit(1)).alias("m")))
    placed = cut(found.join(if_small(sizes), "component").join(classes.select(F.col("rep").alias("node"), "n", "vec"), "node"))
    bundles = max(1, placed.where(F.col("m") <= BLOCK).count() // BUNDLE)
    block = F.pmod(F.xxhash64("node"), F.ceil(F.col("m") / PAIRS))
    common = [F.col("component"), F.col("node").alias("rep"), "n", "vec"]
    small = placed.where(F.col("m") <= BLOCK).select(F.concat(F.lit("s"), F.pmod(F.xxhash64("component"), F.lit(bundles)).cast("string")).alias("g"), F.lit(0).alias("side"), *common)
    large = placed.where(F.col("m") > BLOCK).withColumn("i", block).withColumn("blocks", F.ceil(F.col("m") / PAIRS)).withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), F.col("blocks") - 1)))
    pair = F.concat_ws(":", "component", F.least("i", "j"), F.greatest("i", "j"))
    large = large.select(pair.alias("g"), (F.col("i") > F.col("j")).cast("int").alias("side"), *common)
    counted = small.unionByName(large).groupBy("g").applyInArrow(_count(kind, cosine), "rep long, links long")
    return counted.groupBy("rep").agg(F.sum("links").alias("links"))


def _summary(packed: DataFrame, classes: DataFrame, found: DataFrame, links: DataFrame) -> DataFrame:
    known = classes.select("key", "rep", "n").join(found.withColumnRenamed("node", "rep"), "rep", "left").join(links, "rep", "left")
    known = cut(known.select(F.col("key").alias("_key"), "rep", (F.col("n") - 1 + F.coalesce("links", F.lit(0))).alias("links"), F.coalesce("component", "rep").alias("component")))
    joined = packed.select("vec_id", "key").join(known, F.col("key") == F.col("_key"), "left")
    component = F.coalesce("component", "vec_id")
    return joined.select("vec_id", F.coalesce("links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(True)).alias("kept"))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_copies(table(spark, sf_dir, "embeddings"))


ORACLE = """
WITH RECURSIVE v AS (
  SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL
), p AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id AND list_cosine_similarity(a.e, b.e) >= 0.98
), r(a, b) AS (
  SELECT vec_id, vec_id FROM embeddings UNION SELECT r.a, p.b FROM r JOIN p ON r.b = p.a
), c AS (SELECT a AS vec_id, min(b) AS component_id FROM r GROUP BY a)
SELECT vec_id, (SELECT count(*) FROM p WHERE p.a = c.vec_id) AS n_links, component_id, vec_id = component_id AS kept FROM c
"""
