"""Removal of lines that spread over many sites.

A line is known by the hash of its text without outer blanks. A HyperLogLog sketch of
the sites (sources) is merged for each line by aggregation, so a line's state stays
small however common it is. Lines whose estimate lies clearly above or below the
threshold are settled; the few near it get an exact distinct count. Lines of at least
``MIN_SITES`` sites are boilerplate and are taken out of every document. A sketch of
2**SKETCH_BITS registers holds its first 24 values one by one, so around the threshold
of 10 an estimate is off only where 26-bit hashes of sites collide, far less than ``NEAR``;
with another threshold its standard error is 6.5 %, and NEAR some 4.6 of that.

Blank lines are never removed. Rows without source add no site. Null texts stay null
and have no lines. A document keeps its place, also if all its lines go (its text is
then empty); rows come back one for one with all their columns, also for null or
repeated ids. The counts are in n_lines and n_removed; a column that the input has under
such a name stays as it is, and the count gets an underscore behind its own.
DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linkrank.llm.tables import cut, free, if_small, table

QUERY = "op2_lines"

MIN_SITES = 10
SKETCH_BITS = 8  # 256 registers: a standard error of 6.5 %
NEAR = 0.3  # share of the threshold within which sites are counted exactly


def _lines(text: Column) -> Column:
    return F.split(text, "\n", -1)


def _key(line: Column) -> Column:
    return F.xxhash64(F.btrim(line, F.lit(" \t\r")))


def _shown(line: Column) -> Column:
    return F.btrim(line, F.lit(" \t\r")) != ""


def _exploded(docs: DataFrame, *more: Column) -> DataFrame:
    rows = docs.select(*more, F.posexplode(_lines(F.col("text").cast("string"))).alias("_pos", "_line"))
    return rows.where(_shown(F.col("_line"))).withColumn("_key", _key(F.col("_line"))).drop("_line")


def site_spread(docs: DataFrame, bits: int = SKETCH_BITS) -> DataFrame:
    """(_key, sites): the estimated number of sites of each line."""
    lines = _exploded(docs, F.xxhash64(F.col("source").cast("string")).alias("_hash"), F.col("source").isNotNull().alias("_has"))
    sites = lines.select("_key", F.when(F.col("_has"), F.col("_hash")).alias("_site"))
    return sites.groupBy("_key").agg(F.hll_sketch_agg("_site", F.lit(bits)).alias("_sketch")).select("_key", F.hll_sketch_estimate("_sketch").alias("sites"))


def boilerplate(docs: DataFrame, min_sites: int = MIN_SITES, near: float = NEAR) -> DataFrame:
    """(_key): the lines of at least ``min_sites`` sites."""
    spread = cut(site_spread(docs).where(F.col("sites") >= min_sites * (1 - near)))
    sure = spread.where(F.col("sites") > min_sites * (1 + near)).select("_key")
    close = spread.where(F.col("sites") <= min_sites * (1 + near)).select("_key")
    found = _exploded(docs, F.col("source").cast("string").alias("_site")).where(F.col("_site").isNotNull()).join(if_small(close), "_key", "left_semi")
    exact = found.select("_key", "_site").distinct().groupBy("_key").count().where(F.col("count") >= min_sites).select("_key")
    return sure.unionByName(exact)


def _mask(places: Column) -> Column:
    """A byte for each line up to the last of ``places``, which are sorted: 1 for those among them."""
    gap = lambda p, k: F.concat(F.repeat(F.lit("0"), p - F.when(k > 0, F.get(places, k - 1)).otherwise(-1) - 1), F.lit("1"))
    return F.array_join(F.transform(places, gap), "").cast("binary")


def remove_boilerplate(docs: DataFrame, min_sites: int = MIN_SITES) -> DataFrame:
    """The documents with the boilerplate out of their text, and n_lines and n_removed added.

    A document that holds boilerplate gets a mask of its lines, which meets it by id and
    hash of the text; masks are broadcast if they are few and small, else joined.
    """
    text = F.col("text").cast("string")
    id_, hash_, mask, many = free(docs.columns, "_id", "_hash", "_mask", "_many")
    n_lines, n_removed = free(docs.columns, "n_lines", "n_removed")
    keys = if_small(cut(boilerplate(docs, min_sites)))
    own = [F.col("doc_id").alias(id_), F.xxhash64(text).alias(hash_)]
    places = _exploded(docs, *own).join(keys, "_key").groupBy(id_, hash_).agg(F.sort_array(F.collect_set("_pos")).alias("_at"))
    gone = cut(places.select(id_, hash_, _mask(F.col("_at")).alias(mask), F.size("_at").alias(many)))
    joined = docs.join(if_small(gone, wide=mask), docs["doc_id"].eqNullSafe(gone[id_]) & (F.xxhash64(text) == gone[hash_]), "left")
    parts = F.filter(_lines(text), lambda _, at: F.substring(F.col(mask), at + 1, F.lit(1)) != F.lit(b"1"))
    kept = F.when(F.col(mask).isNull(), text).otherwise(F.array_join(parts, "\n"))
    size = F.when(docs["text"].isNull(), 0).otherwise(F.size(_lines(text)))
    columns = [kept.alias(c) if c == "text" else docs[c] for c in docs.columns]
    return joined.select(*columns, size.cast("long").alias(n_lines), F.coalesce(many, F.lit(0)).cast("long").alias(n_removed))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "source")
    return remove_boilerplate(docs).select("doc_id", "n_lines", "n_removed", F.md5("text").alias("text_md5"))


ORACLE = f"""
WITH l AS (
  SELECT doc_id, source, p, string_split(text, chr(10))[p] AS line
  FROM documents, LATERAL (SELECT unnest(range(1, len(string_split(text, chr(10))) + 1)) AS p)
), k AS (SELECT *, trim(line, ' ' || chr(9) || chr(13)) AS t FROM l),
b AS (SELECT t FROM k WHERE t <> '' GROUP BY t HAVING count(DISTINCT source) >= {MIN_SITES}),
m AS (SELECT k.*, b.t IS NOT NULL AS gone FROM k LEFT JOIN b USING (t))
SELECT doc_id, CAST(count(*) AS BIGINT) AS n_lines, CAST(count(*) FILTER (gone) AS BIGINT) AS n_removed,
       md5(coalesce(string_agg(line, chr(10) ORDER BY p) FILTER (NOT gone), '')) AS text_md5
FROM m GROUP BY doc_id
"""
