"""Mixing sources to target weights by weighted sampling with exponential keys.

Sources, in code point order with null last, take the weights in turn and share a
budget of ``SHARE`` times all words. No target exceeds ``MOST`` times its source's
words: what is above goes to the other sources by weight until none is above. Each
source's documents then get exponential keys scaled by a quality weight; whole
passes over a source come first, and what is left of its target goes to the
documents with the smallest keys, by a prefix sum of their words.

The prefix sum is taken in two steps, as one source may hold any share of the rows: a
source's keys fall into bins of about ``BIN_ROWS`` rows, bins are summed and
accumulated, and only within a bin are rows sorted. A document counts for the
partial pass if the middle of it lies within what is left, so that a source misses
its target by half a document at most.

Null texts have no words. Rows come back one for one; equal keys are ordered by
doc_id, then text, so reruns agree; null ids draw their key by their text and sort
first among equal keys. A column of the input that has the name of a result's stays in
``mixed``, and the result's gets an underscore behind it. Empty input gives no rows.
DataFrame functions only.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkrank.llm.tables import cut, free, if_small, running, table

QUERY = "op8_mixing"

WEIGHTS = (3.0, 1.0, 2.0)
SHARE = 1.5
MOST = 2.0
BIN_ROWS = 4_000
WORD = r"[^\x20\x09-\x0D]+"


def words(text: Column) -> Column:
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def uniform(key: Column, salt: str) -> Column:
    """A number in (0, 1) from the key's text: 52 bits of its MD5."""
    bits = F.conv(F.substring(F.md5(F.concat(F.lit(salt), key)), 1, 13), 16, 10)
    return (bits.cast("double") + 0.5) / float(1 << 52)


def targets(sizes: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST) -> DataFrame:
    """(source, source_size, source_rows, target) from (source, source_size, source_rows).

    With sources ordered by limit over weight, those up to some place are held at
    their limit and the rest share what remains; the place is the first at which the
    level of the rest stays within the next limit. Places and sums over sources come from
    sorted ranges, so no task sees all of them, however many there are.
    """
    numbered = running(sizes.select("source", "source_size", "source_rows"), [F.col("source").isNull(), F.col("source")], _turn=F.lit(1))
    weight = F.element_at(F.array(*map(F.lit, weights)), (F.pmod(F.col("_turn"), F.lit(len(weights))) + 1).cast("int"))
    limited = numbered.withColumn("_w", weight).withColumn("_limit", most * F.col("source_size")).withColumn("_ratio", F.col("_limit") / F.col("_w")).drop("_turn")
    leveled = cut(running(limited, [F.col("_ratio"), F.col("source").isNull(), F.col("source")], _held=F.col("_limit"), _light=F.col("_w")))
    total, heavy = leveled.agg(F.coalesce(F.sum("source_size"), F.lit(0)), F.coalesce(F.sum("_w"), F.lit(0.0))).first()
    leveled = leveled.withColumn("_level", (share * F.lit(total) - F.col("_held")) / (F.lit(heavy) - F.col("_light")))
    best = leveled.agg(F.max(F.when(F.col("_level") <= F.col("_ratio"), F.col("_level")))).first()[0]
    least = F.col("_limit") if best is None else F.least("_limit", F.col("_w") * F.lit(best))
    return leveled.withColumn("target", least.cast("double")).select("source", "source_size", "source_rows", "target")


def _key(docs: DataFrame, weight: Column | None, salt: str) -> Column:
    drawn = uniform(F.coalesce(F.col("doc_id").cast("string"), F.md5(F.coalesce(F.col("text"), F.lit("")))), salt)
    return -F.log(drawn) / (weight if weight is not None else quality_weight(F.col("text")))


def sizes(docs: DataFrame, weight: Column | None = None, salt: str = "mix") -> DataFrame:
    """(doc_id, source, size, key): a row for each document, without its text."""
    return docs.select(
        F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), words(F.col("text")).alias("size"), _key(docs, weight, salt).alias("_key"), F.md5(F.coalesce(F.col("text"), F.lit(""))).alias("_tie")
    )


def quality_weight(text: Column) -> Column:
    """Between 1 and 2: falls with the share of digits and signs in the text."""
    size = F.octet_length(text)
    other = size - F.octet_length(F.translate(text, "0123456789#*$%&|<>{}[]\\^~_=+@", ""))
    return F.lit(2.0) - F.coalesce(other / F.when(size > 0, size), F.lit(1.0))


def mix(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST, weight: Column | None = None, salt: str = "mix") -> DataFrame:
    """doc_id, source, size, source_size, target, passes (times taken) and taken (words taken)."""
    rows = cut(sizes(docs, weight, salt))
    sources = rows.groupBy("source").agg(F.sum("size").alias("source_size"), F.count(F.lit(1)).alias("source_rows"))
    aims = cut(targets(sources, weights, share, most))
    same = F.col("a.source").eqNullSafe(F.col("r.source"))
    joined = rows.alias("r").join(if_small(aims).alias("a"), same).select("r.*", "a.source_size", "a.source_rows", "a.target")
    bins = F.ceil(F.col("source_rows") / BIN_ROWS)
    placed = joined.withColumn("_bin", F.least(bins - 1, F.floor((1 - F.exp(-1.5 * F.col("_key"))) * bins)))
    full = F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0)
    placed = placed.withColumn("_full", full).withColumn("_left", F.col("target") - F.col("_full") * F.col("source_size"))
    sums = placed.groupBy("source", "_bin").agg(F.sum("size").alias("_sum"))
    starts = sums.withColumn("_start", F.sum("_sum").over(Window.partitionBy("source").orderBy("_bin")) - F.col("_sum")).drop("_sum")
    inner = Window.partitionBy("source", "_bin").orderBy("_key", "doc_id", "_tie").rowsBetween(Window.unboundedPreceding, 0)
    ordered = placed.withColumn("_to", F.sum("size").over(inner))
    at = F.col("o.source").eqNullSafe(F.col("s.source")) & (F.col("o._bin") == F.col("s._bin"))
    middle = F.col("s._start") + F.col("o._to") - F.col("o.size") / 2
    taken = ordered.alias("o").join(starts.alias("s"), at).select(
        "o.doc_id", "o.source", "o.size", "o.source_size", "o.target", (F.col("o._full") + F.when((F.col("o.size") > 0) & (middle <= F.col("o._left")), 1).otherwise(0)).cast("long").alias("passes"), "o._key", "o._tie"
    )
    return taken.withColumn("taken", F.col("passes") * F.col("size"))


def mixed(docs: DataFrame, weights: tuple[float, ...] = WEIGHTS, share: float = SHARE, most: float = MOST, weight: Column | None = None, salt: str = "mix") -> DataFrame:
    """The documents that the mix takes, with all their columns, and how often (passes) and how many words (taken).

    A source takes a prefix of its documents in key order, so one row per source, with
    the last key taken, decides about every document where it stands.
    """
    passes, taken, source, full, end, size, here = free(docs.columns, "passes", "taken", "_source", "_full", "_end", "_size", "_here")
    plan = mix(docs, weights, share, most, weight, salt)
    place = F.struct("_key", "doc_id", "_tie")
    ends = plan.withColumn("_full", F.when(F.col("source_size") > 0, F.floor(F.col("target") / F.col("source_size"))).otherwise(0))
    ends = cut(ends.groupBy(F.col("source").alias(source)).agg(F.max("_full").alias(full), F.max(F.when(F.col("passes") > F.col("_full"), place)).alias(end)))
    own = F.struct(_key(docs, weight, salt).alias("_key"), F.col("doc_id").cast("long").alias("doc_id"), F.md5(F.coalesce(F.col("text"), F.lit(""))).alias("_tie"))
    marked = docs.withColumns({size: words(F.col("text")), here: own})
    joined = marked.join(if_small(ends), marked["source"].cast("string").eqNullSafe(F.col(source)))
    times = (F.col(full) + F.when((F.col(size) > 0) & (F.col(here) <= F.col(end)), 1).otherwise(0)).cast("long")
    return joined.withColumn(passes, times).where(F.col(passes) > 0).withColumn(taken, F.col(passes) * F.col(size)).select(*docs.columns, passes, taken)


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


ORACLE = r"""
WITH d AS (
  SELECT doc_id, source, CAST(len(regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')) AS BIGINT) AS size, md5(coalesce(text, '')) AS tie,
         -ln((CAST(('0x' || substr(md5('mix' || coalesce(CAST(doc_id AS VARCHAR), md5(coalesce(text, '')))), 1, 13)) AS BIGINT) + 0.5) / 4503599627370496.0)
           / (2.0 - coalesce((strlen(text) - strlen(translate(text, '0123456789#*$%&|<>{}[]\^~_=+@', ''))) / nullif(CAST(strlen(text) AS DOUBLE), 0), 1.0)) AS k
  FROM documents
), s AS (
  SELECT source, CAST(sum(size) AS BIGINT) AS source_size, [3.0, 1.0, 2.0][1 + (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3] AS w FROM d GROUP BY source
), lv AS (
  SELECT *, 2.0 * source_size AS lim,
         (1.5 * sum(source_size) OVER () - coalesce(sum(2.0 * source_size) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))
           / sum(w) OVER (o ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
  FROM s WINDOW o AS (ORDER BY 2.0 * source_size / w, source NULLS LAST)
), t AS (
  SELECT source, source_size, CAST(least(lim, w * max(CASE WHEN level <= lim / w THEN level END) OVER ()) AS DOUBLE) AS target FROM lv
), p AS (
  SELECT d.*, t.source_size, t.target, CASE WHEN t.source_size > 0 THEN floor(t.target / t.source_size) ELSE 0 END AS f,
         sum(size) OVER (PARTITION BY d.source ORDER BY k, doc_id, tie ROWS UNBOUNDED PRECEDING) - size / 2.0 AS middle
  FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source
)
SELECT doc_id, size, source_size, target, CAST((f + CASE WHEN size > 0 AND middle <= target - f * source_size THEN 1 ELSE 0 END) * size AS BIGINT) AS taken FROM p
"""
