"""Relational operators around ranks: joins of several kinds, roll-ups, windows, sets.

Each is a function of frames; ``QUERIES`` applies them to the given tables.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from linkrank.config import RankConfig
from linkrank.operators.synchronous import sync_pull
from linkrank.plans.lineage import cut
from linkrank.sources import workloads
from linkrank.sources.workloads import table


def as_of(left: DataFrame, right: DataFrame, key: str, at: str, value: str) -> DataFrame:
    """Left rows with the right side's last value of the same key at or before their time.

    Both sides are put in one order per key; ties go to the right side's rows first.
    """
    a = left.withColumns({"_side": F.lit(1), "_v": F.lit(None).cast(right.schema[value].dataType)})
    b = right.select(F.col(key), F.col(at), F.lit(0).alias("_side"), F.col(value).alias("_v"))
    both = a.unionByName(b, allowMissingColumns=True)
    last = F.last("_v", ignorenulls=True).over(Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0))
    return both.withColumn(f"{value}_as_of", last).where("_side = 1").drop("_side", "_v")


def within(left: DataFrame, right: DataFrame, key: str, at: str, seconds: int) -> DataFrame:
    """Pairs (l, r) of structs of the same key with the right time in (left time, left time + seconds].

    Times are cut into bins of that length, so a row meets two bins only.
    """
    bin_ = lambda c: F.floor(F.unix_micros(c.cast("timestamp")) / (seconds * 1_000_000)).cast("long")
    l = left.select(F.struct(*left.columns).alias("l"), F.explode(F.array(bin_(F.col(at)), bin_(F.col(at)) + 1)).alias("_bin"))
    r = right.select(F.struct(*right.columns).alias("r"), bin_(F.col(at)).alias("_bin"))
    gap = F.unix_micros(F.col(f"r.{at}").cast("timestamp")) - F.unix_micros(F.col(f"l.{at}").cast("timestamp"))
    return l.join(r, (F.col(f"l.{key}") == F.col(f"r.{key}")) & (l["_bin"] == r["_bin"])).where((gap > 0) & (gap <= seconds * 1_000_000)).select("l", "r")


def row_numbers(df: DataFrame, *order: str, name: str = "row") -> DataFrame:
    """Rows with their number from 0 in the given order, which should leave no ties.

    Rows are sorted in ranges and numbered within them; the ranges' offsets, one row each,
    are added. No task sees all rows.
    """
    parts = cut(df.repartitionByRange(*order).withColumn("_part", F.spark_partition_id()))
    sizes = parts.groupBy("_part").agg(F.count(F.lit(1)).alias("_n"))
    offsets = sizes.select("_part", (F.sum("_n").over(Window.orderBy("_part")) - F.col("_n")).alias("_from"))
    own = F.row_number().over(Window.partitionBy("_part").orderBy(*order)) - 1
    return parts.withColumn("_own", own).join(F.broadcast(offsets), "_part").withColumn(name, F.col("_from") + F.col("_own")).drop("_part", "_own", "_from")


def tiles(df: DataFrame, k: int, *order: str, name: str = "tile") -> DataFrame:
    """Rows with their tile from 1 to k of about equal numbers of rows; the first tiles take what is over."""
    n = df.count()
    size, over = divmod(n, k)
    at = F.col("_row")
    tile = F.when(at < over * (size + 1), F.floor(at / (size + 1))).otherwise(over + F.floor((at - over * (size + 1)) / max(size, 1)))
    return row_numbers(df, *order, name="_row").withColumn(name, (tile + 1).cast("int")).drop("_row")


def rank_bands(ranks: DataFrame, bands: int = 10) -> DataFrame:
    """(id, rank, band): 0 for the highest; bands of equal width between the extremes."""
    ends = ranks.agg(F.min("rank").alias("_lo"), F.max("rank").alias("_hi"))
    place = F.floor((F.col("_hi") - F.col("rank")) / F.when(F.col("_hi") > F.col("_lo"), F.col("_hi") - F.col("_lo")) * bands)
    return ranks.crossJoin(F.broadcast(ends)).select("id", "rank", F.coalesce(F.least(place, F.lit(bands - 1)), F.lit(0)).cast("int").alias("band"))


def rank_features(ranks: DataFrame, rows: DataFrame, key: str) -> DataFrame:
    """Rows with their vertex's rank and its place among all, as features for a recommender."""
    mean = F.broadcast(ranks.agg(F.avg("rank").alias("_mean")))  # one row
    placed = ranks.crossJoin(mean).select(F.col("id").alias("_id"), "rank", (F.col("rank") / F.col("_mean")).alias("rank_ratio"))
    return rows.join(placed, rows[key] == placed["_id"], "left").drop("_id")


def edge_delta(before: DataFrame, after: DataFrame) -> DataFrame:
    """(src, dst, change): +1 for edges that came, -1 for those that went."""
    pairs = lambda f: f.select("src", "dst")
    return pairs(after).exceptAll(pairs(before)).withColumn("change", F.lit(1)).unionByName(pairs(before).exceptAll(pairs(after)).withColumn("change", F.lit(-1)))


_CFG = RankConfig(max_iter=10, tol=0.0, check_every=5)


def _parts(spark, sf_dir) -> DataFrame:
    return sync_pull(workloads.load(spark, sf_dir, "part_succession"), _CFG).ranks


def _e9(c: Column | str) -> Column:
    return F.round(F.col(c) * 1e9 if isinstance(c, str) else c * 1e9).cast("long")


def topk_parts(spark, sf_dir, k: int = 20):
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), "p_name", "p_brand")
    return _parts(spark, sf_dir).withColumn("rank_e9", _e9("rank")).orderBy(F.desc("rank_e9"), "id").limit(k).join(part, "id").select("id", "p_name", "p_brand", "rank_e9")


def rank_by_brand_rollup(spark, sf_dir):
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), "p_brand", "p_size")
    joined = _parts(spark, sf_dir).withColumn("rank_e9", _e9("rank")).join(part, "id")
    return joined.rollup("p_brand", "p_size").agg(F.sum("rank_e9").alias("mass"), F.count(F.lit(1)).alias("parts")).select("p_brand", "p_size", "mass", "parts")


def top_parts_of_brand(spark, sf_dir, k: int = 3):
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), "p_brand")
    w = Window.partitionBy("p_brand").orderBy(F.desc("rank_e9"), "id")
    return _parts(spark, sf_dir).withColumn("rank_e9", _e9("rank")).join(part, "id").withColumn("place", F.row_number().over(w)).where(F.col("place") <= k).select("p_brand", "place", "id", "rank_e9")


def trade_cube(spark, sf_dir):
    customer, nation, region = (table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    joined = customer.join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))
    return joined.cube("r_name", "c_mktsegment").agg(F.count(F.lit(1)).alias("customers"), F.grouping_id().cast("int").alias("level"))


def customers_without_orders(spark, sf_dir):
    return table(spark, sf_dir, "customer").join(table(spark, sf_dir, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti").select("c_custkey", "c_name")


def last_error_before(spark, sf_dir):
    """Each purchase of a user with the id of the user's last error before it."""
    events = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    errors = events.where("event_type = 'error'").select("user_id", "ts", F.col("event_id").alias("error_id"))
    return as_of(events.where("event_type = 'purchase'").select("event_id", "user_id", "ts"), errors, "user_id", "ts", "error_id").select("event_id", "user_id", "error_id_as_of")


def clicks_then_purchase(spark, sf_dir):
    events = table(spark, sf_dir, "events").select("event_id", "user_id", "ts", "event_type")
    pairs = within(events.where("event_type = 'click'"), events.where("event_type = 'purchase'"), "user_id", "ts", 3600)
    return pairs.select(F.col("l.event_id").alias("click_id"), F.col("r.event_id").alias("purchase_id"))


def change_of_events(spark, sf_dir):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    events = table(spark, sf_dir, "events")
    return events.select("event_id", F.lag("event_id").over(w).alias("previous"), F.round(F.avg("value").over(w.rowsBetween(-2, 0)), 6).alias("mean3"), F.get_json_object("props", "$.k").cast("int").alias("k"))


def outcome_pivot(spark, sf_dir):
    return table(spark, sf_dir, "events").groupBy("user_id").pivot("event_type", ["click", "error", "purchase", "view"]).agg(F.count(F.lit(1)))


def hub_overlap(spark, sf_dir, k: int = 100):
    """Parts among both the most linked to and the most ordered."""
    lines = table(spark, sf_dir, "lineitem")
    ordered = lines.groupBy(F.col("l_partkey").alias("id")).agg(F.sum("l_quantity").alias("q")).orderBy(F.desc("q"), "id").limit(k).select("id")
    linked = workloads.load(spark, sf_dir, "part_succession").in_degrees().orderBy(F.desc("in_degree"), "id").limit(k).select("id")
    return ordered.intersect(linked)


def degree_quantiles(spark, sf_dir):
    ins = workloads.load(spark, sf_dir, "part_succession").in_degrees()
    return tiles(ins, 4, "in_degree", "id", name="quarter").groupBy("quarter").agg(F.min("in_degree").alias("least"), F.max("in_degree").alias("most"), F.count(F.lit(1)).alias("parts"))


def quality_of_linked(spark, sf_dir):
    """Labels of documents that hold a benchmark passage, beside all others'."""
    linked = workloads.passage_links(spark, sf_dir).select((F.col("src") / 2).cast("long").alias("doc_id")).distinct().withColumn("linked", F.lit(True))
    labels = table(spark, sf_dir, "labels")
    return labels.join(linked, "doc_id", "left").groupBy(F.coalesce("linked", F.lit(False)).alias("linked")).agg(F.count(F.lit(1)).alias("documents"), F.sum("quality").alias("good"))


def orders_by_month(spark, sf_dir):
    orders = table(spark, sf_dir, "orders")
    return orders.groupBy(F.date_trunc("month", "o_orderdate").cast("date").alias("month")).agg(F.count(F.lit(1)).alias("orders"), F.count_distinct("o_custkey").alias("customers"))


QUERIES = {
    "topk_parts": topk_parts, "rank_by_brand_rollup": rank_by_brand_rollup, "top_parts_of_brand": top_parts_of_brand, "trade_cube": trade_cube, "customers_without_orders": customers_without_orders,
    "last_error_before": last_error_before, "clicks_then_purchase": clicks_then_purchase, "change_of_events": change_of_events, "outcome_pivot": outcome_pivot, "hub_overlap": hub_overlap,
    "degree_quantiles": degree_quantiles, "quality_of_linked": quality_of_linked, "orders_by_month": orders_by_month,
}


def oracle_sql(rank_sql) -> dict[str, str]:
    """SQL of QUERIES; ``rank_sql`` gives that of a workload's ranks after some steps."""
    ranks = f"({rank_sql('part_succession', 10)})"
    lines = workloads.SQL["part_succession"]
    ins = f"(SELECT v.id, count(e.src) AS in_degree FROM (SELECT DISTINCT l_partkey AS id FROM lineitem) v LEFT JOIN (SELECT DISTINCT src, dst FROM ({lines}) WHERE src <> dst) e ON e.dst = v.id GROUP BY v.id)"
    return {
        "topk_parts": f"SELECT id, p_name, p_brand, rank_e9 FROM (SELECT * FROM {ranks} ORDER BY rank_e9 DESC, id LIMIT 20) JOIN part ON p_partkey = id",
        "rank_by_brand_rollup": f"SELECT p_brand, p_size, CAST(sum(rank_e9) AS BIGINT) AS mass, count(*) AS parts FROM {ranks} JOIN part ON p_partkey = id GROUP BY ROLLUP (p_brand, p_size)",
        "top_parts_of_brand": f"SELECT * FROM (SELECT p_brand, CAST(row_number() OVER (PARTITION BY p_brand ORDER BY rank_e9 DESC, id) AS INTEGER) AS place, id, rank_e9 FROM {ranks} JOIN part ON p_partkey = id) WHERE place <= 3",
        "trade_cube": "SELECT r_name, c_mktsegment, count(*) AS customers, CAST(grouping(r_name, c_mktsegment) AS INTEGER) AS level FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY CUBE (r_name, c_mktsegment)",
        "customers_without_orders": "SELECT c_custkey, c_name FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)",
        "last_error_before": "SELECT p.event_id, p.user_id, e.event_id AS error_id_as_of FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'error') e ON p.user_id = e.user_id AND p.ts >= e.ts",
        "clicks_then_purchase": "SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND p.ts > c.ts AND p.ts <= c.ts + INTERVAL 1 HOUR WHERE c.event_type = 'click' AND p.event_type = 'purchase'",
        "change_of_events": "SELECT event_id, lag(event_id) OVER w AS previous, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean3, CAST(props->>'$.k' AS INTEGER) AS k FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)",
        "outcome_pivot": "SELECT user_id, " + ", ".join(f"nullif(count(*) FILTER (event_type = '{t}'), 0) AS {t}" for t in ("click", "error", "purchase", "view")) + " FROM events GROUP BY user_id",
        "hub_overlap": f"SELECT id FROM (SELECT l_partkey AS id FROM lineitem GROUP BY 1 ORDER BY sum(l_quantity) DESC, 1 LIMIT 100) INTERSECT SELECT id FROM (SELECT id FROM {ins} ORDER BY in_degree DESC, id LIMIT 100)",
        "degree_quantiles": f"SELECT quarter, min(in_degree) AS least, max(in_degree) AS most, count(*) AS parts FROM (SELECT in_degree, CAST(ntile(4) OVER (ORDER BY in_degree, id) AS INTEGER) AS quarter FROM {ins}) GROUP BY quarter",
        "quality_of_linked": f"SELECT l.doc_id IN (SELECT src / 2 FROM ({workloads.SQL['passage_links']})) AS linked, count(*) AS documents, CAST(sum(quality) AS BIGINT) AS good FROM labels l GROUP BY 1",
        "orders_by_month": "SELECT CAST(date_trunc('month', o_orderdate) AS DATE) AS month, count(*) AS orders, count(DISTINCT o_custkey) AS customers FROM orders GROUP BY 1",
    }
