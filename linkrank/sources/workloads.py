"""Graphs over the given tables, as stand-ins for web, social, road and synthetic graphs.

Each builder gives rows (src, dst); text labels where the name says so. ``SQL`` holds
the same edge lists for a SQL engine.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkrank.graph import Graph
from linkrank.operators.nearest import nearest


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _succession(lines: DataFrame, key: str) -> DataFrame:
    order = Window.partitionBy("l_orderkey").orderBy("l_linenumber", "l_partkey", "l_suppkey")
    return lines.select(F.col(key).alias("src"), F.lead(key).over(order).alias("dst")).where("dst IS NOT NULL AND src <> dst")


def part_succession(spark, sf_dir):
    return _succession(table(spark, sf_dir, "lineitem"), "l_partkey")


def supplier_succession(spark, sf_dir):
    return _succession(table(spark, sf_dir, "lineitem"), "l_suppkey")


def order_parts(spark, sf_dir):
    """Orders have even ids, parts odd ones."""
    return table(spark, sf_dir, "lineitem").select((F.col("l_orderkey") * 2).alias("src"), (F.col("l_partkey") * 2 + 1).alias("dst"))


def part_suppliers(spark, sf_dir):
    return table(spark, sf_dir, "lineitem").select((F.col("l_partkey") * 2).alias("src"), (F.col("l_suppkey") * 2 + 1).alias("dst"))


def trade_mutual(spark, sf_dir):
    """Customers have even ids, suppliers odd ones; both directions."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    met = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).select((F.col("o_custkey") * 2).alias("c"), (F.col("l_suppkey") * 2 + 1).alias("s")).distinct()
    return met.select(F.explode(F.array(F.struct(F.col("c").alias("src"), F.col("s").alias("dst")), F.struct(F.col("s").alias("src"), F.col("c").alias("dst")))).alias("e")).select("e.*")


def nation_trade(spark, sf_dir):
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey")
    suppliers = table(spark, sf_dir, "supplier").select("s_suppkey", "s_nationkey")
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey")
    lines = table(spark, sf_dir, "lineitem").select("l_orderkey", "l_suppkey")
    joined = orders.join(lines, F.col("o_orderkey") == F.col("l_orderkey")).join(customers, F.col("o_custkey") == F.col("c_custkey")).join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))
    return joined.select(F.col("c_nationkey").cast("long").alias("src"), F.col("s_nationkey").cast("long").alias("dst")).distinct().where("src <> dst")


def _next_in_time(events: DataFrame, key: list[str], value: str) -> DataFrame:
    """Events with ``following``: the value of the next one of the same key by (ts, event_id).

    Days are sorted each by itself, and a day's last event is followed by the first of the
    key's next day that has one, so a key with any share of the events is not one task.
    """
    dated = events.withColumn("_day", F.to_date("ts"))
    firsts = dated.groupBy(*key, "_day").agg(F.min_by(value, F.struct("ts", "event_id")).alias("_first"))
    later = firsts.select(*key, "_day", F.lead("_first").over((Window.partitionBy(*key) if key else Window).orderBy("_day")).alias("_later"))  # a row for each key and day
    own = F.lead(value).over(Window.partitionBy(*key, "_day").orderBy("ts", "event_id"))
    return dated.withColumn("_own", own).join(later, [*key, "_day"]).withColumn("following", F.coalesce("_own", "_later")).drop("_day", "_own", "_later")


def user_succession(spark, sf_dir):
    events = _next_in_time(table(spark, sf_dir, "events").select("event_type", "ts", "event_id", "user_id").where("event_type IS NOT NULL"), ["event_type"], "user_id")
    return events.select(F.col("user_id").alias("src"), F.col("following").alias("dst")).where("dst IS NOT NULL AND src <> dst")


def event_lattice(spark, sf_dir):
    """Consecutive events of a user both ways; each 20th event and the next of all both ways."""
    events = table(spark, sf_dir, "events").select("event_id", "user_id", "ts")
    own = events.select(F.col("event_id").alias("a"), F.lead("event_id").over(Window.partitionBy("user_id").orderBy("ts", "event_id")).alias("b"))
    next_ = _next_in_time(events, [], "event_id").select(F.col("event_id").alias("a"), F.col("following").alias("b")).where("a % 20 = 0")
    both = own.unionByName(next_).where("b IS NOT NULL AND a <> b")
    return both.select(F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst")))).alias("e")).select("e.*")


TURNS = 1 << 20  # ids of a conversation's turns


def turn_chain(spark, sf_dir):
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn").distinct()
    id_ = F.col("conv_id") * TURNS + F.col("turn")
    return turns.alias("a").join(turns.select("conv_id", (F.col("turn") - 1).alias("turn")), ["conv_id", "turn"]).select(id_.alias("src"), (id_ + 1).alias("dst"))


def page_links(spark, sf_dir):
    """Page addresses and the targets of their links, as text."""
    pages = table(spark, sf_dir, "pages")
    return pages.select(F.col("url").alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("dst")).where("src <> dst")


def host_links(spark, sf_dir):
    """Hosts of the pages and the targets of their links, as text, with multiplicity."""
    pages = table(spark, sf_dir, "pages")
    return pages.select(F.regexp_extract("url", "^[a-z]+://([^/]*)", 1).alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("dst")).where("src <> dst")


def similarity_knn(spark, sf_dir, k: int = 3):
    """Each vector and its k nearest by cosine within its label, ties by id."""
    return nearest(table(spark, sf_dir, "embeddings"), k)


HEAD = 16


def passage_links(spark, sf_dir):
    """Documents (even ids) and the benchmark items (odd ids) whose text they contain.

    Pairs are looked up by the first HEAD characters of an item, or all of a shorter one, cut
    at each place of a document; stretches of 1,000 characters are cut first, as a place in
    a long text is found only by walking to it.
    """
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    items = table(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("passage"), F.substring("text", 1, HEAD).alias("head")).where("length(passage) > 0")
    sizes = [r[0] for r in items.select(F.length("head")).distinct().collect()]  # HEAD numbers at most
    parts = docs.select("doc_id", F.explode(F.expr(f"transform(sequence(1, greatest(length(text), 1), 1000), k -> substring(text, k, {1000 + HEAD - 1}))")).alias("part"))
    cuts = [F.expr(f"transform(sequence(1, greatest(least(1000, length(part) - {n - 1}), 1)), k -> substring(part, k, {n}))") for n in sizes]
    places = parts.select("doc_id", F.explode(F.array_distinct(F.concat(*cuts) if cuts else F.array().cast("array<string>"))).alias("head")).join(items, "head").select("doc_id", "item_id", "passage").distinct()
    found = places.join(docs, "doc_id").where(F.col("text").contains(F.col("passage")))
    return found.select((F.col("doc_id") * 2).alias("src"), (F.col("item_id") * 2 + 1).alias("dst")).distinct()


BUILDERS: dict[str, Callable] = {
    "page_links": page_links, "part_succession": part_succession, "order_parts": order_parts, "part_suppliers": part_suppliers, "trade_mutual": trade_mutual, "user_succession": user_succession,
    "supplier_succession": supplier_succession, "nation_trade": nation_trade, "event_lattice": event_lattice, "turn_chain": turn_chain, "host_links": host_links, "similarity_knn": similarity_knn, "passage_links": passage_links,
}
LABELED = {"page_links", "host_links"}
WEIGHTED = {"host_links"}


def load(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    """The graph of a workload."""
    edges = BUILDERS[name](spark, sf_dir)
    build = Graph.from_labels if name in LABELED else Graph.from_edges
    return build(edges, multiplicity=name in WEIGHTED)


_BOTH = "SELECT a AS src, b AS dst FROM p UNION ALL SELECT b, a FROM p"
SQL: dict[str, str] = {
    "part_succession": "SELECT src, dst FROM (SELECT l_partkey AS src, lead(l_partkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst FROM lineitem)",
    "supplier_succession": "SELECT src, dst FROM (SELECT l_suppkey AS src, lead(l_suppkey) OVER (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS dst FROM lineitem)",
    "order_parts": "SELECT l_orderkey * 2 AS src, l_partkey * 2 + 1 AS dst FROM lineitem",
    "part_suppliers": "SELECT l_partkey * 2 AS src, l_suppkey * 2 + 1 AS dst FROM lineitem",
    "trade_mutual": f"WITH p AS (SELECT DISTINCT o_custkey * 2 AS a, l_suppkey * 2 + 1 AS b FROM orders JOIN lineitem ON o_orderkey = l_orderkey) {_BOTH}",
    "nation_trade": "SELECT CAST(c_nationkey AS BIGINT) AS src, CAST(s_nationkey AS BIGINT) AS dst FROM orders JOIN lineitem ON o_orderkey = l_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey",
    "user_succession": "SELECT src, dst FROM (SELECT user_id AS src, lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS dst FROM events WHERE event_type IS NOT NULL)",
    "event_lattice": f"""WITH p AS (
        SELECT event_id AS a, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events
        UNION ALL SELECT a, b FROM (SELECT event_id AS a, lead(event_id) OVER (ORDER BY ts, event_id) AS b FROM events) WHERE a % 20 = 0) {_BOTH}""",
    "turn_chain": f"SELECT x.conv_id * {TURNS} + x.turn AS src, y.conv_id * {TURNS} + y.turn AS dst FROM conversations x JOIN conversations y ON x.conv_id = y.conv_id AND y.turn = x.turn + 1",
    "page_links": """SELECT url AS src, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS dst FROM pages""",
    "host_links": """SELECT regexp_extract(url, '^[a-z]+://([^/]*)', 1) AS src, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS dst FROM pages""",
    "similarity_knn": """SELECT src, dst FROM (SELECT a.vec_id AS src, b.vec_id AS dst, row_number() OVER (PARTITION BY a.vec_id ORDER BY round(list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])), 9) DESC, b.vec_id) AS r
        FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id <> b.vec_id) WHERE r <= 3""",
    "passage_links": "SELECT doc_id * 2 AS src, item_id * 2 + 1 AS dst FROM documents d JOIN benchmark b ON contains(d.text, b.text) WHERE length(b.text) > 0",
}
