"""More relational operators around graphs and ranks: windows, joins of several kinds, functions on text, time, maps and JSON."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from linkrank.config import RankConfig
from linkrank.graph import Graph
from linkrank.operators.relational import edge_delta
from linkrank.operators.synchronous import sync_pull
from linkrank.plans.lineage import cut
from linkrank.sources import workloads
from linkrank.sources.workloads import table

_CFG = RankConfig(max_iter=10, tol=0.0, check_every=5)


def _e9(ranks: DataFrame) -> DataFrame:
    return ranks.select("id", F.round(F.col("rank") * 1e9).cast("long").alias("rank_e9"))


def _user_ranks(spark, sf_dir) -> DataFrame:
    return _e9(sync_pull(workloads.load(spark, sf_dir, "user_succession"), _CFG).ranks)


def rank_by_nation_rollup(spark, sf_dir):
    """Rank mass of customers by region, nation and segment, with sub-totals."""
    customer, nation, region = (table(spark, sf_dir, t) for t in ("customer", "nation", "region"))
    ranks = _e9(sync_pull(workloads.load(spark, sf_dir, "trade_mutual"), _CFG).ranks).where("id % 2 = 0").select((F.col("id") / 2).cast("long").alias("c_custkey"), "rank_e9")
    joined = customer.join(ranks, "c_custkey").join(F.broadcast(nation), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(region), F.col("n_regionkey") == F.col("r_regionkey"))
    return joined.rollup("r_name", "n_name", "c_mktsegment").agg(F.sum("rank_e9").alias("mass"), F.count(F.lit(1)).alias("customers")).select("r_name", "n_name", "c_mktsegment", "mass", "customers")


def rank_windows(spark, sf_dir):
    """Places of parts within their brand in four ways, and the running mass of their brand."""
    part = table(spark, sf_dir, "part").select(F.col("p_partkey").alias("id"), "p_brand")
    ranks = _e9(sync_pull(workloads.load(spark, sf_dir, "part_succession"), _CFG).ranks).join(part, "id").withColumn("tens", F.floor(F.col("rank_e9") / 100_000))
    by = Window.partitionBy("p_brand").orderBy(F.desc("tens"))
    running = Window.partitionBy("p_brand").orderBy(F.desc("rank_e9"), "id").rowsBetween(Window.unboundedPreceding, 0)
    return ranks.select("id", F.rank().over(by).alias("place"), F.dense_rank().over(by).alias("dense"), F.round(F.percent_rank().over(by), 6).alias("share"), F.sum("rank_e9").over(running).alias("mass"))


def events_of_last_hour(spark, sf_dir):
    """For each event, how many of its user's lie in the hour before it, itself included, and their values' sum."""
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    hour = Window.partitionBy("user_id").orderBy("at").rangeBetween(-3_600_000_000, 0)
    return table(spark, sf_dir, "events").withColumn("at", at).select("event_id", F.count(F.lit(1)).over(hour).alias("events"), F.round(F.sum("value").over(hour), 4).alias("value"))


def supply_and_demand(spark, sf_dir):
    """Nations with customers, suppliers or both: a full join of two counts, by sort and merge."""
    customers = table(spark, sf_dir, "customer").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("customers"))
    suppliers = table(spark, sf_dir, "supplier").where("s_acctbal > 0").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count(F.lit(1)).alias("suppliers"))
    return customers.hint("merge").join(suppliers, "nation", "full").select("nation", "customers", "suppliers")


def rank_bands_of_users(spark, sf_dir, bands: int = 5):
    """Users by bands of rank between the extremes: a range join with a few band limits."""
    ranks = _user_ranks(spark, sf_dir)
    ends = ranks.agg(F.min("rank_e9").alias("lo"), F.max("rank_e9").alias("hi"))
    step = F.greatest(F.floor((F.col("hi") - F.col("lo")) / bands) + 1, F.lit(1))
    limits = ends.select("lo", step.alias("step"), F.explode(F.sequence(F.lit(0), F.lit(bands - 1))).alias("band")).select("band", (F.col("lo") + F.col("band") * F.col("step")).alias("low"), (F.col("lo") + (F.col("band") + 1) * F.col("step")).alias("high"))
    return ranks.join(F.broadcast(limits), (F.col("rank_e9") >= F.col("low")) & (F.col("rank_e9") < F.col("high"))).groupBy("band").agg(F.count(F.lit(1)).alias("users"), F.sum("rank_e9").alias("mass"))


PAGES = 1 << 14  # pages of a block
RUN = 1 << 22  # meetings of pages at a target that a task counts at a time
OUT = 1 << 16  # pairs of a batch that a task gives back


def _meetings(group: pa.Table, least: int):
    """(a, b, shared) of a group's pairs of pages with ``least`` targets in common; one side of the group's pages or both."""
    side, label = group.column("side").to_numpy(), group.column("label").combine_chunks()
    targets = group.column("targets").combine_chunks()
    size, target = targets.value_lengths().to_numpy(), np.unique(targets.flatten().to_numpy(), return_inverse=True)[1]
    page = np.repeat(np.arange(len(side)), size)
    order = np.argsort(target, kind="stable")
    at = np.flatnonzero(side == 1)
    same = not len(at)
    of = np.ones(len(side), bool) if same else side == 1
    place = np.cumsum(of) - 1
    other = order[of[page[order]]]
    first = np.searchsorted(target[other], np.arange(int(target.max(initial=-1)) + 2))
    names = np.flatnonzero(of)
    mine = np.flatnonzero(np.ones(len(side), bool) if same else side == 0)
    begin = np.concatenate(([0], np.cumsum(size)))
    step = max(1, RUN // max(1, len(names)))
    for lo in range(0, len(mine), step):
        rows = mine[lo : lo + step]
        edges = np.repeat(begin[rows] - np.concatenate(([0], np.cumsum(size[rows])))[:-1], size[rows]) + np.arange(int(size[rows].sum()))
        counts = np.zeros(len(rows) * len(names), np.int32)
        row = np.repeat(np.arange(len(rows)), size[rows])
        met = first[target[edges] + 1] - first[target[edges]]
        ends = np.cumsum(met)
        a = 0
        while a < len(edges):
            b = max(a + 1, int(np.searchsorted(ends, (ends[a - 1] if a else 0) + RUN, "right")))
            n = met[a:b]
            which = np.repeat(first[target[edges[a:b]]] - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
            counts += np.bincount(np.repeat(row[a:b], n) * len(names) + place[page[other[which]]], minlength=len(counts)).astype(np.int32)
            a = b
        found = np.flatnonzero(counts >= least)
        x, y = rows[found // len(names)], names[found % len(names)]
        if same:
            ok = x < y
            x, y, found = x[ok], y[ok], found[ok]
        for k in range(0, len(x), OUT):
            left, right = label.take(pa.array(x[k : k + OUT])), label.take(pa.array(y[k : k + OUT]))
            swap = pc.greater(left, right)
            yield pa.record_batch([pc.if_else(swap, right, left), pc.if_else(swap, left, right), pa.array(counts[found[k : k + OUT]].astype(np.int64))], names=["a", "b", "shared"])


def shared_targets(spark, sf_dir, least: int = 2):
    """Pairs of pages that link to the same targets at least ``least`` times: a self join, joined by the target within pairs of blocks of pages.

    A page moves once for each block, with its address and the hashes of its targets, which
    are checked for collisions. Pages that meet are counted in the task that names them, so
    no pair is moved or stored.
    """
    graph = Graph.from_labels(workloads.page_links(spark, sf_dir))
    lists = graph.edges.groupBy("src").agg(F.collect_list("dst").alias("targets")).where(F.size("targets") >= least)  # no other page has that many targets
    pages = cut(lists.join(graph.labels, F.col("src") == F.col("id")).select("src", "label", "targets"))
    blocks = max(1, -(-pages.count() // PAGES))
    placed = pages.withColumn("i", F.pmod(F.xxhash64("src", F.lit(7)), F.lit(blocks))).withColumn("j", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(blocks - 1).cast("long"))))
    sided = placed.select(F.least("i", "j").alias("lo"), F.greatest("i", "j").alias("hi"), (F.col("i") > F.col("j")).cast("int").alias("side"), "label", "targets")

    def meet(tables: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _meetings(pa.Table.from_batches(tables), least):
            yield batch

    dealt = sided.repartition(max(8, min(blocks * (blocks + 1) // 2, 10_000)), "lo", "hi")  # by number, as a group is little data and much work
    return dealt.groupBy("lo", "hi").applyInArrow(meet, "a string, b string, shared long")


def new_pages_delta(spark, sf_dir):
    """Edges that come and go between the links of the pages of even and of odd ids."""
    pages = table(spark, sf_dir, "pages")
    links = lambda rows: rows.select(F.parse_url("url", F.lit("HOST")).alias("src"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("dst"))
    return edge_delta(links(pages.where("page_id % 2 = 0")), links(pages.where("page_id % 2 = 1"))).groupBy("src", "change").agg(F.count(F.lit(1)).alias("links"))


def sampled_parts(spark, sf_dir):
    """A tenth of the parts, chosen by a hash that any engine has."""
    return table(spark, sf_dir, "part").where(F.conv(F.substring(F.md5(F.col("p_partkey").cast("string").cast("binary")), 1, 8), 16, 10).cast("long") % 10 == 0).select("p_partkey")


def distinct_and_quantiles(spark, sf_dir):
    """Distinct customers by status, whether the sketch is within a tenth of it, and quartiles of prices."""
    return table(spark, sf_dir, "orders").groupBy("o_orderstatus").agg(
        F.count_distinct("o_custkey").alias("customers"), (F.abs(F.approx_count_distinct("o_custkey", 0.02) - F.count_distinct("o_custkey")) <= 0.1 * F.count_distinct("o_custkey")).alias("sketch_is_near"),
        F.round(F.percentile("o_totalprice", 0.25), 4).alias("lower"), F.round(F.median("o_totalprice"), 4).alias("middle"),
    )


def text_functions(spark, sf_dir):
    """Hosts, lower-cased paths, and how far a page's host is from that of its first link."""
    pages = table(spark, sf_dir, "pages").withColumn("first", F.regexp_extract("html", 'href="([^"]*)"', 1))
    return pages.select("page_id", F.parse_url("url", F.lit("HOST")).alias("host"), F.lower(F.regexp_replace("url", "^[a-z]+://[^/]*", "")).alias("path"), F.length("first").alias("size"), F.levenshtein(F.parse_url("url", F.lit("HOST")), F.regexp_extract("first", "^[a-z]+://([^/]*)", 1)).alias("distance"), F.element_at(F.split("url", "/"), -1).alias("tail"))


def time_functions(spark, sf_dir):
    """Days, hours and weeks between an order's first and last shipment."""
    lines = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.min("l_shipdate").alias("a"), F.max("l_shipdate").alias("b"))
    return lines.select("l_orderkey", F.datediff("b", "a").alias("days"), F.expr("timestampdiff(HOUR, a, b)").alias("hours"), F.date_format(F.date_trunc("month", F.col("a") + F.expr("INTERVAL 7 DAYS")), "yyyy-MM").alias("month"))


def map_functions(spark, sf_dir):
    """Per user: counts by event type as a map, the types of more than one event, and a total over a merged map."""
    counts = table(spark, sf_dir, "events").groupBy("user_id", "event_type").agg(F.count(F.lit(1)).alias("n"))
    maps = counts.groupBy("user_id").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("event_type", "n")))).alias("m"))
    merged = F.map_concat(F.map_filter("m", lambda k, _: k != "view"), F.create_map(F.lit("none"), F.lit(0).cast("long")))
    return maps.select("user_id", F.coalesce(F.try_element_at("m", F.lit("click")), F.lit(0)).cast("long").alias("clicks"), F.size(F.map_filter("m", lambda _, n: n > 1)).alias("often"), F.aggregate(F.map_values(merged), F.lit(0).cast("long"), lambda a, x: a + x).alias("not_views"))


def json_functions(spark, sf_dir):
    """A property read by path, by schema and as a variant, and written back."""
    events = table(spark, sf_dir, "events").withColumn("s", F.from_json("props", "k INT")).withColumn("v", F.parse_json("props"))
    return events.select("event_id", F.get_json_object("props", "$.k").cast("int").alias("by_path"), F.col("s.k").alias("by_schema"), F.try_variant_get("v", "$.k", "int").alias("by_variant"), F.to_json(F.struct(F.col("s.k").alias("k"))).alias("written"))


def struct_functions(spark, sf_dir):
    """Each user's highest event and lowest, as records, spread over columns again; bits of the number of events."""
    found = table(spark, sf_dir, "events").groupBy("user_id").agg(
        F.array(F.struct(F.lit("most").alias("what"), F.max_by("event_id", F.struct("value", "event_id")).alias("event_id")), F.struct(F.lit("least").alias("what"), F.min_by("event_id", F.struct("value", "event_id")).alias("event_id"))).alias("ends"), F.bit_count(F.count(F.lit(1))).alias("bits"),
    )
    return found.select("user_id", "bits", F.inline("ends"))


def array_functions(spark, sf_dir):
    """Of each order: its parts in line order, the distinct ones, those of even key, and the sum of neighbours' products modulo 1009."""
    lines = table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(F.sort_array(F.collect_list(F.struct("l_linenumber", "l_partkey", "l_suppkey"))).alias("l"))
    keys = lines.select("l_orderkey", F.transform("l", lambda x: x["l_partkey"]).alias("p"))
    pairs = F.zip_with(F.slice("p", 1, F.greatest(F.size("p") - 1, F.lit(0))), F.slice("p", 2, F.size("p")), lambda a, b: F.pmod(a * b, F.lit(1009)))
    return keys.select("l_orderkey", F.size("p").alias("parts"), F.size(F.array_distinct("p")).alias("different"), F.size(F.filter("p", lambda x: x % 2 == 0)).alias("even"), F.aggregate(pairs, F.lit(0).cast("long"), lambda a, x: a + x).alias("products"))


def nan_functions(spark, sf_dir):
    """Logarithms of account balances, with those of negative ones caught."""
    x = F.expr("CASE WHEN c_acctbal > 0 THEN ln(c_acctbal) ELSE double('NaN') END")
    return table(spark, sf_dir, "customer").select("c_custkey", F.round(F.nanvl(x, F.lit(-1.0)), 6).alias("log_balance"), F.isnan(x).alias("caught"), F.round(F.pow(F.abs("c_acctbal"), 0.5), 4).alias("root"))


QUERIES = {
    f.__name__: f
    for f in (rank_by_nation_rollup, rank_windows, events_of_last_hour, supply_and_demand, rank_bands_of_users, shared_targets, new_pages_delta, sampled_parts, distinct_and_quantiles, text_functions, time_functions, map_functions, json_functions, struct_functions, array_functions, nan_functions)
}


def oracle_sql(rank_sql) -> dict[str, str]:
    """SQL of QUERIES; ``rank_sql`` gives that of a workload's ranks after some steps."""
    part, user, trade = (f"({rank_sql(w, 10)})" for w in ("part_succession", "user_succession", "trade_mutual"))
    links = "SELECT DISTINCT * FROM (SELECT url AS src, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS dst FROM pages) WHERE src <> dst"
    half = lambda k: f"SELECT regexp_extract(url, '^[a-z]+://([^/]*)', 1) AS src, unnest(regexp_extract_all(html, 'href=\"([^\"]*)\"', 1)) AS dst FROM pages WHERE page_id % 2 = {k}"
    return {
        "rank_by_nation_rollup": f"SELECT r_name, n_name, c_mktsegment, CAST(sum(rank_e9) AS BIGINT) AS mass, count(*) AS customers FROM customer JOIN {trade} ON id = 2 * c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY ROLLUP (r_name, n_name, c_mktsegment)",
        "rank_windows": f"""SELECT id, CAST(rank() OVER w AS INTEGER) AS place, CAST(dense_rank() OVER w AS INTEGER) AS dense, round(percent_rank() OVER w, 6) AS share, CAST(sum(rank_e9) OVER (PARTITION BY p_brand ORDER BY rank_e9 DESC, id ROWS UNBOUNDED PRECEDING) AS BIGINT) AS mass
FROM (SELECT *, floor(rank_e9 / 100000) AS tens FROM {part} JOIN part ON p_partkey = id) WINDOW w AS (PARTITION BY p_brand ORDER BY tens DESC)""",
        "events_of_last_hour": "SELECT event_id, count(*) OVER w AS events, round(sum(value) OVER w, 4) AS value FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts RANGE BETWEEN INTERVAL 1 HOUR PRECEDING AND CURRENT ROW)",
        "supply_and_demand": "SELECT coalesce(a.nation, b.nation) AS nation, customers, suppliers FROM (SELECT c_nationkey AS nation, count(*) AS customers FROM customer GROUP BY 1) a FULL JOIN (SELECT s_nationkey AS nation, count(*) AS suppliers FROM supplier WHERE s_acctbal > 0 GROUP BY 1) b ON a.nation = b.nation",
        "rank_bands_of_users": f"WITH r AS MATERIALIZED (SELECT * FROM {user}), e AS (SELECT min(rank_e9) AS lo, greatest(CAST(floor((max(rank_e9) - min(rank_e9)) / 5) AS BIGINT) + 1, 1) AS step FROM r) SELECT CAST((rank_e9 - lo) // step AS INTEGER) AS band, count(*) AS users, CAST(sum(rank_e9) AS BIGINT) AS mass FROM r, e GROUP BY 1",
        "shared_targets": f"WITH l AS ({links}) SELECT x.src AS a, y.src AS b, count(*) AS shared FROM l x JOIN l y ON x.dst = y.dst AND x.src < y.src GROUP BY 1, 2 HAVING count(*) >= 2",
        "new_pages_delta": f"SELECT src, 1 AS change, count(*) AS links FROM (({half(1)}) EXCEPT ALL ({half(0)})) GROUP BY src UNION ALL SELECT src, -1, count(*) FROM (({half(0)}) EXCEPT ALL ({half(1)})) GROUP BY src",
        "sampled_parts": "SELECT p_partkey FROM part WHERE CAST('0x' || substr(md5(CAST(p_partkey AS VARCHAR)), 1, 8) AS BIGINT) % 10 = 0",
        "distinct_and_quantiles": "SELECT o_orderstatus, count(DISTINCT o_custkey) AS customers, true AS sketch_is_near, round(quantile_cont(o_totalprice, 0.25), 4) AS lower, round(quantile_cont(o_totalprice, 0.5), 4) AS middle FROM orders GROUP BY 1",
        "text_functions": "SELECT page_id, regexp_extract(url, '^[a-z]+://([^/]*)', 1) AS host, lower(regexp_replace(url, '^[a-z]+://[^/]*', '')) AS path, CAST(length(f) AS INTEGER) AS size, CAST(levenshtein(regexp_extract(url, '^[a-z]+://([^/]*)', 1), regexp_extract(f, '^[a-z]+://([^/]*)', 1)) AS INTEGER) AS distance, string_split(url, '/')[-1] AS tail FROM (SELECT *, regexp_extract(html, 'href=\"([^\"]*)\"', 1) AS f FROM pages)",
        "time_functions": "SELECT l_orderkey, CAST(date_diff('day', a, b) AS INTEGER) AS days, date_sub('hour', a, b) AS hours, strftime(date_trunc('month', a + INTERVAL 7 DAY), '%Y-%m') AS month FROM (SELECT l_orderkey, min(l_shipdate) AS a, max(l_shipdate) AS b FROM lineitem GROUP BY 1)",
        "map_functions": "WITH c AS (SELECT user_id, event_type, count(*) AS n FROM events GROUP BY 1, 2) SELECT user_id, CAST(coalesce(sum(n) FILTER (event_type = 'click'), 0) AS BIGINT) AS clicks, CAST(count(*) FILTER (n > 1) AS INTEGER) AS often, CAST(coalesce(sum(n) FILTER (event_type <> 'view'), 0) AS BIGINT) AS not_views FROM c GROUP BY 1",
        "json_functions": "SELECT event_id, CAST(props->>'$.k' AS INTEGER) AS by_path, CAST(props->>'$.k' AS INTEGER) AS by_schema, CAST(props->>'$.k' AS INTEGER) AS by_variant, '{\"k\":' || (props->>'$.k') || '}' AS written FROM events",
        "struct_functions": "WITH x AS (SELECT user_id, CAST(bit_count(count(*)) AS INTEGER) AS bits, first(event_id ORDER BY value DESC, event_id DESC) AS hi, first(event_id ORDER BY value, event_id) AS lo FROM events GROUP BY 1) SELECT user_id, bits, 'most' AS what, hi AS event_id FROM x UNION ALL SELECT user_id, bits, 'least', lo FROM x",
        "array_functions": "WITH p AS (SELECT l_orderkey, list(l_partkey ORDER BY l_linenumber, l_partkey, l_suppkey) AS p FROM lineitem GROUP BY 1) SELECT l_orderkey, CAST(len(p) AS INTEGER) AS parts, CAST(len(list_distinct(p)) AS INTEGER) AS different, CAST(len([x FOR x IN p IF x % 2 = 0]) AS INTEGER) AS even, CAST(coalesce(list_sum([(p[k] * p[k + 1]) % 1009 FOR k IN range(1, len(p))]), 0) AS BIGINT) AS products FROM p",
        "nan_functions": "SELECT c_custkey, round(CASE WHEN c_acctbal > 0 THEN ln(c_acctbal) ELSE -1.0 END, 6) AS log_balance, c_acctbal <= 0 AS caught, round(sqrt(abs(c_acctbal)), 4) AS root FROM customer",
    }
