import random

from linkrank.config import RankConfig
from linkrank.functions.scripting import script_ranks
from linkrank.functions.udf import rank_view
from linkrank.graph import assign_blocks, csr_blocks
from linkrank.operators.helped import sync_helped
from linkrank.operators.synchronous import sync_pull
from linkrank.sources import edges as io
from linkrank.streaming.maintain import EVENTS, event_stream, late_rows, windowed
from tests.core.graphs import close, graph, random_edges, ranks


def test_script_equals_method(spark):
    pairs = random_edges(random.Random(3), 20, 70)
    spark.createDataFrame(pairs, "src long, dst long").createOrReplaceTempView("some_edges")
    want = ranks(sync_pull(graph(spark, pairs), RankConfig(max_iter=4, tol=0.0, partitions=2)))
    assert close(ranks(script_ranks(spark, "some_edges", "script_ranks_test", 4)), want, 1e-12)
    for name in ("", "_ids", "_shares"):
        spark.sql(f"DROP TABLE script_ranks_test{name}")


def test_blocks_history_ledger_and_view(spark, tmp_path):
    g = graph(spark, random_edges(random.Random(3), 20, 70))
    csr = csr_blocks(g, assign_blocks(g, 3))
    io.write_blocks(csr, f"{tmp_path}/csr")
    key = lambda r: (r.block, r.ids, r.in_ptr, r.in_src, r.in_coef)
    assert sorted(map(key, io.read_blocks(spark, f"{tmp_path}/csr").collect())) == sorted(map(key, csr.collect()))
    found = sync_helped(g, RankConfig(max_iter=2, tol=0.0, blocks=2, partitions=2), workers=2)
    for _ in range(2):
        io.append_history(found, f"{tmp_path}/history")
        io.append_ledger(found, f"{tmp_path}/ledger")
    assert spark.read.parquet(f"{tmp_path}/history").count() == 4
    assert spark.read.parquet(f"{tmp_path}/ledger").where("won").groupBy("iteration", "block").count().where("count <> 2").count() == 0
    rank_view(found, "some_ranks")
    assert spark.sql("SELECT count(*) AS n FROM some_ranks WHERE rank > 0").first().n == found.ranks.count()


def test_late_rows_are_counted(spark, tmp_path):
    day = lambda d, k: (k, f"2024-01-{d:02d} 00:00:00", 1, "view", 1.0, "{}")
    for k, rows in enumerate([[day(10, 1), day(11, 2)], [day(12, 3)], [day(1, 4)], [day(13, 5)]]):
        frame = spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, value double, props string")
        frame.selectExpr("event_id", "CAST(ts AS timestamp_ntz) AS ts", "user_id", "event_type", "value", "props").coalesce(1).write.mode("append").parquet(f"{tmp_path}/{k}")
    import shutil, glob, os

    os.makedirs(f"{tmp_path}/in")
    for k in range(4):
        for f in glob.glob(f"{tmp_path}/{k}/*.parquet"):
            shutil.copy(f, f"{tmp_path}/in/{k}-{os.path.basename(f)}")
            os.utime(f"{tmp_path}/in/{k}-{os.path.basename(f)}", (1_700_000_000 + k, 1_700_000_000 + k))
    query = windowed(event_stream(spark, f"{tmp_path}/in", 1)).writeStream.format("memory").queryName("late_test").outputMode("append").trigger(availableNow=True).start()
    query.awaitTermination()
    assert late_rows(query) >= 1 and EVENTS
    assert 1 not in {r.start.day for r in spark.table("late_test").collect()}
