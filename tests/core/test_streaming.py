from pyspark.sql import functions as F

from linkrank.config import RankConfig
from linkrank.graph import Graph
from linkrank.operators.sequential import solve_exact
from linkrank.sources import workloads
from linkrank.streaming import maintain
from tests.core.graphs import close, ranks


def slices(spark, sf_dir, path, n=3):
    events = spark.read.parquet(f"{sf_dir}/events.parquet").orderBy("ts", "event_id").collect()
    cut = len(events) // n
    for k in range(n):
        part = events[k * cut : (k + 1) * cut if k < n - 1 else None]
        spark.createDataFrame(part, maintain.EVENTS).coalesce(1).write.parquet(f"{path}/{k}")
    return events


def drain(df, name, mode="append"):
    q = df.writeStream.outputMode(mode).format("memory").queryName(name).trigger(availableNow=True).start()
    q.awaitTermination()
    return df.sparkSession.table(name)


def test_windows_and_sessions(spark, sf_dir, tmp_path):
    slices(spark, sf_dir, tmp_path)
    spark.read.parquet(f"{tmp_path}/0").write.parquet(f"{tmp_path}/again")  # repeats
    events = lambda: maintain.event_stream(spark, f"{tmp_path}/*")
    got = drain(maintain.windowed(events()), "by_day", "complete").agg(F.sum("events")).first()[0]
    want = spark.read.parquet(f"{sf_dir}/events.parquet").count()
    assert got == want
    assert drain(maintain.sessions(events()), "by_session").agg(F.sum("events")).first()[0] <= want


def test_stream_join_equals_batch(spark, sf_dir, tmp_path):
    slices(spark, sf_dir, tmp_path, 1)
    events = maintain.event_stream(spark, f"{tmp_path}/*")
    got = drain(maintain.purchases_after_clicks(events, maintain.event_stream(spark, f"{tmp_path}/*")), "bought")
    from linkrank.operators.relational import clicks_then_purchase

    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, clicks_then_purchase(spark, sf_dir).collect()))


def test_succession_equals_batch(spark, sf_dir, tmp_path):
    slices(spark, sf_dir, tmp_path)
    got = []
    for k in range(3):
        assert spark.read.parquet(f"{tmp_path}/{k}").count()
    stream = spark.readStream.schema(maintain.EVENTS).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/*")
    got = {tuple(r) for r in drain(maintain.succession_edges(stream), "follow").collect()}
    want = {tuple(r) for r in workloads.user_succession(spark, sf_dir).distinct().collect()}
    assert got == want


def test_ranks_follow_batches(spark, tmp_path):
    keeper = maintain.RankKeeper(spark, RankConfig(tol=1e-4, partitions=2), folder=str(tmp_path / "edges"))
    keeper.update(spark.createDataFrame([(0, 1), (1, 2), (2, 0), (2, 3), (3, 0)], "src long, dst long"), 0)
    keeper.update(spark.createDataFrame([(3, 1)], "src long, dst long"), 1)
    keeper.update(spark.createDataFrame([(3, 1)], "src long, dst long"), 1)
    want = solve_exact(Graph.from_edges(spark.createDataFrame([(0, 1), (1, 2), (2, 0), (2, 3), (3, 0), (3, 1)], "src long, dst long")))
    assert close(ranks(keeper.result), ranks(want), 1e-3) and keeper.steps[2] <= 2
