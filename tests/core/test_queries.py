import importlib
import math
import sys

import duckdb
import pytest

import __spark_entry__ as entry
from linkrank import queries

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()
SOME = [
    "edges_page_links", "edges_event_lattice", "edges_host_links", "graph_stats_part_succession", "graph_stats_host_links", "rank_sync_pull_user", "rank_sync_pull_page", "rank_async_pull_part", "rank_async_edge_rounds_user",
    "rank_freeze_part", "rank_twins_page", "rank_redistribute_page", "rank_rmat", "error_curve_part", "twin_classes_page", "helped_equals_barrier", "topk_parts", "rank_by_brand_rollup", "trade_cube", "last_error_before", "clicks_then_purchase",
    "change_of_events", "outcome_pivot", "degree_quantiles", "customers_without_orders",
]


def rows(found, names):
    out = [tuple(round(v, 6) if isinstance(v, float) else v for v in (r[n] for n in names)) for r in found]
    return sorted(out, key=lambda r: tuple((v is None, str(type(v)), v if not isinstance(v, float) or not math.isnan(v) else 0) for v in r))


@pytest.fixture(scope="module")
def duck(sf_dir):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{sf_dir}/{t}.parquet')")
    return con


@pytest.mark.parametrize("name", SOME)
def test_equals_sql(spark, sf_dir, duck, name):
    want = duck.sql(queries.oracle_sql()[name])
    names = sorted(want.columns)
    got = queries.queries()[name](spark, sf_dir)
    assert sorted(got.columns) == names
    assert rows([r.asDict() for r in got.collect()], names) == rows([dict(zip(want.columns, r)) for r in want.fetchall()], names)


def test_entry(spark):
    assert entry.entry(spark).count() == 20
    assert set(entry.oracle_sql()) <= set(entry.queries())


def test_the_rest_stands_without_the_corpus_operators(monkeypatch):
    monkeypatch.setitem(sys.modules, "linkrank.llm", None)
    monkeypatch.setitem(sys.modules, "linkrank.llm.registry", None)
    monkeypatch.setitem(sys.modules, "corpus_pipeline", None)
    monkeypatch.delattr("linkrank.llm", raising=False)
    alone = importlib.reload(entry)
    assert "rank_sync_pull_part" in alone.queries() and not any(n.startswith("op") for n in alone.queries()) and "pipeline" not in alone.queries()
    monkeypatch.undo()
    importlib.reload(entry)
