import math

import numpy as np
import pytest

from linkrank.operators import nearest as op
from linkrank.plans.lineage import plan_text

SCHEMA = "vec_id long, label int, embedding array<float>"


def brute(rows, k):
    """The k nearest by comparing all pairs: first what is not a number, last what is unknown."""
    found = set()
    for i, label, e in rows:
        scored = []
        for j, other, f in rows:
            if i is None or j is None or label is None or label != other or i == j:
                continue
            if not e or not f or len(e) != len(f) or None in e or None in f:
                scored.append((1, 0.0, j))
                continue
            norm = math.hypot(*e) * math.hypot(*f)
            cos = sum(x * y for x, y in zip(e, f)) / norm if norm and math.isfinite(norm) else math.nan
            scored.append((-1, 0.0, j) if math.isnan(cos) else (0, -round(cos, 9), j))
        found |= {(i, j) for *_, j in sorted(scored)[:k]}
    return found


@pytest.mark.parametrize("block", [4096, 16])
def test_equals_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(op, "BLOCK", block)
    rng = np.random.default_rng(3)
    x = np.repeat(rng.standard_normal((60, 4)), 2, axis=0).astype(np.float32)  # each vector twice, so there are ties
    rows = [(k, k % 3, v) for k, v in enumerate(x.tolist())]
    rows += [(200, 0, [0.0] * 4), (201, 0, None), (202, 0, []), (203, 0, [1.0, None, 2.0, 3.0]), (204, 0, [1.0, 2.0]), (205, None, [1.0] * 4), (None, 0, [1.0] * 4), (206, 1, [float("inf"), 1.0, 0.0, 0.0]), (207, 7, [1.0] * 4)]
    df = spark.createDataFrame(rows, SCHEMA)
    got = op.nearest(df, 3)
    assert "FlatMapGroupsInArrow" in plan_text(got)  # pairs were rows of a join before
    assert {(r.src, r.dst) for r in got.collect()} == brute(rows, 3)  # a zero vector ended the run before
    assert op.nearest(df.limit(0), 3).count() == 0


def test_statistics_of_the_graph_take_no_join_of_pairs(spark, tmp_path):
    from linkrank import queries

    rows = [(k, 0, [float(k % 7), float(k % 5), 1.0]) for k in range(50)] + [(60, 0, [0.0] * 3)]
    spark.createDataFrame(rows, SCHEMA).write.parquet(f"{tmp_path}/embeddings.parquet")
    found = queries.queries()["graph_stats_similarity_knn"](spark, str(tmp_path)).first()  # a zero vector ended the run before
    assert (found["vertices"], found["edges"]) == (51, 153)


def test_cosines_that_round_to_one_value_are_taken_by_id():
    rng = np.random.default_rng(5)
    x = rng.standard_normal((40, 8))
    x = np.concatenate([x, x + rng.standard_normal(x.shape) * 1e-12, x, x[:3]])  # cosines that differ by less than a billionth, and equal ones
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    ids, size = rng.permutation(len(x)), np.full(len(x), 8)
    got = sorted((int(a), int(b)) for p, q, _ in op._best(x, size, ids, x, size, ids, 4, True) for a, b in zip(p, q))
    near = np.round(x @ x.T, 9)
    want = sorted((int(i), int(j)) for i, row in zip(ids, near) for _, j in sorted((-c, j) for c, j in zip(row, ids) if j != i)[:4])
    assert got == want


def test_statistics_read_the_edges_once_and_store_no_graph(spark, tmp_path, monkeypatch):
    from linkrank import queries
    from linkrank.graph import Graph

    rows = [(k, k % 2, [float(k % 7), float(k % 5), 1.0]) for k in range(50)] + [(60, 0, [0.0] * 3), (70, 9, [1.0] * 3)]
    spark.createDataFrame(rows, SCHEMA).write.parquet(f"{tmp_path}/embeddings.parquet")
    want = queries.graph_stats(queries.workloads.load(spark, str(tmp_path), "similarity_knn")).collect()
    monkeypatch.setattr(Graph, "from_edges", lambda *a, **k: pytest.fail("a graph was stored"))
    assert queries.queries()["graph_stats_similarity_knn"](spark, str(tmp_path)).collect() == want
