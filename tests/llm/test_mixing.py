import random

import pytest

from linkrank.llm import mixing
from tests.llm.oracle import same


@pytest.mark.parametrize("sf", ["0.001", "0.01"])
def test_equals_sql(spark, sf):
    same(spark, mixing.query, mixing.ORACLE, f"/root/testdata/sf{sf}")


def test_bins_do_not_change_the_mix(spark, monkeypatch):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    want = sorted(map(tuple, mixing.mix(docs).collect()))
    monkeypatch.setattr(mixing, "BIN_ROWS", 2)
    assert sorted(map(tuple, mixing.mix(docs).collect())) == want


def reshare(sizes, weights, share, most):
    """Targets by repeated resharing, as the rule says."""
    total, held = share * sum(sizes.values()), {}
    while True:
        rest = [k for k in sizes if k not in held]
        w = sum(weights[k] for k in rest)
        level = {k: (total - sum(held.values())) * weights[k] / w for k in rest}
        above = {k: most * sizes[k] for k in rest if level[k] > most * sizes[k]}
        if not above:
            return held | level
        held |= above


def test_targets_equal_repeated_resharing(spark):
    rng = random.Random(6)
    for _ in range(4):
        size = {f"s{k:02d}": rng.choice([0, 5, 50, 500]) + rng.randrange(9) for k in range(9)} | {None: 17}
        names = sorted((k for k in size if k), key=lambda s: s) + [None]
        weights = {k: mixing.WEIGHTS[i % 3] for i, k in enumerate(names)}
        got = {r.source: r.target for r in mixing.targets(spark.createDataFrame([(k, v, 1) for k, v in size.items()], "source string, source_size long, source_rows long")).collect()}
        want = reshare(size, weights, 1.5, 2.0)
        assert all(abs(got[k] - want[k]) < 1e-6 for k in want)


def test_edges(spark):
    rows = [(1, "a b c", "x", 1), (1, "a b c", "x", 1), (2, None, None, 2), (3, "", "y", 3), (None, "word " * 1000, "x", 4), (5, "e", None, 5)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, target int")
    got = mixing.mix(docs).collect()
    assert len(got) == 6 and all(0 <= r.taken <= 2 * r.size for r in got)
    assert sorted(map(str, got)) == sorted(map(str, mixing.mix(docs).collect()))
    assert mixing.mix(docs.limit(0)).count() == 0
    none = mixing.mix(docs.where("doc_id = 3")).collect()
    assert [(r.size, r.taken) for r in none] == [(0, 0)]


def test_clashing_names_stay_and_null_ids_spread(spark):
    rows = [(None if k % 2 else k, f"text {k} " * (1 + k % 5), "s", k, -1, "own") for k in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, passes int, _size int, _here string")
    got = mixing.mixed(docs).collect()
    assert got[0].__fields__ == [*docs.columns, "passes_", "taken"]
    assert all(r._size == -1 and r._here == "own" and r.passes in range(60) and r.taken == r.passes_ * (r.text.count(" ")) for r in got)
    keys = [r._key for r in mixing.sizes(docs).where("doc_id IS NULL").collect()]
    assert len(set(keys)) == 30
