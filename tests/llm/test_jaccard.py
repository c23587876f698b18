import random
import re

import pytest

from linkrank.llm import jaccard as jac
from linkrank.llm.tables import release
from tests.llm.oracle import same, shuffled
from tests.llm.test_components import brute as components


def sets(text):
    words = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m[0].lower(), text or ""))
    return {tuple(words[k : k + 5]) for k in range(max(1, len(words) - 4))} if words else set()


def brute(rows):
    found = [sets(t) for _, t in rows]
    links = [(x, y) for x in range(len(rows)) for y in range(x) if found[x] and found[y] and 100 * len(found[x] & found[y]) >= 80 * len(found[x] | found[y])]
    root = components(links)
    least = {}
    for x in root:
        if rows[x][0] is not None:
            least[root[x]] = min(least.get(root[x], 1 << 60), rows[x][0])
    return sorted((rows[x][0], len(found[x]), least[root[x]] if x in root else rows[x][0]) for x in range(len(rows)))


def made(seed, n=260):
    """Groups of texts with a few changes each, passages that many share, and chains of small changes."""
    rng = random.Random(seed)
    word = lambda: f"w{rng.randrange(3000)}"
    passages = [[word() for _ in range(40)] for _ in range(3)]
    texts = []
    while len(texts) < n:
        kind = rng.random()
        if kind < 0.3:
            texts.append([word() for _ in range(rng.randrange(1, 150))])
        elif kind < 0.6:
            texts.append(rng.choice(passages) + [word() for _ in range(rng.choice([2, 4, 6, 8, 60]))])
        elif kind < 0.7:
            base = [word() for _ in range(rng.randrange(30, 200))]
            for _ in range(rng.randrange(2, 30)):
                base = list(base)
                base[rng.randrange(len(base))] = word()
                texts.append(list(base))
        elif texts:
            base = list(rng.choice(texts))
            for _ in range(rng.randrange(4)):
                base[rng.randrange(len(base))] = word()
            texts.append(base)
    return [(k, " ".join(w.upper() if rng.random() < 0.01 else w for w in t)) for k, t in enumerate(texts[:n])]


@pytest.mark.parametrize("seed,short,counters", [(1, 16, 1 << 22), (2, 2, 1 << 22), (3, 2, 256)])
def test_equals_brute_force(spark, monkeypatch, seed, short, counters):
    monkeypatch.setattr(jac, "SHORT", short)
    monkeypatch.setattr(jac, "COUNTERS", counters)
    rows = made(seed)
    got = jac.jaccard_classes(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()
    want = brute(rows)
    assert sorted(map(tuple, got)) == want
    assert sum(c != d for d, _, c in want) > 40


def test_equals_sql(spark):
    same(spark, jac.query, jac.ORACLE, "/root/testdata/sf0.01")


def test_edges(spark):
    rows = [(5, None, 1), (4, "", 2), (3, " \n\t", 3), (9, "One two", 4), (8, "one TWO", 5), (8, "one TWO", 5), (None, "one two", 6), (7, "a " * 40000, 7), (6, "a a a a a a", 8), (2, "one two three four five", 9), (1, "one two three four five.", 10)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_shingles int")
    got = sorted(map(tuple, jac.jaccard_classes(docs).collect()), key=str)
    want = [(5, 0, 5), (4, 0, 4), (3, 0, 3), (9, 1, 8), (8, 1, 8), (8, 1, 8), (None, 1, 8), (7, 1, 6), (6, 1, 6), (2, 1, 2), (1, 1, 1)]
    assert got == sorted(want, key=str)
    assert jac.jaccard_classes(docs.limit(0)).count() == 0
    kept = sorted(((r.doc_id, r.n_shingles) for r in jac.first_of_each(docs).collect()), key=str)
    assert kept == sorted([(1, 10), (2, 9), (3, 3), (4, 2), (5, 1), (6, 8), (8, 5), (None, 6)], key=str)
    assert jac.first_of_each(docs.limit(0)).count() == 0


def test_repeated_ids_of_different_texts(spark):
    a, b, c = (" ".join(f"{k}{j}" for j in range(60)) for k in "abc")
    rows = [(1, a, 1), (1, b, 2), (2, a.upper(), 3), (2, c, 4), (3, b, 5), (4, c + " end", 6), (1, a + " end", 7), (5, "", 8), (5, None, 9), (5, "five words of a text", 10), (2, c, 4)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, row int")
    kept = sorted((r.doc_id, r.row) for r in jac.first_of_each(docs).collect())
    assert kept in ([(1, 1), (1, 2), (2, 4), (5, 8), (5, 9), (5, 10)], [(1, 2), (1, 7), (2, 4), (5, 8), (5, 9), (5, 10)])
    assert jac.first_of_each(docs).columns == docs.columns


def test_shuffles_go_before_classes_are_made(spark):
    rng = random.Random(5)
    texts = [[f"w{rng.randrange(9999)}" for _ in range(600)] for _ in range(150)]
    rows = [(2 * k + c, " ".join([*t[:300], f"c{c}", *t[300:]])) for k, t in enumerate(texts) for c in range(2)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    release(spark)
    before = shuffled(spark, wait=1)
    some, _ = jac._rooted(docs)
    assert shuffled(spark, before + 100_000) <= before + 100_000  # the sets alone are some 1.4 MB
    assert some.select("root").distinct().count() == 150


def test_passes_move_a_part_at_a_time(spark, monkeypatch):
    rng = random.Random(6)
    texts = [[f"w{rng.randrange(9999)}" for _ in range(600)] for _ in range(200)]
    rows = [(2 * k + c, " ".join([*t[:300], f"c{c}", *t[300:]])) for k, t in enumerate(texts) for c in range(2)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    monkeypatch.setattr(jac, "PASS_SHINGLES", 1 << 16, raising=False)
    release(spark)
    before, most, cut = shuffled(spark, wait=1), [0], jac.cut

    def seen(df):
        out = cut(df)
        most[0] = max(most[0], shuffled(spark, 1 << 60) - before)
        return out

    monkeypatch.setattr(jac, "cut", seen)
    found = jac.jaccard_classes(docs).collect()
    assert sorted((r.doc_id, r.component_id) for r in found) == [(k, k - k % 2) for k in range(400)]
    assert most[0] < 2_800_000, most  # 3.6 MB in one pass


def test_equals_brute_force_in_passes(spark, monkeypatch):
    monkeypatch.setattr(jac, "PASS_SHINGLES", 1 << 10)
    monkeypatch.setattr(jac, "SHORT", 4)
    rows = made(4)
    assert sorted(map(tuple, jac.jaccard_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect())) == brute(rows)
