import random
import re

import numpy as np

from linkrank.llm import decontaminate as dec


def tokens(text):
    return re.findall(r"[^\W_]+", (text or "").lower())


def brute(docs, items):
    """Leaks by laying every item over every place of every document."""
    out = set()
    for d, text in docs:
        words = tokens(text)
        for i, passage in items:
            item = tokens(passage)
            if len(item) < dec.SHORTEST:
                continue
            for shift in range(-len(item) + 1, len(words)):
                eq = [0 <= shift + j < len(words) and words[shift + j] == w for j, w in enumerate(item)]
                best = at = 0.0
                n = equal = 0
                for e in eq:
                    at, n = (at + (1 if e else -4), n + e)
                    if at < 0:
                        at, n = 0.0, 0
                    if at > best:
                        best, equal = at, n
                if sum(eq) >= dec.IDENTITY * len(item) or equal >= dec.LEAST:
                    out.add((d, i))
    return out


def test_equals_brute_force(spark):
    rng = random.Random(8)
    vocabulary = [f"w{k}" for k in range(400)]
    items = [(k, " ".join(rng.choice(vocabulary) for _ in range(n))) for k, n in enumerate([4, 5, 8, 12, 15, 20, 30, 40, 25, 18])]
    docs = []
    for k in range(120):
        words = [rng.choice(vocabulary) for _ in range(rng.randrange(5, 120))]
        if k % 2:
            item = items[rng.randrange(len(items))][1].split()
            for _ in range(rng.choice([0, 0, 1, 2, len(item) // 6])):
                item[rng.randrange(len(item))] = "changed"
            part = item[: rng.choice([len(item), len(item), 14, 6])]
            at = rng.randrange(len(words))
            words[at:at] = part
        docs.append((k, " ".join(w.title() if rng.random() < 0.2 else w + rng.choice(["", ",", "."]) for w in words)))
    got = dec.find_leaks(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()
    want = brute(docs, items)
    found = {(r.doc_id, r.item_id) for r in got}
    assert found <= want
    exact = {(d, i) for d, i in want if tuple(tokens(dict(items)[i])) in {tuple(tokens(dict(docs)[d])[k : k + len(tokens(dict(items)[i]))]) for k in range(200)}}
    assert exact <= found
    assert len(found) >= 0.9 * len(want) and len(want) > 30


def test_given_tables(spark):
    sf = "/root/testdata/sf0.01"
    docs = [(r.doc_id, r.text) for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    items = [(r.item_id, r.text) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    want = {(d, i) for d, t in docs for i, p in items if f" {' '.join(tokens(p))} " in f" {' '.join(tokens(t))} "}
    found = {(r.doc_id, r.item_id) for r in dec.query(spark, sf).collect()}
    assert want <= found and len(found) <= len(want) + 1 and want


def test_edges(spark):
    passage = "one two three four five six seven eight nine ten eleven twelve thirteen fourteen fifteen"
    docs = spark.createDataFrame([(1, None, 1), (1, f"x {passage} y", 2), (1, f"x {passage} y", 2), (None, passage.upper(), 3), (2, "", 4), (3, "word " * 60000, 5)], "doc_id long, text string, item_id int")
    bench = spark.createDataFrame([(7, passage, 0), (8, None, 0), (9, "a b", 0), (9, "", 0)], "item_id long, text string, doc_id int")
    got = {(r.doc_id, r.item_id, r.n_equal, r.n_words) for r in dec.find_leaks(docs, bench).collect()}
    assert got == {(1, 7, 15, 15), (None, 7, 15, 15)}
    assert sorted((r.doc_id, r.item_id) for r in dec.drop_leaks(docs, bench).collect()) == [(1, 1), (2, 4), (3, 5)]  # a null text holds nothing, whatever other rows of its id hold
    assert dec.find_leaks(docs.limit(0), bench).count() == 0 and dec.find_leaks(docs, bench.limit(0)).count() == 0


def test_compare():
    words = np.arange(100, dtype=np.uint64)
    item = np.arange(40, 60, dtype=np.uint64)
    item[[3, 9]] = 0
    assert dec.compare(words, 0, item, 40) == (40, 20, 18)
    assert dec.compare(words[45:], 45, item, 40) == (50, 10, 10)


def stated(equal):
    """Whether a stretch of the flags has LEAST equal words or more, and IDENTITY of its words equal."""
    return any(sum(equal[a:b]) >= dec.LEAST and 5 * sum(equal[a:b]) >= 4 * (b - a) for a in range(len(equal)) for b in range(a + 1, len(equal) + 1))


def test_longest_equals_stated_rule():
    rng = np.random.default_rng(5)
    both = set()
    for _ in range(400):
        item = np.arange(1, 1 + int(rng.integers(15, 50)), dtype=np.uint64)
        words = np.where(rng.random(len(item)) < rng.choice([0.1, 0.2, 0.3]), 0, item).astype(np.uint64)
        first, n, equal = dec.longest(words, 0, item, 0)
        assert equal == (words[first : first + n] == item[first : first + n]).sum() >= dec.IDENTITY * n - 1e-9
        assert (equal >= dec.LEAST) == stated((words == item).tolist())
        both.add(equal >= dec.LEAST)
    assert both == {True, False}


def test_stretches_with_changed_words(spark):
    item = [f"i{k}" for k in range(40)]
    changed = {1: (16, {10}), 2: (13, {6}), 3: (24, {3, 8, 13, 18, 23}), 4: (13, {3, 6}), 5: (24, {2, 5, 8, 11, 14, 17, 20})}
    docs = [(k, " ".join([f"a{j}" for j in range(30)] + ["changed" if j in out else item[j] for j in range(n)] + [f"b{j}" for j in range(30)])) for k, (n, out) in changed.items()]
    got = dec.find_leaks(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame([(7, " ".join(item))], "item_id long, text string")).collect()
    assert {(r.doc_id, r.start, r.n_words, r.n_equal) for r in got} == {(1, 30, 16, 15), (2, 30, 13, 12), (3, 30, 23, 19)}


def test_rows_are_dropped_by_their_own_text(spark):
    passage = " ".join(f"p{k}" for k in range(20))
    rows = [(1, f"x {passage}", 1), (1, "a clean text", 2), (None, f"{passage} y", 3), (None, "another clean text", 4), (None, None, 5), (2, "a clean text", 6), (2, f"x {passage}", 7)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, own int")
    bench = spark.createDataFrame([(1, passage, 1)], "item_id long, text string, seed int")
    kept = dec.drop_leaks(docs, bench)
    assert kept.columns == docs.columns and sorted(r.own for r in kept.collect()) == [2, 4, 5, 6]


def test_items_of_few_words_match_texts_of_just_these(spark):
    docs = spark.createDataFrame([(1, "Forty two!"), (2, "it is forty two"), (3, "Paris"), (4, "one two three four"), (5, "one two three four five"), (6, "forty")], "doc_id long, text string")
    bench = spark.createDataFrame([(1, "forty two"), (2, "paris."), (3, "one two three four"), (4, "  "), (2, "paris.")], "item_id long, text string")
    assert {(r.doc_id, r.item_id, r.start, r.n_words) for r in dec.find_leaks(docs, bench).collect()} == {(1, 1, 0, 2), (3, 2, 0, 1), (4, 3, 0, 4)}


def test_a_seed_of_many_documents_in_shares(spark, monkeypatch):
    passage = " ".join(f"p{k}" for k in range(14))
    docs = spark.createDataFrame([(k, f"{passage} {k}") for k in range(300)], "doc_id long, text string")
    bench = spark.createDataFrame([(1, passage), (2, passage + " end")], "item_id long, text string")
    monkeypatch.setattr(dec, "if_small", lambda df, *_: df)
    assert {(r.doc_id, r.item_id) for r in dec.find_leaks(docs, bench).collect()} == {(k, i) for k in range(300) for i in (1, 2)}
