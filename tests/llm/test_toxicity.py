import random
import re
import zlib

import numpy as np
import pytest

from linkrank.llm import toxicity as tox
from linkrank.llm.fit import logistic, sigmoid


def brute(scores):
    """Maximal segments by definition: the best segment (longest of ties not needed), then both sides."""

    def go(lo, hi):
        best = None
        for s in range(lo, hi):
            total = 0.0
            for e in range(s, hi):
                total += scores[e]
                if total > 1e-12 and (best is None or total > best[2] + 1e-12):
                    best = (s, e + 1, total)
        return go(lo, best[0]) + [best] + go(best[1], hi) if best else []

    return go(0, len(scores))


def test_maximal_segments_equal_the_definition():
    rng = random.Random(3)
    for _ in range(400):
        scores = [rng.choice([-3, -2, -1, 1, 2, 3]) + rng.random() * 1e-3 for _ in range(rng.randrange(14))]
        got = tox.maximal_segments(np.array(scores, float))
        want = brute(scores)
        assert [x[:2] for x in got] == [x[:2] for x in want]
        assert np.allclose([x[2] for x in got], [x[2] for x in want])


def test_long_runs_stay_linear():
    scores = np.where(np.arange(300_000) % 2, -1.5, 1.0)
    assert len(tox.maximal_segments(scores)) == 150_000


def test_logistic_finds_the_boundary():
    x = np.linspace(-3, 3, 601)
    y = (sigmoid(2 * x - 1) > np.random.default_rng(0).random(601)).astype(float)
    slope, shift = logistic(x, y)
    assert 1.5 < slope < 2.6 and -1.5 < shift < -0.5
    assert logistic(x, np.ones(601))[0] == 0.0


@pytest.fixture(scope="module")
def small(spark):
    rng = random.Random(1)
    words = [f"w{k}" for k in range(200)]
    rows = []
    for k in range(400):
        text = [rng.choice(words) for _ in range(60)]
        if k % 4 == 0:
            for _ in range(6):
                text[20 + rng.randrange(12)] = rng.choice(["vilest", "vileness", "nasty"])
        rows.append((k, " ".join(text), int(k % 4 == 0)))
    return spark.createDataFrame(rows, "doc_id long, text string, toxic int")


def test_toxic_passages_are_found(small, spark):
    model = tox.fit(small)
    got = {r.doc_id: r for r in tox.score_toxicity(small, model).collect()}
    assert sum((got[k].score >= 0.5) == (k % 4 == 0) for k in range(400)) >= 395
    best = max(got[4].passages, key=lambda p: p.score)
    assert 18 <= best.start < best.end <= 34


def test_edges(small, spark):
    model = tox.fit(small)
    odd = spark.createDataFrame([(1, None, 0.1), (1, "", 0.2), (None, "vilest " * 20000, 0.3), (2, "!!! ...", None)], "doc_id long, text string, score double")
    got = tox.score_toxicity(odd, model).collect()
    assert len(got) == 4 and all(0 <= r.score <= 1 for r in got)
    assert [r.score for r in got if r.doc_id is None][0] > 0.9
    assert len({round(r.score, 12) for r in got if r.doc_id is not None}) == 1
    assert tox.score_toxicity(odd.limit(0), model).count() == 0
    none = tox.fit(small.limit(0))
    assert all(0 <= r.score <= 1 for r in tox.score_toxicity(odd, none).collect())


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"
    got = tox.query(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").select("predicted", "toxic").collect()
    assert np.mean([r.predicted == r.toxic for r in got]) > 0.94
    assert np.mean([r.predicted for r in got if r.toxic]) > 0.7


def test_query_equals_brute_force(spark, tmp_path):
    """Word scores, segments, law, calibration and scores of the whole query again, from the definitions."""
    rng = random.Random(9)
    words = [f"w{k}" for k in range(80)]
    docs = []
    for k in range(400):
        text = [rng.choice(words) for _ in range(rng.randrange(5, 60))]
        if k % 4 == 0:
            text[2:2] = [rng.choice(["Vilest", "vileness", "nasty"]) for _ in range(rng.randrange(1, 5))]
        docs.append((k, " ".join(text)))
    docs += [(400, None), (401, "vilest " * 3000)]
    spark.createDataFrame([(*d, "en", "s", 0) for d in docs], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(k, 0, int(k % 4 == 0)) for k in range(350)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    got = {r.doc_id: r for r in tox.query(spark, str(tmp_path)).collect()}

    held = {k: zlib.crc32(str(k).encode()) % 5 == 0 for k, _ in docs}
    train = [(re.findall(r"[a-z0-9]+", t.lower()), k % 4 == 0) for k, t in docs[:350] if not held[k]]
    forms = lambda w: [(w, 0)] + [(w[:n], n) for n in tox.STEMS if len(w) > n]
    counts, n = {}, [0.0, 0.0]
    for text, toxic in train:
        for f in {f for w in text for f in forms(w)}:
            counts.setdefault(f, [0, 0])[toxic] += 1
    whole = {f for f in counts if f[1] == 0}
    n = [float(sum(counts[f][c] for f in whole)) for c in (0, 1)]
    score = {}
    for f, y in counts.items():
        if sum(y) >= tox.MIN_COUNT:
            prior = sum(y) * tox.PRIOR
            odds = [np.log((y[c] + prior) / max(n[c] + tox.PRIOR * sum(n) - y[c] - prior, 0.5)) for c in (0, 1)]
            s, sd = odds[1] - odds[0], np.sqrt(1 / (y[1] + prior) + 1 / (y[0] + prior))
            if abs(s / sd) >= tox.SIGNIFICANT and abs(s) >= tox.LEAST:
                score[f] = max(tox.FLOOR, s * (1 - tox.SHRINK / abs(s / sd)))
            elif sum(y) >= tox.KNOWN:
                score[f] = 0.0
    of_word = lambda w: next((score[f] - tox.DRIFT for f in forms(w) if f in score), -tox.DRIFT)
    seen = [round(of_word(w), 1) for text, toxic in train if not toxic for w in text]
    values, rates = np.unique(seen, return_counts=True)
    rates = rates / rates.sum()
    decay = tox._decay(rates, values)
    space = max(1e-4, decay * (rates * abs(values) * np.exp(decay * values)).sum())

    def evidence(text):
        found = sorted((s for *_, s in brute([of_word(w) for w in text])), reverse=True) if len(text) < 100 else [sum(of_word(w) for w in text)]
        x = [decay * s - np.log(space * max(len(text), 1)) for s in found]
        best, total, factorial = None, 0.0, 0.0
        for r, v in enumerate((v for v in x if v > 0), 1):
            total, factorial = total + v, factorial + np.log(r)
            tail = max(0.0, total - (r - 1) * np.log(max(total, 1)) + factorial - np.log(r)) if total > r - 1 else 0.0
            best = max(factorial + tail, -1e9 if best is None else best)
        return best if best is not None else x[0] if x else -np.log(space * max(len(text), 1)) - 1

    y = np.array([float(t) for _, t in train])
    slope, shift = logistic(np.array([evidence(t) for t, _ in train]), y, np.log((y.sum() + 1) / ((1 - y).sum() + 1)))
    for k, text in docs:
        want = 1 / (1 + np.exp(-np.clip(slope * evidence(re.findall(r"[a-z0-9]+", (text or "").lower())) + shift, -700, 700)))
        assert got[k].held_out == held[k] and abs(got[k].score - want) < 1e-6 and got[k].predicted == (want >= 0.5), k
    assert {got[k].predicted for k, _ in docs} == {0, 1} and got[401].predicted == 1


def test_many_segments_count_together():
    model = tox.Model(np.zeros(0, np.uint64), np.zeros(0), 1.0, 0.1, 1.0, 0.0)
    weak = [tox._joint_evidence(1000, [7.0] * r, model) for r in (1, 2, 5, 50, 500)]
    assert weak == sorted(weak) and weak[-1] > weak[0] + 100
    assert tox._joint_evidence(1000, [1.0] * 500, model) == tox._evidence(1000, 1.0, model) < 0
