import random
import zlib

import numpy as np
import pytest

from linkrank.llm import quality
from linkrank.llm.text import mix


@pytest.fixture(scope="module")
def small(spark):
    rng = random.Random(4)
    good = ["alpha", "beta", "gamma", "delta", "epsilon", "zeta", "theta"]
    rows = [(k, " ".join(rng.choice(good) if k % 3 else rng.choice(["buy!!", "$$$", "click", "###"]) for _ in range(40 + rng.randrange(40))), int(k % 3 > 0)) for k in range(300)]
    return spark.createDataFrame(rows, "doc_id long, text string, quality int")


def test_classes_are_told_apart(small):
    model = quality.fit(small)
    got = {r.doc_id: r for r in quality.score_quality(small, model).collect()}
    assert sum((got[k].score >= 0.5) == (k % 3 > 0) for k in range(300)) >= 295
    assert got[1].difference > got[0].difference


def test_the_difference_is_of_whole_texts():
    model = quality.Model(b"good words here " * 20, b"#### $$$$ ####" * 20, ())
    coders = model.coders()
    text = "good words here " * 200
    assert quality.features(text, coders)[0] > quality.features(text + "#### $$$$ ####" * 400, coders)[0]
    assert quality.features("", coders) == quality.features(None, coders) == (0.0, 0.0, 0.0)


def test_edges(small, spark):
    model = quality.fit(small)
    odd = spark.createDataFrame([(1, None, 0.5), (1, "", 0.5), (None, "alpha " * 30000, 0.1)], "doc_id long, text string, score double")
    got = quality.score_quality(odd, model).collect()
    assert len(got) == 3 and all(0 <= r.score <= 1 for r in got)
    assert len({r.score for r in got if r.doc_id == 1}) == 1
    assert quality.score_quality(odd.limit(0), model).count() == 0
    assert all(0 <= r.score <= 1 for r in quality.score_quality(odd, quality.fit(small.limit(0))).collect())


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.1"
    got = quality.query(spark, sf).join(spark.read.parquet(f"{sf}/labels.parquet"), "doc_id").where("held_out").select("predicted", "quality").collect()
    assert np.mean([r.predicted == r.quality for r in got]) > 0.96


def test_query_equals_brute_force(spark, monkeypatch, tmp_path):
    """Dictionaries, differences, fit and scores of the whole query again, without Spark."""
    rng = random.Random(6)
    word = {1: ["alpha", "beta", "gamma", "delta"], 0: ["buy!!", "$$$", "click", "###"]}
    docs = [(k, " ".join(rng.choice(word[k % 4 > 0]) for _ in range(rng.randrange(1, 300)))) for k in range(200)] + [(200, None), (201, "")]
    spark.createDataFrame([(*d, "en", "s", 0) for d in docs], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(k, int(k % 4 > 0), 0) for k in range(180)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    got = {r.doc_id: r for r in quality.query(spark, str(tmp_path)).collect()}

    held = {k: zlib.crc32(str(k).encode()) % 3 == 1 for k in range(202)}
    hashes = {r.id: r for r in spark.range(202).select("id", quality.F.expr("pmod(xxhash64(id, 7), 3)").alias("third"), quality.F.expr("xxhash64(id, 3)").alias("key")).collect()}
    learned = [k for k in range(180) if not held[k]]
    content = {}
    for c in (1, 0):
        pieces = []
        for k in learned:
            if hashes[k].third == 0 and int(k % 4 > 0) == c:
                text = docs[k][1]
                own = sorted((_mixed((hashes[k].key & (1 << 62) - 1) + j), j) for j in range(-(-len(text) // quality.SHARE)))
                pieces += [(turn, place, text[j * quality.SHARE : (j + 1) * quality.SHARE]) for turn, (place, j) in enumerate(own)]
        content[c] = "".join(p for *_, p in sorted(pieces)).encode()
    assert all(len(x) < quality.DICTIONARY_BYTES for x in content.values())
    coders = quality.Model(content[1], content[0], ()).coders()

    def difference(text):
        raw = (text or "").encode()
        sizes = [sum(len(c.compress(raw[a : a + quality.PIECE])) for a in range(0, len(raw), quality.PIECE)) for c in coders]
        return (sizes[1] - sizes[0]) / len(raw) if raw else 0.0

    used = [k for k in learned if hashes[k].third]
    n = [sum(k % 4 == 0 for k in learned), sum(k % 4 > 0 for k in learned)]
    slope, shift = quality.logistic(np.array([difference(docs[k][1]) for k in used]), np.array([float(k % 4 > 0) for k in used]), np.log((n[1] + 1) / (n[0] + 1)))
    for k, text in docs:
        want = 1 / (1 + np.exp(-(slope * difference(text) + shift)))
        assert got[k].held_out == held[k] and abs(got[k].score - want) < 1e-9 and got[k].predicted == (want >= 0.5)


def _mixed(x):
    return int(mix(np.array([x], np.uint64))[0]) >> 1
