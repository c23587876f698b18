import random
import re
import zlib

import numpy as np

from linkrank.llm import language as lang
from linkrank.llm.tables import remainder
from linkrank.llm.text import mix


def parse(text, train):
    """Phrases by the definition: cut where the phrase with the next letter isn't in the training text."""
    n, at = 0, 0
    while at < len(text):
        size = 1
        while at + size < len(text) and text[at : at + size + 1] in train and text[at : at + 1] in train:
            size += 1
        n, at = n + 1, at + size
    return n


def test_phrases_equal_the_definition(monkeypatch):
    rng = random.Random(2)
    train = {k: "".join(rng.choice(s) for _ in range(300)).encode() for k, s in (("a", "abc "), ("b", "abd "))}
    model = lang.build(train)
    texts = ["".join(rng.choice("abcde ") for _ in range(rng.randrange(500))).encode() for _ in range(60)] + [b"", b"e", b"eee"]
    data = np.frombuffer(b"".join(texts), np.uint8)
    offsets = np.cumsum([0, *map(len, texts)])
    got = lang.phrases(data, offsets, model)
    for k, t in enumerate(texts):
        assert got[k].tolist() == [parse(t, train["a"]), parse(t, train["b"])], t


def test_phrases_of_long_texts_are_not_cut_at_lanes(monkeypatch):
    rng = random.Random(7)
    base = "".join(rng.choice("abc ") for _ in range(600))
    model = lang.build({"a": base.encode(), "b": "".join(rng.choice("ab ") for _ in range(400)).encode()})
    texts = [(base[50:] + base[:500]) * 3, "".join(rng.choice("abcd ") for _ in range(5000)), base * 4, "c" * 3000, "abz" * 900]
    data = np.frombuffer("".join(texts).encode(), np.uint8)
    offsets = np.cumsum([0, *map(len, texts)])
    monkeypatch.setattr(lang, "LANE", 1 << 20)
    whole = lang.phrases(data, offsets, model)
    assert whole[:, 0].tolist() == [parse(t.encode(), base.encode()) for t in texts]
    for lane, ahead in ((512, 64), (64, 64), (50, 3), (7, 2), (512, 0)):
        monkeypatch.setattr(lang, "LANE", lane)
        monkeypatch.setattr(lang, "AHEAD", ahead)
        assert (lang.phrases(data, offsets, model) == whole).all()


def test_pieces_come_from_anywhere_and_are_bounded(spark):
    text = " ".join(f"{k:05d}" for k in range(20000))
    docs = spark.createDataFrame([(1, text, "en"), (2, "short", "en"), (3, "x" * 1000, "fr"), (4, None, "fr"), (5, "", "de")], "doc_id long, text string, lang string")
    got = lang.bounded_pieces(docs, "lang", 384, 20).collect()
    en = [r.piece for r in sorted(got, key=lambda r: r.n) if r.lang == "en"]
    assert len(en) == 20 and "short" in en[:2] and max(text.find(p) for p in en) > len(text) / 2
    assert sorted(len(r.piece) for r in got if r.lang == "fr") == [232, 384, 384] and not [r for r in got if r.lang == "de"]


def test_query_equals_brute_force(spark, tmp_path):
    """Training text, phrases and scores of the whole query again, by the definition."""
    rng = random.Random(5)
    word = {k: ["".join(rng.choice(s) for _ in range(rng.randrange(2, 6))) for _ in range(30)] for k, s in (("aa", "abcde"), ("bb", "bcdxy"), ("cc", "cdmno"))}
    docs = [(k, " ".join(rng.choice(word[("aa", "bb", "cc")[k % 3]]) for _ in range(rng.randrange(3, 150))), ("aa", "bb", "cc")[k % 3]) for k in range(90)] + [(90, None, "aa"), (91, "12 !", None), (92, "abc", None)]
    spark.createDataFrame([(*d, "s", 0) for d in docs], "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    got = {r.doc_id: r for r in lang.query(spark, str(tmp_path)).collect()}
    held = {k: zlib.crc32(str(k).encode()) % 5 == 0 for k, *_ in docs}
    keys = {r.id: r.key & (1 << 62) - 1 for r in spark.range(100).select("id", lang.F.expr("xxhash64(id, 3)").alias("key")).collect()}
    train = {}
    for name in word:
        pieces = []
        for k, text, own in docs:
            if own == name and not held[k]:
                n = -(-len(text or "") // lang.SHARE)
                places = sorted((int(mix(np.array([keys[k] + j], np.uint64))[0]) >> 1, j) for j in range(n))
                pieces += [(turn, place, text[j * lang.SHARE : (j + 1) * lang.SHARE]) for turn, (place, j) in enumerate(places)]
        train[name] = b""
        for *_, piece in sorted(pieces):
            clean = re.sub("[^a-z]+", " ", piece).lstrip().encode()
            if len(train[name]) + bool(train[name]) + len(clean) <= lang.TRAIN_BYTES:
                train[name] += (b" " if train[name] else b"") + clean
    for k, text, _ in docs:
        clean = re.sub("[^a-z]+", " ", text or "").lstrip().encode()
        bits = {name: parse(clean, t) * np.log2(len(t) + 1) for name, t in train.items()}
        best = min(sorted(bits), key=bits.get)
        some = bool(clean.strip())
        want = 1 / sum(2 ** -((b - bits[best]) / 8) for b in bits.values()) if some else 0.0
        assert got[k].held_out == held[k] and got[k].lang_pred == (best if some else "und") and abs(got[k].score - want) < 1e-9, k


def test_letters():
    raw = np.frombuffer("Él!! x\n9".encode() + b"7 B", np.uint8)
    out, bounds = lang.letters(raw, np.array([0, len(raw) - 3, len(raw)]))
    assert out.tobytes().decode() == "él x b" and bounds.tolist() == [0, 6, 7]


def test_edges(spark):
    docs = spark.createDataFrame(
        [(1, "the cat and the hat", "en", 1.0), (2, "le chat et la rue", "fr", 2.0), (3, None, "en", 3.0), (4, "12 !", "fr", 4.0), (4, "12 !", "fr", 4.0), (None, "the hat", None, 5.0), (6, "☃ 5", "en", 6.0), (7, "the " * 50000, None, 7.0)],
        "doc_id long, text string, lang string, score double",
    )
    model = lang.train(docs, remainder("doc_id", 5) >= 0)
    got = {}
    for r in lang.predict_language(docs, model).collect():
        got.setdefault(r.doc_id, []).append(r.lang_pred)
    assert got == {1: ["en"], 2: ["fr"], 3: ["und"], 4: ["und", "und"], None: ["en"], 6: ["und"], 7: ["en"]}
    assert lang.predict_language(docs.limit(0), model).count() == 0
    none = lang.train(docs.limit(0), remainder("doc_id", 5) >= 0)
    assert {r.lang_pred for r in lang.predict_language(docs, none).collect()} == {"und"}


def test_held_out_accuracy(spark):
    sf = "/root/testdata/sf0.01"
    got = lang.query(spark, sf).join(spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert np.mean([r.lang_pred == r.lang for r in got]) > 0.97
    assert all(0 <= r.score <= 1 for r in got)


def test_learns_every_language(spark):
    rng = random.Random(4)
    rows, tried = [], []
    for k in range(103):
        own = ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(6)) for _ in range(12)]
        rows += [(100 * k + j, " ".join(rng.choice(own) for _ in range(25)), f"l{k:03d}") for j in range(2 if k < 100 else 1)]
        tried.append((k, " ".join(rng.choice(own) for _ in range(15))))
    model = lang.train(spark.createDataFrame(rows, "doc_id long, text string, lang string"), lang.F.lit(True))
    got = {r.doc_id: r.lang_pred for r in lang.predict_language(spark.createDataFrame(tried, "doc_id long, text string"), model).collect()}
    assert len(model.languages) == 103 and got == {k: f"l{k:03d}" for k, _ in tried}
