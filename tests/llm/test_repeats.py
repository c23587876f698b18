import hashlib
import random
import tracemalloc

import numpy as np
import pyarrow as pa
import pytest

from linkrank.llm import repeats as rep
from linkrank.llm.tables import release
from tests.llm.oracle import shuffled

L = rep.LENGTH


def brute(rows):
    first = {}
    for i, t in rows:
        raw = (t or "").encode()
        if i is not None:
            for k in range(len(raw) - L + 1):
                w = raw[k : k + L]
                first[w] = min(first.get(w, i), i)
    out = []
    for i, t in rows:
        raw = (t or "").encode()
        gone = np.zeros(len(raw), bool)
        if i is not None:
            for k in range(len(raw) - L + 1):
                if first[raw[k : k + L]] < i:
                    gone[k : k + L] = True
        kept = bytes(np.frombuffer(raw, np.uint8)[~gone])
        out.append((i, len(raw), int(gone.sum()), int((np.diff(np.concatenate(([0], gone.astype(int)))) == 1).sum()), hashlib.sha256(kept).hexdigest()))
    return sorted(out, key=str)


def got(docs):
    return sorted((tuple(r)[:5] for r in rep.remove_repeats(docs).collect()), key=str)


def made(seed, n=120):
    rng = random.Random(seed)
    letters = "abcdeé "
    piece = lambda k: "".join(rng.choice(letters) for _ in range(k))
    shared = [piece(rng.choice([40, 49, 50, 51, 60, 200])) for _ in range(12)] + ["ab" * 60, "x" * 300, "For " * 90]
    texts = []
    for _ in range(n):
        if texts and rng.random() < 0.2:
            t = list(rng.choice(texts))
            for _ in range(rng.randrange(4)):
                t[rng.randrange(len(t))] = "z"
            texts.append("".join(t))
        else:
            texts.append("".join(rng.choice([piece(rng.randrange(1, 90)), rng.choice(shared), rng.choice(shared)[: rng.randrange(1, 400)]]) for _ in range(rng.randrange(1, 8))) or "q")
    ids = list(range(n))
    rng.shuffle(ids)
    return list(zip(ids, texts))


@pytest.mark.parametrize("seed,wide,flush,segment", [(1, 256, 1 << 19, 1 << 22), (2, 2, 40, 1 << 22), (3, 0, 7, 120)])
def test_equals_brute_force(spark, monkeypatch, seed, wide, flush, segment):
    for name, value in (("WIDE", wide), ("FLUSH", flush), ("SEGMENT", segment)):
        monkeypatch.setattr(rep, name, value)
    rows = made(seed)
    assert got(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)) == brute(rows)


def test_windows_of_a_shard():
    texts = [b"a" * 60, b"b" + b"a" * 55 + b"c", b"a" * 49 + b"d"]
    offsets = np.cumsum([0, *map(len, texts)])
    found = rep.earlier_windows(np.frombuffer(b"".join(texts), np.uint8), offsets, np.array([3, 1, 2]))
    assert [tuple(map(int, x)) for x in zip(*found)] == [(0, 0, 11)]


def test_pieces_tile_the_windows():
    raw = np.frombuffer("".join(t for _, t in made(9, 8)).encode(), np.uint8)
    row, start, count, *_ = rep.pieces(raw, np.array([0, 30, 300, len(raw)]))
    covered = sorted(k for s, c in zip(start, count) for k in range(s, s + c))
    assert covered == list(range(30, 251)) + list(range(300, len(raw) - L + 1)) and count.max() <= rep.REACH


def test_edges(spark):
    text = "".join(chr(97 + k % 23) + str(k) for k in range(60))
    rows = [(1, None, 0), (2, "", 0), (3, text, 0), (3, text, 0), (4, text, 1), (None, text, 2), (5, text[:49], 3), (6, "é" * 25 + text[:10], 4), (7, "é" * 25, 5), (-9, "y" * 200000, 6), (8, "y" * 60, 7)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, n_bytes int")
    assert got(docs) == brute([r[:2] for r in rows])
    assert rep.remove_repeats(docs.limit(0)).count() == 0


def test_given_tables(spark):
    rows = [(r.doc_id, r.text) for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").collect()]
    assert sorted(map(tuple, rep.query(spark, "/root/testdata/sf0.001").collect()), key=str) == brute(rows)


def test_shuffles_go_before_whole_documents_are_moved(spark):
    rng = random.Random(5)
    rows = [(k, "".join(rng.choice("abcdefgh ") for _ in range(20_000))) for k in range(60)]
    docs = spark.createDataFrame(rows, "doc_id long, text string").selectExpr("doc_id", "CAST(text AS BINARY) AS raw")
    release(spark)
    before = shuffled(spark, wait=1)
    found = rep.found_windows(docs, 8, 1_200_000)
    assert shuffled(spark, before + 50_000) <= before + 50_000  # the entries alone are some 800 kB
    assert found.where("length(payload) > 0").count() == 0


def test_a_task_copies_little_at_a_time():
    class shared:
        value = np.full((4, 1 << (rep.BITS - 6)), -1, np.int64).view(np.uint64)  # every piece is asked, as one of a wide anchor too

    text = np.random.default_rng(1).integers(97, 123, 1 << 18).astype(np.uint8).tobytes()
    batch = pa.record_batch({"doc_id": pa.array([7]), "raw": pa.array([text], pa.binary())})
    tracemalloc.start()
    sizes, windows = [], 0
    for rows in rep._texts(shared, 8, 4)([batch]):
        sizes.append(rows.nbytes)
        windows += sum(len(t.as_py() or b"") - L + 1 for t in rows.column(3))
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert windows == 2 * (len(text) - L + 1)  # in pieces and one by one
    assert max(sizes) < 2 * rep.TEXT_RUN and peak < 100 << 20, (max(sizes), peak)


def test_passes_move_a_part_at_a_time(spark, monkeypatch, tmp_path):
    rng = random.Random(7)
    texts = ["".join(rng.choice("abcdefgh ") for _ in range(20_000)) for _ in range(60)]
    rows = [(k, t[:9_000] + texts[k // 2][9_000:]) for k, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    monkeypatch.setattr(rep, "PASS_BYTES", 1 << 16, raising=False)
    release(spark)
    most, cut = [0], rep.cut

    def seen(df):
        before = shuffled(spark, 1 << 60)
        out = cut(df)
        most[0] = max(most[0], shuffled(spark, 1 << 60) - before)
        return out

    monkeypatch.setattr(rep, "cut", seen)
    out = rep.query(spark, str(tmp_path))
    before = shuffled(spark, 1 << 60)
    found = out.collect()
    assert sorted(map(tuple, found), key=str) == brute(rows)
    assert max(most[0], shuffled(spark, 1 << 60) - before) < 900_000, most  # 1.1 MB in one pass
