import re

import corpus_pipeline as pipeline
from linkrank.llm import decontaminate, lines, mixing, quality
from tests.llm.test_decontaminate import tokens
from tests.llm.test_jaccard import brute as classes


def test_stages_equal_brute_force(spark, tmp_path):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    columns, seen = docs.columns, [docs]
    for k, (_, stage) in enumerate(pipeline.STAGES):
        stage(spark, seen[-1], sf).write.parquet(f"{tmp_path}/{k}")
        seen.append(spark.read.parquet(f"{tmp_path}/{k}"))
        assert seen[-1].columns == columns or k == 4
    raw, good, clean, first, unleaked, mixed = ([r.asDict() for r in d.collect()] for d in seen)

    model = quality.train(docs, spark.read.parquet(f"{sf}/labels.parquet"))
    coders = model.coders()
    score = {r["doc_id"]: quality.sigmoid(quality._table(quality.np.array([quality.features(r["text"], coders)])) @ quality.np.array(model.weights[:-1]) + model.weights[-1])[0] for r in raw}
    assert {r["doc_id"] for r in good} == {k for k, v in score.items() if v >= 0.5} and 0.7 * len(raw) < len(good) < len(raw)

    sites = {}
    for r in good:
        for line in r["text"].split("\n"):
            sites.setdefault(line.strip(" \t\r"), set()).add(r["source"])
    want = {r["doc_id"]: "\n".join(x for x in r["text"].split("\n") if not x.strip(" \t\r") or len(sites[x.strip(" \t\r")]) < lines.MIN_SITES) for r in good}
    assert {r["doc_id"]: r["text"] for r in clean} == want and all(r["n_chars"] == len(r["text"]) for r in clean)

    want = {d for d, _, c in classes([(r["doc_id"], r["text"]) for r in clean]) if d == c}
    assert {r["doc_id"] for r in first} == want and len(first) < len(clean)

    items = [" ".join(tokens(r.text)) for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    holds = lambda r: any(f" {i} " in f" {' '.join(tokens(r['text']))} " for i in items)
    leaks = {r["doc_id"] for r in first if holds(r)}
    assert leaks and {r["doc_id"] for r in unleaked} == {r["doc_id"] for r in first} - leaks

    plan = {r.doc_id: r for r in mixing.mix(seen[4]).collect()}
    assert {r["doc_id"]: (r["passes"], r["taken"]) for r in mixed} == {k: (r.passes, r.taken) for k, r in plan.items() if r.passes}
    size = {r["doc_id"]: len(re.findall(r"[^\x20\x09-\x0D]+", r["text"])) for r in unleaked}
    for source in {r["source"] for r in unleaked}:
        own = [r for r in plan.values() if r.source == source]
        assert abs(sum(r.taken for r in own) - own[0].target) <= max(size[r.doc_id] for r in own)


def test_edges(spark):
    rows = [(1, None, "en", None, None), (None, "a b c", None, "s", 5), (2, "", "en", "s", 0)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    for frame in (docs, docs.limit(0)):
        for _, stage in pipeline.STAGES:
            frame = stage(spark, frame, "/root/testdata/sf0.001")
            frame.count()
    assert frame.columns == [*docs.columns, "passes", "taken"]


def test_repeated_ids_clashing_names_and_long_texts(spark, tmp_path):
    """Every stage keeps the unrelated rows of an id, and columns whose names it uses itself."""
    passage = next(r.text for r in spark.read.parquet("/root/testdata/sf0.001/benchmark.parquet").collect() if len(tokens(r.text)) > 20)
    clean = [" ".join(f"{c}{j}" for j in range(60)) for c in "abcdef"]
    rows = [(1, clean[0]), (1, clean[1]), (1, f"x {passage} y"), (None, clean[2]), (None, f"{passage} z"), (2, clean[0].upper() + "\nfoot"), (2, clean[3]), (3, "long " * 300000), (None, None), (4, None)]
    names = ["n_removed", "passes", "_own", "_hash", "_leak", "_later", "_size"]
    schema = "doc_id long, text string, lang string, source string, n_chars long, " + ", ".join(f"{n} int" for n in names)
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or ""), *(k for _ in names)) for k, (i, t) in enumerate(rows)], schema)
    for k, (name, stage) in enumerate(pipeline.STAGES):
        if name == "quality":
            continue
        out = stage(spark, docs, "/root/testdata/sf0.001")
        assert out.columns[: len(docs.columns)] == docs.columns
        out.write.parquet(f"{tmp_path}/{k}")
        docs = spark.read.parquet(f"{tmp_path}/{k}")
        got = docs.collect()
        assert all(r[n] == got[j].n_removed for j, r in enumerate(got) for n in names)
        if name == "near_copies":
            assert sorted(r.n_removed for r in got) == [0, 1, 2, 3, 4, 6, 7, 8, 9]
        if name == "decontamination":
            assert sorted(r.n_removed for r in got) == [0, 1, 3, 6, 7, 8, 9]
