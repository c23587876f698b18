import pytest

from linkrank.llm import lines
from tests.llm.oracle import same


@pytest.mark.parametrize("sf", ["0.001", "0.01"])
def test_equals_sql(spark, sf):
    same(spark, lines.query, lines.ORACLE, f"/root/testdata/sf{sf}")


def test_spread_and_removal(spark):
    rows = [(k, f"own {k}\n foot\t\n\nfew", f"s{k % 12}") for k in range(24)] + [(k, "few", None) for k in range(50, 80)]
    rows += [(30, "nine", f"n{k}") for k in range(9)] + [(31, "ten", f"n{k}") for k in range(10)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string")
    got = {(r.doc_id, r.source): r for r in lines.remove_boilerplate(docs).collect()}
    assert len(got) == len(rows)
    assert got[3, "s3"].text == "own 3\n" and (got[3, "s3"].n_lines, got[3, "s3"].n_removed) == (4, 2)
    assert got[50, None].text == "" and got[30, "n1"].text == "nine" and got[31, "n1"].text == ""


def test_edges(spark):
    rows = [(1, None, "a", 5), (1, "x\ny", "a", 6), (1, "x\ny", "a", 6), (None, "x", None, None), (2, "", "b", 7), (3, "\n\n", "c", 8), (4, "word " * 40000, "d", 9)]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, n_lines long")
    got = lines.remove_boilerplate(docs, 1).collect()
    assert len(got) == 7 and lines.remove_boilerplate(docs.limit(0)).count() == 0
    by = {(r.doc_id, r.source): r for r in got}
    assert got[0].__fields__ == ["doc_id", "text", "source", "n_lines", "n_lines_", "n_removed"]
    assert sorted((r.n_lines or 0, r.n_lines_, r.n_removed) for r in got) == [(0, 1, 1), (5, 0, 0), (6, 2, 2), (6, 2, 2), (7, 1, 0), (8, 3, 0), (9, 1, 1)]
    assert by[1, "a"].text in (None, "") and by[None, None].text == "" and by[3, "c"].text == "\n\n" and by[4, "d"].text == ""
    assert [r.text for r in lines.remove_boilerplate(docs, 2).collect() if r.doc_id == 4] == ["word " * 40000]


def test_many_lines_of_one_document(spark):
    shared = [f"line {k}" for k in range(0, 40000, 3)]
    docs = [(k, "\n".join(shared[k:]), f"s{k}") for k in range(3)] + [(9, "\n".join(f"line {k}" for k in range(40000)), "s9")]
    got = {r.doc_id: r for r in lines.remove_boilerplate(spark.createDataFrame(docs, "doc_id long, text string, source string"), 4).collect()}
    assert got[9].text == "\n".join(f"line {k}" for k in range(40000) if k % 3 or k < 6) and got[9].n_removed == len(shared) - 2
    assert got[1].text == "line 3" and got[2].text == "" and (got[2].n_lines, got[2].n_removed) == (len(shared) - 2, len(shared) - 2)
