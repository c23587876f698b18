import hashlib
import re

import pytest

from linkrank.llm import pii

FORMS = {
    "email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+",
    "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)",
    "card": r"[0-9]([\x20-]?[0-9])+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}


def brute(text):
    out = []
    for kind, form in FORMS.items():
        for m in re.finditer(form, text or ""):
            digits = re.sub("[^0-9]", "", m[0])
            ok = {
                "email": True,
                "ip": kind == "ip" and all(int(x) <= 255 for x in m[0].split(".")),
                "card": 13 <= len(digits) <= 19 and pii.luhn(digits),
                "phone": 9 <= len(digits) <= 15,
            }[kind]
            if ok:
                out.append((kind, *m.span()))
    return out


CASES = [
    "", "no data", "a@b.c@d.e", "x@y@z.example.org, q.w+e%r_t-y@h-1.co.uk.", "@x.y a@.b a@b. a@b..c", "1.2.3.4.5.6.7.8", "256.1.1.1 1.2.3.400 01.002.03.4",
    "1.2..3.4 1.2.3 9.9.9.9", "4111 1111 1111 1111", "4111-1111-1111-1112 5500000000000004", "+1 (212) 555-0100. +49.30.123456 +1234 + 12345678901", "+1+2125550100 23",
    "é4111111111111111é a@b.cö 😀 u@v.w", "12 4111 1111 1111 1111", "http://a.b/c?d=e@f.g", "7" * 3000 + ".1.1.1", "a" * 3000 + "@b.c",
]


@pytest.mark.parametrize("text", CASES)
def test_base_spans_equal_the_patterns(text):
    assert [x for x in pii.spans(text, pii.automaton()) if x[0] in pii.BASE] == brute(text)


def test_random_texts():
    import random

    rng = random.Random(5)
    anchors = pii.automaton()
    for _ in range(3000):
        text = "".join(rng.choice("0123456789..--  ++@@ab(") for _ in range(rng.randrange(60)))
        assert [x for x in pii.spans(text, anchors) if x[0] in pii.BASE] == brute(text), text


def test_added_kinds():
    found = pii.spans("See https://u@h.org/x?y=1). IBAN: GB82 WEST 1234 5698 7654 32, account no. 12345678", pii.automaton())
    assert ("url", 4, 25) in found
    assert sum(x[0] == "account" for x in found) == 2


def test_nulls_repeats_and_extra_columns(spark):
    rows = [(1, None, "a"), (1, "m@n.o", "b"), (None, "1.1.1.1", None), (2, "", "c")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, spans string")
    got = sorted(map(tuple, pii.find_pii(docs).drop("n_spans").collect()), key=str)
    empty = hashlib.sha256(b"").hexdigest()
    assert (1, 0, 0, 0, 0, empty, "") in got and (2, 0, 0, 0, 0, empty, "") in got
    assert (1, 1, 0, 0, 0, hashlib.sha256(b"email:0:5").hexdigest(), "email:0:5") in got
    assert len(got) == 4 and pii.find_pii(docs.limit(0)).count() == 0
    assert {r.text for r in pii.redact_pii(docs).collect()} == {None, "[email]", "[ip]", ""}


def test_query_equals_the_patterns(spark, sf_dir):
    texts = {r.doc_id: r.text for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}
    for r in pii.query(spark, sf_dir).collect():
        want = brute(texts[r.doc_id])
        assert r.base_sha256 == hashlib.sha256(",".join(f"{k}:{s}:{e}" for k, s, e in want).encode()).hexdigest()
        assert (r.n_email, r.n_ip, r.n_card, r.n_phone) == tuple(sum(x[0] == k for x in want) for k in pii.BASE)


def test_secrets():
    key = "24be64439e3e49cf46b2d7c90f3602a3d0b907ff"
    cases = {f'x token = "{key}"### 1': [key], f"TOKEN: {key.upper()}": [key.upper()], f"Bearer {key}": [key], "password: hunter22, ok": ["hunter22"], 'api_key="abc123" short': [],
             "the token is lost and internationalisation": [], f"mytoken = {key}": [], f"secret = {key} password={key}": [key, key], "token = abcdefghijklmnopqrst": []}
    for text, want in cases.items():
        assert [text[a:b] for kind, a, b in pii.spans(text, pii.automaton()) if kind == "secret"] == want, text


def test_planted_secrets_are_found(spark):
    sf_dir = "/root/testdata/sf0.01"  # the smallest tables hold none
    texts = {r.doc_id: r.text or "" for r in spark.read.parquet(f"{sf_dir}/documents.parquet").collect()}
    found = {r.doc_id: r for r in pii.query(spark, sf_dir).collect()}
    held = [k for k, t in texts.items() if re.search('(?i)token = "[0-9a-f]{40}"', t)]
    assert held and all("secret:" in found[k].spans and found[k].n_spans > 0 for k in held)
