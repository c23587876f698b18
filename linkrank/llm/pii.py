"""Personal data by anchor expansion.

An Aho-Corasick automaton walks each text once and stops at the characters and
words that personal data cannot do without: at-signs, schemes, digits, plus signs
and cues of identifiers, keys and passwords. A small parser for each kind then expands the place to the
left and right and validates what it finds. Positions are code points, ends are
exclusive, and spans of one kind do not overlap.

Null text counts as empty and has no spans. A row comes back for each input row,
also for null or repeated ids.
"""

from __future__ import annotations

import hashlib
import re

import ahocorasick
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkrank.llm.tables import table
from linkrank.llm.text import slices, utf8

QUERY = "op9_pii"

# fixed values: the kinds in output order, and the forms of the first four
BASE = ("email", "ip", "card", "phone")
EXTRA = ("url", "account", "secret")
DOMAIN = r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+"
LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
CARD = r"[0-9](?:[\x20-]?[0-9])+"
PHONE = r"\+[0-9][\x20().0-9-]+[0-9]"
CUES = ("iban", "account", "passport", "ssn", "social security", "licence no", "license no")
SECRETS = ("token", "secret", "api key", "api_key", "apikey", "access key", "access_key", "private key", "private_key", "bearer")
PASSWORDS = ("password", "passwd", "passphrase")

_domain, _card, _phone = map(re.compile, (DOMAIN, CARD, PHONE))
_dotted, _spaced, _digits = re.compile(r"[0-9.]+"), re.compile(r"[0-9\x20-]+"), re.compile(r"[0-9]+")
_scheme = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+.-")
_rest_of_url = re.compile(r"[A-Za-z0-9\[][^\s<>\"'`{}|\\^]*")
_identifier = re.compile(r"(?i:[\x20\x09]*(?:number|no\.?|nr\.?|#|:|=|is))*[\x20\x09]*([A-Z0-9]+(?:[\x20-]?[A-Z0-9]+)*)")
_secret = re.compile(r"""["']?[\x20\x09]*(?:[:=][\x20\x09]*)?["']?([A-Za-z0-9+/_.~-]{16,}={0,2})""")
_password = re.compile(r"""["']?[\x20\x09]*[:=][\x20\x09]*["']?([^\s"'<>,;]{6,})""")


def luhn(digits: str) -> bool:
    total = 0
    for k, c in enumerate(reversed(digits)):
        v = int(c) * (1 + k % 2)
        total += v - 9 * (v > 9)
    return total % 10 == 0


def _quads(text: str, lo: int, hi: int) -> list[tuple[int, int]]:
    """Four runs of digits joined by single dots, left to right, each at most 255.

    Linear also where a regular expression would try each digit of a long run.
    """
    out, chain = [], []
    for m in _digits.finditer(text, lo, hi):
        if chain and m.start() != chain[-1].end() + 1:
            chain = []
        chain.append(m)
        if len(chain) == 4:
            if all(len(part := x[0].lstrip("0")) <= 3 and int(part or 0) <= 255 for x in chain):
                out.append((chain[0].start(), m.end()))
            chain = []
    return out


def automaton() -> ahocorasick.Automaton:
    found = ahocorasick.Automaton()
    for c in "0123456789":
        found.add_word(c, ("digit", 1))
    found.add_word("@", ("at", 1))
    found.add_word("+", ("plus", 1))
    found.add_word("://", ("scheme", 3))
    for what, cues in (("cue", CUES), ("secret", SECRETS), ("password", PASSWORDS)):
        for cue in cues:
            for form in {cue, cue.upper(), cue.title(), cue.capitalize()}:
                found.add_word(form, (what, len(form)))
    found.make_automaton()
    return found


def spans(text: str, anchors: ahocorasick.Automaton) -> list[tuple[str, int, int]]:
    """(kind, start, end) of all personal data, by kind in output order, then start."""
    out: dict[str, list[tuple[int, int]]] = {k: [] for k in BASE + EXTRA}
    dotted = spaced = mailed = linked = named = hidden = 0
    for last, (what, width) in anchors.iter(text):
        at = last - width + 1
        if what == "digit":
            if at >= dotted:
                dotted = _dotted.match(text, at).end()
                out["ip"] += _quads(text, at, dotted)
            if at >= spaced:
                spaced = _spaced.match(text, at).end()
                for m in _card.finditer(text, at, spaced):
                    digits = m[0].replace(" ", "").replace("-", "")
                    if 13 <= len(digits) <= 19 and luhn(digits):
                        out["card"].append(m.span())
        elif what == "at":
            start = at
            while start > mailed and text[start - 1] in LOCAL:
                start -= 1
            if start < at and (m := _domain.match(text, at + 1)):
                mailed = m.end()
                out["email"].append((start, mailed))
        elif what == "plus":
            if (m := _phone.match(text, at)) and 9 <= sum(c.isdigit() for c in m[0]) <= 15:
                out["phone"].append(m.span())
        elif what == "scheme":
            start = at
            while start > linked and text[start - 1] in _scheme:
                start -= 1
            while start < at and not ("a" <= text[start].lower() <= "z"):
                start += 1
            if start < at and (m := _rest_of_url.match(text, last + 1)):
                linked = m.start() + len(m[0].rstrip(".,;:!?)]"))
                if linked > m.start():
                    out["url"].append((start, linked))
        elif what in ("secret", "password"):
            m = (_secret if what == "secret" else _password).match(text, last + 1) if at >= hidden and not (at and text[at - 1].isalnum()) else None
            if m and (what == "password" or any(c.isdigit() for c in m[1])):
                hidden = m.end()
                out["secret"].append(m.span(1))
        elif at >= named and not (at and text[at - 1].isalnum()):
            m = _identifier.match(text, last + 1)
            if m and 6 <= sum(c.isalnum() for c in m[1]) <= 34 and sum(c.isdigit() for c in m[1]) >= 4:
                named = m.end()
                out["account"].append(m.span(1))
    return [(kind, *span) for kind in BASE + EXTRA for span in out[kind]]


def _joined(found) -> str:
    return ",".join(f"{kind}:{start}:{end}" for kind, start, end in found)


def _find(batches):
    anchors = automaton()
    for batch in batches:
        _, offsets = utf8(batch.column(1))
        for lo, hi in slices(offsets):
            rows = []
            for text in batch.column(1).slice(lo, hi - lo).to_pylist():
                found = spans(text, anchors) if text else []
                base = [x for x in found if x[0] in BASE]
                rows.append([sum(x[0] == kind for x in base) for kind in BASE] + [hashlib.sha256(_joined(base).encode()).hexdigest(), _joined(found), len(found)])
            columns = list(zip(*rows))
            yield pa.record_batch(
                [batch.column(0).slice(lo, hi - lo), *(pa.array(c, pa.int64()) for c in columns[:4]), *(pa.array(c, pa.string()) for c in columns[4:6]), pa.array(columns[6], pa.int64())],
                names=["doc_id", *(f"n_{k}" for k in BASE), "base_sha256", "spans", "n_spans"],
            )


def find_pii(docs: DataFrame) -> DataFrame:
    """doc_id, a count for each base kind, the digest of the base spans, all spans, and their number."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(
        _find, "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, spans string, n_spans long"
    )


def _redact(batches):
    anchors = automaton()
    for batch in batches:
        out = []
        for text in batch.column(1).to_pylist():
            parts, at = [], 0
            for start, end, kind in sorted((s, e, k) for k, s, e in spans(text, anchors)) if text else ():
                if start >= at:
                    parts += [text[at:start], f"[{kind}]"]
                at = max(at, end)
            out.append(None if text is None else "".join(parts) + text[at:])
        yield pa.record_batch([batch.column(0), pa.array(out, pa.string())], names=["doc_id", "text"])


def redact_pii(docs: DataFrame) -> DataFrame:
    """doc_id and the text with each span replaced by its kind in brackets."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text")).mapInArrow(_redact, "doc_id long, text string")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_pii(table(spark, sf_dir, "documents"))
