"""Language of a text by cross-parsing.

For each language a suffix automaton of labelled text answers, letter by letter,
whether what was read since the last cut occurs in that text. Where it does not, a
phrase ends: a text parses into few, long phrases over its own language and into
many short ones over others. The language with the smallest cost wins; the cost of a
language is its number of phrases times the bits of a position in its training text.

Training takes up to ``TRAIN_BYTES`` of every labelled language, in pieces from anywhere
in the texts of about ``TRAIN_ROWS`` rows of each, chosen by a hash of the id. Texts are
parsed whole, in lanes of ``LANE`` letters that a kernel advances side by side. A lane
starts ``AHEAD`` letters early to guess the state it is entered in; where the guess is not
the state in which the lane before ends, it is parsed again from that one, until all
agree, so phrases are those of the whole text. Text that is null or has no letter is ``und`` with score 0, as is all text if no
language was learned. Equal costs go to the first code. Rows come back one for one,
also for null or repeated ids.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkrank.llm.tables import bounded_pieces, bounded_sample, remainder, table
from linkrank.llm.text import fold, slices, utf8

QUERY = "op4_language"

TRAIN_BYTES = 16_384
TRAIN_ROWS = 128
SHARE = 384  # characters of a text that are learned from together
GROUP = 100  # languages parsed at a time
LANE = 512
AHEAD = 64
UNDETERMINED = "und"
_NONE = 0xFFFF

_LETTER = np.zeros(256, bool)
_LETTER[[*range(0x61, 0x7B), *range(0x80, 256)]] = True


def letters(data: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Folded letters with one blank (0x20) for each run of anything else, and new offsets."""
    folded = fold(data)
    keep = _LETTER[folded]
    out = np.where(keep, folded, 0x20)
    if len(out):
        first = np.zeros(len(out) + 1, bool)
        first[offsets] = True
        kept = keep | np.concatenate(([False], keep[:-1])) & ~first[:-1]
    else:
        kept = keep
    return out[kept], np.concatenate(([0], np.cumsum(kept)))[offsets]


def suffix_automaton(symbols: bytes) -> list[dict[int, int]]:
    """Transitions of the automaton of all substrings; state 0 is the start."""
    moves: list[dict[int, int]] = [{}]
    link, size = [-1], [0]
    last = 0
    for c in symbols:
        new = len(moves)
        moves.append({})
        size.append(size[last] + 1)
        link.append(0)
        at = last
        while at >= 0 and c not in moves[at]:
            moves[at][c] = new
            at = link[at]
        if at >= 0:
            to = moves[at][c]
            if size[to] == size[at] + 1:
                link[new] = to
            else:
                twin = len(moves)
                moves.append(dict(moves[to]))
                size.append(size[at] + 1)
                link.append(link[to])
                while at >= 0 and moves[at].get(c) == to:
                    moves[at][c] = twin
                    at = link[at]
                link[to] = link[new] = twin
        last = new
    return moves


@dataclass(frozen=True)
class Model:
    languages: tuple[str, ...]
    codes: np.ndarray  # byte -> symbol, 0 for bytes not seen in training
    moves: np.ndarray  # (state of all languages, symbol) -> state within the language
    bases: np.ndarray  # first state of each language
    bits: np.ndarray  # bits of a position in each language's text


def build(texts: dict[str, bytes]) -> Model:
    """A model from the normalised training text of each language."""
    names = tuple(sorted(k for k, v in texts.items() if v.strip()))
    seen = sorted({b for k in names for b in texts[k]})
    codes = np.zeros(256, np.uint8)
    codes[seen] = np.arange(1, len(seen) + 1)
    tables = []
    for k in names:
        moves = suffix_automaton(codes[np.frombuffer(texts[k], np.uint8)].tobytes())
        own = np.full((len(moves) + 1, len(seen) + 1), _NONE, np.uint16)  # the last state has no move
        for state, to in enumerate(moves):
            for c, target in to.items():
                own[state, c] = target
        tables.append(own)
    bases = np.cumsum([0, *(len(t) for t in tables)])[:-1]
    return Model(names, codes, np.concatenate(tables) if tables else np.zeros((0, 1), np.uint16), np.array(bases, np.int64), np.log2([len(texts[k]) + 1 for k in names]))


class _Parser:
    """Advances many places of a text side by side over the automata of a model's languages."""

    def __init__(self, data: np.ndarray, model: Model):
        self.symbols = model.codes[data]
        self.width = model.moves.shape[1]
        self.flat = model.moves.ravel()
        self.base = (model.bases * self.width)[:, None]
        roots = model.moves[model.bases]
        stuck = np.diff(np.append(model.bases, len(model.moves)))[:, None] - 1
        self.roots = np.where(roots == _NONE, stuck, roots.astype(np.int64))

    def advance(self, first: np.ndarray, size: np.ndarray, state: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """States (languages, lanes) after ``size`` letters from ``first`` on, and phrases ended; state 0 has none to end."""
        order = np.argsort(-size, kind="stable")
        at, size, state = first[order], size[order], state[:, order]
        active = len(size) - np.searchsorted(size[::-1], np.arange(int(size.max(initial=0))), "right")
        count = np.zeros(state.shape, np.int64)
        for t, k in enumerate(active.tolist()):
            c = self.symbols[at[:k] + t]
            was = state[:, :k]
            to = self.flat[self.base + was * self.width + c].astype(np.int64)
            ends = to == _NONE
            count[:, :k] += ends & (was > 0)
            state[:, :k] = np.where(ends, self.roots[:, c], to)
        back = np.argsort(order, kind="stable")
        return state[:, back], count[:, back]


def phrases(data: np.ndarray, offsets: np.ndarray, model: Model) -> np.ndarray:
    """Phrases of each row's letters over each language: an array (rows, languages)."""
    rows, langs = len(offsets) - 1, len(model.languages)
    sizes = np.diff(offsets)
    out = np.repeat((sizes > 0).astype(float)[:, None], langs, axis=1)  # the phrase that the text's end cuts
    if not langs or not len(data):
        return out
    lanes = -(-sizes // LANE)
    row = np.repeat(np.arange(rows), lanes)
    place = np.arange(len(row)) - np.repeat(np.cumsum(lanes) - lanes, lanes)
    start = offsets[row] + LANE * place
    size = np.minimum(LANE, offsets[row + 1] - start)
    parser = _Parser(data, model)
    ahead = np.where(place > 0, min(AHEAD, LANE), 0)
    entered, _ = parser.advance(start - ahead, ahead, np.zeros((langs, len(row)), np.int64))
    left, count = parser.advance(start, size, entered)
    while True:
        wrong = np.flatnonzero((place[1:] > 0) & (entered[:, 1:] != left[:, :-1]).any(axis=0)) + 1
        if not len(wrong):
            break
        entered[:, wrong] = left[:, wrong - 1]
        left[:, wrong], count[:, wrong] = parser.advance(start[wrong], size[wrong], entered[:, wrong])
    np.add.at(out, row, count.T)
    return out


def groups(model: Model):
    """Models of GROUP of the languages each, views of the whole one's tables."""
    ends = np.append(model.bases, len(model.moves))
    for a in range(0, len(model.languages), GROUP):
        b = min(a + GROUP, len(model.languages))
        yield Model(model.languages[a:b], model.codes, model.moves[ends[a] : ends[b]], model.bases[a:b] - ends[a], model.bits[a:b])


def _predictor(shared):
    def predict(batches):
        model = shared.value
        names = np.array([*model.languages, UNDETERMINED], object)
        for batch in batches:
            data, offsets = utf8(batch.column(1))
            best, score, cost = [], [], []
            for lo, hi in slices(offsets):
                own = offsets[lo : hi + 1] - offsets[lo]
                part, bounds = letters(data[offsets[lo] : offsets[hi]], own)
                plain = np.concatenate(([0], np.cumsum((part >= 0x61) & (part < 0x7B))))
                some = np.diff(plain[bounds]) > 0
                for k in np.flatnonzero(~some & (np.diff(bounds) > 0)):
                    some[k] = any(c.isalpha() for c in batch.column(1)[lo + int(k)].as_py())
                if not model.languages:
                    best += [0] * (hi - lo)
                    score += [0.0] * (hi - lo)
                    cost += [0.0] * (hi - lo)
                    continue
                bits = np.concatenate([phrases(part, bounds, some_of) for some_of in groups(model)], axis=1) * model.bits
                win = bits.argmin(axis=1)
                low = bits.min(axis=1)
                p = 1 / np.exp2(-(bits - low[:, None]) / 8).sum(axis=1)
                best += np.where(some, win, len(model.languages)).tolist()
                score += np.where(some, p, 0.0).tolist()
                cost += np.where(some, low / np.maximum(np.diff(bounds), 1), 0.0).tolist()
            yield pa.record_batch([batch.column(0), pa.array(names[best], pa.string()), pa.array(score, pa.float64()), pa.array(cost, pa.float64())], names=["doc_id", "lang_pred", "score", "bits_per_letter"])

    return predict


def training_text(rows: list[tuple[str, str]]) -> dict[str, bytes]:
    """Normalised text of each language: its pieces in order, as many as fit in TRAIN_BYTES."""
    by: dict[str, list[bytes]] = {}
    for lang, text in rows:
        raw = np.frombuffer((text or "").encode(), np.uint8)
        piece = letters(raw, np.array([0, len(raw)]))[0].tobytes()
        own = by.setdefault(lang, [])
        if sum(map(len, own)) + len(own) + len(piece) <= TRAIN_BYTES:
            own.append(piece)
    return {lang: b" ".join(parts) for lang, parts in by.items()}


def train(docs: DataFrame, where) -> Model:
    """A model from the rows of ``docs`` (doc_id, text, lang) that ``where`` allows."""
    known = docs.where(F.col("lang").isNotNull() & where).select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.col("lang").cast("string").alias("lang"))
    count = dict(known.groupBy("lang").count().collect())
    pieces = bounded_pieces(bounded_sample(known, "lang", TRAIN_ROWS, count), "lang", SHARE, 4 * TRAIN_BYTES // SHARE)
    return build(training_text([(r.lang, r.piece) for r in pieces.orderBy("lang", "n").collect()]))


def predict_language(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, lang_pred, score, and the cost of the best language in bits a letter."""
    shared = docs.sparkSession.sparkContext.broadcast(model)
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(_predictor(shared), "doc_id long, lang_pred string, score double, bits_per_letter double")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return predict_language(docs, train(docs, remainder("doc_id", 5) != 0)).select(
        "doc_id", F.coalesce(remainder("doc_id", 5) == 0, F.lit(False)).alias("held_out"), "lang_pred", "score", "bits_per_letter"
    )
