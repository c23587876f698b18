"""Toxic passages by maximum-scoring segments.

Each word gets the log-odds of the toxic class against the other, of the documents
that hold it, smoothed by a Dirichlet prior whose mean is the rate in both classes
together. Its beginnings of ``STEMS`` bytes have log-odds too, so that unseen
inflections of a word count; of a word's known forms the longest decides. Words whose
log-odds are not significant cost a small drift instead, so scores fall outside toxic
passages. One linear scan per text finds all maximal-scoring
segments. A segment's score becomes an expected count by the extreme-value law of
such scores under the clean word distribution, and a text's score is a logistic
function, fitted on training rows, of how rare its best segments are together, however many.

Training reads about ``TRAIN_ROWS`` labelled rows of each class, chosen by a hash
of the id (the classes' true shares enter the calibration), which bounds the model: words
and stems that occur fewer than ``MIN_COUNT`` times have no score of their own, and
those that tell nothing are kept if at least ``KNOWN`` rows hold them. Null and empty texts get the score
of a text without any positive word. Rows come back one for one, also for null or
repeated ids.
"""

from __future__ import annotations

from dataclasses import dataclass, replace

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkrank.llm.fit import logistic, sigmoid
from linkrank.llm.tables import remainder, table, training_rows
from linkrank.llm.text import NOT_WORD, chunks, fold, prefix_sums, slices, span_hashes, tokens, utf8

QUERY = "op10_toxicity"

TRAIN_ROWS = 4_000
MIN_COUNT = 3
KNOWN = 20  # documents from which on a form without significance counts as known
PRIOR = 0.1  # weight of the prior, as a share of the training words
SIGNIFICANT = 5.0
SHRINK = 2.0
LEAST = 1.5
DRIFT = 0.1
FLOOR = -0.5
STEMS = (8, 7, 6, 5, 4, 3, 2)
REPORTED = 0.01


@dataclass(frozen=True)
class Model:
    words: np.ndarray  # sorted hashes of the scored words and stems
    scores: np.ndarray
    decay: float
    space: float
    slope: float
    shift: float


def maximal_segments(scores: np.ndarray) -> list[tuple[int, int, float]]:
    """All maximal-scoring segments (start, end, score) of a sequence, left to right.

    Only positive places open a segment; a stack holds the candidates with the
    running totals at their ends, and each knows the nearest one to its left whose
    total before it is smaller, so that a search skips what cannot be merged. A new
    candidate swallows those that it improves. Each is pushed and swallowed once.
    """
    total = np.concatenate(([0.0], np.cumsum(scores)))
    stack: list[tuple] = []  # start, end, total before, total after, nearest lower to the left
    for at in np.flatnonzero(scores > 0).tolist():
        start, before, after = at, total[at], total[at + 1]
        k = len(stack) - 1
        while True:
            while k >= 0 and stack[k][2] >= before:
                k = stack[k][4]
            if k < 0 or stack[k][3] >= after:
                break
            start, before, k = stack[k][0], stack[k][2], stack[k][4]
            while len(stack) and stack[-1][0] >= start:
                stack.pop()
        stack.append((start, at + 1, before, after, k))
    return [(s, e, float(b - a)) for s, e, a, b, _ in stack]


def _forms(data: np.ndarray, own: np.ndarray):
    """The rows' word ranges, and hashes of the words' forms, longest first: (form, which words have it)."""
    data = fold(data)
    starts, ends, bounds = tokens(data, own, NOT_WORD)
    sums = prefix_sums(data)
    every = np.arange(len(starts))

    def forms():
        yield span_hashes(sums, starts, ends), every
        for size in STEMS:
            longer = np.flatnonzero(ends - starts > size)
            yield span_hashes(sums, starts[longer], starts[longer] + size) ^ np.uint64(size), longer

    return bounds, forms()


def _word_counts(batches):
    """Rows of (word, class, documents), summed within a slice."""
    for batch in batches:
        data, offsets = utf8(batch.column(0))
        toxic = batch.column(1).to_numpy(zero_copy_only=False).astype(np.int64)
        for lo, hi in slices(offsets):
            bounds, forms = _forms(data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo])
            row = np.repeat(np.arange(hi - lo), np.diff(bounds))
            for words, which in forms:
                order = np.lexsort((words, row[which]))
                words, own = words[order], row[which][order]
                once = np.ones(len(words), bool)
                once[1:] = (words[1:] != words[:-1]) | (own[1:] != own[:-1])
                words, label = words[once], toxic[lo:hi][own[once]]
                for c in (0, 1):
                    seen, n = np.unique(words[label == c], return_counts=True)
                    yield pa.record_batch([seen.view(np.int64), np.full(len(seen), c), n, np.full(len(seen), len(which) == len(row))], names=["word", "toxic", "n", "whole"])


def word_scores(texts: DataFrame):
    """Hashes and scores of the known forms, 0 for those that tell nothing.

    ``texts`` has text and toxic (0 or 1). Only sums and the bounded list of forms reach
    the driver.
    """
    count = lambda c: F.sum(F.when(F.col("toxic") == c, F.col("n")).otherwise(0)).alias(f"y{c}")
    counted = texts.mapInArrow(_word_counts, "word long, toxic long, n long, whole boolean").groupBy("word").agg(count(1), count(0), F.max("whole").alias("whole")).persist()
    n1, n0 = (float(x or 0) for x in counted.where("whole").agg(F.sum("y1"), F.sum("y0")).first())
    rows = []
    if n1 and n0:
        prior = (F.col("y1") + F.col("y0")) * PRIOR
        odds = lambda y, n: F.log((F.col(y) + prior) / F.greatest(n + PRIOR * (n1 + n0) - F.col(y) - prior, F.lit(0.5)))
        scored = counted.where(F.col("y1") + F.col("y0") >= MIN_COUNT).select("word", (F.col("y1") + F.col("y0")).alias("n"), (odds("y1", n1) - odds("y0", n0)).alias("s"), F.sqrt(1 / (F.col("y1") + prior) + 1 / (F.col("y0") + prior)).alias("sd"))
        scored = scored.withColumn("z", F.col("s") / F.col("sd")).withColumn("tells", (F.abs("z") >= SIGNIFICANT) & (F.abs("s") >= LEAST))
        score = F.when(F.col("tells"), F.greatest(F.lit(FLOOR), F.col("s") * (1 - SHRINK / F.abs("z")))).otherwise(0.0)  # towards 0 by SHRINK standard deviations
        known = scored.where(F.col("tells") | (F.col("n") >= KNOWN)).select("word", score.alias("score"))
        rows = known.select("word", "score").collect()
    counted.unpersist()
    words, scores = np.array([r.word for r in rows], np.int64), np.array([r.score for r in rows], float)
    at = np.argsort(words.view(np.uint64))
    return words.view(np.uint64)[at], scores[at]


def _decay(rates: np.ndarray, values: np.ndarray) -> float:
    """The positive root of sum(rates * exp(x * values)) = 1, by bisection; 1 where there is none."""
    total = lambda x: float((rates * np.exp(np.minimum(700, x * values))).sum())
    if not (values > 0).any() or (rates * values).sum() >= 0:
        return 1.0
    lo, hi = 0.0, 1.0
    while total(hi) < 1 and hi < 64:
        lo, hi = hi, hi * 2
    for _ in range(60):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if total(mid) < 1 else (lo, mid)
    return hi


def _scored(column, model: Model):
    """For each slice: its rows' word ranges, and a score for each word; long texts are hashed in chunks."""
    data, offsets = utf8(column)
    coarse = np.zeros(1 << 20, bool)
    coarse[model.words & np.uint64(len(coarse) - 1)] = True
    for lo, hi in slices(offsets):
        part, own = data[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo]
        every, total = [np.zeros(0)], np.zeros(len(own), np.int64)
        for a, b in chunks(part, NOT_WORD):
            bounds, forms = _forms(part[a:b], np.clip(own, a, b) - a)
            scores, decided = np.full(bounds[-1], -DRIFT), np.zeros(bounds[-1], bool)
            for words, which in forms if len(model.words) else ():
                maybe = np.flatnonzero(coarse[words & np.uint64(len(coarse) - 1)] & ~decided[which])
                at = np.minimum(np.searchsorted(model.words, words[maybe]), len(model.words) - 1)
                known = model.words[at] == words[maybe]
                at, which = at[known], which[maybe[known]]
                scores[which] += model.scores[at]
                decided[which] = True
            every.append(scores)
            total += bounds
        yield total, np.concatenate(every)


def _segments(column, model: Model):
    """For each row: its number of words, and its maximal segments as (start, end, score)."""
    for bounds, scores in _scored(column, model):
        for k in range(len(bounds) - 1):
            part = scores[bounds[k] : bounds[k + 1]]
            yield len(part), maximal_segments(part) if (part > 0).any() else []


def _evidence(n: int, best: float, model: Model) -> float:
    """Minus the log of the expected number of clean segments that score as well."""
    return model.decay * best - float(np.log(model.space * max(n, 1))) if best > 0 else -float(np.log(model.space * max(n, 1))) - 1


def _joint_evidence(n: int, found: list[float], model: Model) -> float:
    """The strongest evidence of the best r segments, for any r: several weak ones may be strong together.

    By the extreme-value law a clean text has a Poisson number, one on average, of segments
    whose normalised score is above 0, and these scores are exponential. This is minus the
    log of the probability of r such segments with as large a sum, by its leading term.
    """
    x = model.decay * np.sort(np.array(found, float))[::-1] - np.log(model.space * max(n, 1))
    x = x[x > 0]
    if not len(x):
        return _evidence(n, max(found, default=0.0), model)
    r = np.arange(1, len(x) + 1)
    factorial = np.cumsum(np.log(r))
    total = np.cumsum(x)
    tail = total - (r - 1) * np.log(np.maximum(total, 1)) + factorial - np.log(r)
    return float((factorial + np.where(total > r - 1, np.maximum(tail, 0), 0)).max())


def _scorer(model: Model):
    def score(batches):
        for batch in batches:
            out, found = [], []
            for n, segments in _segments(batch.column(1), model):
                x = _joint_evidence(n, [s for *_, s in segments], model)
                out.append(x)
                found.append([{"start": s, "end": e, "score": v} for s, e, v in segments if _evidence(n, v, model) >= -np.log(REPORTED)])
            p = sigmoid(model.slope * np.array(out, float) + model.shift)
            kind = pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64()), ("score", pa.float64())]))
            yield pa.record_batch([batch.column(0), pa.array(p, pa.float64()), pa.array(np.array(out, float)), pa.array(found, kind)], names=["doc_id", "score", "evidence", "passages"])

    return score


def fit(labelled: DataFrame, odds: float | None = None) -> Model:
    """A model from rows of (doc_id, text, toxic), which are to be bounded in number.

    ``odds``: log-odds of the toxic class among all labelled rows, where the given
    rows have another share of it.
    """
    texts = labelled.select("text", F.col("toxic").cast("int").alias("toxic")).persist()
    model = _uncalibrated(texts)
    seen = texts.mapInArrow(_evidences(model), "x double, y long").collect()
    texts.unpersist()
    slope, shift = logistic(np.array([r.x for r in seen], float), np.array([r.y for r in seen], float), odds)
    return replace(model, slope=slope, shift=shift)


def _uncalibrated(texts: DataFrame) -> Model:
    """Word scores, and the law of segments in clean texts under them."""
    raw = Model(*word_scores(texts), 1.0, 1.0, 1.0, 0.0)

    def clean_scores(batches):
        for batch in batches:
            for _, found in _scored(batch.column(0), raw):
                values, n = np.unique(np.round(found, 1), return_counts=True)
                yield pa.record_batch([values, n], names=["v", "n"])

    seen = texts.where("toxic = 0").mapInArrow(clean_scores, "v double, n long").groupBy("v").agg(F.sum("n")).collect()
    values, rates = np.array([r[0] for r in seen], float), np.array([r[1] for r in seen], float)
    rates /= max(rates.sum(), 1)
    decay = _decay(rates, values)
    space = max(1e-4, decay * float((rates * np.abs(values) * np.exp(np.minimum(50, decay * values))).sum()))
    return replace(raw, decay=decay, space=space)


def _evidences(model: Model):
    def features(batches):
        for batch in batches:
            x = [_joint_evidence(n, [s for *_, s in found], model) for n, found in _segments(batch.column(0), model)]
            yield pa.record_batch([pa.array(np.array(x, float)), batch.column(1).cast(pa.int64())], names=["x", "y"])

    return features


def score_toxicity(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, score, evidence, and the significant passages as word ranges."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(_scorer(model), "doc_id long, score double, evidence double, passages array<struct<start:long,end:long,score:double>>")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    model = fit(*training_rows(docs, table(spark, sf_dir, "labels"), "toxic", TRAIN_ROWS, remainder("doc_id", 5) != 0))
    return score_toxicity(docs, model).select(
        "doc_id", F.coalesce(remainder("doc_id", 5) == 0, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted"), F.size("passages").alias("n_passages")
    )
