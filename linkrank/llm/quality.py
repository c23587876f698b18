"""Text quality by compression with two dictionaries.

Two zstandard dictionaries hold pieces of good and of bad labelled texts. A text is
cut in pieces, each piece is compressed with either dictionary, and the difference of
the sizes, in bytes per byte of text, says which class the text resembles. A logistic
function of that difference alone, fitted on other labelled texts, turns it into a
probability.

Training reads about ``TRAIN_ROWS`` labelled rows of each class, chosen by a hash
of the id: a third of them fills the dictionaries, with at most ``DICTIONARY_BYTES`` in
pieces from anywhere in the texts, the rest calibrates; the classes' true shares enter
the calibration. Texts are processed whole. Null and empty texts have a difference of 0
and get the score of that. Rows come back one for one, also for null or repeated ids.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkrank.llm.fit import logistic, sigmoid
from linkrank.llm.tables import bounded_pieces, remainder, table, training_rows

QUERY = "op6_quality"

TRAIN_ROWS = 3_000
DICTIONARY_BYTES = 440_000  # of each class
SHARE = 512  # characters of a text that enter a dictionary together
PIECE = 1_024
LEVEL = 9


@dataclass(frozen=True)
class Model:
    good: bytes
    bad: bytes
    weights: tuple[float, ...]  # of the difference, and a constant

    def coders(self):
        return [zstandard.ZstdCompressor(level=LEVEL, dict_data=_dictionary(x), write_content_size=False, write_checksum=False, write_dict_id=False) for x in (self.good, self.bad)]


def _dictionary(content: bytes) -> zstandard.ZstdCompressionDict:
    return zstandard.ZstdCompressionDict(content, dict_type=zstandard.DICT_TYPE_RAWCONTENT)


def dictionary(pieces: list[str]) -> bytes:
    """Dictionary content: whole pieces, as many as fit."""
    out, size = [], 0
    for x in pieces:
        raw = x.encode()
        if size + len(raw) <= DICTIONARY_BYTES:
            out.append(raw)
            size += len(raw)
    return b"".join(out).ljust(8, b"\n")


def features(text: str | None, coders) -> tuple[float, float, float]:
    """The size difference by length (positive: more like good text), which is the score's; density and log length beside it."""
    raw = (text or "").encode()
    if not raw:
        return 0.0, 0.0, 0.0
    good = bad = 0
    for at in range(0, len(raw), PIECE):
        piece = raw[at : at + PIECE]
        good += len(coders[0].compress(piece))
        bad += len(coders[1].compress(piece))
    return (bad - good) / len(raw), min(good, bad) / len(raw), float(np.log1p(len(raw)))


def _table(x: np.ndarray) -> np.ndarray:
    """What the logistic function sees: the difference."""
    return x[:, :1]


def _scorer(model: Model):
    def score(batches):
        coders = model.coders()
        for batch in batches:
            x = np.array([features(t.as_py(), coders) for t in batch.column(1)], float).reshape(-1, 3)
            p = sigmoid(_table(x) @ np.array(model.weights[:-1]) + model.weights[-1])
            yield pa.record_batch([batch.column(0), pa.array(p, pa.float64()), pa.array(x[:, 0])], names=["doc_id", "score", "difference"])

    return score


def fit(labelled: DataFrame, odds: float | None = None) -> Model:
    """A model from rows of (doc_id, text, quality), which are to be bounded in number."""
    rows = labelled.select("doc_id", F.col("text").cast("string").alias("text"), F.col("quality").cast("int").alias("quality")).persist()
    fills = F.pmod(F.xxhash64("doc_id", F.lit(7)), F.lit(3)) == 0
    pieces = bounded_pieces(rows.where(fills), "quality", SHARE, DICTIONARY_BYTES // SHARE).orderBy("quality", "n").collect()
    content = [dictionary([r.piece for r in pieces if r.quality == str(c)]) for c in (1, 0)]
    raw = Model(*content, ())

    def measure(batches):
        coders = raw.coders()
        for batch in batches:
            d = np.array([features(t.as_py(), coders)[0] for t in batch.column(0)], float)
            yield pa.record_batch([pa.array(d), batch.column(1).cast(pa.int64())], names=["d", "y"])

    seen = rows.where(~fills).select("text", "quality").mapInArrow(measure, "d double, y long").collect()
    rows.unpersist()
    return Model(*content, logistic(np.array([r.d for r in seen], float), np.array([r.y for r in seen], float), odds))


def score_quality(docs: DataFrame, model: Model) -> DataFrame:
    """doc_id, score and the normalised size difference."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    return rows.mapInArrow(_scorer(model), "doc_id long, score double, difference double")


def keep_good(docs: DataFrame, model: Model, least: float = 0.5) -> DataFrame:
    """The documents whose score is at least ``least``, with all their columns."""

    def scored(texts: pa.Array) -> pa.Array:
        coders = model.coders()
        x = np.array([features(t.as_py(), coders) for t in texts], float).reshape(-1, 3)
        return pa.array(sigmoid(_table(x) @ np.array(model.weights[:-1]) + model.weights[-1]))

    score = F.arrow_udf(scored, "double")
    return docs.where(score(F.col("text").cast("string")) >= least)


def train(docs: DataFrame, labels: DataFrame) -> Model:
    return fit(*training_rows(docs, labels, "quality", TRAIN_ROWS, remainder("doc_id", 3) != 1))


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    return score_quality(docs, train(docs, table(spark, sf_dir, "labels"))).select(
        "doc_id", F.coalesce(remainder("doc_id", 3) == 1, F.lit(False)).alias("held_out"), "score", (F.col("score") >= 0.5).cast("int").alias("predicted")
    )
