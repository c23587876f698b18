"""Benchmark passages in documents, by spaced seeds.

A seed is a fixed mask over a run of words: the words at its places are hashed, those
between are ignored, so a changed word spoils only the seeds that look at it. Seeds
of the benchmark's items and of the documents meet in a join on the hash; around each
meeting the two word sequences are compared place by place. A document leaks an item
if at least ``IDENTITY`` of the item's words stand in line in it, or a stretch of at
least ``LEAST`` such words does (of all its words, where the item has fewer).

Words are runs of letters and digits, without case. Items of fewer words than the
longest mask spans are also looked up by the hash of all their words. Items of fewer than
``SHORTEST`` words stand in many a text by chance: they match documents of just these
words. Null and empty texts and items match nothing. In the list of leaks repeated rows are
one leak, and null ids count as one id; ``drop_leaks`` decides on each row by its own text.

Before the join two bitmaps, sized after the benchmark's seeds, drop document seeds that
cannot meet any. What is left meets the benchmark's seeds in a broadcast join or, with a
benchmark too large for that, in ``SALTS`` shares of each seed, as one may be in any number
of documents.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkrank.llm.tables import cut, free, if_small, table
from linkrank.llm.text import NOT_WORD, fold, mix, slices, utf8, word_hashes

QUERY = "op1_decontaminate"

# fixed values: the places that each mask looks at
MASKS = ((0, 1, 3, 4, 7, 9), (0, 2, 3, 5, 8, 9), (0, 1, 2, 6, 7, 10), (0, 4, 5, 6, 9, 11), (0, 1, 2, 4, 5), (0, 1, 3, 5, 6))
SPAN = 1 + max(map(max, MASKS))
SHORTEST = 5
LEAST = 12
IDENTITY = 0.8
PAD = 64  # words kept on either side of a seed for the comparison
PLACES = 1024  # of a bitmap for each seed: of other seeds one in a million passes both
MOST_BITS = 28  # places of a bitmap, as a power of 2: 32 MB; beyond 2**18 seeds (some 2,000 items) more pass, and the join drops them
SALTS = 16


def seeds(words: np.ndarray, short: tuple[int, ...] = ()):
    """(place, hash) arrays of a word sequence: of each mask, and of plain runs of the ``short`` lengths."""
    for salt, places in enumerate((*MASKS, *(tuple(range(n)) for n in short))):
        last = len(words) - max(places)
        if last > 0:
            out = np.full(last, salt if salt < len(MASKS) else 64 + len(places), np.uint64)
            for k in places:
                out = out * np.uint64(0xD6E8FEB86659FD93) + words[k : k + last]
            yield np.arange(last), mix(out)


def whole(words: np.ndarray) -> np.ndarray:
    """The hash of a text of few words, known from all runs of words."""
    out = np.full(1, 32 + len(words), np.uint64)
    for w in words:
        out = out * np.uint64(0xD6E8FEB86659FD93) + w
    return mix(out)


def _folded(data, offsets, lo, hi):
    own = offsets[lo : hi + 1] - offsets[lo]
    return word_hashes(fold(data[offsets[lo] : offsets[hi]]), own, NOT_WORD)


def _item_words(batches):
    for batch in batches:
        data, offsets = utf8(batch.column(1))
        for lo, hi in slices(offsets):
            words, bounds = _folded(data, offsets, lo, hi)
            parts = [words[a:b] for a, b in zip(bounds[:-1], bounds[1:])]
            yield pa.record_batch([batch.column(0).slice(lo, hi - lo), pa.array(np.diff(bounds)), pa.array([p.tobytes() for p in parts], pa.binary())], names=["item_id", "n_words", "words"])


def _item_seeds(batches):
    for batch in batches:
        ids, place, hashes = [], [], []
        for item, raw in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
            words = np.frombuffer(raw, np.uint64)
            for at, h in seeds(words) if len(words) >= SPAN else seeds(words, (len(words),)) if len(words) >= SHORTEST else ((np.zeros(1, np.int64), whole(words)),):
                ids += [item] * len(h)
                place.append(at)
                hashes.append(h)
        join = lambda x: np.concatenate(x).view(np.int64) if x else np.zeros(0, np.int64)
        yield pa.record_batch([pa.array(ids, pa.int64()), join(place), join(hashes)], names=["item_id", "place", "seed"])


def _bitmaps(found: DataFrame, n: int) -> list[np.ndarray]:
    """Two bitmaps of PLACES places a seed, by the seeds' low and high bits, of 2**MOST_BITS places at most."""
    power = min(MOST_BITS, max(16, (PLACES * n).bit_length()))
    out = []
    for place in (F.col("seed").bitwiseAND((1 << power) - 1), F.shiftrightunsigned("seed", 64 - power)):
        bit = F.expr("shiftleft(1L, int(place & 63))")
        words = found.select(place.alias("place")).groupBy(F.shiftright("place", 6).alias("at")).agg(F.bit_or(bit).alias("bits")).toArrow()
        out.append(np.zeros(1 << (power - 6), np.uint64))
        out[-1][words.column("at").to_numpy()] = words.column("bits").to_numpy().view(np.uint64)
    return out


def _set(bitmap: np.ndarray, places: np.ndarray) -> np.ndarray:
    return (bitmap[places >> np.uint64(6)] >> (places & np.uint64(63))) & np.uint64(1) > 0


def _stretches(shared, short: tuple[int, ...]):
    """Document stretches around seeds that may meet the benchmark's, a slice of texts at a time."""
    kinds = dict(doc_id=pa.int64(), own=pa.int64(), start=pa.int64(), words=pa.binary(), place=pa.list_(pa.int64()), seed=pa.list_(pa.int64()))

    def find(batches):
        low, high = shared.value
        width = np.uint64((64 * len(high)).bit_length() - 1)
        for batch in batches:
            data, offsets = utf8(batch.column(2))
            ids, own = batch.column(0).to_pylist(), batch.column(1).to_pylist()
            for lo, hi in slices(offsets):
                words, bounds = _folded(data, offsets, lo, hi)
                few = np.flatnonzero((np.diff(bounds) > 0) & (np.diff(bounds) < SHORTEST))
                every = [*seeds(words, short), *((bounds[k : k + 1], whole(words[bounds[k] : bounds[k + 1]])) for k in few)]
                at, hashes = [], []
                for place, h in every:
                    hit = np.flatnonzero(_set(low, h & np.uint64(64 * len(low) - 1)))
                    hit = hit[_set(high, h[hit] >> (np.uint64(64) - width))]
                    at.append(place[hit])
                    hashes.append(h[hit])
                at, hashes = (np.concatenate(x) if x else np.zeros(0, np.int64) for x in (at, hashes))
                order = np.argsort(at, kind="stable")
                at, hashes = at[order], hashes[order]
                row = np.searchsorted(bounds, at, "right") - 1
                new = np.flatnonzero(np.concatenate(([True], (np.diff(row) > 0) | (np.diff(at) > SPAN))))[: len(at)] if len(at) else np.zeros(0, np.int64)
                out = {k: [] for k in kinds}
                for a, b in zip(new, np.append(new[1:], len(at))):
                    k = int(row[a])
                    start, end = max(bounds[k], at[a] - PAD), min(bounds[k + 1], at[b - 1] + SPAN + PAD)
                    out["doc_id"].append(ids[lo + k])
                    out["own"].append(own[lo + k])
                    out["start"].append(int(start - bounds[k]))
                    out["words"].append(words[start:end].tobytes())
                    out["place"].append((at[a:b] - bounds[k]).tolist())
                    out["seed"].append(hashes[a:b].view(np.int64).tolist())
                if len(new):
                    yield pa.record_batch([pa.array(out[k], kinds[k]) for k in out], names=list(out))

    return find


def _equal(words: np.ndarray, start: int, item: np.ndarray, shift: int) -> np.ndarray:
    at = np.arange(len(item)) + (shift - start)
    inside = (at >= 0) & (at < len(words))
    equal = np.zeros(len(item), bool)
    equal[inside] = words[at[inside]] == item[inside]
    return equal


def compare(words: np.ndarray, start: int, item: np.ndarray, shift: int) -> tuple[int, int, int]:
    """(first word, words, equal words) of the best stretch of an item laid over words at ``shift``.

    ``words`` begin at the document's word ``start``; item word j stands at j + shift.
    Equal words score 1, others so much less that at least IDENTITY of a stretch with a
    positive score is equal.
    """
    equal = _equal(words, start, item, shift)
    total = np.concatenate(([0.0], np.cumsum(np.where(equal, 1.0, -IDENTITY / (1 - IDENTITY)))))
    low = np.minimum.accumulate(total)
    end = int((total - low).argmax())
    first = int(np.flatnonzero(total[: end + 1] == low[end])[-1]) if end else 0
    whole = int(equal.sum())
    if whole >= IDENTITY * len(item):
        hit = np.flatnonzero(equal)
        return shift + int(hit[0]), int(hit[-1] - hit[0] + 1), whole
    return shift + first, end - first, int(equal[first:end].sum())


def longest(words: np.ndarray, start: int, item: np.ndarray, shift: int) -> tuple[int, int, int]:
    """As ``compare``, for the stretch with the most equal words of those with at least IDENTITY of their words equal.

    Each end takes the first place from which IDENTITY holds; that stretch has all equal words of the shorter ones.
    """
    equal = _equal(words, start, item, shift)
    total = np.round(np.concatenate(([0.0], np.cumsum(equal - IDENTITY))), 6)  # exact IDENTITY counts
    first = np.searchsorted(-np.minimum.accumulate(total), -total)
    count = np.concatenate(([0], np.cumsum(equal)))
    end = int((count - count[first]).argmax())
    hit = np.flatnonzero(equal[first[end] : end]) + first[end]
    return (shift + int(hit[0]), int(hit[-1] - hit[0] + 1), len(hit)) if len(hit) else (shift, 0, 0)


def _verify(batches):
    names = ["doc_id", "own", "item_id", "start", "n_words", "n_equal"]
    for batch in batches:
        out = []
        for doc, own, start, words, item_id, item, shift in zip(*(c.to_pylist() for c in batch.columns)):
            words, item = np.frombuffer(words, np.uint64), np.frombuffer(item, np.uint64)
            least = min(LEAST, np.ceil(IDENTITY * len(item)))
            first, n, equal = compare(words, start, item, shift)
            if equal < least:
                first, n, equal = longest(words, start, item, shift)
            if equal >= least:
                out.append((doc, own, item_id, first, n, equal))
        columns = list(zip(*out)) or [()] * 6
        yield pa.record_batch([pa.array(c, pa.int64()) for c in columns], names=names)


def _own() -> F.Column:
    """What tells a text from others: the same in every row that holds it."""
    return F.xxhash64(F.col("text").cast("string"))


def _meetings(hits: DataFrame, known: DataFrame) -> DataFrame:
    """Hits joined to the benchmark's seeds: by broadcast, or with the hits of each seed in shares."""
    small = if_small(known)
    if small is not known:
        return hits.join(small, "seed")
    salt = F.pmod(F.xxhash64("doc_id", "own", "start"), F.lit(SALTS))
    copies = known.withColumn("salt", F.explode(F.sequence(F.lit(0).cast("long"), F.lit(SALTS - 1).cast("long"))))
    return hits.withColumn("salt", salt).join(copies, ["seed", "salt"]).drop("salt")


def _checked(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, own, item_id, start, n_words, n_equal): leaks of the rows; ``own`` is the hash of a row's text."""
    spark = docs.sparkSession
    items = cut(benchmark.select(F.col("item_id").cast("long").alias("item_id"), F.col("text").cast("string").alias("text")).where("text IS NOT NULL").mapInArrow(_item_words, "item_id long, n_words long, words binary").where("n_words > 0").distinct())
    known = cut(items.select("item_id", "words").mapInArrow(_item_seeds, "item_id long, place long, seed long"))
    short = tuple(sorted(r[0] for r in items.where(f"n_words >= {SHORTEST} AND n_words < {SPAN}").select("n_words").distinct().collect()))
    texts = docs.select(F.col("doc_id").cast("long").alias("doc_id"), _own().alias("own"), F.col("text").cast("string").alias("text"))
    shared = spark.sparkContext.broadcast(_bitmaps(known, known.count()))
    try:
        found = cut(texts.mapInArrow(_stretches(shared, short), "doc_id long, own long, start long, words binary, place array<long>, seed array<long>"))
    finally:
        shared.destroy()
    hits = found.select("doc_id", "own", "start", F.explode(F.arrays_zip("place", "seed")).alias("h")).select("doc_id", "own", "start", F.col("h.place").alias("at"), F.col("h.seed").alias("seed"))
    met = _meetings(hits, known).select("doc_id", "own", "start", "item_id", (F.col("at") - F.col("place")).alias("shift")).distinct()
    one = found.dropDuplicates(["doc_id", "own", "start"])  # repeated rows have equal stretches
    pairs = met.alias("m").join(one.alias("f"), F.col("m.doc_id").eqNullSafe(F.col("f.doc_id")) & (F.col("m.own") == F.col("f.own")) & (F.col("m.start") == F.col("f.start")))
    pairs = pairs.join(if_small(items.select("item_id", F.col("words").alias("item")), 20_000, "item").alias("i"), F.col("m.item_id").eqNullSafe(F.col("i.item_id")))
    return pairs.select("m.doc_id", "m.own", "m.start", "f.words", "m.item_id", "i.item", "m.shift").mapInArrow(_verify, "doc_id long, own long, item_id long, start long, n_words long, n_equal long")


def find_leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """(doc_id, item_id, start, n_words, n_equal): a row for each document and item it leaks."""
    best = F.max(F.struct("n_equal", (-F.col("n_words")).alias("w"), (-F.col("start")).alias("s"))).alias("b")
    return _checked(docs, benchmark).groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", (-F.col("b.s")).alias("start"), (-F.col("b.w")).alias("n_words"), F.col("b.n_equal").alias("n_equal"))


def drop_leaks(docs: DataFrame, benchmark: DataFrame) -> DataFrame:
    """The rows whose text leaks no item, with all their columns.

    A row is known by its id and the hash of its text, so other texts of the same id, or of
    a null id, stay.
    """
    leak, text = free(docs.columns, "_leak", "_text")
    leaks = cut(_checked(docs, benchmark).select(F.col("doc_id").alias(leak), F.col("own").alias(text)).distinct())
    return docs.join(if_small(leaks), docs["doc_id"].cast("long").eqNullSafe(F.col(leak)) & (_own() == F.col(text)), "left_anti")


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return find_leaks(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
