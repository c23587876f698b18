"""Removal of byte strings that an earlier document holds, by suffix arrays of shards.

Every start of a ``LENGTH``-byte window belongs to one anchor: the ``GRAM``-byte string
within the window with the smallest hash, the leftmost of equal ones. Equal windows have
equal anchors, so windows need comparing only where anchors agree. Runs of windows with
one anchor are pieces; they tile a document.

* Of each anchor and piece the smallest document is found, first within tasks, then in
  blocks of anchors. Pieces that an earlier document holds as a whole are settled.
* Two pieces of an anchor share a window only if they agree on the ``SIDE`` bytes before
  the anchor or on those after it. Those that agree with another document's on a side,
  by a short hash, are looked at byte by byte: they are gathered in shards, a shard's suffix array is induced, and its common prefixes tell which windows
  occur in an earlier document. Where an anchor has more than ``WIDE`` such pieces, its
  windows are spread over shards by their own hash instead.
* Each document then drops the bytes under all windows found.

Matches never cross documents, overlaps count, and windows are judged on the input.
Null text is empty. A null id is no earlier document and loses nothing; rows with
the same id are not earlier than each other. Rows come back one for one.
"""

from __future__ import annotations

import hashlib
import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkrank.llm.suffixes import common_prefixes, suffix_array
from linkrank.llm.tables import cut, release, table
from linkrank.llm.text import mix, prefix_sums, slices, span_hashes, utf8, window_hashes

QUERY = "op7_repeats"

LENGTH = 50
GRAM = 14
REACH = LENGTH - GRAM + 1  # grams of a window
SIDE = (LENGTH - GRAM) // 2  # of the bytes around its anchor a window holds as many on one side
SEGMENT = 1 << 20  # bytes of one document that are handled at a time
FLUSH = 1 << 19
BLOCK_PIECES = 400_000
SHARD_BYTES = 3 << 19
PART_BYTES = 6 << 20
WIDE = 1 << 14
BITS = 25
SEEN = 200_000
PASSES = 2  # over the blocks of anchors, and over whole documents, at most: what one moves is gone before the next
PASS_BYTES = 1 << 25  # of the corpus for each pass, about
TEXT_RUN = 1 << 18  # bytes of text that are copied at a time, by addresses of eight bytes each

_PIECE = np.dtype([("doc", "<i8"), ("start", "<u4"), ("count", "<u1")])
_ENTRY = np.dtype([("anchor", "<u4"), ("low", "<u4"), ("high", "<u2"), ("left", "<u2"), ("right", "<u2"), *_PIECE.descr])


def pieces(data: np.ndarray, offsets: np.ndarray, of=None, hashed: bool = True):
    """(row, start in data, windows, anchor hash, text hash, hashes of the anchor's sides) of the pieces of rows laid end to end.

    ``of`` tells from their anchors' hashes which pieces are wanted; without ``hashed`` the last three are left out.
    """
    n = len(data)
    if n < LENGTH:
        return (np.zeros(0, np.int64),) * 3 + (np.zeros(0, np.uint64),) * (4 if hashed else 1)
    sums = prefix_sums(data)
    grams = window_hashes(sums, GRAM)
    low = (grams & ~np.uint64((1 << 24) - 1)) | np.arange(len(grams), dtype=np.uint64)
    best, width = low, 1
    while width * 2 <= REACH:
        best = np.minimum(best[: len(best) - width], best[width:])
        width *= 2
    if width < REACH:
        best = np.minimum(best[: len(best) - (REACH - width)], best[REACH - width :])
    anchor = (best & np.uint64((1 << 24) - 1)).astype(np.int64)
    valid = np.zeros(n + 1, np.int32)
    long = np.diff(offsets) >= LENGTH
    np.add.at(valid, offsets[:-1][long], 1)
    np.add.at(valid, (offsets[1:] - LENGTH + 1)[long], -1)
    valid = np.cumsum(valid[: len(anchor)]) > 0
    new = valid.copy()
    new[1:] &= (anchor[1:] != anchor[:-1]) | ~valid[:-1]
    start = np.flatnonzero(new)
    end = np.flatnonzero(valid & ~np.append(valid[1:] & ~new[1:], False)) + 1
    if of is not None:
        own = of(grams[anchor[start]])
        start, end = start[own], end[own]
    row, at = np.searchsorted(offsets, start, "right") - 1, anchor[start]
    if not hashed:
        return row, start, end - start, grams[at]
    left = span_hashes(sums, np.maximum(offsets[row], at - SIDE), at)
    right = span_hashes(sums, at + GRAM, np.minimum(offsets[row + 1], at + GRAM + SIDE))
    return row, start, end - start, grams[at], span_hashes(sums, start, end + LENGTH - 1), left, right


def _all_pieces(batch, of=None, hashed: bool = True):
    """Arrays of a batch's pieces by runs of rows: (rows, starts in the row, windows, anchors, other hashes, absolute starts, bytes)."""
    data, offsets = utf8(batch.column(1))
    known = batch.column(0).is_valid().to_numpy(zero_copy_only=False)
    for lo, hi in slices(offsets, SEGMENT):
        for a in range(offsets[lo], max(offsets[hi] - LENGTH + 1, offsets[lo] + 1), SEGMENT):
            b = min(offsets[hi], a + SEGMENT + LENGTH - 1) if hi == lo + 1 else offsets[hi]
            own = np.clip(offsets[lo : hi + 1], a, b) - a
            row, start, count, anchor, *hashes = pieces(data[a:b], own, of, hashed)
            ok = known[lo + row]
            row, start, count, anchor, *hashes = (x[ok] for x in (row, start, count, anchor, *hashes))
            yield lo + row, start + a - offsets[lo + row], count, anchor, hashes, start + a, data
            if hi > lo + 1:
                break


def place(doc, parts: int):
    """The part of a document id; the same function as ``_part``."""
    return np.mod(doc ^ (doc >> 16), parts)


def _part(parts: int):
    return F.pmod(F.col("doc_id").bitwiseXOR(F.shiftright("doc_id", 16)), F.lit(parts))


def _packed(found: list[np.ndarray], parts: int):
    """Rows (0, part, payload) of settled pieces."""
    rows = np.concatenate(found)
    part = place(rows["doc"], parts)
    order = np.argsort(part, kind="stable")
    return _rows(0, part[order], rows, order)


def _rows(kind: int, key: np.ndarray, rows: np.ndarray, which: np.ndarray | None = None, names: tuple[str, ...] = _PIECE.names):
    """A row (kind, key, payload) for each key; the payload holds one column after the other of its rows, or of those at ``which``."""
    cuts = np.flatnonzero(np.concatenate(([True], np.diff(key) != 0))) if len(key) else np.zeros(0, np.int64)
    which = np.arange(len(rows)) if which is None else which
    out = []
    for a, b in zip(cuts, np.append(cuts[1:], len(which))):
        own = rows[which[a:b]]
        out.append(b"".join(np.ascontiguousarray(own[n]).tobytes() for n in names))
    return pa.record_batch([np.full(len(cuts), kind, np.int32), key[cuts].astype(np.int64), pa.array(out, pa.binary())], names=["kind", "key", "payload"])


def _unpack(raw: list[bytes], kind: np.dtype) -> np.ndarray:
    """The rows of payloads that hold one column after the other."""
    sizes = [len(x) // kind.itemsize for x in raw]
    out = np.empty(sum(sizes), kind)
    at = 0
    for x, n in zip(raw, sizes):
        byte = 0
        for name in kind.names:
            out[name][at : at + n] = np.frombuffer(x, kind[name], n, byte)
            byte += n * kind[name].itemsize
        at += n
    return out


def _entries(blocks: int, parts: int, turn: int = 0, turns: int = 1):
    """Rows (1, block, entries) of a run's pieces but for those of which it has an earlier document; of these (0, blocks + part, pieces). Of one in ``turns`` blocks."""
    block_of = lambda anchor: (anchor >> np.uint64(32)) % np.uint64(blocks)
    of = None if turns == 1 else lambda anchor: block_of(anchor) % np.uint64(turns) == turn
    kind = np.dtype([("block", "<i8"), *_ENTRY.descr])

    def pack(held):
        rows = np.concatenate(held)
        held.clear()  # a run is held once from here on, and sorted by addresses
        anchor, text = rows["block"].astype(np.uint64) << np.uint64(32) | rows["anchor"], rows["high"].astype(np.uint64) << np.uint64(32) | rows["low"]
        order = np.lexsort((rows["doc"], text, anchor))
        anchor, text = anchor[order], text[order]
        same = (anchor[1:] == anchor[:-1]) & (text[1:] == text[:-1])
        del anchor, text
        same = np.concatenate(([False], same))
        group = np.flatnonzero(~same)
        doc = rows["doc"][order]
        later = doc > np.repeat(doc[group], np.diff(np.append(group, len(rows))))
        lost, kept = order[later], order[~later]
        yield _rows(1, rows["block"][kept], rows, kept, _ENTRY.names)
        if len(lost):
            part = place(rows["doc"][lost], parts)
            turn = np.argsort(part, kind="stable")
            yield _rows(0, part[turn] + blocks, rows, lost[turn], _PIECE.names)

    def emit(batches):
        held, size = [], 0
        for batch in batches:
            ids = batch.column(0).fill_null(0).to_numpy()
            for row, start, count, anchor, (text, left, right), _, _ in _all_pieces(batch, of):
                rows = np.empty(len(row), kind)
                rows["block"] = block_of(anchor)
                rows["anchor"] = anchor & np.uint64(0xFFFFFFFF)
                rows["low"], rows["high"] = text & np.uint64(0xFFFFFFFF), text >> np.uint64(48)
                rows["left"], rows["right"] = left & np.uint64(0xFFFF), right & np.uint64(0xFFFF)
                rows["doc"], rows["start"], rows["count"] = ids[row], start, count
                held.append(rows)
                size += len(rows)
                if size >= FLUSH:
                    yield from pack(held)
                    held, size = [], 0
        if size:
            yield from pack(held)

    return emit


def _settle(blocks: int, parts: int):
    """Of a block's entries: the pieces that an earlier document holds, and the pieces to be compared (kind 2, or 3 where an anchor has many)."""

    def settle(group: pa.Table) -> pa.Table:
        key = group.column("key")[0].as_py()
        if key >= blocks:
            return group.set_column(1, "key", pa.array(np.full(group.num_rows, key - blocks)))
        rows = _unpack(group.column("payload").to_pylist(), _ENTRY)
        whole = rows["high"].astype(np.uint64) << np.uint64(32) | rows["low"]
        order = np.lexsort((rows["doc"], whole, rows["anchor"]))
        rows, whole = rows[order], whole[order]
        text = np.ones(len(rows), bool)
        text[1:] = (rows["anchor"][1:] != rows["anchor"][:-1]) | (whole[1:] != whole[:-1])
        heads = np.flatnonzero(text)
        first = np.repeat(rows["doc"][heads], np.diff(np.append(heads, len(rows))))
        later = rows["doc"] > first
        gone = np.empty(int(later.sum()), _PIECE)
        for name in _PIECE.names:
            gone[name] = rows[name][later]
        own = rows[~later]
        open_ = np.zeros(len(own), bool)
        for side in ("left", "right"):
            key = own["anchor"].astype(np.uint64) << np.uint64(16) | own[side]
            order = np.lexsort((own["doc"], key))
            key, doc = key[order], own["doc"][order]
            begin = np.flatnonzero(np.concatenate(([True], key[1:] != key[:-1])))
            size = np.diff(np.append(begin, len(own)))
            open_[order] |= np.repeat(doc[begin + size - 1] > doc[begin], size)
        asked = np.flatnonzero(open_)
        begin = np.flatnonzero(np.concatenate(([True], own["anchor"][asked][1:] != own["anchor"][asked][:-1])))[: len(asked)]
        size = np.diff(np.append(begin, len(asked)))
        wide = np.zeros(len(own), bool)
        wide[asked] = np.repeat(size, size) > WIDE
        out = [_packed([gone], parts)] if len(gone) else []
        for kind, which in ((2, open_ & ~wide), (3, open_ & wide)):
            if which.any():
                ask = np.empty(int(which.sum()), _PIECE)
                for name in _PIECE.names:
                    ask[name] = own[name][which]
                out.append(_rows(kind, np.zeros(len(ask), np.int64), ask))
        return pa.Table.from_batches(out) if out else pa.table({"kind": pa.array([], pa.int32()), "key": pa.array([], pa.int64()), "payload": pa.array([], pa.binary())})

    return settle


def _spots(doc: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    h = mix(mix(doc.astype(np.int64).view(np.uint64)) + start.astype(np.uint64))
    return h & np.uint64((1 << BITS) - 1), h >> np.uint64(64 - BITS)


def _asked(batches):
    """(table, word, bits): the places of asked pieces in two bitmaps for each kind."""
    for batch in batches:
        for kind in (2, 3):
            raw = [x.as_py() for k, x in zip(batch.column(0).to_pylist(), batch.column(1)) if k == kind]
            if raw:
                rows = _unpack(raw, _PIECE)
                for side, spot in enumerate(_spots(rows["doc"], rows["start"])):
                    words, where = np.unique(spot >> np.uint64(6), return_inverse=True)
                    value = np.zeros(len(words), np.uint64)
                    np.bitwise_or.at(value, where, np.uint64(1) << (spot & np.uint64(63)))
                    yield pa.record_batch([np.full(len(words), 2 * (kind - 2) + side, np.int32), words.astype(np.int64), value.view(np.int64)], names=["side", "word", "bits"])


def _has(bits: np.ndarray, spot: np.ndarray) -> np.ndarray:
    return (bits[spot >> np.uint64(6)] >> (spot & np.uint64(63))) & np.uint64(1) > 0


def _texts(shared, shards: int, parts: int):
    """Rows (shard, doc, start, text) of the asked pieces, and of the windows of those of wide anchors.

    Windows of which the task has met an earlier document go to shards + part, without text.
    """

    seen: dict[int, int] = {}

    def windows(pick, doc, start, count, at, data):
        """The windows of some wide anchors' pieces, one by one."""
        which, place_ = np.repeat(pick, count[pick]), _ranges(count[pick])
        doc, start, at = doc[which], start[which] + place_, at[which] + place_
        sums = prefix_sums(data[at.min() : at.max() + LENGTH])
        hashes = span_hashes(sums, at - at.min(), at - at.min() + LENGTH)
        shard, settled = (hashes % np.uint64(shards)).astype(np.int64), np.zeros(len(at), bool)
        for k, (h, d) in enumerate(zip(hashes.tolist(), doc.tolist())):
            met = seen.get(h)
            settled[k] = met is not None and met < d
            if met is None or d < met:
                if len(seen) >= SEEN:
                    seen.clear()
                seen[h] = d
        shard[settled] = shards + place(doc[settled], parts)
        return _text_rows(shard, doc, start, data, at, np.full(len(at), LENGTH), settled)

    def emit(batches):
        bits = shared.value
        seen.clear()
        for batch in batches:
            ids = batch.column(0).fill_null(0).to_numpy()
            for row, start, count, anchor, _, at, data in _all_pieces(batch, hashed=False):
                doc = ids[row]
                low, high = _spots(doc, start)
                asked = np.flatnonzero(_has(bits[0], low) & _has(bits[1], high))
                for a, b in slices(np.concatenate(([0], np.cumsum(count[asked] + LENGTH - 1))), TEXT_RUN):
                    pick = asked[a:b]
                    yield _text_rows((anchor[pick] % np.uint64(shards)).astype(np.int64), doc[pick], start[pick], data, at[pick], count[pick] + LENGTH - 1)
                asked = np.flatnonzero(_has(bits[2], low) & _has(bits[3], high))
                for a, b in slices(np.concatenate(([0], np.cumsum(count[asked] * LENGTH))), TEXT_RUN):
                    yield windows(asked[a:b], doc, start, count, at, data)

    return emit


def _ranges(sizes: np.ndarray) -> np.ndarray:
    """0 .. n - 1 for each size n, one after the other."""
    return np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes, sizes)


def _text_rows(shard, doc, start, data, at, size, without=None):
    """Rows (shard, doc, start, text): the bytes data[at : at + size], or none."""
    if without is not None:
        size = np.where(without, 0, size)
    raw = data[np.repeat(at, size) + _ranges(size)]
    offsets = np.concatenate(([0], np.cumsum(size))).astype(np.int32)
    missing = None if without is None else pa.array(~without).buffers()[1]
    text = pa.Array.from_buffers(pa.binary(), len(size), [missing, pa.py_buffer(offsets), pa.py_buffer(np.ascontiguousarray(raw))])
    return pa.record_batch([pa.array(shard, pa.int64()), pa.array(doc, pa.int64()), pa.array(start.astype(np.int64)), text], names=["shard", "doc", "start", "text"])


def earlier_windows(data: np.ndarray, offsets: np.ndarray, docs: np.ndarray):
    """(text, start, windows): runs of windows that start in a text of a smaller document, by the texts' suffix array."""
    n, size = len(docs), np.diff(offsets)
    owner = np.repeat(np.arange(n), size + 1)
    inside = np.ones(len(owner), bool)
    inside[offsets[1:] + np.arange(n)] = False
    s = np.zeros(len(owner), np.uint16)
    s[inside] = data.astype(np.uint16) + 1
    order = suffix_array(s, 257)
    shared = common_prefixes(s, order)
    new = shared[order] < LENGTH
    new[0] = True
    doc = docs[owner[order]]
    begin = np.flatnonzero(new)
    least = np.repeat(np.minimum.reduceat(doc, begin), np.diff(np.append(begin, len(order))))
    hit = np.zeros(len(s), bool)
    hit[order] = doc > least
    place_ = _ranges(size + 1)
    hit &= place_ <= size[owner] - LENGTH
    edge = np.diff(np.concatenate(([0], hit.astype(np.int8), [0])))
    first, last = np.flatnonzero(edge == 1), np.flatnonzero(edge == -1)
    return owner[first], place_[first], last - first


def _compare(parts: int):
    def compare(group: pa.Table) -> pa.Table:
        doc, start = group.column("doc").to_numpy(), group.column("start").to_numpy()
        if group.column("text").null_count:
            rows = np.ones(len(doc), _PIECE)
            rows["doc"], rows["start"] = doc, start
        else:
            data, offsets = utf8(group.column("text"))
            which, place_, count = earlier_windows(data[offsets[0] : offsets[-1]], offsets - offsets[0], doc)
            rows = np.empty(len(which), _PIECE)
            rows["doc"], rows["start"], rows["count"] = doc[which], start[which] + place_, count
        return pa.Table.from_batches([_packed([rows], parts)])

    return compare


def _remove(key, left: pa.Table, right: pa.Table) -> pa.Table:
    """Digest rows of a part's documents, their found windows in the right table."""
    rows = _unpack(right.column("payload").to_pylist(), _PIECE) if right.num_rows else np.zeros(0, _PIECE)
    rows = rows[np.argsort(rows["doc"], kind="stable")]
    ids = left.column("doc_id").to_pylist()
    wanted = np.array([0 if i is None else i for i in ids], np.int64)
    lo, hi = np.searchsorted(rows["doc"], wanted), np.searchsorted(rows["doc"], wanted, "right")
    out = []
    for k, raw in enumerate(left.column("raw")):
        raw = raw.as_py() or b""
        own = rows[lo[k] : hi[k]] if ids[k] is not None else rows[:0]
        removed = spans = 0
        if len(own):
            cover = np.zeros(len(raw) + 1, np.int32)
            np.add.at(cover, own["start"].astype(np.int64), 1)
            np.add.at(cover, np.minimum(own["start"].astype(np.int64) + own["count"] + LENGTH - 1, len(raw)), -1)
            gone = np.cumsum(cover[:-1]) > 0
            removed, spans = int(gone.sum()), int((gone & ~np.concatenate(([False], gone[:-1]))).sum())
            rest = np.frombuffer(raw, np.uint8)[~gone].tobytes()
        else:
            rest = raw
        out.append((ids[k], len(raw), removed, spans, hashlib.sha256(rest).hexdigest(), rest))
    kinds = [("doc_id", pa.int64()), ("n_bytes", pa.int64()), ("n_removed", pa.int64()), ("n_spans", pa.int64()), ("kept_sha256", pa.string()), ("kept", pa.binary())]
    return pa.table({name: pa.array([r[j] for r in out], kind) for j, (name, kind) in enumerate(kinds)})


def found_windows(docs: DataFrame, parts: int, total: int) -> DataFrame:
    """(key, payload): for each part of documents the runs of windows that an earlier document holds."""
    spark = docs.sparkSession
    blocks = max(256, math.ceil(total / (REACH + 1) * 2 / BLOCK_PIECES))
    rows = "kind int, key long, payload binary"
    turns, settled = _turns(total), None
    for turn in range(turns):
        own = cut(docs.select("doc_id", "raw").mapInArrow(_entries(blocks, parts, turn, turns), rows).groupBy("key").applyInArrow(_settle(blocks, parts), rows))
        settled = own if settled is None else settled.unionByName(own)
        release(spark)  # the turn's entries, the largest shuffle
    asked = settled.where("kind > 1")
    words = asked.select("kind", "payload").mapInArrow(_asked, "side int, word long, bits long").groupBy("side", "word").agg(F.bit_or("bits").alias("bits"))
    bits = np.zeros((4, 1 << (BITS - 6)), np.uint64)
    for r in words.toArrow().to_batches():  # four bitmaps of fixed size
        bits[r.column(0).to_numpy(), r.column(1).to_numpy()] = r.column(2).to_numpy().view(np.uint64)
    n = asked.agg(F.sum(F.octet_length("payload"))).first()[0] or 0
    shards = max(256, math.ceil(n / _PIECE.itemsize * 2 * LENGTH / SHARD_BYTES))
    texts = docs.select("doc_id", "raw").mapInArrow(_texts(spark.sparkContext.broadcast(bits), shards, parts), "shard long, doc long, start long, text binary")
    compared = cut(texts.groupBy("shard").applyInArrow(_compare(parts), rows))
    del texts
    release(spark)  # the texts, before whole documents are moved
    return settled.where("kind = 0").unionByName(compared).select("key", "payload")


def _turns(total: int) -> int:
    return min(PASSES, max(1, math.ceil(total / PASS_BYTES)))


def remove_repeats(docs: DataFrame, texts: bool = True) -> DataFrame:
    """(doc_id, n_bytes, n_removed, n_spans, kept_sha256, kept): a row for each document; kept are the bytes that stay.

    Without ``texts`` the last column is left out, and documents are moved a part at a time.
    """
    raw = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").cast("binary").alias("raw"))
    total = raw.agg(F.sum(F.octet_length("raw"))).first()[0] or 0
    parts = max(128, math.ceil(total / PART_BYTES))
    found = found_windows(raw, parts, total)
    keyed = raw.withColumn("part", F.coalesce(_part(parts), F.pmod(F.xxhash64("raw"), F.lit(parts))))
    columns = "doc_id long, n_bytes long, n_removed long, n_spans long, kept_sha256 string"
    if texts:
        return keyed.groupBy("part").cogroup(found.groupBy("key")).applyInArrow(_remove, f"{columns}, kept binary")
    digests = lambda key, left, right: _remove(key, left, right).drop_columns(["kept"])
    turns, out = _turns(total), None
    for turn in range(turns):
        of = lambda name: F.pmod(F.col(name), F.lit(turns)) == turn  # noqa: B023, E731
        own = cut(keyed.where(of("part")).groupBy("part").cogroup(found.where(of("key")).groupBy("key")).applyInArrow(digests, columns))
        out = own if out is None else out.unionByName(own)
        release(docs.sparkSession)  # the turn's documents
    return out


def query(spark: SparkSession, sf_dir: str) -> DataFrame:
    return remove_repeats(table(spark, sf_dir, "documents"), texts=False)
