"""Vectorised views of text columns for Arrow kernels.

A kernel reads a batch's text column as one byte array with row offsets and
walks it in slices of about ``SLICE`` bytes, so that its working memory does not
follow the batch size. A document longer than that is a slice by itself, whose words
are hashed in chunks of about ``SLICE`` bytes that end between words. Nulls read as
empty text.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

SLICE = 1 << 19

_ROOT = 0x9E3779B97F4A7C15 | 1


class Powers:
    """Powers of an odd number modulo 2**64 and of its inverse, grown on demand."""

    up = np.ones(1, np.uint64)
    down = np.ones(1, np.uint64)

    @classmethod
    def upto(cls, n: int) -> tuple[np.ndarray, np.ndarray]:
        if len(cls.up) < n:
            size = -(-n // 65536) * 65536
            inverse = pow(_ROOT, -1, 1 << 64)
            for name, base in (("up", _ROOT), ("down", inverse)):
                steps = np.full(size, base, np.uint64)
                steps[0] = 1
                setattr(cls, name, np.cumprod(steps, dtype=np.uint64))
        return cls.up[:n], cls.down[:n]


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: spreads every input bit over the result."""
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xFF51AFD7ED558CCD)
    x = x ^ (x >> np.uint64(33))
    x = x * np.uint64(0xC4CEB9FE1A85EC53)
    return x ^ (x >> np.uint64(33))


BYTE_VALUES = mix(np.arange(1, 257, dtype=np.uint64) * np.uint64(0x2545F4914F6CDD1D))

#: The separators of ``[^\x20\x09-\x0D]+``.
BLANK = np.zeros(256, bool)
BLANK[[0x20, *range(0x09, 0x0E)]] = True

LOWER = np.arange(256, dtype=np.uint8)
LOWER[0x41:0x5B] += 32

#: Everything but ASCII letters, digits and the bytes of longer characters.
NOT_WORD = np.ones(256, bool)
NOT_WORD[[*range(0x30, 0x3A), *range(0x41, 0x5B), *range(0x61, 0x7B), *range(0x80, 256)]] = False


def utf8(column) -> tuple[np.ndarray, np.ndarray]:
    """The column's bytes and its ``len + 1`` offsets into them."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if not len(column):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    kind = pa.large_binary() if pa.types.is_binary(column.type) or pa.types.is_large_binary(column.type) else pa.large_string()
    if column.null_count:
        column = pc.fill_null(column, b"" if kind == pa.large_binary() else "")
    column = column.cast(kind)
    _, offsets, data = column.buffers()
    offsets = np.frombuffer(offsets, np.int64)[column.offset : column.offset + len(column) + 1]
    return np.frombuffer(data, np.uint8) if data is not None and data.size else np.zeros(0, np.uint8), offsets


def slices(offsets: np.ndarray, most: int = SLICE) -> Iterator[tuple[int, int]]:
    """Row ranges of about ``most`` bytes; at least one row each."""
    lo, rows = 0, len(offsets) - 1
    while lo < rows:
        hi = int(np.searchsorted(offsets, offsets[lo] + most, "right")) - 1
        hi = min(rows, max(hi, lo + 1))
        yield lo, hi
        lo = hi


def chunks(data: np.ndarray, gap: np.ndarray, most: int = SLICE) -> Iterator[tuple[int, int]]:
    """Ranges of about ``most`` bytes that end before a byte of ``gap``, so that no word is cut."""
    lo, n = 0, len(data)
    while lo < n:
        hi = lo + most
        while hi < n:
            ends = np.flatnonzero(gap[data[hi : hi + 4096]])
            if len(ends):
                hi += int(ends[0])
                break
            hi += 4096
        hi = min(hi, n)
        yield lo, hi
        lo = hi


def fold(data: np.ndarray) -> np.ndarray:
    """Lower case of ASCII and of the two-byte letters from U+00C0 to U+00DE."""
    out = LOWER[data]
    if len(out) > 1:
        second = np.flatnonzero((out[:-1] == 0xC3) & (out[1:] >= 0x80) & (out[1:] <= 0x9E) & (out[1:] != 0x97)) + 1
        out[second] += 0x20
    return out


def tokens(data: np.ndarray, offsets: np.ndarray, gap: np.ndarray = BLANK) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Start and end of each word, and for each row the range of its words.

    ``data`` are the rows' bytes alone, ``offsets`` count from 0.
    """
    n = len(data)
    if not n:
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    word = ~gap[data]
    edge = np.zeros(n + 1, bool)
    edge[offsets] = True
    before = np.empty(n, bool)
    before[0] = True
    np.logical_not(word[:-1], out=before[1:])
    starts = np.flatnonzero(word & (before | edge[:n]))
    after = np.empty(n, bool)
    after[-1] = True
    np.logical_not(word[1:], out=after[:-1])
    ends = np.flatnonzero(word & (after | edge[1:])) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def prefix_sums(data: np.ndarray) -> np.ndarray:
    up, _ = Powers.upto(len(data) + 1)
    out = np.zeros(len(data) + 1, np.uint64)
    np.cumsum(BYTE_VALUES[data] * up[: len(data)], out=out[1:])
    return out


def span_hashes(sums: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Hashes of byte spans, equal for equal bytes wherever they stand."""
    _, down = Powers.upto(len(sums))
    return mix((sums[ends] - sums[starts]) * down[starts] + (ends - starts).astype(np.uint64))


def window_hashes(sums: np.ndarray, size: int) -> np.ndarray:
    """Hashes of the ``size`` bytes at each place: those of span_hashes."""
    last = len(sums) - size
    _, down = Powers.upto(len(sums))
    return mix((sums[size:] - sums[:last]) * down[:last] + np.uint64(size))


def word_hashes(data: np.ndarray, offsets: np.ndarray, gap: np.ndarray = BLANK):
    """Hash of each word, and for each row the range of its words."""
    found, bounds = [np.zeros(0, np.uint64)], np.zeros(len(offsets), np.int64)
    for lo, hi in chunks(data, gap):
        starts, ends, own = tokens(data[lo:hi], np.clip(offsets, lo, hi) - lo, gap)
        found.append(span_hashes(prefix_sums(data[lo:hi]), starts, ends))
        bounds += own
    return found[1] if len(found) == 2 else np.concatenate(found), bounds


def shingles(words: np.ndarray, n: int) -> np.ndarray:
    """Hash of each run of ``n`` words; of the whole sequence where it is shorter."""
    if not len(words):
        return words
    n = min(n, len(words))
    last = len(words) - n + 1
    out = np.full(last, n, np.uint64)
    for k in range(n):
        out = out * np.uint64(0xD6E8FEB86659FD93) + words[k : k + last]
    return mix(out)
