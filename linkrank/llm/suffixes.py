"""Suffix arrays by induced sorting, and permuted common prefixes, on whole arrays.

The passes that induce suffixes from sorted ones go through the buckets of first
symbols; within a bucket, whole runs of suffixes are moved at once.
"""

from __future__ import annotations

import numpy as np

_WIDE = 2_048


def _types(s: np.ndarray) -> np.ndarray:
    """Whether each suffix is smaller than the next (the end is smaller than anything)."""
    step = np.append(np.where(s[1:] > s[:-1], 1, np.where(s[1:] < s[:-1], -1, 0)), -1)
    where = np.where(step != 0, np.arange(len(s)), len(s))
    following = np.minimum.accumulate(where[::-1])[::-1]
    return step[following] > 0


def _deal(before: np.ndarray, s: np.ndarray, c: int, pending: list[list]) -> np.ndarray:
    """Appends each suffix to its first symbol's list, in order; gives back those of symbol c."""
    heads = s[before]
    own = before[heads == c]
    rest = heads != c
    before, heads = before[rest], heads[rest]
    if len(before):
        order = np.argsort(heads, kind="stable")
        before, heads = before[order], heads[order]
        cuts = np.flatnonzero(np.diff(heads)) + 1
        for part in np.split(before, cuts):
            pending[s[part[0]]].append(part)
    return own


def _induce(s: np.ndarray, small: np.ndarray, sigma: int, seeds: np.ndarray) -> np.ndarray:
    """All suffixes in order, from the leftmost-smaller ones in order (or in text order: then by substrings)."""
    none = np.zeros(0, np.int64)
    heads = s[seeds]
    at = np.argsort(heads, kind="stable")
    sorted_seeds = seeds[at]
    cuts = np.searchsorted(heads[at], np.arange(sigma + 1))
    pending: list[list] = [[] for _ in range(sigma)]
    pending[s[-1]].append(np.array([len(s) - 1]))
    larger: list[np.ndarray] = []
    for c in range(sigma):
        runs, batch = [], np.concatenate(pending[c]) if pending[c] else none
        pending[c] = []
        while len(batch):
            runs.append(batch)
            before = batch[batch > 0] - 1
            batch = _deal(before[~small[before]], s, c, pending)
        larger.append(np.concatenate(runs) if runs else none)
        own = sorted_seeds[cuts[c] : cuts[c + 1]]
        if len(own):
            _deal(own[own > 0] - 1, s, c, pending)
    smaller: list[np.ndarray] = [none] * sigma
    for c in range(sigma - 1, -1, -1):
        runs, batch = [], np.concatenate(pending[c]) if pending[c] else none
        while len(batch):
            runs.append(batch)
            before = batch[batch > 0] - 1
            batch = _deal(before[small[before]], s, c, pending)
        smaller[c] = np.concatenate(runs)[::-1] if runs else none
        own = larger[c][::-1]
        own = own[own > 0] - 1
        own = own[small[own]]
        if len(own):
            _deal(own, s, c, pending)
    return np.concatenate([x for pair in zip(larger, smaller) for x in pair])


def _names(s: np.ndarray, seeds: np.ndarray, ordered: np.ndarray) -> np.ndarray:
    """A name for each leftmost-smaller substring in text order; equal substrings have equal names."""
    size = np.append(np.diff(seeds) + 1, len(s) - seeds[-1])
    length = np.zeros(len(s), np.int64)
    length[seeds] = size
    a, b = ordered[:-1], ordered[1:]
    same = length[a] == length[b]
    if len(ordered) > 1:
        same &= (a != seeds[-1]) & (b != seeds[-1])
    active, k = np.flatnonzero(same), 0
    while len(active):
        active = active[length[a[active]] > k]
        differ = s[a[active] + k] != s[b[active] + k]
        same[active[differ]] = False
        active = active[~differ]
        k += 1
    name = np.zeros(len(s), np.int64)
    name[ordered] = np.concatenate(([0], np.cumsum(~same)))
    return name[seeds]


def _doubled(names: np.ndarray) -> np.ndarray:
    """Suffix order of a string of many different symbols, by ranks of doubled lengths."""
    rank, n, step = names.astype(np.int64), len(names), 1
    while True:
        follow = np.zeros(n, np.int64)
        follow[: max(0, n - step)] = rank[step:] + 1
        key = rank * (n + 2) + follow
        order = np.argsort(key, kind="stable")
        new = np.concatenate(([0], np.cumsum(np.diff(key[order]) > 0)))
        rank = np.empty(n, np.int64)
        rank[order] = new
        if new[-1] == n - 1:
            return order
        step *= 2


def suffix_array(s: np.ndarray, sigma: int) -> np.ndarray:
    """Starts of the suffixes of ``s`` (symbols below ``sigma``) in order.

    Leftmost-smaller substrings are sorted by inducing, named, and their string is
    sorted by the same function; where it has too many names for buckets, by doubling.
    """
    if len(s) < 2:
        return np.arange(len(s))
    s = s.astype(np.uint16 if sigma <= 1 << 16 else np.int64)  # narrow symbols are sorted by radix
    small = _types(s)
    seeds = np.flatnonzero(small & np.concatenate(([False], ~small[:-1])))
    if len(seeds) > 1:
        first = _induce(s, small, sigma, seeds)
        is_seed = np.zeros(len(s), bool)
        is_seed[seeds] = True
        names = _names(s, seeds, first[is_seed[first]])
        distinct = int(names.max()) + 1
        if distinct == len(seeds):
            order = np.argsort(names)
        else:
            order = suffix_array(names, distinct) if distinct <= _WIDE else _doubled(names)
        seeds = seeds[order]
    return _induce(s, small, sigma, seeds)


def common_prefixes(s: np.ndarray, order: np.ndarray) -> np.ndarray:
    """For each position the length it shares with the suffix before it in order.

    In text order the length falls by at most one from place to place. It is measured
    only where the symbols before the two suffixes differ; elsewhere it is one less
    than at the place before.
    """
    n = len(s)
    if not n:
        return np.zeros(0, np.int64)
    former = np.full(n, -1)
    former[order[1:]] = order[:-1]
    at = np.arange(n)
    joined = (former > 0) & (at > 0)
    joined[joined] = s[at[joined] - 1] == s[former[joined] - 1]
    out = np.zeros(n, np.int64)
    active, k = np.flatnonzero(~joined & (former >= 0)), 0
    while len(active):
        inside = (active + k < n) & (former[active] + k < n)
        out[active[~inside]] = k
        active = active[inside]
        equal = s[active + k] == s[former[active] + k]
        out[active[~equal]] = k
        active = active[equal]
        k += 1
    base = np.maximum.accumulate(np.where(joined, 0, at))
    return np.where(joined, np.maximum(0, out[base] - (at - base)), out)
