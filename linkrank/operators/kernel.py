"""Sweeps over compressed blocks of a graph, on arrays in one task."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

DEEP = 8  # vertices a level on average, below which a sweep goes vertex by vertex
RUN = 1 << 20  # edges whose shares are held at a time


@dataclass
class Block:
    """A block's vertices and in-edges: ids[k] reads inputs[source[pointer[k]:pointer[k + 1]]].

    inputs are the ids of all vertices read, own ones included; own[k] is the place of
    ids[k] among them.
    """

    ids: np.ndarray
    pointer: np.ndarray
    source: np.ndarray
    coef: np.ndarray
    inputs: np.ndarray
    own: np.ndarray
    _levels: tuple | None = field(default=None, repr=False)
    _laid: list | None = field(default=None, repr=False)

    @staticmethod
    def of(ids: np.ndarray, pointer: np.ndarray, src: np.ndarray, coef: np.ndarray) -> Block:
        inputs = np.unique(np.concatenate([ids, src]))
        return Block(ids, pointer, np.searchsorted(inputs, src), coef, inputs, np.searchsorted(inputs, ids))

    @staticmethod
    def of_edges(ids: np.ndarray, src: np.ndarray, dst: np.ndarray, coef: np.ndarray) -> Block:
        ids = np.sort(ids)
        order = np.lexsort((src, dst))
        return Block.of(ids, np.searchsorted(dst[order], np.append(ids, np.iinfo(np.int64).max)), src[order], coef[order])

    def levels(self) -> tuple[list[np.ndarray], np.ndarray]:
        """The vertices in groups, each reading new values of earlier groups only, and which edges read what a pass has not written yet."""
        if self._levels is None:
            n = len(self.ids)
            at = np.full(len(self.inputs), -1)
            at[self.own] = np.arange(n)
            src, dst = at[self.source], np.repeat(np.arange(n), np.diff(self.pointer))
            late = src >= dst
            early = (src >= 0) & ~late
            src, dst = src[early], dst[early]
            waits = np.bincount(dst, minlength=n)
            order = np.argsort(src, kind="stable")
            first, readers = np.searchsorted(src[order], np.arange(n + 1)), dst[order]
            groups, group = [], np.flatnonzero(waits == 0)
            while len(group):
                groups.append(group)
                freed = readers[_ranges(first[group], first[group + 1])]
                np.subtract.at(waits, freed, 1)
                freed = np.unique(freed)
                group = freed[waits[freed] == 0]
            self._levels = groups, late
        return self._levels

    def sums(self, rank: np.ndarray) -> np.ndarray:
        """Of each vertex: the shares that its in-neighbours' ranks give."""
        out, lo = np.empty(len(self.ids)), 0
        while lo < len(self.ids):
            hi = max(lo + 1, int(np.searchsorted(self.pointer, self.pointer[lo] + RUN, "right")) - 1)
            a, b = self.pointer[lo], self.pointer[hi]
            at = np.repeat(np.arange(hi - lo), np.diff(self.pointer[lo : hi + 1]))
            out[lo:hi] = np.bincount(at, rank[self.source[a:b]] * self.coef[a:b], hi - lo)
            lo = hi
        return out

    def lay_by_level(self) -> None:
        """Puts the edges in the order of a sweep, in place, so that a pass reads them one after the other.

        For blocks that are only swept whole: ``sums`` needs the order by vertex.
        """
        levels, late = self.levels()
        if len(levels) * DEEP > len(self.ids):
            return
        order = np.concatenate([np.zeros(0, np.int64), *(_ranges(self.pointer[g], self.pointer[g + 1]) for g in levels)])
        self.source[:], self.coef[:] = self.source[order], self.coef[order]
        late, self._laid, at = late[order], [], 0
        for group in levels:
            sizes = (self.pointer[group + 1] - self.pointer[group]).astype(np.int32)
            end = at + int(sizes.sum())
            self._laid.append((group, sizes, at, end, np.flatnonzero(late[at:end]).astype(np.int32)))
            at = end
        self._levels = None


def _ranges(starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """The numbers from each start up to its end, one range after the other."""
    sizes = ends - starts
    return np.arange(int(sizes.sum())) - np.repeat(np.cumsum(sizes) - sizes - starts, sizes)


def sweep(block: Block, rank: np.ndarray, base: float, damping: float, active: np.ndarray | None = None) -> np.ndarray:
    """One in-place pass in id order: each vertex reads what those before it have just written. Returns the changes.

    Vertices that do not wait for each other are computed together.
    """
    change = np.zeros(len(block.ids))
    pointer, source, coef, own = block.pointer, block.source, block.coef, block.own
    if block._laid is not None:
        before = rank.copy()
        for group, sizes, a, b, late in block._laid:
            share = rank[source[a:b]]
            share[late] = before[source[a:b][late]]
            new = base + damping * np.bincount(np.repeat(np.arange(len(group)), sizes), share * coef[a:b], len(group))
            change[group] = np.abs(new - rank[own[group]])
            rank[own[group]] = new
        return change
    levels, late = block.levels()
    if len(levels) * DEEP > len(block.ids):
        for k in range(len(block.ids)) if active is None else np.flatnonzero(active):
            a, b = pointer[k], pointer[k + 1]
            new = base + damping * float(rank[source[a:b]] @ coef[a:b]) if b > a else base
            change[k] = abs(new - rank[own[k]])
            rank[own[k]] = new
        return change
    before = rank.copy()
    for group in levels:
        group = group if active is None else group[active[group]]
        sizes = pointer[group + 1] - pointer[group]
        edges = _ranges(pointer[group], pointer[group + 1])
        new = base + damping * np.bincount(np.repeat(np.arange(len(group)), sizes), np.where(late[edges], before[source[edges]], rank[source[edges]]) * coef[edges], len(group))
        change[group] = np.abs(new - rank[own[group]])
        rank[own[group]] = new
    return change


def sweep_shares(block: Block, rank: np.ndarray, base: float, damping: float, active: np.ndarray | None = None) -> np.ndarray:
    """One pass over held shares: all vertices read what was written before the pass, then write. Returns the changes."""
    new = base + damping * block.sums(rank)
    old = rank[block.own]
    if active is not None:
        new = np.where(active, new, old)
    rank[block.own] = new
    return np.abs(new - old)
