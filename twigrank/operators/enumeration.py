"""Enumeration of all matches of one query on arrays, for the baseline that ranks only after it has computed everything.

Every match is computed and its weight compared, but only the k least are kept: no match is written anywhere. Partial
matches go level by level, in lexicographic order; the last branch of the root is solved on its own and meets what is
above it root by root, by outer sums. Both sides come in chunks, so that memory is bounded whatever the number of matches.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd

from twigrank.model import TreePattern
from twigrank.operators.pathfirst import in_order

#: Rows of a chunk, cells of an outer sum that is computed at once, and cells from which a root gets one of its own.
CHUNK, BLOCK, OUTER = 1 << 20, 1 << 18, 1 << 11
HALF = 1 << 31

Rows = tuple[dict[int, np.ndarray], np.ndarray]  # nodes by place, cost spent


class Enumeration:
    """rows: e, c, d, w of one query's candidates. pairs: places that must not share a node. levels: partial matches by the
    number of their nodes, less one; best: the k least (weight, nodes..)."""

    def __init__(self, pattern: TreePattern, rows: pd.DataFrame, pairs: list[tuple[int, int]], k: int):
        self.size, self.pairs, self.k = len(pattern.order), pairs, k
        self.parent = [pattern.place(e.parent) for e in pattern.preorder_edges()]
        kids = [pattern.place(v) for v in pattern.children(pattern.root)]
        self.split = max(kids) if len(kids) > 1 else self.size
        e, c, d, w = (rows[x].to_numpy(np.int64) for x in ("e", "c", "d", "w"))
        self.links = []
        for place in range(self.size - 1):
            at = np.flatnonzero(e == place)
            if not in_order(c[at], d[at], w[at]):
                at = at[np.lexsort((w[at], d[at], c[at]))]
            keys, first = np.unique(c[at], return_index=True)
            self.links.append((keys, np.append(first, len(at)), d[at], w[at]))
        at = np.flatnonzero(e < 0)
        at = at[np.argsort(d[at])]
        self.roots: Rows = {0: d[at]}, w[at]
        self.levels = [0] * self.size
        self.room: dict[np.dtype, np.ndarray] = {}
        self.best: list[tuple[int, ...]] = []

    def run(self) -> None:
        self.levels[0] = len(self.roots[1])
        if self.split == self.size:
            for rows in self.solve(self.roots, 1, self.size, self.levels):
                self.offer(*rows)
            return
        for group in self.groups():
            for above in self.solve(group, 1, self.split, self.levels):
                first = np.unique(above[0][0])
                for last in range(self.split, self.size):
                    for below in self.solve(({0: first}, np.zeros(len(first), np.int64)), self.split, last + 1):
                        self.cross(above, below, last)

    def degrees(self, place: int, nodes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Where the children of each node begin at an edge place, and how many there are."""
        keys, first, _, _ = self.links[place]
        if not len(keys):
            return np.zeros(len(nodes), np.int64), np.zeros(len(nodes), np.int64)
        at = np.minimum(np.searchsorted(keys, nodes), len(keys) - 1)
        return first[at], np.where(keys[at] == nodes, first[at + 1] - first[at], 0)

    def solve(self, rows: Rows, place: int, end: int, levels: list[int] | None = None) -> Iterator[Rows]:
        """rows with the nodes of places `place` to `end` - 1 bound as well, in chunks, depth first."""
        nodes, spent = rows
        if place == end:
            if len(spent):
                yield rows
            return
        start, count = self.degrees(place - 1, nodes[self.parent[place - 1]])
        _, _, d, w = self.links[place - 1]
        part = np.cumsum(count) // CHUNK
        cuts = [0, *(np.flatnonzero(np.diff(part)) + 1), len(spent)]
        for a, b in zip(cuts, cuts[1:]):
            n = count[a:b]
            up = np.repeat(np.arange(a, b), n)
            down = np.arange(len(up)) + np.repeat(start[a:b] - (np.cumsum(n) - n), n)
            found = {i: x[up] for i, x in nodes.items()} | {place: d[down]}
            cost = spent[up] + w[down]
            clash = [found[i] == found[j] for i, j in self.pairs if j == place and i in found]
            if clash:
                keep = ~np.logical_or.reduce(clash)
                found, cost = {i: x[keep] for i, x in found.items()}, cost[keep]
            if levels is not None:
                levels[place] += len(cost)
            yield from self.solve((found, cost), place + 1, end, levels)

    def groups(self) -> Iterator[Rows]:
        """The roots, as many at once as have a chunk of rows on either side of the split."""
        below: dict[int, np.ndarray] = {}  # for each place: matches of the subtree, by parent key
        for place in range(self.size - 1, 0, -1):
            keys, first, d, _ = self.links[place - 1]
            ways = np.ones(len(d))
            for child in (p + 1 for p, up in enumerate(self.parent) if up == place):
                ways = ways * self.ways(below, child, d)
            below[place] = np.add.reduceat(ways, first[:-1]) if len(keys) else ways
        nodes, spent = self.roots
        above, last = np.ones(len(spent)), self.ways(below, self.split, nodes[0])
        for child in (p + 1 for p, up in enumerate(self.parent) if up == 0 and p + 1 < self.split):
            above = above * self.ways(below, child, nodes[0])
        part = (np.cumsum(np.maximum(above, last)) // CHUNK).astype(np.int64)
        cuts = [0, *(np.flatnonzero(np.diff(part)) + 1), len(spent)]
        for a, b in zip(cuts, cuts[1:]):
            yield {0: nodes[0][a:b]}, spent[a:b]

    def ways(self, below: dict[int, np.ndarray], place: int, nodes: np.ndarray) -> np.ndarray:
        keys = self.links[place - 1][0]
        if not len(keys):
            return np.zeros(len(nodes))
        at = np.minimum(np.searchsorted(keys, nodes), len(keys) - 1)
        return np.where(keys[at] == nodes, below[place][at], 0)

    def cross(self, above: Rows, below: Rows, last: int) -> None:
        """Every row above with every row of the last branch (bound up to place `last`) at the same root: counted, and
        offered where these are whole matches."""
        (up, spent), (down, cost) = above, below
        pairs = [(i, j) for i, j in self.pairs if i in up and 0 < i and j in down and j >= self.split]
        whole = last == self.size - 1
        roots, a0, na = np.unique(up[0], return_index=True, return_counts=True)
        b0 = np.searchsorted(down[0], roots)
        nb = np.searchsorted(down[0], roots, "right") - b0
        cells = na * nb
        if not whole and not pairs:
            self.levels[last] += int(cells.sum())
            return
        small = np.flatnonzero((cells > 0) & (cells < OUTER))
        part = np.cumsum(cells[small]) // CHUNK
        for at in np.split(small, np.flatnonzero(np.diff(part)) + 1):
            n = cells[at]
            which = np.repeat(np.arange(len(at)), n)
            cell = np.arange(len(which)) - np.repeat(np.cumsum(n) - n, n)
            i, j = a0[at][which] + cell // nb[at][which], b0[at][which] + cell % nb[at][which]
            clash = [up[x][i] == down[y][j] for x, y in pairs]
            if clash:
                keep = ~np.logical_or.reduce(clash)
                i, j = i[keep], j[keep]
            self.levels[last] += len(i)
            if whole:
                self.offer({x: v[i] for x, v in up.items()} | {y: v[j] for y, v in down.items() if y}, spent[i] + cost[j])
        for r in np.flatnonzero(cells >= OUTER):
            self.outer(up, spent, slice(a0[r], a0[r] + na[r]), down, cost, slice(b0[r], b0[r] + nb[r]), pairs, last)

    def outer(self, up: dict, spent: np.ndarray, a: slice, down: dict, cost: np.ndarray, b: slice, pairs: list, last: int) -> None:
        root, whole = up[0][a.start], last == self.size - 1
        wide = max(1, min(b.stop - b.start, BLOCK))
        tall = max(1, BLOCK // wide)
        if len(pairs) < 2:
            self.levels[last] += (a.stop - a.start) * (b.stop - b.start) - sum(shared(up[i][a], down[j][b]) for i, j in pairs)
            if not whole or not self.k:
                return
        spent, cost, room = self.narrow(spent[a], cost[b])
        for i in range(a.start, a.stop, tall):
            for j in range(b.start, b.stop, wide):
                x, y = slice(i, min(i + tall, a.stop)), slice(j, min(j + wide, b.stop))
                clash = None
                if len(pairs) > 1:
                    clash = np.logical_or.reduce([up[p][x, None] == down[q][None, y] for p, q in pairs])
                    self.levels[last] += clash.size - int(np.count_nonzero(clash))
                    if not whole:
                        continue
                if not self.k:
                    continue
                one, other = spent[x.start - a.start : x.stop - a.start, None], cost[None, y.start - b.start : y.stop - b.start]
                total = np.add(one, other, out=room[: one.size * other.size].reshape(one.size, other.size))
                if len(self.best) < self.k:
                    hit = np.ones(total.shape, bool)
                else:
                    limit = self.best[-1][0] - (root > self.best[-1][1])  # what weighs the same at a later root comes later
                    if total.min() > limit:
                        continue
                    hit = total <= limit
                p, q = np.nonzero(hit if clash is None else hit & ~clash)
                p, q = p + x.start, q + y.start
                if clash is None and pairs:
                    keep = np.logical_and.reduce([up[s][p] != down[t][q] for s, t in pairs])
                    p, q = p[keep], q[keep]
                self.offer({s: v[p] for s, v in up.items()} | {t: v[q] for t, v in down.items() if t}, total[p - x.start, q - y.start].astype(np.int64))

    def narrow(self, spent: np.ndarray, cost: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Both as the least type that holds their sums, and room for a block of these."""
        ends = [int(x) for y in (spent, cost) for x in (y.min(), y.max())]
        fits = -HALF <= ends[0] + ends[2] and ends[1] + ends[3] < HALF and all(-HALF <= x < HALF for x in ends)
        kind = np.dtype(np.int32 if fits else np.int64)
        if kind not in self.room:
            self.room[kind] = np.empty(BLOCK, kind)
        return spent.astype(kind), cost.astype(kind), self.room[kind]

    def offer(self, nodes: dict[int, np.ndarray], cost: np.ndarray) -> None:
        """Rank whole matches, which come in lexicographic order, with the k least so far."""
        if not len(cost) or not self.k:
            return
        if len(cost) > self.k:
            limit = np.partition(cost, self.k - 1)[self.k - 1]
            less = np.flatnonzero(cost < limit)
            at = np.concatenate([less, np.flatnonzero(cost == limit)[: self.k - len(less)]])
        else:
            at = np.arange(len(cost))
        table = zip(cost[at].tolist(), *(nodes[i][at].tolist() for i in range(self.size)))
        self.best = sorted([*self.best, *table])[: self.k]


def shared(x: np.ndarray, y: np.ndarray) -> int:
    """Pairs of equal values of two columns."""
    (u, n), (v, m) = np.unique(x, return_counts=True), np.unique(y, return_counts=True)
    _, i, j = np.intersect1d(u, v, assume_unique=True, return_indices=True)
    return int((n[i] * m[j]).sum())
