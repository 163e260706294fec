"""Path-first search of one query on arrays: instances of the pattern's longest path come lightest first, in pages of growing
size, and meet all solutions of the branches that hang off the path. The branches don't guide the paths.

A page is all paths up to a weight: that of the n-th lightest, which level cuts find without following the rest. Paths of
one weight are never parted, so that ties are all seen. They come in chunks, and only the k least matches are kept.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd

from twigrank.model import TreePattern

#: Rows of a chunk, and paths of the first page.
CHUNK, PAGE = 1 << 19, 64


class Step:
    """Links from one node of the path to the next, by node, then by weight with the least way on."""

    def __init__(self, a: np.ndarray, b: np.ndarray, w: np.ndarray, wf: np.ndarray):
        if not in_order(a, b):
            at = np.lexsort((b, a))
            a, b, w, wf = a[at], b[at], w[at], wf[at]
        self.keys, first = np.unique(a, return_index=True)
        self.first = np.append(first, len(a))
        self.base = int(wf.min(initial=0))
        self.span = int(wf.max(initial=0)) - self.base + 2
        flat = np.repeat(np.arange(len(self.keys)), np.diff(self.first)) * self.span + (wf - self.base)
        at = np.argsort(flat, kind="stable")
        self.b, self.w, self.wf, self.flat = b[at], w[at], wf[at], flat[at]

    def upto(self, at: np.ndarray, left: np.ndarray) -> np.ndarray:
        """How many links of each node (by its place among the keys) weigh, with the way on, at most what is left."""
        return np.searchsorted(self.flat, at * self.span + np.clip(left - self.base, -1, self.span - 1), "right") - self.first[at]


class PathFirst:
    """rows: e, c, d, w as `kernel.spine_rows` gives them. best: the k least (weight, nodes..). known_k: stop when the next
    path, with the least that the branches add, is heavier than the k-th match; else follow all paths."""

    def __init__(self, pattern: TreePattern, rows: pd.DataFrame, k: int, injective: bool = True, known_k: bool = True):
        self.k, self.known_k, self.best = k, known_k, []
        self.reached: int | None = None  # the weight up to which paths were followed; None: all
        names = pattern.spine()
        whole, self.names = pattern.reroot(names[0]), names
        e, c, d, w = (rows[x].to_numpy(np.int64) for x in ("e", "c", "d", "w"))
        place = {(x.parent, x.child): i for i, x in enumerate(pattern.preorder_edges())}

        def links(u: str, v: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
            at = np.flatnonzero(e == place.get((u, v), place.get((v, u))))
            return (c[at], d[at], w[at]) if (u, v) in place else (d[at], c[at], w[at])

        self.steps: list[Step] = []
        on, cost = None, None
        for u, v in reversed(list(zip(names, names[1:]))):
            a, b, ways = links(u, v)
            rest = np.zeros(len(a), np.int64)
            if on is not None:
                goes, rest = look_up(on, cost, b)
                a, b, ways, rest = a[goes], b[goes], ways[goes], rest[goes]
            step = Step(a, b, ways, ways + rest)
            on, cost = step.keys, step.wf[step.first[:-1]]
            self.steps.insert(0, step)
        self.floors = cost
        # edges of the branches, parents first, and the least that each branch adds anywhere
        self.order, self.sides, self.least, self.empty = list(names), [], 0, not len(cost)
        self.branches: list[tuple[int, Branch]] = []
        for u in names:
            hanging = frozenset(v for v in whole.children(u) if v in names)
            side = whole.subtree(u, without=hanging)
            if len(side.order) > 1:
                self.branches.append((names.index(u), Branch(side, links)))
                floors = self.solve(side, links)
                self.empty = self.empty or not len(floors)
                self.least += int(floors.min(initial=NEVER)) if len(floors) else 0
        self.spot = [self.order.index(v) for v in pattern.order]
        pairs = pattern.overlapping_pairs() if injective else []
        self.pairs = [tuple(sorted((self.spot[i], self.spot[j]))) for i, j in pairs]

    def solve(self, side: TreePattern, links) -> np.ndarray:
        """The least weights of a branch at the nodes it hangs from; its edges go to `sides`."""
        tables = {x.child: links(x.parent, x.child) for x in side.preorder_edges()}
        for x in side.preorder_edges():
            a, b, w = tables[x.child]
            self.sides.append((self.order.index(x.parent), Step(a, b, w, w)))
            self.order.append(x.child)
        least: dict[str, tuple[np.ndarray, np.ndarray]] = {}
        for u in reversed(side.order):
            nodes, cost = None, None
            for v in side.children(u):
                a, b, w = tables[v]
                if v in least:
                    goes, rest = look_up(*least[v], b)
                    a, w = a[goes], w[goes] + rest[goes]
                step = Step(a, a, w, w)
                keys, floor = step.keys, step.wf[step.first[:-1]]
                if nodes is not None:
                    both, i, j = np.intersect1d(nodes, keys, assume_unique=True, return_indices=True)
                    keys, floor = both, cost[i] + floor[j]
                nodes, cost = keys, floor
            if nodes is not None:
                least[u] = nodes, cost
        return least[side.root][1]

    def run(self) -> None:
        if self.empty or not self.k:
            return
        n, low = PAGE, None
        while True:
            limit = self.limit(n)
            if limit is None or limit != low:
                n = max(n, sum(self.merge(list(nodes), spent) for nodes, spent in self.follow(limit, low)))
            if limit is None or self.known_k and len(self.best) == self.k and self.best[-1][0] <= limit + self.least:
                self.reached = limit
                return
            n, low = 4 * n, limit

    def limit(self, n: int) -> int | None:
        """The weight of the n-th lightest path, None if there are fewer. Each level keeps n rows of least bound, of which
        each has a path of its own bound."""
        at = np.argsort(self.floors, kind="stable")[:n]
        nodes, spent = self.steps[0].keys[at], np.zeros(len(at), np.int64)
        for step in self.steps:
            at = np.searchsorted(step.keys, nodes)
            count = step.first[at + 1] - step.first[at]
            if count.sum() > n:
                few, many = int((spent + step.wf[step.first[at]]).min()), int((spent + step.wf[step.first[at + 1] - 1]).max())
                while few < many:  # the least bound that n rows don't exceed
                    mid = (few + many) // 2
                    few, many = (few, mid) if step.upto(at, mid - spent).sum() >= n else (mid + 1, many)
                less, equal = step.upto(at, few - 1 - spent), step.upto(at, few - spent)
                equal = equal - less
                count = less + np.clip(n - less.sum() - (np.cumsum(equal) - equal), 0, equal)
            up, down = spread(count, step.first[at])
            nodes, spent = step.b[down], spent[up] + step.w[down]
        return int(spent.max()) if len(spent) >= n else None

    def follow(self, limit: int | None, low: int | None, level: int = 0, nodes: list[np.ndarray] | None = None, spent: np.ndarray | None = None) -> Iterator[tuple[list[np.ndarray], np.ndarray]]:
        """Paths heavier than `low` and no heavier than `limit`, in chunks, depth first."""
        if nodes is None:
            nodes, spent = [self.steps[0].keys], np.zeros(len(self.floors), np.int64)
        if level == len(self.steps):
            yield nodes, spent
            return
        step = self.steps[level]
        at = np.searchsorted(step.keys, nodes[level])
        start = step.first[at]
        count = step.first[at + 1] - start if limit is None else step.upto(at, limit - spent)
        if low is not None and level + 1 == len(self.steps):
            skip = step.upto(at, low - spent)
            start, count = start + skip, np.maximum(count - skip, 0)
        for found, cost, _ in self.grown(nodes, spent, start, count, step):
            yield from self.follow(limit, low, level + 1, found, cost)

    def grown(self, nodes: list[np.ndarray], spent: np.ndarray, start: np.ndarray, count: np.ndarray, step: Step) -> Iterator[tuple[list[np.ndarray], np.ndarray, np.ndarray]]:
        """Rows with one more node, without those where one graph node serves both places of a pair, and which they come from."""
        part = np.cumsum(count) // CHUNK
        cuts = [0, *(np.flatnonzero(np.diff(part)) + 1), len(spent)]
        for a, b in zip(cuts, cuts[1:]):
            up, down = spread(count[a:b], start[a:b])
            if not len(up):
                continue
            up += a
            found, cost = [*(x[up] for x in nodes), step.b[down]], spent[up] + step.w[down]
            clash = [found[i] == found[j] for i, j in self.pairs if j == len(nodes)]
            if clash:
                keep = ~np.logical_or.reduce(clash)
                found, cost, up = [x[keep] for x in found], cost[keep], up[keep]
            if len(cost):
                yield found, cost, up

    def merge(self, nodes: list[np.ndarray], spent: np.ndarray) -> int:
        """Rank the matches of these paths: with all solutions of their branches. Returns the number of paths."""
        for found, cost, _ in self.completed(nodes, spent, np.arange(len(spent))):
            self.offer([found[i] for i in self.spot], cost)
        return len(spent)

    def completed(self, nodes: list[np.ndarray], spent: np.ndarray, origin: np.ndarray, done: int = 0) -> Iterator[tuple[list[np.ndarray], np.ndarray, np.ndarray]]:
        """All matches that these paths are part of, and the paths they come from."""
        if done == len(self.sides):
            yield nodes, spent, origin
            return
        parent, step = self.sides[done]
        goes, at = look_up(step.keys, np.arange(len(step.keys)), nodes[parent])
        nodes, spent, origin, at = [x[goes] for x in nodes], spent[goes], origin[goes], at[goes]
        for found, cost, up in self.grown(nodes, spent, step.first[at], step.first[at + 1] - step.first[at], step):
            yield from self.completed(found, cost, origin[up], done + 1)

    def offer(self, nodes: list[np.ndarray], cost: np.ndarray) -> None:
        """Rank whole matches with the k least so far."""
        if len(self.best) == self.k:
            last = self.best[-1]
            at = np.flatnonzero((cost < last[0]) | (cost == last[0]) & (nodes[0] <= last[1]))
            nodes, cost = [x[at] for x in nodes], cost[at]
        at = least_rows([cost, *nodes], self.k)
        table = zip(*(x[at].tolist() for x in (cost, *nodes)))
        self.best = sorted([*self.best, *table])[: self.k]


    def counters(self) -> dict[str, int]:
        """What `kernel.spine_first` counts with this k, after a run with known_k. A partial path comes before its successors
        in the order of (bound, nodes), so that the queue gives out partials in just this order: the popped ones are sorted,
        and their successors, which wait in the queue, are only counted."""
        partials = nodes = 0
        for _, branch in self.branches:
            for i, n in enumerate(branch.partials(), 1):
                partials, nodes = partials + n, nodes + n * i
        bounds, table, length, pushes, ways = self.popped()
        step = np.where(length == len(self.names), 0, pushes)
        # completed paths: their injective matches, by place in the order
        whole = np.flatnonzero(length == len(self.names))
        ok = np.ones(len(whole), bool)
        for i, j in self.pairs:
            if j < len(self.names):
                ok &= table[i][whole] != table[j][whole]
        place, weight = [], []
        if not self.empty:
            for _, cost, origin in self.completed([x[whole[ok]] for x in table], bounds[whole[ok]], whole[ok]):
                place.append(origin)
                weight.append(cost)
        place = np.concatenate([*place, np.zeros(0, np.int64)])
        weight = np.concatenate([*weight, np.zeros(0, np.int64)])
        at = np.argsort(place, kind="stable")
        place, weight = place[at], weight[at]
        end = self.stop(bounds, place, weight)
        waits = len(self.floors) + np.cumsum(step - 1)
        waiting = len(self.floors) + np.cumsum(step * (length + 1) - length)
        more = end < len(bounds) or (len(bounds) > 0 and waits[-1] > 0)  # one more pop tells that it is over
        found = np.searchsorted(place, np.arange(end), "right")
        stored = waiting[:end] + np.where(length[:end] == len(self.names), found, 0) * len(self.order)
        pushed = len(self.floors) + int(step[:end].sum())
        partials += pushed + int(ways[:end].sum())
        nodes += len(self.floors) + int((step * (length + 1))[:end].sum()) + int(ways[:end].sum()) * len(self.order)
        return {
            "pops": end + more,
            "pushes": pushed,
            "max_partials": max([len(self.floors), int(waits[:end].max(initial=0))]),
            "max_nodes": max([len(self.floors), int(stored.max(initial=0))]),
            "total_partials": partials,
            "total_nodes": nodes,
            "results": min(self.k, int(np.searchsorted(place, end))),
        }

    def popped(self) -> tuple[np.ndarray, list[np.ndarray], np.ndarray, np.ndarray, np.ndarray]:
        """Bounds, nodes (NONE: not yet bound), numbers of nodes, successors and matches of the partial paths whose bound is
        within what the run reached, in the order of the queue."""
        parts, limit = [], self.reached
        bound, nodes, spent = self.floors, [self.steps[0].keys], np.zeros(len(self.floors), np.int64)
        if limit is not None:
            at = np.flatnonzero(bound <= limit)
            bound, nodes, spent = bound[at], [nodes[0][at]], spent[at]
        for level, step in enumerate(self.steps):
            at = np.searchsorted(step.keys, nodes[level])
            every = step.first[at + 1] - step.first[at]
            parts.append((bound, nodes, every, np.zeros(len(bound), np.int64)))
            up, down = spread(every if limit is None else step.upto(at, limit - spent), step.first[at])
            bound, nodes, spent = spent[up] + step.wf[down], [*(x[up] for x in nodes), step.b[down]], spent[up] + step.w[down]
        ways = np.ones(len(bound), np.int64)
        for i, branch in self.branches:
            ways = ways * branch.ways(branch.side.root, nodes[i])
        parts.append((bound, nodes, np.zeros(len(bound), np.int64), ways))
        bounds, pushes, ways = (np.concatenate([x[i] for x in parts]) for i in (0, 2, 3))
        length = np.concatenate([np.full(len(x[0]), len(x[1])) for x in parts])
        table = [np.concatenate([x[1][i] if i < len(x[1]) else np.full(len(x[0]), NONE) for x in parts]) for i in range(len(self.names))]
        at = np.lexsort([*reversed(table), bounds])
        return bounds[at], [x[at] for x in table], length[at], pushes[at], ways[at]

    def stop(self, bounds: np.ndarray, place: np.ndarray, weight: np.ndarray) -> int:
        """The first partial that shows, by its bound, that the k least of the matches before it are the answers."""
        if len(weight) < self.k:
            return len(bounds)
        kept, at = sorted(weight[: self.k].tolist()), self.k - 1
        while True:
            better = np.flatnonzero(weight[at + 1 :] < kept[-1])
            after = at + 1 + int(better[0]) if len(better) else None
            first = max(int(np.searchsorted(bounds, kept[-1] - self.least, "right")), int(place[at]) + 1)
            if after is None or first <= place[after]:
                return min(first, len(bounds))
            at = after
            kept = sorted([*kept, int(weight[at])])[: self.k]


class Branch:
    """Numbers of solutions of a branch, by sums and products over its links."""

    def __init__(self, side: TreePattern, links):
        self.side, self.tables = side, {}
        for x in side.preorder_edges():
            a, b, _ = links(x.parent, x.child)
            at = np.argsort(a, kind="stable")
            self.tables[x.child] = (*np.unique(a[at], return_index=True), b[at])

    def ways(self, u: str, nodes: np.ndarray, within: tuple[str, ...] | None = None) -> np.ndarray:
        """For each node the solutions of what hangs below pattern node u (of the pattern nodes `within` only)."""
        out = np.ones(len(nodes), np.int64)
        for v in self.side.children(u):
            if within is None or v in within:
                keys, first, b = self.tables[v]
                each = np.add.reduceat(self.ways(v, b, within), first) if len(keys) else np.zeros(0, np.int64)
                out = out * look_up(keys, each, nodes)[1]
        return out

    def partials(self) -> list[int]:
        """Partial solutions with 1, 2, .. nodes, bound in pre-order from every node that has a link."""
        starts = np.unique(np.concatenate([self.tables[v][0] for v in self.side.children(self.side.root)]))
        return [int(self.ways(self.side.root, starts, self.side.order[:i]).sum()) for i in range(1, len(self.side.order) + 1)]


#: More than any weight, and less than any node.
NEVER, NONE = (1 << 63) - 1, -(1 << 63)


def in_order(*columns: np.ndarray) -> bool:
    """Whether rows come in lexicographic order, as those of sorted links do, which need no sort again."""
    tie = np.ones(max(len(columns[0]) - 1, 0), bool)
    for x in columns:
        if (tie & (x[:-1] > x[1:])).any():
            return False
        tie &= x[:-1] == x[1:]
    return True


def look_up(keys: np.ndarray, values: np.ndarray, wanted: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Which of `wanted` are among the sorted keys, and their values (0 where they aren't)."""
    if not len(keys):
        return np.zeros(len(wanted), bool), np.zeros(len(wanted), np.int64)
    at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
    goes = keys[at] == wanted
    return goes, np.where(goes, values[at], 0)


def spread(count: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """For rows with `count` links from place `start` on: the row and the place of each link."""
    up = np.repeat(np.arange(len(count)), count)
    return up, np.arange(len(up)) + np.repeat(start - (np.cumsum(count) - count), count)


def least_rows(columns: list[np.ndarray], k: int) -> np.ndarray:
    """Places of the k least rows in lexicographic order, in any order. Rows that tie are told apart column by column."""
    at, sure, need = np.arange(len(columns[0])), [], k
    for x in columns:
        if len(at) <= need:
            break
        v = np.partition(x[at], need - 1)[need - 1]
        less, at = at[x[at] < v], at[x[at] == v]
        sure.append(less)
        need -= len(less)
    return np.concatenate([*sure, at[:need]])
