"""Guided search with a priority queue, one query at a time in Arrow-fed Python: for many queries with small candidate
graphs, and for the counters (pops, pushes, stored partial matches) that a bulk-parallel search does not have."""

from __future__ import annotations

import heapq
import time
from collections import defaultdict
from collections.abc import Callable, Iterator
from dataclasses import asdict, dataclass
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twigrank.model import TreePattern
from twigrank.operators.enumeration import Enumeration
from twigrank.operators.index import GraphIndex
from twigrank.operators.pathfirst import PathFirst, in_order
from twigrank.operators.search import answers, expand, open_frontier, topk, topk_iso, with_qid
from twigrank.operators.shared import SharedRows
from twigrank.operators.sweep import CandidateGraph, only, sweep_up
from twigrank.plans.storage import stored

#: Candidate rows of one query that a task takes; queries with more go to the frame search.
KERNEL_ROWS = 5_000_000
#: The length of a way that doesn't exist.
NO_WAY = (1 << 63) - 1


@dataclass
class Counters:
    pops: int = 0
    pushes: int = 0
    max_partials: int = 0
    max_nodes: int = 0
    total_partials: int = 0
    total_nodes: int = 0
    results: int = 0


class Queue:
    """A heap that counts what is stored in it."""

    def __init__(self, counters: Counters):
        self.heap: list[tuple[int, tuple]] = []
        self.nodes, self.counters = 0, counters

    def push(self, bound: int, match: tuple) -> None:
        heapq.heappush(self.heap, (bound, match))
        c = self.counters
        c.pushes += 1
        self.nodes += len(match)
        c.total_partials += 1
        c.total_nodes += len(match)
        c.max_partials, c.max_nodes = max(c.max_partials, len(self.heap)), max(c.max_nodes, self.nodes)

    def pop(self) -> tuple[int, tuple]:
        bound, match = heapq.heappop(self.heap)
        self.counters.pops += 1
        self.nodes -= len(match)
        return bound, match

    def __bool__(self) -> bool:
        return bool(self.heap)


class Links:
    """Rows of one edge by one of its ends, which come in order of it; they become tuples, in order, when they are asked for."""

    def __init__(self, ends: np.ndarray, *columns: np.ndarray):
        self.keys, self.first = np.unique(ends, return_index=True)
        last = np.append(self.first[1:], len(ends)) if len(ends) else self.first
        self.widest = int((last - self.first).max(initial=0))
        self.spans = dict(zip(self.keys.tolist(), zip(self.first.tolist(), last.tolist())))
        self.columns, self.made = columns, {}

    def get(self, end: int, default: list | None = None) -> list[tuple[int, ...]]:
        if end not in self.made:
            if end not in self.spans:
                return [] if default is None else default
            a, b = self.spans[end]
            self.made[end] = sorted(zip(*(x[a:b].tolist() for x in self.columns)))
        return self.made[end]


class Candidates:
    """Links of one query: for each edge place and parent node the children in order of weight with all below."""

    def __init__(self, pattern: TreePattern, rows: pd.DataFrame):
        self.parent = [pattern.place(e.parent) for e in pattern.preorder_edges()]
        self.size = len(pattern.order)
        e, c, d, w, wf = (rows[x].to_numpy(np.int64) for x in ("e", "c", "d", "w", "wf"))
        self.arrays: list[tuple[np.ndarray, ...]] = []  # c, d, w of each edge
        self.links: list[Links] = []
        for place in range(len(self.parent)):
            at = np.flatnonzero(e == place)
            if not in_order(c[at]):
                at = at[np.argsort(c[at], kind="stable")]
            self.arrays.append((c[at], d[at], w[at]))
            self.links.append(Links(c[at], wf[at], d[at], w[at]))
        at = e < 0
        self.roots: list[tuple[int, int, int]] = list(zip(wf[at].tolist(), d[at].tolist(), w[at].tolist()))
        self.out_degree = max([len(self.roots), *(x.widest for x in self.links)])


def guided(cand: Candidates, counters: Counters, k: int | None = None, injective: bool = False, in_hand: bool = True, trace: list | None = None) -> Iterator[tuple[int, tuple]]:
    """(weight, match) in order of (weight, match). in_hand: the successor of equal bound stays in hand, so that every pop
    ends in a match (with `injective`, in a match or none). trace: gets (bound, partial match, its successors' bounds and
    nodes, least bound that waits) of each expansion."""
    queue = Queue(counters)
    for floor, c, _ in cand.roots:
        queue.push(floor, (c,))
    while queue and (k is None or counters.results < k):
        bound, match = queue.pop()
        while match is not None and len(match) < cand.size:
            place = len(match) - 1
            options = cand.links[place].get(match[cand.parent[place]], [])
            hold, least = None, options[0][0] if options else 0
            if trace is not None:
                trace.append((bound, match, [(bound - least + wf, d) for wf, d, _ in options], queue.heap[0][0] if queue else None))
            for wf, d, _ in options:
                if injective and d in match:
                    continue
                if in_hand and hold is None and wf == least:
                    hold = (*match, d)
                else:
                    queue.push(bound - least + wf, (*match, d))
            match = hold
        if match is not None:
            counters.results += 1
            yield bound, match


def violations(cand: Candidates) -> list[str]:
    """What a run over all homomorphic matches of one query breaks of the search's guarantees (nothing, by its theory):
    every node met is in some match; bounds never fall; an expanded partial has a successor of its own bound, which is then
    the least of all that wait; the k-th pop ends in the k-th match; no more pushes in total, and no more partials at any
    time, than matches; work between matches within the out-degree for each pattern node; and for injective matches no more
    pops and no larger queue than for homomorphic ones."""
    c, trace, found, broken, done = Counters(), [], [], set(), 0
    for weight, match in guided(cand, c, trace=trace):
        found.append(match)
        if c.pops != len(found):
            broken.add("one pop for each match")
        if sum(len(options) for _, _, options, _ in trace[done:]) > max(cand.out_degree, 1) * cand.size:
            broken.add("delay")
        done = len(trace)
    met = {(len(match), d) for _, match, options, _ in trace for _, d in options} | {(0, d) for _, d, _ in cand.roots}
    if met - {(i, d) for match in found for i, d in enumerate(match)}:
        broken.add("no spurious node")
    for bound, _, options, waiting in trace:
        after = [b for b, _ in options]
        if after and min(after) < bound:
            broken.add("bounds never fall")
        if not after or min(after) != bound:
            broken.add("successor of equal bound")
        elif waiting is not None and waiting < bound:
            broken.add("successor is least of all")
    if c.pushes > len(found) or c.pushes + c.pops > 2 * len(found):
        broken.add("pushes")
    if c.max_partials > len(found):
        broken.add("queue size")
    iso = Counters()
    n_iso = sum(1 for _ in guided(cand, iso, injective=True))
    if n_iso != sum(len(set(m)) == len(m) for m in found) or iso.pops > c.pops or iso.max_partials > max(len(found), 1):
        broken.add("injective bounds")
    return sorted(broken)


def verify(cg: CandidateGraph) -> DataFrame:
    """qid, results and the guarantees that `violations` finds broken, of each query. cg: after the down-sweep or not."""
    pattern = cg.pattern

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        cand, c = Candidates(pattern, rows), Counters()
        n = sum(1 for _ in guided(cand, c))
        return pd.DataFrame([{"qid": key[0], "results": n, "broken": ", ".join(violations(cand))}])

    return candidate_rows(cg).groupBy("qid").applyInPandas(one, "qid int, results long, broken string")


def exhaustive(cand: Candidates, counters: Counters, k: int | None = None, injective: bool = False) -> Iterator[tuple[int, tuple]]:
    """All matches by depth-first search, stored, sorted, then given out."""
    found: list[tuple[int, tuple]] = []
    todo = [(w, (c,)) for _, c, w in cand.roots]
    while todo:
        spent, match = todo.pop()
        counters.total_partials += 1
        counters.total_nodes += len(match)
        if len(match) == cand.size:
            found.append((spent, match))
            continue
        place = len(match) - 1
        for _, d, w in cand.links[place].get(match[cand.parent[place]], []):
            if not (injective and d in match):
                todo.append((spent + w, (*match, d)))
    found.sort()
    counters.max_partials, counters.max_nodes = len(found), len(found) * cand.size
    for row in found if k is None else found[:k]:
        counters.results += 1
        yield row


class Walk:
    """Links of one query in both directions between pattern nodes, for searches that don't start at the root."""

    def __init__(self, pattern: TreePattern, cand: Candidates):
        self.near: dict[tuple[str, str], Links] = {}
        for place, e in enumerate(pattern.preorder_edges()):
            c, d, w = cand.arrays[place]
            at = np.argsort(d, kind="stable")
            self.near[e.parent, e.child], self.near[e.child, e.parent] = Links(c, w, d), Links(d[at], w[at], c[at])

    def solve(self, pattern: TreePattern, counters: Counters) -> list[tuple[int, tuple]]:
        """All matches of a subpattern, (weight, nodes in its order), each partial match counted as stored."""
        edges = pattern.preorder_edges()
        starts = {c for v in pattern.children(pattern.root) for c in self.near[pattern.root, v].keys.tolist()}
        found, todo = [], [(0, (c,)) for c in sorted(starts)]
        while todo:
            spent, match = todo.pop()
            counters.total_partials += 1
            counters.total_nodes += len(match)
            if len(match) == len(pattern.order):
                found.append((spent, match))
                continue
            e = edges[len(match) - 1]
            todo += [(spent + w, (*match, d)) for w, d in self.near[e.parent, e.child].get(match[pattern.place(e.parent)], [])]
        return sorted(found)


def spine_first(pattern: TreePattern, cand: Candidates, counters: Counters, k: int | None = None, injective: bool = False) -> Iterator[tuple[int, tuple]]:
    """Longest leaf-to-leaf path first: path instances lightest first, each completed by all solutions of the branches that
    hang off it, until the next path is no lighter than the k-th match in hand (paths are followed by weight alone: the
    branches don't guide them). Stored: paths that wait, branch solutions and matches."""
    names, walk = pattern.spine(), Walk(pattern, cand)
    if len(pattern.order) == 1:
        yield from exhaustive(cand, counters, k, injective)
        return
    whole = pattern.reroot(names[0])
    sides = {a: whole.subtree(a, without=frozenset(v for v in whole.children(a) if v in names)) for a in names}
    order = [*names, *(x for a in names for x in sides[a].order[1:])]
    solved: dict[str, dict[int, list[tuple[int, tuple]]]] = {}
    least = 0  # what the branches add at least
    for a in names:
        if len(sides[a].order) > 1:
            solved[a] = defaultdict(list)
            for w, x in walk.solve(sides[a], counters):
                solved[a][x[0]].append((w, x))
            least += min((rows[0][0] for rows in solved[a].values()), default=0)
    # the least way on from each node of the path, by the path's own links
    ahead: list[dict[int, int]] = [{} for _ in names]
    for i in range(len(names) - 2, -1, -1):
        near = walk.near[names[i], names[i + 1]]
        if not len(near.keys):
            continue
        ways, d = near.columns
        if i + 2 < len(names):  # through the least way on, where there is one
            nodes = np.array(sorted(ahead[i + 1]), np.int64)
            on = np.array([ahead[i + 1][x] for x in nodes.tolist()], np.int64)
            at = np.searchsorted(nodes, d)
            goes = (at < len(nodes)) & (np.append(nodes, -1)[at] == d)
            ways = np.where(goes, ways + np.append(on, 0)[at], NO_WAY)
        least_way = np.minimum.reduceat(ways, near.first)
        ahead[i] = {c: x for c, x in zip(near.keys.tolist(), least_way.tolist()) if x < NO_WAY}
    queue = Queue(counters)
    for c, floor in sorted(ahead[0].items()):
        queue.push(floor, (c,))
    found: list[tuple[int, tuple]] = []
    spot = [order.index(n) for n in pattern.order]
    kth: list[int] = []  # the k least weights found, negated, in a heap
    while queue:
        bound, path = queue.pop()
        if k is not None and len(kth) >= k and (not k or -kth[0] < bound + least):
            break
        if len(path) < len(names):
            i = len(path) - 1
            for w, d in walk.near[names[i], names[i + 1]].get(path[-1], []):
                if i + 2 == len(names) or d in ahead[i + 1]:
                    queue.push(bound - ahead[i][path[-1]] + w + ahead[i + 1].get(d, 0), (*path, d))
            continue
        rows = [(bound, path)]
        for a, c in zip(names, path):
            if a in solved:
                rows = [(s + w, (*m, *x[1:])) for s, m in rows for w, x in solved[a].get(c, [])]
        for s, m in rows:
            match = tuple(m[i] for i in spot)
            counters.total_partials += 1
            counters.total_nodes += len(match)
            if not injective or len(set(match)) == len(match):
                found.append((s, match))
                if k is not None and (len(kth) < k or kth and s < -kth[0]):
                    (heapq.heappush if len(kth) < k else heapq.heapreplace)(kth, -s)
        counters.max_nodes = max(counters.max_nodes, queue.nodes + len(found) * len(order))
    found.sort()
    for row in found if k is None else found[:k]:
        counters.results += 1
        yield row


def candidate_rows(cg: CandidateGraph) -> DataFrame:
    """qid, e (place of the pattern edge, -1: roots), c, d, w, wf of all queries in one table: only links that a root reaches,
    whether cg comes after the down-sweep or not. Links that don't depend on the query get its qid here."""
    return reduce(DataFrame.union, candidate_parts(cg)[0])


def candidate_parts(cg: CandidateGraph) -> tuple[list[DataFrame], dict[str, DataFrame]]:
    """The candidate rows of the roots and of each edge, and (qid, c) of the nodes reached. The queue subtracts branches from
    bounds again, so costs must add up; other algebras raise and belong to the frame search."""
    if not cg.algebra.adds:
        raise ValueError(f"the queue kernel takes sums only, not {cg.algebra}")
    roots = with_qid(cg.reach[cg.pattern.root]).select("qid", F.lit(-1).alias("e"), F.lit(-1).cast("long").alias("c"), F.col("c").alias("d"), F.col("own").alias("w"), (F.col("floor") + F.col("own")).alias("wf"))
    out = [roots]
    reached = {cg.pattern.root: roots.select("qid", F.col("d").alias("c"))}
    for place, e in enumerate(cg.pattern.preorder_edges()):
        link = cg.link[e.child]
        on = ["qid", "c"] if "qid" in link.columns else ["c"]
        rows = link.select(*on, "d", "w", "wf").join(reached[e.parent], on, "left_semi") if len(on) == 2 else link.select("c", "d", "w", "wf").join(reached[e.parent], "c")
        out.append(rows.select("qid", F.lit(place).alias("e"), "c", "d", "w", "wf"))
        reached[e.child] = out[-1].select("qid", F.col("d").alias("c")).distinct()
    return out, reached


def too_large(rows: DataFrame, limit: int) -> DataFrame:
    """qid of the queries with more candidate rows than a task takes."""
    return rows.groupBy("qid").count().where(F.col("count") > limit).select("qid")


def each_query(rows: DataFrame | SharedRows, one: Callable[[tuple, pd.DataFrame], pd.DataFrame], schema: str) -> DataFrame:
    return rows.apply(one, schema) if isinstance(rows, SharedRows) else rows.groupBy("qid").applyInPandas(one, schema)


def run(cg: CandidateGraph, k: int | None = 5, method: str = "guided", injective: bool = True, in_hand: bool = True, limit: int = KERNEL_ROWS, rows: DataFrame | SharedRows | None = None) -> DataFrame:
    """qid, rank, weight, n0..: each query's heap search (or 'bulk': enumerate and sort) in its own group; queries with
    more than `limit` candidate rows by the frame search. rows: the stored `candidate_rows` of cg, where there are such."""
    size, pattern, sign = len(cg.pattern.order), cg.pattern, cg.algebra.sign

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        cand, counters = Candidates(pattern, rows), Counters()
        found = guided(cand, counters, k, injective, in_hand) if method == "guided" else exhaustive(cand, counters, k, injective)
        table = [(key[0], r, sign * w, *m) for r, (w, m) in enumerate(found, 1)]
        return pd.DataFrame(table, columns=["qid", "rank", "weight", *(f"n{i}" for i in range(size))])

    schema = "qid int, rank int, weight long, " + ", ".join(f"n{i} long" for i in range(size))
    if isinstance(rows, SharedRows):
        return rows.apply(one, schema)
    rows = stored(candidate_rows(cg)) if rows is None else rows
    large = stored(too_large(rows, limit))
    if large.isEmpty():
        return rows.groupBy("qid").applyInPandas(one, schema)
    down = only(cg, large)
    pairs = down.pairs() if injective else []
    if k is None:
        frontier = open_frontier(down)
        for level in range(size - 1):
            frontier = expand(down, frontier, level, pairs)
        rest = answers(down, frontier, None)
    else:
        rest = topk_iso(down, k) if injective else topk(down, k)
    return rows.join(large, "qid", "left_anti").groupBy("qid").applyInPandas(one, schema).unionByName(rest)


def counters(cg: CandidateGraph, k: int | None = 5, method: str = "guided", injective: bool = True, in_hand: bool = True, rows: DataFrame | SharedRows | None = None, limit: int = KERNEL_ROWS) -> DataFrame:
    """qid, us (time of the search) and the counters of each query's search (method: guided, bulk or spine, the last on
    `spine_rows`); a query with more than `limit` candidate rows raises, for counters exist in the queue kernel only."""
    pattern = cg.pattern

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        if len(rows) > limit:
            raise ValueError(f"query {key[0]} has {len(rows)} candidate rows, more than {limit}")
        cand, c = Candidates(pattern, rows), Counters()
        at = time.perf_counter()
        found = guided(cand, c, k, injective, in_hand) if method == "guided" else spine_first(pattern, cand, c, k, injective) if method == "spine" else exhaustive(cand, c, k, injective)
        for _ in found:
            pass
        us = (time.perf_counter() - at) * 1e6
        return pd.DataFrame([{"qid": key[0], **asdict(c), "out_degree": cand.out_degree, "us": us}])

    schema = "qid int, pops long, pushes long, max_partials long, max_nodes long, total_partials long, total_nodes long, results long, out_degree long, us double"
    return each_query(candidate_rows(cg) if rows is None else rows, one, schema)


def enumerated(cg: CandidateGraph, k: int, injective: bool = True, limit: int = KERNEL_ROWS, rows: DataFrame | SharedRows | None = None) -> DataFrame:
    """qid, rank, weight, n0..: all matches of each query, computed by a task of its own that keeps the k least, without a match
    being written. Queries with more than `limit` candidate rows are joined level by level."""
    size, pattern, sign, pairs = len(cg.pattern.order), cg.pattern, cg.algebra.sign, cg.pairs() if injective else []

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        found = Enumeration(pattern, rows, pairs, k)
        found.run()
        table = [(key[0], r, sign * w, *m) for r, (w, *m) in enumerate(found.best, 1)]
        return pd.DataFrame(table, columns=["qid", "rank", "weight", *(f"n{i}" for i in range(size))])

    schema = "qid int, rank int, weight long, " + ", ".join(f"n{i} long" for i in range(size))
    if isinstance(rows, SharedRows):
        return rows.apply(one, schema)
    rows = stored(candidate_rows(cg).drop("wf")) if rows is None else rows.drop("wf")
    large = stored(too_large(rows, limit))
    if large.isEmpty():
        return rows.groupBy("qid").applyInPandas(one, schema)
    down = only(cg, large)
    frontier = open_frontier(down)
    for level in range(size - 1):
        frontier = expand(down, frontier, level, pairs)
    return rows.join(large, "qid", "left_anti").groupBy("qid").applyInPandas(one, schema).unionByName(answers(down, frontier, k))


def bulk_counters(cg: CandidateGraph, k: int | None = 5, limit: int = KERNEL_ROWS, rows: DataFrame | SharedRows | None = None) -> DataFrame:
    """The counters of `exhaustive` on injective matches, from an enumeration on arrays that ranks the k least (k None: only
    counts) and stores none of them: for more matches than a task can hold. Its time is no search time of the queue kernels,
    and is not given."""
    pattern, size, pairs = cg.pattern, len(cg.pattern.order), cg.pairs()

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        if len(rows) > limit:
            raise ValueError(f"query {key[0]} has {len(rows)} candidate rows, more than {limit}")
        found = Enumeration(pattern, rows, pairs, k or 0)
        found.run()
        n = found.levels[-1]
        c = Counters(0, 0, n, n * size, sum(found.levels), sum(x * i for i, x in enumerate(found.levels, 1)), n if k is None else min(n, k))
        return pd.DataFrame([{"qid": key[0], **asdict(c)}])

    schema = "qid int, pops long, pushes long, max_partials long, max_nodes long, total_partials long, total_nodes long, results long"
    rows = candidate_rows(cg) if rows is None else rows
    return each_query(rows if isinstance(rows, SharedRows) else rows.drop("wf"), one, schema)


def spine_counters(pattern: TreePattern, k: int, rows: DataFrame | SharedRows, limit: int = KERNEL_ROWS) -> DataFrame:
    """The counters of `spine_first` on injective matches, from path-first search on arrays, which finds the same answers;
    without its time, as in `bulk_counters`. rows: of `spine_rows`."""

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        if len(rows) > limit:
            raise ValueError(f"query {key[0]} has {len(rows)} candidate rows, more than {limit}")
        found = PathFirst(pattern, rows, k)
        found.run()
        return pd.DataFrame([{"qid": key[0], **found.counters()}])

    schema = "qid int, pops long, pushes long, max_partials long, max_nodes long, total_partials long, total_nodes long, results long"
    return each_query(rows if isinstance(rows, SharedRows) else rows.select("qid", "e", "c", "d", "w"), one, schema)


def path_first(rows: DataFrame | SharedRows, pattern: TreePattern, k: int, injective: bool = True, known_k: bool = True) -> DataFrame:
    """qid, rank, weight, n0..: path-first search of each query on arrays, by a task of its own. rows: of `spine_rows`."""
    size = len(pattern.order)

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        found = PathFirst(pattern, rows, k, injective, known_k)
        found.run()
        table = [(key[0], r, *row) for r, row in enumerate(found.best, 1)]
        return pd.DataFrame(table, columns=["qid", "rank", "weight", *(f"n{i}" for i in range(size))])

    schema = "qid int, rank int, weight long, " + ", ".join(f"n{i} long" for i in range(size))
    return each_query(rows if isinstance(rows, SharedRows) else rows.select("qid", "e", "c", "d", "w"), one, schema)


def spine_rows(index: GraphIndex, pattern: TreePattern, bindings: DataFrame) -> DataFrame:
    """qid, e, c, d, w, wf as `candidate_rows` gives them, but for the path-first search: links of the longest path are reduced
    by the path's own demands only, those of each branch by the branch's own."""
    names = pattern.spine()
    top = min(names, key=pattern.place)
    whole, path = pattern.reroot(names[0]), pattern.subtree(top).restricted(names)  # what is left doesn't depend on the root
    place = {(e.parent, e.child): i for i, e in enumerate(pattern.preorder_edges())}
    cg = sweep_up(index, path, bindings, keep=True)
    on_path = candidate_parts(cg)
    parts = [(path, on_path[0])]
    for a in names:
        side = whole.subtree(a, without=frozenset(v for v in whole.children(a) if v in names))
        if len(side.order) > 1:
            own = sweep_up(index, side, bindings)
            if "qid" not in own.reach[a].columns:  # the same for all queries: at the nodes of their paths
                own.reach[a] = own.reach[a].join(on_path[1][a].distinct(), "c")
            parts.append((side, candidate_parts(own)[0]))
    out = None
    for part, rows in parts:
        for e, links in zip(part.preorder_edges(), rows[1:]):
            ends = ("c", "d") if (e.parent, e.child) in place else ("d", "c")
            at = place.get((e.parent, e.child), place.get((e.child, e.parent)))
            one = links.select("qid", F.lit(at).alias("e"), F.col(ends[0]).alias("c"), F.col(ends[1]).alias("d"), "w", "wf")
            out = one if out is None else out.unionByName(one)
    return out


def lateral(cg: CandidateGraph, k: int = 5, injective: bool = True) -> DataFrame:
    """The same answers from a table function, called laterally on each query's candidates: `LATERAL anyk_matches(..)`. The
    candidates of a query are one array; queries with more than KERNEL_ROWS of them raise."""
    from pyspark.sql.functions import udtf

    size, pattern, sign = len(cg.pattern.order), cg.pattern, cg.algebra.sign
    names = ", ".join(f"n{i} bigint" for i in range(size))

    class AnyKMatches:
        def eval(self, rows):
            frame = pd.DataFrame([(r["e"], r["c"], r["d"], r["w"], r["wf"]) for r in rows], columns=["e", "c", "d", "w", "wf"])
            for rank, (weight, match) in enumerate(guided(Candidates(pattern, frame), Counters(), k, injective), 1):
                yield (rank, sign * weight, *match)

    spark = cg.reach[pattern.root].sparkSession
    spark.udtf.register("anyk_matches", udtf(AnyKMatches, returnType=f"rank int, weight bigint, {names}"))
    rows = stored(candidate_rows(cg))
    if not too_large(rows, KERNEL_ROWS).isEmpty():
        raise ValueError("a query has too many candidate rows for an array; use run()")
    nested = rows.groupBy("qid").agg(F.collect_list(F.struct("e", "c", "d", "w", "wf")).alias("rows"))
    nested.createOrReplaceTempView("anyk_candidates")
    return spark.sql("SELECT q.qid, m.* FROM anyk_candidates q, LATERAL anyk_matches(q.rows) m")
