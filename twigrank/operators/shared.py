"""Reduction of one query at a time on arrays, for batches whose queries reach most of the graph: links between unbound nodes
are then nearly the same for every query, and go to each task once instead of once for each query.

A task takes some queries: their own links, at nodes that they bind, and all links between unbound nodes. It sweeps each query
up and down as `sweep_up` and `candidate_rows` (or `spine_rows`) do, and hands the same rows to the search.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, replace
from functools import reduce

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twigrank.model import TreePattern
from twigrank.operators.index import BROADCAST_IDS, GraphIndex
from twigrank.operators.pathfirst import look_up
from twigrank.plans.storage import stored

#: How many times fewer rows than with links for each query tell that sharing pays; in own, bindings have places from here down.
GAIN, BINDINGS = 1.5, -2
#: Links of a packed row at least, but for the last of a part; bits of a whole number.
PACK, UNSIGNED = 1 << 18, (1 << 64) - 1

Arrays = tuple[np.ndarray, ...]


@dataclass(frozen=True)
class SharedRows:
    """own: qid, e, c, d, w of links at bound nodes, with the bindings as rows of e = BINDINGS - place. links: e, c, d, w of those
    between unbound nodes, one e for all edges with the same arcs (edges: e by place), as `packed` rows. Both have the task's key."""

    pattern: TreePattern
    own: DataFrame
    links: DataFrame
    edges: dict[int, int]
    tasks: int
    kind: str = "plain"

    def candidates(self, injective: bool) -> SharedRows:
        """With the rows that `candidate_rows` gives after a sweep."""
        return replace(self, kind="apart" if injective else "plain")

    def paths(self) -> SharedRows:
        """With the rows that `spine_rows` gives."""
        return replace(self, kind="spine")

    def apply(self, one: Callable[[tuple, pd.DataFrame], pd.DataFrame], schema: str) -> DataFrame:
        """one for each query that has rows, as groupBy("qid").applyInPandas does it."""
        pattern, edges, kind = self.pattern, self.edges, self.kind
        names = [x.split()[0] for x in schema.split(", ")]

        def task(own: pd.DataFrame, links: pd.DataFrame) -> pd.DataFrame:
            out = [found for qid, rows in reduced(pattern, own, links, edges, kind) if len(found := one((qid,), rows))]
            return pd.concat(out)[names] if out else pd.DataFrame(columns=names)

        own, links = (df.repartition(self.tasks, "task").groupBy("task") for df in (self.own, self.links))
        return own.cogroup(links).applyInPandas(task, schema)


def share(index: GraphIndex, pattern: TreePattern, bindings: DataFrame, limit: int) -> SharedRows | None:
    """None where links for each query are no more rows than all links for each task, or a query could have more than `limit`
    rows; patterns with demands on labels or ids are not for arrays."""
    nodes, order = pattern.nodes, pattern.preorder_edges()
    between = [(i, x) for i, x in enumerate(order) if not (nodes[x.parent].bound or nodes[x.child].bound)]
    if not between or any(n.ids is not None or n.labels_all or n.labels_any for n in nodes.values()):
        return None
    below = {x.child: [i for i, y in enumerate(order) if y.parent == x.child and nodes[y.child].bound] for _, x in between}
    qids = sorted(r["qid"] for r in bindings.select("qid").distinct().limit(BROADCAST_IDS + 1).collect())
    tasks = min(len(qids), 2 * bindings.sparkSession.sparkContext.defaultParallelism)
    if not all(below.values()) or not GAIN * tasks < len(qids) <= BROADCAST_IDS:
        return None
    own = None
    for i, x in enumerate(order):
        if nodes[x.parent].bound or nodes[x.child].bound:
            arcs = index.between(pattern, x)
            for end, name in (("c", x.parent), ("d", x.child)):
                if nodes[name].bound:
                    at = bindings.where(F.col("pnode") == name).select("qid", F.col("node_id").alias(end)).distinct()
                    arcs = arcs.join(F.broadcast(at), [k for k in ("qid", end) if k in arcs.columns])
            arcs = arcs.select("qid", F.lit(i).alias("e"), "c", "d", "w")
            own = arcs if own is None else own.unionByName(arcs)
    kinds: dict[tuple, int] = {}
    edges = {i: kinds.setdefault((nodes[x.parent].ntype, nodes[x.child].ntype, x.elabel, x.direction), i) for i, x in between}
    links = reduce(DataFrame.unionByName, (index.between(pattern, order[i]).select(F.lit(i).alias("e"), "c", "d", "w") for i in sorted(set(edges.values()))))
    sizes = {r["e"]: r for r in links.groupBy("e").agg(F.count("*").alias("n"), F.countDistinct("d").alias("ends")).collect()}
    if sum(r["n"] for r in sizes.values()) > limit:
        return None
    # the task of each query: keys that fall into partitions of their own
    keys = bindings.sparkSession.range(100 * tasks).select("id", F.pmod(F.hash("id"), F.lit(tasks)).alias("at")).groupBy("at").agg(F.min("id").alias("id")).collect()
    keys = sorted(r["id"] for r in keys)
    task_of = bindings.sparkSession.createDataFrame([(q, keys[i % len(keys)]) for i, q in enumerate(qids)], "qid int, task long")
    codes = reduce(lambda col, n: col.when(F.col("pnode") == n, BINDINGS - pattern.place(n)), pattern.order, F.when(F.lit(False), 0))
    bound = bindings.select("qid", codes.alias("e"), F.col("node_id").alias("c"), F.col("node_id").alias("d"), F.lit(0).cast("long").alias("w")).distinct()
    own = stored(own.unionByName(bound).join(F.broadcast(task_of), "qid"))
    have = own.groupBy("qid", "e").agg(F.count("*").alias("n"))
    most = have.where("e >= 0").groupBy("qid").agg(F.sum("n").alias("n")).agg(F.max("n")).first()[0] or 0
    reach = {r["e"]: r["n"] for r in have.groupBy("e").agg(F.sum("n").alias("n")).collect()}
    if most + sum(sizes[s]["n"] for s in edges.values() if s in sizes) > limit:
        return None
    for i, x in between:
        if edges[i] in sizes and min(reach.get(j, 0) for j in below[x.child]) <= GAIN * len(keys) * sizes[edges[i]]["ends"]:
            return None
    links = stored(links.mapInPandas(packed, "e int, c binary, d binary, w binary")).withColumn("task", F.explode(F.array(*map(F.lit, keys)).cast("array<bigint>")))
    return SharedRows(pattern, own, links, edges, tasks)


def packed(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
    """e and the columns c, d, w of many links in each row, so that what goes to every task is few rows."""

    def row(e: int, rows: list[pd.DataFrame]) -> pd.DataFrame:
        return pd.DataFrame({"e": [e]} | {x: [narrowed(np.concatenate([r[x].to_numpy(np.int64) for r in rows]))] for x in ("c", "d", "w")})

    held: dict[int, list[pd.DataFrame]] = {}
    for part in parts:
        for e, rows in part.groupby("e"):
            held.setdefault(e, []).append(rows)
            if sum(map(len, held[e])) >= PACK:
                yield row(e, held.pop(e))
    for e, rows in held.items():
        yield row(e, rows)


def narrowed(x: np.ndarray) -> bytes:
    """The least value, the bytes of a number, and what each number has above the least in so many bytes."""
    least = int(x.min())
    above = x.view(np.uint64) - np.uint64(least & UNSIGNED)
    size = np.min_scalar_type(int(above.max())).itemsize
    return least.to_bytes(8, "little", signed=True) + bytes([size]) + above.astype(f"<u{size}").tobytes()


def unpacked(x: bytes) -> np.ndarray:
    least = int.from_bytes(x[:8], "little", signed=True)
    return (np.frombuffer(x, f"<u{x[8]}", offset=9).astype(np.uint64) + np.uint64(least & UNSIGNED)).view(np.int64)


class Links:
    """Links between two pattern nodes in the order of the first; their second ends as places among all, for look-ups."""

    def __init__(self, c: np.ndarray, d: np.ndarray, w: np.ndarray):
        at = np.lexsort((d, c))
        self.c, self.d, self.w = c[at], d[at], w[at]
        self.ends, self.at = np.unique(self.d, return_inverse=True)

    def into(self, nodes: np.ndarray, floors: np.ndarray) -> Arrays:
        """c, d, w of the links that end in one of the nodes, and w with that node's floor."""
        known, place = look_up(self.ends, np.arange(len(self.ends)), nodes)
        to, rest = np.zeros(len(self.ends), bool), np.zeros(len(self.ends), np.int64)
        to[place[known]], rest[place[known]] = True, floors[known]
        goes = np.flatnonzero(to[self.at])
        w = self.w[goes]
        return self.c[goes], self.d[goes], w, w + rest[self.at[goes]]


def starts(sorted_: np.ndarray) -> np.ndarray:
    return np.flatnonzero(np.append(True, sorted_[1:] != sorted_[:-1])) if len(sorted_) else np.zeros(0, np.int64)


def sweep(pattern: TreePattern, links: Callable[[str, str], Links], taken: dict[str, np.ndarray], start: np.ndarray | None = None) -> tuple[Arrays, dict[str, Arrays], dict[str, np.ndarray]]:
    """Roots with their floors; c, d, w, wf of the links by child, of those that a root reaches; the nodes reached. taken: nodes
    that are no candidates; start: roots to begin from only."""
    least: dict[str, Arrays] = {}
    link: dict[str, Arrays] = {}
    for u in reversed(pattern.order):
        nodes, cost = None, None
        for v in pattern.children(u):
            of = links(u, v)
            link[v] = of.into(*least[v]) if v in least else (of.c, of.d, of.w, of.w)
            first = starts(link[v][0])
            keys, floor = link[v][0][first], np.minimum.reduceat(link[v][3], first) if len(first) else link[v][3]
            if nodes is not None:
                keys, i, j = np.intersect1d(nodes, keys, assume_unique=True, return_indices=True)
                floor = cost[i] + floor[j]
            nodes, cost = keys, floor
        if nodes is not None:
            if u in taken:
                free = ~np.isin(nodes, taken[u])
                nodes, cost = nodes[free], cost[free]
            least[u] = nodes, cost
    nodes, cost = least[pattern.root]
    if start is not None:
        on = np.isin(nodes, start)
        nodes, cost = nodes[on], cost[on]
    reached = {pattern.root: nodes}
    for x in pattern.preorder_edges():
        c = link[x.child][0]
        first = starts(c)
        keep = np.repeat(np.isin(c[first], reached[x.parent]), np.diff(np.append(first, len(c))))
        link[x.child] = tuple(y[keep] for y in link[x.child])
        reached[x.child] = np.unique(link[x.child][1])
    return (nodes, cost), link, reached


def reduced(pattern: TreePattern, own: pd.DataFrame, shared: pd.DataFrame, edges: dict[int, int], kind: str) -> Iterator[tuple[int, pd.DataFrame]]:
    """Each query of a task that has rows, with e, c, d, w, wf of its rows."""
    place = {(x.parent, x.child): i for i, x in enumerate(pattern.preorder_edges())}
    columns = lambda df: [df[x].to_numpy(np.int64) for x in ("e", "c", "d", "w")]
    raw = {}
    for s in set(edges.values()):
        of = shared[shared["e"] == s]
        raw[s] = tuple(np.concatenate([np.zeros(0, np.int64), *map(unpacked, of[x])]) for x in ("c", "d", "w"))
    between: dict[tuple[int, bool], Links] = {}
    own = own.sort_values("qid", kind="stable")
    qids, table = own["qid"].to_numpy(), columns(own)
    cuts = [*starts(qids), len(qids)]
    for a, b in zip(cuts, cuts[1:]):
        e, *rest = (x[a:b] for x in table)
        mine: dict[tuple[str, str], Links] = {}
        bound = {n: np.unique(rest[0][e == BINDINGS - i]) for i, n in enumerate(pattern.order) if pattern.nodes[n].bound}

        def links(u: str, v: str) -> Links:
            flip = (u, v) not in place
            i = place[(v, u) if flip else (u, v)]
            known, key = (between, (edges[i], flip)) if i in edges else (mine, (u, v))
            if key not in known:
                c, d, w = raw[edges[i]] if i in edges else (x[e == i] for x in rest)
                known[key] = Links(d, c, w) if flip else Links(c, d, w)
            return known[key]

        rows = spine(pattern, links, place) if kind == "spine" else whole(pattern, links, place, bound, kind == "apart")
        parts = [(np.full(len(x[0]), i), *x) for i, x in rows if len(x[0])]
        if parts:
            yield int(qids[a]), pd.DataFrame(dict(zip(("e", "c", "d", "w", "wf"), map(np.concatenate, zip(*parts)))))


def whole(pattern: TreePattern, links: Callable[[str, str], Links], place: dict, bound: dict[str, np.ndarray], injective: bool) -> list[tuple[int, Arrays]]:
    """e and c, d, w, wf of the roots and of each edge."""
    nodes = pattern.nodes
    taken: dict[str, np.ndarray] = {}
    if injective:
        every = np.concatenate([*bound.values(), np.zeros(0, np.int64)])
        if len(np.unique(every)) < len(every):  # two pattern nodes bound to one graph node
            return []
        for u in pattern.order:
            alike = [x for n, x in bound.items() if nodes[n].ntype == nodes[u].ntype]
            if alike and not nodes[u].bound and pattern.depends_on_query(u):
                taken[u] = np.concatenate(alike)
    (roots, floors), link, _ = sweep(pattern, links, taken)
    none = np.full(len(roots), -1)
    return [(-1, (none, roots, np.zeros(len(roots), np.int64), floors)), *((place[x.parent, x.child], link[x.child]) for x in pattern.preorder_edges())]


def spine(pattern: TreePattern, links: Callable[[str, str], Links], place: dict) -> list[tuple[int, Arrays]]:
    """e and c, d, w, wf of each edge: the longest path by its own demands, each branch by the branch's own."""
    names = pattern.spine()
    path, around = pattern.subtree(min(names, key=pattern.place)).restricted(names), pattern.reroot(names[0])
    _, link, reached = sweep(path, links, {})
    parts = [(path, link)]
    for a in names:
        side = around.subtree(a, without=frozenset(v for v in around.children(a) if v in names))
        if len(side.order) > 1:
            parts.append((side, sweep(side, links, {}, None if side.depends_on_query(a) else reached[a])[1]))
    out = []
    for part, link in parts:
        for x in part.preorder_edges():
            c, d, w, wf = link[x.child]
            out.append((place[x.parent, x.child], (c, d, w, wf)) if (x.parent, x.child) in place else (place[x.child, x.parent], (d, c, w, wf)))
    return out
