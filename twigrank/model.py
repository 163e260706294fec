"""Patterns and weight algebras: small driver-side objects, never data."""

from __future__ import annotations

import re
from dataclasses import dataclass, field, replace
from enum import Enum
from functools import reduce

from pyspark.sql import Column
from pyspark.sql import functions as F


class PatternError(ValueError):
    """The pattern is no rooted tree, or names a node twice with different demands."""


@dataclass(frozen=True)
class PNode:
    """A pattern node: its type, whether each query binds it to one node, and further demands on the graph node."""

    name: str
    ntype: str
    bound: bool = False
    ids: tuple[int, ...] | None = None
    labels_all: tuple[str, ...] = ()
    labels_any: tuple[str, ...] = ()


@dataclass(frozen=True)
class PEdge:
    parent: str
    child: str
    elabel: str | None = None
    direction: str | None = None  # 'out': the arc goes from parent to child, 'in': the other way


@dataclass(frozen=True)
class TreePattern:
    nodes: dict[str, PNode]
    edges: tuple[PEdge, ...]
    root: str
    order: tuple[str, ...] = field(default=(), compare=False)

    def __post_init__(self):
        parents: dict[str, str] = {}
        for e in self.edges:
            if e.child in parents or e.child == self.root:
                raise PatternError(f"{e.child} has two parents or closes a cycle")
            parents[e.child] = e.parent
        order = self._walk(self.root, set())
        if set(order) != set(self.nodes):
            raise PatternError(f"not connected to the root: {sorted(set(self.nodes) - set(order))}")
        object.__setattr__(self, "order", tuple(order))

    def _walk(self, u: str, seen: set[str]) -> list[str]:
        if u in seen or u not in self.nodes:
            raise PatternError(f"{u} closes a cycle or has no type")
        seen.add(u)
        return [u, *(x for v in self.children(u) for x in self._walk(v, seen))]

    def children(self, u: str) -> list[str]:
        return [e.child for e in self.edges if e.parent == u]

    def edge_to(self, v: str) -> PEdge:
        return next(e for e in self.edges if e.child == v)

    def preorder_edges(self) -> list[PEdge]:
        return [self.edge_to(v) for v in self.order[1:]]

    def place(self, name: str) -> int:
        return self.order.index(name)

    def subtree(self, u: str, without: frozenset[str] = frozenset()) -> "TreePattern":
        """The pattern below and with u, without the branches of the children named."""
        keep = [u, *(x for v in self.children(u) if v not in without for x in self.subtree(v).order)]
        return TreePattern({n: self.nodes[n] for n in keep}, tuple(e for e in self.edges if e.parent in keep and e.child in keep), u)

    def restricted(self, names: list[str]) -> "TreePattern":
        """The pattern of the named nodes only, which must hang together and hold the root."""
        return TreePattern({n: x for n, x in self.nodes.items() if n in names}, tuple(e for e in self.edges if e.child in names), self.root)

    def reroot(self, root: str) -> "TreePattern":
        """The same tree hung from another node; any node may be the root."""
        near: dict[str, list[tuple[str, PEdge]]] = {n: [] for n in self.nodes}
        for e in self.edges:
            near[e.parent].append((e.child, e))
            near[e.child].append((e.parent, e))
        flip, edges, todo, seen = {"out": "in", "in": "out", None: None}, [], [root], {root}
        while todo:
            u = todo.pop(0)
            for v, e in near[u]:
                if v not in seen:
                    seen.add(v)
                    edges.append(PEdge(u, v, e.elabel, e.direction if e.parent == u else flip[e.direction]))
                    todo.append(v)
        return TreePattern(self.nodes, tuple(edges), root)

    def bound_below(self, u: str) -> int:
        """How many bound nodes u and its branches have."""
        return int(self.nodes[u].bound) + sum(map(self.bound_below, self.children(u)))

    def leaves(self) -> list[str]:
        return [n for n in self.order if not self.children(n)]

    def depends_on_query(self, u: str) -> bool:
        return self.nodes[u].bound or any(map(self.depends_on_query, self.children(u)))

    def overlapping_pairs(self) -> list[tuple[int, int]]:
        """Places of node pairs that one graph node could serve; only these need an injectivity check."""
        out = []
        for j, b in enumerate(self.order):
            for i, a in enumerate(self.order[:j]):
                x, y = self.nodes[a], self.nodes[b]
                apart = x.ntype != y.ntype or (x.ids is not None and y.ids is not None and not set(x.ids) & set(y.ids))
                if not apart:
                    out.append((i, j))
        return out

    def spine(self) -> list[str]:
        """Names along the longest leaf-to-leaf path; ties go to the earliest end points in pre-order."""
        ends = [n for n in self.order if not self.children(n) or (n == self.root and len(self.children(n)) == 1)] or [self.root]

        def up(n: str) -> list[str]:
            path = [n]
            while path[-1] != self.root:
                path.append(self.edge_to(path[-1]).parent)
            return path

        best: list[str] = [self.root]
        for i, a in enumerate(ends):
            for b in ends[i + 1 :]:
                left, right = up(a), up(b)
                meet = next(x for x in left if x in right)
                path = left[: left.index(meet) + 1] + right[: right.index(meet)][::-1]
                if len(path) > len(best):
                    best = path
        return best

    def with_nodes(self, **changes: dict) -> "TreePattern":
        return TreePattern({n: replace(x, **changes.get(n, {})) for n, x in self.nodes.items()}, self.edges, self.root)

    def with_edges(self, **labels: dict) -> "TreePattern":
        return TreePattern(self.nodes, tuple(replace(e, **labels.get(e.child, {})) for e in self.edges), self.root)


_NODE = re.compile(r"\(\s*(\w+)\s*(?::\s*(\w+)\s*(\*)?)?\s*\)")
_LINK = re.compile(r"\s*(<?)-(?:\[(\w+)\]-)?(>?)\s*")


def parse_pattern(text: str) -> TreePattern:
    """``(o:order)-(c:customer*), (o)-[R]->(p:part)``: comma-separated paths; ``*`` marks nodes that queries bind, the first
    node is the root, ``[label]`` demands an edge label, an arrow head a direction."""
    nodes: dict[str, PNode] = {}
    edges: list[PEdge] = []
    root = None
    for path in text.split(","):
        path, at, last, link = path.strip(), 0, None, None
        while at < len(path):
            m = _NODE.match(path, at)
            if not m:
                raise PatternError(f"no node at {path[at:]!r}")
            name, ntype, star = m.groups()
            if ntype:
                if name in nodes:
                    raise PatternError(f"{name} is declared twice")
                nodes[name] = PNode(name, ntype, bool(star))
            elif name not in nodes:
                raise PatternError(f"{name} has no type")
            root = root or name
            if last:
                back, label, ahead = link.groups()
                edges.append(PEdge(last, name, label, "in" if back else "out" if ahead else None))
            last, at = name, m.end()
            if at < len(path):
                link = _LINK.match(path, at)
                if not link or link.end() == at:
                    raise PatternError(f"no edge at {path[at:]!r}")
                at = link.end()
    return TreePattern(nodes, tuple(edges), root or "")


class Algebra(Enum):
    """How edge weights make up a match's weight, and which end of the order comes first.

    All are order-preserving in each argument, which is all that the level cut needs; bounds are recombined from the
    branches still open rather than subtracted, so minimum and maximum work like sums.
    """

    SUM = ("sum", 1)
    SUM_MAX = ("sum", -1)
    RELIABILITY = ("sum", 0)  # weights are probabilities in millionths; their -ln in billionths is summed
    MAX = ("max", 1)
    MAX_MAX = ("max", -1)
    MIN = ("min", 1)

    def cost(self, w: Column) -> Column:
        """What is minimised, from an edge weight. A probability of nothing or less gives no cost (null: no such way), one
        above a million raises when it is met."""
        if self is Algebra.RELIABILITY:
            cost = F.round(-F.log(w / F.lit(1e6)) * F.lit(1e9)).cast("long")
            return F.when(w > 1_000_000, F.raise_error(F.lit("a probability is above a million millionths")).cast("long")).when(w > 0, cost)
        return -w if self.value[1] < 0 else w

    def weight(self, cost: Column) -> Column:
        return -cost if self.value[1] < 0 else cost

    @property
    def adds(self) -> bool:
        """Whether costs add up, so that a part can be subtracted from a bound again."""
        return self.value[0] == "sum"

    @property
    def sign(self) -> int:
        return -1 if self.value[1] < 0 else 1

    def combine(self, *parts: Column) -> Column:
        parts = [p for p in parts if p is not None]
        if not parts:
            return F.lit(0).cast("long")
        kind = self.value[0]
        if self is Algebra.MAX_MAX:
            kind = "min"  # of negated weights
        if len(parts) == 1:
            return parts[0]
        return reduce(lambda a, b: a + b, parts) if kind == "sum" else F.greatest(*parts) if kind == "max" else F.least(*parts)

    def neutral(self) -> Column | None:
        """The cost of no edge; None where it is no number and must be left out of a combination."""
        return F.lit(0).cast("long") if self.value[0] == "sum" else None
