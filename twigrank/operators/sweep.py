"""The reduction: an up-sweep that fuses semi-joins with cheapest completions, and a down-sweep that drops the rest.

With `injective`, queries that bind two pattern nodes to one graph node are left out, and nodes that a query binds elsewhere
in the pattern are no candidates of others; only pairs of unbound nodes are then left for the search to check.

Tables: reach[u] = (qid?, c, m_<child>.., floor); link[v] = (qid?, c, d, w, wf, f_<child of v>..) for the edge from v's
parent, with w the edge's cost, wf its cost with everything below d. A branch without bound nodes has no qid: it is the
same for all queries and is computed once. link[v] holds only nodes c that earlier, more selective branches of the parent
have kept, where there are such branches.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from twigrank.model import Algebra, TreePattern
from twigrank.operators.index import GraphIndex
from twigrank.plans.storage import rows_at_most, stored

#: Candidates of a node, from its selective branches, that are sent to all tasks to prune the arcs of the others.
FEW = 500_000


@dataclass
class CandidateGraph:
    pattern: TreePattern
    algebra: Algebra
    reach: dict[str, DataFrame]
    link: dict[str, DataFrame]
    node_weight: bool = False
    injective: bool = False
    kept: bool = False  # links and roots are stored
    open: dict[str, tuple[DataFrame, DataFrame]] = field(default_factory=dict)  # arcs and the nodes below, whose join is the link

    def pairs(self) -> list[tuple[int, int]]:
        """Places that one graph node could still serve both, to be checked by an injective search."""
        return unbound_pairs(self.pattern) if self.injective else self.pattern.overlapping_pairs()

    def keys(self, u: str) -> list[str]:
        return ["qid", "c"] if self.pattern.depends_on_query(u) else ["c"]


def unbound_pairs(pattern: TreePattern) -> list[tuple[int, int]]:
    """Of the places that one graph node could serve both, those that an injective sweep doesn't keep apart."""
    bound = lambda a, b: pattern.nodes[a].bound and pattern.depends_on_query(b)
    order = pattern.order
    return [(i, j) for i, j in pattern.overlapping_pairs() if not (bound(order[i], order[j]) or bound(order[j], order[i]))]


def demands(index: GraphIndex, pattern: TreePattern, u: str, df: DataFrame) -> DataFrame:
    """df (with column c) reduced to nodes that meet u's further demands."""
    p = pattern.nodes[u]
    if p.ids is not None:
        df = df.where(F.col("c").isin(list(p.ids)))
    if p.labels_all or p.labels_any:
        ok = index.nodes.where(F.col("ntype") == p.ntype)
        for x in p.labels_all:
            ok = ok.where(F.array_contains("labels", x))
        if p.labels_any:
            ok = ok.where(F.arrays_overlap("labels", F.array(*map(F.lit, p.labels_any))))
        df = df.join(ok.select(F.col("node_id").alias("c")), "c", "left_semi")
    return df


def seed(index: GraphIndex, pattern: TreePattern, u: str, bindings: DataFrame) -> DataFrame:
    """Candidates of a leaf with floor 0: those that the queries bind, or all nodes of the type that have an arc."""
    p = pattern.nodes[u]
    if p.bound:
        df = bindings.where(F.col("pnode") == u).select("qid", F.col("node_id").alias("c")).distinct()
    elif p.ids is not None:
        df = index.arcs.sparkSession.createDataFrame([(i,) for i in sorted(set(p.ids))], "c long")
    else:
        df = index.arcs.where(F.col("src_type") == p.ntype).select(F.col("src").alias("c")).distinct()
    return demands(index, pattern, u, df)


def own_weight(index: GraphIndex, df: DataFrame, algebra: Algebra) -> DataFrame:
    """df with column own: the cost of node c itself (0 for nodes without one)."""
    nodes = index.nodes.select(F.col("node_id").alias("c"), algebra.cost(F.col("nweight")).alias("own"))
    return df.join(nodes, "c", "left").withColumn("own", F.coalesce("own", F.lit(0)).cast("long"))


def taken(pattern: TreePattern, u: str) -> list[str]:
    """The bound nodes of an unbound node's type that an injective sweep keeps apart from it."""
    own = pattern.nodes[u]
    return [] if own.bound else [x for x in pattern.order if pattern.nodes[x].bound and pattern.nodes[x].ntype == own.ntype]


def clashing(pattern: TreePattern, bindings: DataFrame) -> DataFrame:
    """qid of queries that bind two pattern nodes to one graph node."""
    a, b = bindings.select("qid", "node_id", F.col("pnode").alias("a")), bindings.select("qid", "node_id", F.col("pnode").alias("b"))
    return a.join(b, ["qid", "node_id"]).where("a < b").select("qid").distinct()


def same_terminals(bindings: DataFrame) -> DataFrame:
    """(qid, first) of all queries: the first query with the same terminals."""
    terminals = F.array_sort(F.collect_set(F.struct("pnode", "node_id")))
    each = bindings.groupBy("qid").agg(terminals.alias("_t"))
    return stored(each.select("qid", F.min("qid").over(Window.partitionBy("_t")).alias("first")))


def alike(bindings: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The bindings of the first query of each set of queries with equal terminals, and (qid, first) of all: equal queries
    have equal answers, which `spread` hands to each."""
    members = same_terminals(bindings)
    return stored(bindings.join(members.where("qid = first").select("qid"), "qid", "left_semi")), members


def spread(rows: DataFrame, members: DataFrame) -> DataFrame:
    """rows of the first query of each set, for every query of the set."""
    return rows.withColumnRenamed("qid", "first").join(members, "first").select(rows.columns)


def sweep_up(index: GraphIndex, pattern: TreePattern, bindings: DataFrame, algebra: Algebra = Algebra.SUM, node_weight: bool = False, injective: bool = False, keep: bool = False, lean: bool = False) -> CandidateGraph:
    """Reach and link tables of all pattern nodes, from the leaves up. Branch minima are aggregated before siblings meet:
    the inner join of the aggregates is the intersection of the branches, and needs no exchange of its own. Branches with
    the most bound nodes come first; what they leave of the parent's candidates, if it is little, prunes the arcs of the
    other branches before these are joined. With `keep` links and roots are stored as they are found, for several passes. With
    `lean` there are no links, but stored roots and reach, for `search.topk`, which follows few links and finds them from the arcs
    (`open`); the minima of a branch are then found once for all queries that bind the same nodes in it."""
    cg = CandidateGraph(pattern, algebra, {}, {}, node_weight, injective, keep)
    if injective and any(pattern.nodes[x].bound and pattern.nodes[y].bound for x in pattern.order for y in pattern.order if x < y):
        bindings = bindings.join(clashing(pattern, bindings), "qid", "left_anti")
    for u in reversed(pattern.order):
        kids = sorted(pattern.children(u), key=lambda v: (bool(pattern.children(v)) or not pattern.nodes[v].bound, -pattern.bound_below(v), pattern.place(v)))
        if not kids:
            base = seed(index, pattern, u, bindings)
        else:
            base, few = None, False
            for v in kids:
                key = cg.keys(v)
                floors = [F.col(f"m_{x}").alias(f"f_{x}") for x in pattern.children(v)]
                below = cg.reach[v].select(*[k for k in key if k != "c"], F.col("c").alias("d"), F.col("floor").alias("_floor"), F.col("own").alias("_own"), *floors)
                arcs = index.between(pattern, pattern.edge_to(v)).withColumn("w", algebra.cost(F.col("w"))).where("w is not null")
                firsts = None
                if lean:
                    below = below if pattern.nodes[v].bound and not pattern.children(v) else stored(below)
                    cg.open[v] = arcs, below
                    alone = pattern.nodes[u].bound or injective and any(taken(pattern, x) for x in pattern.subtree(v).order)
                    firsts = same_terminals(bindings.where(F.col("pnode").isin(*pattern.subtree(v).order))) if pattern.children(v) and "qid" in key and not alone else None
                if firsts is not None:
                    own = base.select("c").distinct() if few else None
                    below = below.join(F.broadcast(firsts.where("qid = first").select("qid")), "qid", "left_semi")
                else:
                    own = base.select(*key) if "qid" in key and few else base.select("c").distinct() if few else None
                if few and pattern.children(v):  # candidates of u first, so that few arcs meet the branch
                    arcs = arcs.join(F.broadcast(own), "c")
                if pattern.nodes[u].bound and "qid" in key:  # only from the nodes that the query binds
                    bound = bindings.where(F.col("pnode") == u).select("qid", F.col("node_id").alias("c")).distinct()
                    arcs = arcs.join(bound, [k for k in ("qid", "c") if k in arcs.columns])
                link = arcs.join(below, [k for k in ("qid", "d") if k in arcs.columns and k in below.columns])
                # the node weight of d goes with the edge that reaches it
                link = link.withColumn("w", F.col("w") + F.col("_own") if node_weight else F.col("w"))
                rest = None if not pattern.children(v) else F.col("_floor")
                link = link.withColumn("wf", algebra.combine(F.col("w"), rest)).drop("_floor", "_own")
                link = link.select(*key, "d", "w", "wf", *[f"f_{x}" for x in pattern.children(v)])
                if not lean:
                    cg.link[v] = stored(link) if keep else link
                least = (link if lean else cg.link[v]).groupBy(*key).agg(F.min("wf").alias(f"m_{v}"))
                if firsts is not None:
                    least = least.withColumnRenamed("qid", "first").join(F.broadcast(firsts), "first").drop("first")
                base = least if base is None else base.join(least, [k for k in key if k in base.columns], "inner")
                if v != kids[-1] and not few and (pattern.bound_below(v) > 1 or pattern.nodes[v].bound):
                    base = stored(base)
                    few = rows_at_most(base, FEW)
            if pattern.nodes[u].bound:  # an inner or root node may be bound as well
                own = bindings.where(F.col("pnode") == u).select("qid", F.col("node_id").alias("c")).distinct()
                base = base.join(own, [k for k in ("qid", "c") if k in base.columns])
            base = demands(index, pattern, u, base)
        if injective and "qid" in base.columns and not pattern.nodes[u].bound:
            if apart := taken(pattern, u):
                base = base.join(bindings.where(F.col("pnode").isin(apart)).select("qid", F.col("node_id").alias("c")).distinct(), ["qid", "c"], "left_anti")
        floor = algebra.combine(*[F.col(f"m_{v}") for v in pattern.children(u)])
        base = base.withColumn("floor", floor)
        base = own_weight(index, base, algebra) if node_weight else base.withColumn("own", F.lit(0).cast("long"))
        cg.reach[u] = stored(base) if (keep or lean) and u == pattern.root else base
    return cg


def sweep_down(cg: CandidateGraph) -> CandidateGraph:
    """Only what some root candidate reaches, by semi-joins from the root; what is left occurs in some match."""
    pattern, reach, link = cg.pattern, {cg.pattern.root: cg.reach[cg.pattern.root]}, {}
    for e in pattern.preorder_edges():
        u, v = e.parent, e.child
        on = [k for k in cg.keys(v) if k in reach[u].columns]
        link[v] = cg.link[v].join(reach[u].select(*on).distinct(), on, "left_semi")
        key = [k for k in cg.keys(v) if k != "c"]
        used = link[v].select(*key, F.col("d").alias("c")).distinct()
        reach[v] = cg.reach[v].join(used, [*key, "c"], "left_semi")
    return CandidateGraph(pattern, cg.algebra, reach, link, cg.node_weight, cg.injective)


def fixed(cg: CandidateGraph) -> CandidateGraph:
    """cg with its links stored, for several pages or methods over one reduction."""
    return CandidateGraph(cg.pattern, cg.algebra, {cg.pattern.root: stored(cg.reach[cg.pattern.root])} | {u: df for u, df in cg.reach.items() if u != cg.pattern.root}, {v: stored(df) for v, df in cg.link.items()}, cg.node_weight, cg.injective, True)


def only(cg: CandidateGraph, queries: DataFrame) -> CandidateGraph:
    """cg for some of its queries (qid)."""
    own = lambda df: df.join(queries, "qid", "left_semi") if "qid" in df.columns else df
    return CandidateGraph(cg.pattern, cg.algebra, {u: own(df) for u, df in cg.reach.items()}, {v: own(df) for v, df in cg.link.items()}, cg.node_weight, cg.injective)


def count_matches(cg: CandidateGraph) -> DataFrame:
    """qid, n: the number of homomorphic matches, by sums and products over the links, without enumerating any."""
    counts: dict[str, DataFrame] = {}
    pattern = cg.pattern
    one = F.lit(1).cast("decimal(38,0)")
    for u in reversed(pattern.order):
        base = cg.reach[u].select(*[k for k in cg.keys(u)]).withColumn("n", one)
        for v in pattern.children(u):
            key = [k for k in cg.keys(v) if k != "c"]
            through = cg.link[v].select(*key, "c", "d").join(counts[v].select(*key, F.col("c").alias("d"), F.col("n").alias("below")), [*key, "d"])
            each = through.groupBy(*key, "c").agg(F.sum("below").cast("decimal(38,0)").alias("times"))
            base = base.join(each, [*key, "c"]).withColumn("n", (F.col("n") * F.col("times")).cast("decimal(38,0)")).drop("times")
        counts[u] = base
    root = counts[pattern.root]
    root = root if "qid" in root.columns else root.withColumn("qid", F.lit(0))
    return root.groupBy("qid").agg(F.sum("n").cast("decimal(38,0)").alias("n"))


def spurious(up: CandidateGraph, down: CandidateGraph) -> DataFrame:
    """pnode, after_up, after_down: rows of each reach table before and after the down-sweep."""
    out = None
    for u in up.pattern.order:
        for cg, after in ((up, 1), (down, 0)):
            row = cg.reach[u].select(F.lit(u).alias("pnode"), F.lit(after).alias("_up"))
            out = row if out is None else out.union(row)
    return out.groupBy("pnode").agg(F.sum("_up").alias("after_up"), F.sum(1 - F.col("_up")).alias("after_down"))


def choose_root(index: GraphIndex, pattern: TreePattern) -> str:
    """The root for which the arcs that the sweep must scan above unbound leaves are fewest."""
    sizes = {(r["src_type"], r["dst_type"]): r["n"] for r in index.arcs.groupBy("src_type", "dst_type").agg(F.count("*").alias("n")).collect()}  # a row for each pair of types

    def cost(root: str) -> tuple[int, int]:
        p = pattern.reroot(root)
        loose = sum(sizes.get((p.nodes[e.parent].ntype, p.nodes[e.child].ntype), 0) for e in p.edges if not p.depends_on_query(e.child))
        return loose, p.order.index(root)

    return min(pattern.order, key=lambda u: (cost(u), pattern.place(u)))
