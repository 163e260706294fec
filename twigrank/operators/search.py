"""Guided any-k search on DataFrames.

A frontier row is a partial match: the bound nodes n0.. in pre-order, the cost spent, and the floor of each branch not yet
opened; its bound combines them and is exact, so a partial match is worth expanding only if it is among the k best of its
level: each of k better ones has a completion at its own bound that comes first. Levels are cut by (bound, n0, n1, ..);
weights are whole numbers, so the order is total and the cut is exact for homomorphic matches. What a page cuts off is
kept as the deferred frontier, from which the next page goes on. With injective matches a kept partial may die, so a
page is certified: only rows before the first partial that waits, in the order of (bound, n0, n1, ..), are final, and the
frontier of the queries that lack some goes on with a beam of four times the size.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from twigrank.model import TreePattern
from twigrank.operators.sweep import FEW, CandidateGraph, fixed, only
from twigrank.plans.storage import rows_at_most, stored


LEAST = -(1 << 63)


def with_qid(df: DataFrame) -> DataFrame:
    return df if "qid" in df.columns else df.withColumn("qid", F.lit(0))


def places(df: DataFrame) -> list[str]:
    return sorted((c for c in df.columns if c[0] == "n" and c[1:].isdigit()), key=lambda c: int(c[1:]))


def bound_of(cg: CandidateGraph, df: DataFrame) -> Column:
    open_ = [F.col(c) for c in df.columns if c.startswith("f_")]
    spent = F.col("spent") if "spent" in df.columns else None
    return cg.algebra.combine(*([spent] if spent is not None else []), *open_)


def open_frontier(cg: CandidateGraph) -> DataFrame:
    """Root candidates: qid, n0, floors of the root's branches, bound."""
    root = cg.pattern.root
    df = with_qid(cg.reach[root])
    floors = [F.col(f"m_{v}").alias(f"f_{v}") for v in cg.pattern.children(root)]
    spent = cg.algebra.neutral()
    own = [F.col("own").alias("spent")] if cg.node_weight else [spent.alias("spent")] if spent is not None else []
    df = df.select("qid", F.col("c").alias("n0"), *own, *floors)
    return df.withColumn("bound", bound_of(cg, df)) if floors or own else df.withColumn("bound", F.lit(0).cast("long"))


def expand(cg: CandidateGraph, frontier: DataFrame, level: int, injective: list[tuple[int, int]]) -> DataFrame:
    """All direct successors at the next pre-order edge: one join of the frontier with the edge's links, or with its arcs and
    the nodes below them."""
    pattern = cg.pattern
    e = pattern.preorder_edges()[level]
    u, v = pattern.place(e.parent), level + 1
    on = [f"n{u}", *(["qid"] if e.child not in cg.open and "qid" in cg.link[e.child].columns else [])]
    arcs, below = cg.open.get(e.child, (None, None))
    link = cg.link[e.child].drop("wf") if arcs is None else arcs
    link = link.withColumnRenamed("c", f"n{u}").withColumnRenamed("d", f"n{v}").withColumnRenamed("w", "_w")
    df = frontier.drop("bound", f"f_{e.child}").join(link, on)
    if arcs is not None:
        below = below.drop("_floor").withColumnRenamed("d", f"n{v}")
        df = df.join(below, [k for k in ("qid", f"n{v}") if k in below.columns])
        df = (df.withColumn("_w", F.col("_w") + F.col("_own")) if cg.node_weight else df).drop("_own")
    for i, j in injective:
        if j == v:
            df = df.where(F.col(f"n{i}") != F.col(f"n{j}"))
    df = df.withColumn("spent", cg.algebra.combine(F.col("spent"), F.col("_w")) if "spent" in df.columns else F.col("_w")).drop("_w")
    floors = sorted(c for c in df.columns if c.startswith("f_"))
    kept = [c for c in ("cut", "most") if c in df.columns]
    df = df.select("qid", *[f"n{i}" for i in range(v + 1)], "spent", *floors, *kept)
    return df.withColumn("bound", bound_of(cg, df))


def ranked(df: DataFrame, k: int) -> DataFrame:
    """df with the rank of each row in its query, ranks up to k only (a group limit before and after the shuffle)."""
    by = Window.partitionBy("qid").orderBy("bound", *places(df))
    return df.withColumn("_r", F.row_number().over(by)).where(F.col("_r") <= k)


def numbered(df: DataFrame, names: list[str]) -> DataFrame:
    """df with the rank of each row in its query, over any number of rows: a range sort, and for each query the number of
    its rows in earlier parts. No task gets a query's rows."""
    parts = df.repartitionByRange("qid", "bound", *names).sortWithinPartitions("qid", "bound", *names)
    rows = stored(parts.withColumn("_at", F.monotonically_increasing_id()).withColumn("_part", F.shiftright("_at", 33)))
    each = rows.groupBy("qid", "_part").agg(F.count("*").alias("_n"), F.min("_at").alias("_first"))
    before = F.sum("_n").over(Window.partitionBy("qid").orderBy("_part").rowsBetween(Window.unboundedPreceding, -1))
    each = each.select("qid", "_part", "_first", F.coalesce(before, F.lit(0)).alias("_before"))
    return rows.join(each, ["qid", "_part"]).withColumn("rank", (F.col("_at") - F.col("_first") + F.col("_before") + 1).cast("int")).drop("_at", "_part", "_first", "_before")


def answers(cg: CandidateGraph, df: DataFrame, k: int | None) -> DataFrame:
    """qid, rank, weight, n0.. from complete rows."""
    names = [f"n{i}" for i in range(len(cg.pattern.order))]
    if k is None:
        df = numbered(df, names)
    else:
        df = df.withColumn("rank", F.row_number().over(Window.partitionBy("qid").orderBy("bound", *names))).where(F.col("rank") <= k)
    return df.select("qid", "rank", cg.algebra.weight(F.col("bound")).alias("weight"), *names)


def topk(cg: CandidateGraph, k: int) -> DataFrame:
    """The k lightest homomorphic matches of each query, by level cuts. A level that binds a node of the query itself has
    no more rows than the one before, and is not cut again."""
    roots = open_frontier(cg)
    few = bool(cg.open) and rows_at_most(roots.select("qid").distinct(), FEW // max(k, 1))
    frontier = ranked(roots, k).drop("_r")
    for level, v in enumerate(cg.pattern.order[1:]):
        frontier = expand(cg, F.broadcast(frontier) if few else frontier, level, [])
        if not cg.pattern.nodes[v].bound:
            frontier = ranked(frontier, k).drop("_r")
    return answers(cg, frontier, k)


def precut(cg: CandidateGraph, k: int) -> CandidateGraph:
    """cg with the k lightest links of each parent only, by weight with all below, then child: enough for the k lightest
    homomorphic matches where costs add up (other algebras raise: a bound that another branch decides ties heavier links)."""
    if not cg.algebra.adds:
        raise ValueError(f"links are cut for sums only, not for {cg.algebra}")

    def lightest(v: str) -> DataFrame:
        by = Window.partitionBy(*cg.keys(cg.pattern.edge_to(v).child)).orderBy("wf", "d")
        return cg.link[v].withColumn("_r", F.row_number().over(by)).where(F.col("_r") <= k).drop("_r")

    return CandidateGraph(cg.pattern, cg.algebra, cg.reach, {v: lightest(v) for v in cg.link}, cg.node_weight, cg.injective)


def topk_iso(cg: CandidateGraph, k: int, beam: int | None = None) -> DataFrame:
    """The k lightest injective matches of each query: `topk` where no two unbound pattern nodes can be one graph node.

    Else one plan keeps `beam` partials (16 k, if not given) a query and level, each with the place of the first partial that
    was cut so far; matches before it are final. Queries that lack some go to the injective cursor. The last of a whole beam is
    the heaviest that the next levels need: successors beyond its bound are cut before they are sorted."""
    pairs = cg.pairs()
    if not pairs:
        return topk(cg, k)
    beam, depth = beam or 16 * k, len(cg.pattern.edges)
    roots = open_frontier(cg)
    few = cg.kept and rows_at_most(roots.select("qid").distinct(), FEW // beam)
    frontier = roots.withColumn("most", F.lit(None).cast("long")).withColumn("cut", F.lit(None).cast("struct<" + ",".join(["bound:bigint", *(f"n{i}:bigint" for i in range(depth + 1))]) + ">"))
    for level in range(depth + 1):
        if level:
            frontier = expand(cg, F.broadcast(frontier) if few else frontier, level - 1, pairs)
            frontier = frontier.where(F.col("most").isNull() | (F.col("bound") <= F.col("most")))
        if level and cg.pattern.nodes[cg.pattern.order[level]].bound:
            continue  # no more rows than before
        kept, each = ranked(frontier, beam + 1), Window.partitionBy("qid")
        first_cut = F.max(F.when(F.col("_r") > beam, place_of(level, depth))).over(each)
        most = F.least("most", F.max(F.when(F.col("_r") == beam, F.col("bound"))).over(each))
        kept = kept.withColumn("_first", first_cut).withColumn("most", most).where(F.col("_r") <= beam)
        beyond = F.when(F.col("most").isNotNull(), F.struct((F.col("most") + 1).alias("bound"), *[F.lit(LEAST).alias(f"n{i}") for i in range(depth + 1)]))
        frontier = kept.withColumn("cut", F.least("cut", "_first", beyond)).drop("_r", "_first")
    names = [f"n{i}" for i in range(depth + 1)]
    seen = roots.select("qid").distinct()
    both = stored(frontier.select("qid", "bound", *names, "cut").unionByName(seen, allowMissingColumns=True))
    final = both.where(F.col("n0").isNotNull() & (F.col("cut").isNull() | (place_of(depth, depth) < F.col("cut"))))
    # a query is done with k final matches, or if nothing of it was cut; one without any match kept is not known to be
    state = both.groupBy("qid").agg(F.count("n0").alias("rows"), F.max("cut").alias("cut")).join(final.groupBy("qid").agg(F.count("*").alias("have")), "qid", "left")
    short = stored(state.where((F.coalesce("have", F.lit(0)) < k) & (F.col("cut").isNotNull() | (F.col("rows") == 0))).select("qid"))
    if short.isEmpty():
        return answers(cg, final, k)
    rest = AnyK(only(cg, short), injective=True).next(k)
    return answers(cg, final.join(short, "qid", "left_anti"), k).unionByName(rest)


def place_of(level: int, depth: int) -> Column:
    """The place of a row of a level in the order of all rows; a partial stands before all its completions."""
    return F.struct("bound", *[F.col(f"n{i}") if i <= level else F.lit(LEAST).alias(f"n{i}") for i in range(depth + 1)])


def upto(cg: CandidateGraph, limits: DataFrame | int, injective: bool = False) -> DataFrame:
    """All matches whose bound is at most a limit: one number, or (qid, t). No sort until the end, no cut but the limit."""
    pairs = cg.pairs() if injective else []
    frontier = open_frontier(cg)

    def within(df: DataFrame) -> DataFrame:
        if isinstance(limits, int):
            return df.where(F.col("bound") <= limits)
        return df.join(limits.select("qid", "t"), "qid").where(F.col("bound") <= F.col("t")).drop("t")

    frontier = within(frontier)
    for level in range(len(cg.pattern.edges)):
        frontier = within(expand(cg, frontier, level, pairs))
    return answers(cg, frontier, None)


def with_iso(pattern: TreePattern, matches: DataFrame) -> DataFrame:
    """matches with is_iso: no graph node serves two pattern nodes."""
    names = places(matches)
    return matches.withColumn("is_iso", F.size(F.array_distinct(F.array(*names))) == len(names))


def iso_filter(pattern: TreePattern, matches: DataFrame) -> DataFrame:
    """Injective matches only; checks just the pairs that could coincide."""
    for i, j in pattern.overlapping_pairs():
        matches = matches.where(F.col(f"n{i}") != F.col(f"n{j}"))
    return matches


def distinct_subgraphs(pattern: TreePattern, matches: DataFrame) -> DataFrame:
    """qid, weight, edges: matches that use the same set of graph edges collapse to one."""
    pairs = [F.concat_ws("-", F.least(f"n{pattern.place(e.parent)}", f"n{pattern.place(e.child)}"), F.greatest(f"n{pattern.place(e.parent)}", f"n{pattern.place(e.child)}")) for e in pattern.edges]
    return matches.select("qid", F.array_join(F.array_sort(F.array_distinct(F.array(*pairs))), " ").alias("edges"), "weight").groupBy("qid", "edges").agg(F.min("weight").alias("weight"))


class AnyK:
    """A cursor over the ranked matches of a batch of queries: each call is exact and complete, and goes on where the last
    one stopped, however calls are mixed. Cut partials wait in the deferred frontier, one stored table for each level; the
    last level holds complete matches that were found but not given out yet."""

    def __init__(self, cg: CandidateGraph, injective: bool = False):
        self.cg, self.pairs = cg if cg.kept else fixed(cg), cg.pairs() if injective else []
        self.depth = len(cg.pattern.edges)
        self.deferred: list[DataFrame | None] = [open_frontier(self.cg)] + [None] * self.depth
        self.given: DataFrame | None = None  # qid, given: matches given out so far
        self.begun = False

    def place(self, level: int) -> Column:
        return place_of(level, self.depth)

    def descend(self, keep: Callable[[DataFrame], DataFrame]) -> None:
        """Expand what `keep` keeps of each level; the rest waits."""
        kept = None
        for level in range(self.depth + 1):
            rows, waiting = None if kept is None else expand(self.cg, kept, level - 1, self.pairs), self.deferred[level]
            if waiting is not None:
                rows = waiting if rows is None else rows.unionByName(waiting)
            if level == self.depth:
                self.deferred[level], self.begun = stored(rows), True
                return
            if level or self.begun:  # the roots are stored already
                rows = stored(rows)
            kept = stored(keep(rows).select(rows.columns))
            self.deferred[level] = self.after(rows, kept, level)

    def after(self, rows: DataFrame, kept: DataFrame, level: int) -> DataFrame:
        """The rows that come after the kept ones of their query."""
        last = kept.groupBy("qid").agg(F.max(self.place(level)).alias("_last"))
        return rows.join(last, "qid", "left").where(F.col("_last").isNull() | (self.place(level) > F.col("_last"))).drop("_last")

    def first_waiting(self) -> DataFrame:
        """qid, cut: the place of the first partial that waits."""
        parts = [df.groupBy("qid").agg(F.min(self.place(level)).alias("cut")) for level, df in enumerate(self.deferred[:-1]) if df is not None]
        return reduce(DataFrame.unionByName, parts).groupBy("qid").agg(F.min("cut").alias("cut"))

    def next(self, n: int, max_rounds: int = 40) -> DataFrame:
        """The next n matches of each query, ranks counted on."""
        asked, beam = None, n * 16 if self.pairs else n
        for _ in range(max_rounds):
            mine = asked
            self.descend(lambda rows: ranked(rows if mine is None else rows.join(mine, "qid", "left_semi"), beam))
            if not self.pairs:
                final = self.deferred[-1]
                break
            ready = self.deferred[-1].join(cut := stored(self.first_waiting()), "qid", "left")
            final = ready.where(F.col("cut").isNull() | (self.place(self.depth) < F.col("cut"))).drop("cut")
            have = final.groupBy("qid").agg(F.count("*").alias("have"))
            asked = stored(cut.join(have, "qid", "left").where(F.coalesce("have", F.lit(0)) < n).select("qid"))
            if asked.isEmpty():
                break
            beam *= 4
        else:
            raise RuntimeError("injective search did not certify its answers")
        return self.give(ranked(final, n))

    def give(self, rows: DataFrame) -> DataFrame:
        """rows with _r, complete and final, as answers; the others stay ready."""
        page = stored(rows)
        self.deferred[-1] = self.after(self.deferred[-1], page.drop("_r"), self.depth)
        names = [f"n{i}" for i in range(self.depth + 1)]
        before = F.lit(0)
        if self.given is not None:
            page, before = page.join(self.given, "qid", "left"), F.coalesce("given", F.lit(0))
        page = page.withColumn("rank", (F.col("_r") + before).cast("int"))
        now = page.groupBy("qid").agg(F.max("rank").alias("given"))
        self.given = stored(now if self.given is None else now.unionByName(self.given).groupBy("qid").agg(F.max("given").alias("given")))
        return page.select("qid", "rank", self.cg.algebra.weight(F.col("bound")).alias("weight"), *names)

    def until(self, weight: int | None) -> DataFrame:
        """All further matches up to this weight (for heaviest-first orders: down to it; None: whatever is left)."""
        within = F.lit(True) if weight is None else F.col("bound") <= weight * self.cg.algebra.sign
        self.descend(lambda rows: rows.where(within))
        found = numbered(self.deferred[-1].where(within), [f"n{i}" for i in range(self.depth + 1)])
        return self.give(found.withColumnRenamed("rank", "_r"))

    def all(self) -> DataFrame:
        """Everything that is left, by one join chain without cuts."""
        return self.until(None)

    def for_time(self, seconds: float, page: int = 1) -> DataFrame:
        """Pages of doubling size until the time is over; what is returned is a certified prefix for every query."""
        end, out = time.monotonic() + seconds, None
        while out is None or (time.monotonic() < end and not self.exhausted()):
            rows = self.next(page)
            out, page = rows if out is None else out.union(rows), page * 2
        return out

    def exhausted(self) -> bool:
        return all(d is None or d.isEmpty() for d in self.deferred)

    def __iter__(self):
        """Rows of a single query, one after another, in pages of doubling size. Rows of a page that are not taken go back."""
        page = 1
        while True:
            rows = self.next(page).orderBy("rank").collect()  # at most one page
            at = 0
            try:
                for at, row in enumerate(rows, 1):
                    yield row
            finally:
                self.put_back(rows[at:])
            if len(rows) < page:
                return
            page = min(page * 2, 4096)

    def put_back(self, rows: list) -> None:
        """Rows that were given out last, of one query, are ready again."""
        if rows:
            spark, ready = self.cg.reach[self.cg.pattern.root].sparkSession, self.deferred[-1]
            sign, names = self.cg.algebra.sign, [f"n{i}" for i in range(self.depth + 1)]
            table = [(r["qid"], *(r[x] for x in names), r["weight"] * sign, r["weight"] * sign) for r in rows]
            back = spark.createDataFrame(table, "qid int, " + ", ".join(f"{x} long" for x in names) + ", spent long, bound long")
            self.deferred[-1] = stored(ready.unionByName(back.select(ready.columns)))
            self.given = stored(self.given.withColumn("given", F.when(F.col("qid") == rows[0]["qid"], F.lit(rows[0]["rank"] - 1)).otherwise(F.col("given"))))

    def close(self) -> None:
        self.deferred = [None] * len(self.deferred)
