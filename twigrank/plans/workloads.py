"""Graphs, templates, terminal assignments and the experiments over them.

Template shapes are our own stand-ins: two paths, a star, a fork and a two-branch tree with three terminals, with distinct
and with repeated types. Each has a batch of queries that bind its starred nodes by whole-number formulas of the query's
number q, which SQL rebuilds.
"""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import lru_cache, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from twigrank.model import Algebra, TreePattern, parse_pattern
from twigrank.operators import baselines, kernel, search
from twigrank.operators.index import BROADCAST_IDS, GraphIndex, build_index
from twigrank.operators.shared import SharedRows, share
from twigrank.operators.sweep import CandidateGraph, alike, count_matches, spread, sweep_up, unbound_pairs
from twigrank.plans import sqlgen
from twigrank.plans.storage import stored
from twigrank.sources import graphs
from twigrank.sources.graphs import BASE, CODES

BATCH = 300

TEMPLATES: dict[str, dict[str, str]] = {
    "trade4": {
        "T1": "(o:order)-(c:customer*), (o)-(p:part)-(s:supplier*)",
        "T2": "(o:order)-(p:part)-(s:supplier*), (o)-(p2:part)-(s2:supplier*)",
        "T3": "(p:part)-(s:supplier*), (p)-(s2:supplier*), (p)-(s3:supplier*)",
        "T4": "(p:part)-(s:supplier*), (p)-(s2:supplier*), (p)-(o:order)-(c:customer*)",
        "T5": "(o:order)-(p:part)-(s:supplier*), (p)-(s2:supplier*), (o)-(p2:part)-(s3:supplier*)",
    },
    "trade3": {
        "T1": "(o:order)-(c:customer*), (o)-(p:part*)",
        "T2": "(p:part)-(o:order)-(c:customer*), (p)-(o2:order)-(c2:customer*)",
        "T3": "(o:order)-(c:customer*), (o)-(p:part*), (o)-(p2:part)",
        "T4": "(p:part)-(o:order)-(c:customer*), (p)-(o2:order)-(c2:customer*), (p)-(o3:order)",
        "T5": "(p:part)-(o:order)-(c:customer*), (o)-(p2:part*), (p)-(o2:order)-(c2:customer*)",
    },
    "activity": {
        "T1": "(u:user)-(d:day*), (u)-(k:k)-(e:etype*)",
        "T2": "(d:day)-(u:user)-(k:k*), (d)-(u2:user)-(k2:k*)",
        "T3": "(u:user)-(k:k*), (u)-(k2:k*), (u)-(d:day*)",
        "T4": "(u:user)-(d:day*), (u)-(d2:day*), (u)-(k:k)-(e:etype*)",
        "T5": "(d:day)-(u:user)-(k:k*), (u)-(e:etype*), (d)-(u2:user)-(k2:k*)",
    },
    "sparse6": {
        "T1": "(o:order)-(c:customer)-(n:nation*), (o)-(p:part*)",
        "T2": "(p:part)-(o:order)-(c:customer*), (p)-(o2:order)-(c2:customer*)",
        "T3": "(c:customer)-(n:nation*), (c)-(o:order*), (c)-(o2:order*)",
        "T4": "(o:order)-(c:customer*), (o)-(p:part)-(s:supplier*), (p)-(o2:order*)",
        "T5": "(c:customer)-(o:order)-(p:part*), (c)-(o2:order)-(p2:part*), (c)-(n:nation*)",
    },
    "docs": {"T3": "(d:doc)-(l:lang*), (d)-(s:source*), (d)-(y:quality*)"},
    "talk": {"path": "(a:turn)-(b:turn)-(c:turn)-(d:turn), (a)-(r:role*)"},
    "web": {"path": "(t:target)-(p:page)-(h:host*), (t)-(p2:page)-(h2:host*)"},
    "knn": {"T2": "(m:vec)-(a:vec)-(x:vec*), (m)-(b:vec)-(y:vec*)"},
}


#: For each graph the rank, among the nodes of its type in id order, of the node that query q binds to a pattern node.
FORMULAS: dict[str, dict[str, str]] = {
    "trade4": {"s": "7 * q", "s2": "11 * q + 1", "s3": "13 * q + 2", "c": "17 * q"},
    "activity": {"k": "7 * q", "k2": "11 * q + 1", "d": "13 * q", "d2": "17 * q + 3", "e": "q"},
    "docs": {"l": "q", "s": "3 * q", "y": "q + 1"},
    "talk": {"r": "q"},
    "web": {"h": "3 * q", "h2": "5 * q + 1"},
    "knn": {"x": "q", "y": "7 * q + 3"},
}
#: Graphs whose terminals lie around an anchor instead, since queries of unrelated ones have hardly a match.
ANCHORED = ("trade3", "sparse6")
BUILDERS: dict[str, Callable[[SparkSession, str], graphs.LabeledGraph]] = {
    "trade4": graphs.trade,
    "trade3": lambda s, d: graphs.trade(s, d, 3),
    "flags": lambda s, d: graphs.trade(s, d, 4, flags=True),
    "sparse6": graphs.sparse6,
    "activity": graphs.activity,
    "docs": graphs.docs,
    "talk": graphs.talk,
    "web": graphs.web,
    "knn": graphs.knn,
}


def pattern(graph: str, template: str) -> TreePattern:
    return parse_pattern(TEMPLATES[graph][template])


def bindings_sql(graph: str, p: TreePattern, size: int, dialect: str) -> str:
    """qid, pnode, node_id: the terminals of queries 0 .. size-1."""
    numbers = f"(SELECT {'range' if dialect == 'duckdb' else 'id'} AS q FROM range({size}))"
    bound = [n for n in p.order if p.nodes[n].bound]
    if graph in ANCHORED:
        return anchored_bindings(graph, p, bound, numbers)
    parts = []
    for n in bound:
        t, f = p.nodes[n].ntype, FORMULAS[graph][n]
        ranks = f"(SELECT x, row_number() OVER (ORDER BY x) - 1 AS i, count(*) OVER () AS total FROM (SELECT DISTINCT src AS x FROM arcs WHERE src_type = '{t}') d)"
        parts.append(f"SELECT CAST(q AS BIGINT) AS qid, '{n}' AS pnode, x AS node_id FROM {numbers} z JOIN {ranks} r ON ({f}) % r.total = r.i")
    return " UNION ALL ".join(parts)


def anchored_bindings(graph: str, p: TreePattern, bound: list[str], numbers: str) -> str:
    """Terminals around an anchor order (the one of rank 50 q), so that a match exists for nearly every query: its customer,
    its first and last part, the customer of that part's last order, and for the sparse graph nation, supplier and others."""
    o0 = CODES["order"] * BASE

    def near(t: str, name: str, frm: str, at: str) -> str:
        least = f"(SELECT src, min(dst) AS lo, max(dst) AS hi FROM arcs WHERE src_type = '{frm}' AND dst_type = '{t}' GROUP BY src) {name}"
        return f"JOIN {least} ON {name}.src = {at}"

    steps = [near("customer", "oc", "order", f"{o0} + 50 * q"), near("part", "op", "order", f"{o0} + 50 * q"), near("order", "po", "part", "op.lo"), near("customer", "c2", "order", "po.hi")]
    columns = {"c": "oc.lo", "p": "op.lo", "p2": "op.hi", "c2": "c2.lo"}
    if graph == "sparse6":
        steps += [near("nation", "cn", "customer", "oc.lo"), near("supplier", "ps", "part", "op.lo"), near("order", "co", "customer", "oc.lo"), near("part", "p2", "order", "co.lo")]
        o2 = "co.lo" if "".join(sorted(bound)) == "noo2" else "po.lo"
        columns |= {"n": "cn.lo", "s": "ps.lo", "o": f"{o0} + 50 * q", "p2": "p2.lo", "o2": o2}
    anchor = f"(SELECT CAST(q AS BIGINT) AS qid, {', '.join(f'{columns[n]} AS {n}_id' for n in bound)} FROM {numbers} z {' '.join(steps)}) a"
    return " UNION ALL ".join(f"SELECT qid, '{n}' AS pnode, {n}_id AS node_id FROM {anchor}" for n in bound)


class Context:
    """The index of one graph in one session and its bindings; built once, as an offline index is."""

    def __init__(self, spark: SparkSession, sf_dir: str, graph: str):
        self.spark, self.sf_dir, self.graph = spark, sf_dir, graph
        self.index: GraphIndex = build_index(BUILDERS[graph](spark, sf_dir))
        self._ranks: dict[str, tuple[DataFrame, int]] = {}
        self._bindings: dict[tuple, DataFrame] = {}
        self._alike: dict[tuple, tuple[DataFrame, DataFrame]] = {}

    def ranks(self, ntype: str) -> tuple[DataFrame, int]:
        """(x, i): the nodes of a type with their ranks in id order, and their number. The ids are range-partitioned; the
        driver sees the number of rows of each part only."""
        if ntype not in self._ranks:
            ids = self.index.arcs.where(F.col("src_type") == ntype).select(F.col("src").alias("x")).distinct()
            rows = stored(ids.repartitionByRange("x").sortWithinPartitions("x").withColumn("_at", F.monotonically_increasing_id()))
            part, place = F.shiftright("_at", 33), F.col("_at").bitwiseAND((1 << 33) - 1)
            sizes = sorted(rows.groupBy(part.alias("part")).count().collect())
            offsets = [(r["part"], sum(x["count"] for x in sizes[:k])) for k, r in enumerate(sizes)]
            offsets = self.spark.createDataFrame(offsets, "part long, offset long")
            ranked = rows.withColumn("part", part).join(F.broadcast(offsets), "part").select("x", (F.col("offset") + place).alias("i"))
            self._ranks[ntype] = ranked, sum(r["count"] for r in sizes)
        return self._ranks[ntype]

    def bindings(self, p: TreePattern, size: int) -> DataFrame:
        """qid, pnode, node_id: the terminals of queries 0 .. size-1."""
        bound = [n for n in p.order if p.nodes[n].bound]
        key = (size, *((n, p.nodes[n].ntype) for n in bound))
        if key in self._bindings:
            return self._bindings[key]
        if self.graph in ANCHORED:
            view = f"arcs_{self.graph}"
            self.index.arcs.createOrReplaceTempView(view)
            found = self.spark.sql(bindings_sql(self.graph, p, size, "spark").replace("FROM arcs ", f"FROM {view} "))
        else:
            formulas, parts = FORMULAS["trade4" if self.graph == "flags" else self.graph], []
            for n in bound:
                ranks, total = self.ranks(p.nodes[n].ntype)
                wanted = self.spark.range(size).selectExpr("id AS qid", f"({formulas[n].replace('q', 'id')}) % {max(total, 1)} AS i")
                few = F.broadcast(wanted) if size <= BROADCAST_IDS else wanted
                parts.append(ranks.join(few, "i").select("qid", F.lit(n).alias("pnode"), F.col("x").alias("node_id")))
            found = reduce(DataFrame.unionByName, parts)
        self._bindings[key] = stored(found.select(F.col("qid").cast("int").alias("qid"), "pnode", F.col("node_id").cast("long").alias("node_id")))
        return self._bindings[key]

    def alike(self, p: TreePattern, size: int) -> tuple[DataFrame, DataFrame]:
        """Bindings of the queries that differ in their terminals, and (qid, first) of all queries. The formulas repeat: of 300
        queries of activity 30 differ in T1 and T4, 100 in T2 and T5."""
        key = (size, *((n, p.nodes[n].ntype) for n in p.order if p.nodes[n].bound))
        if key not in self._alike:
            self._alike[key] = alike(self.bindings(p, size))
        return self._alike[key]

    def candidates(self, p: TreePattern, size: int, **options) -> CandidateGraph:
        if not any(n.bound for n in p.nodes.values()):
            return sweep_up(self.index, p, self.spark.createDataFrame([], "qid int, pnode string, node_id long"), **options)
        return sweep_up(self.index, p, self.bindings(p, size), **options)


@lru_cache(maxsize=64)
def _context(app: str, spark: SparkSession, sf_dir: str, graph: str) -> Context:
    return Context(spark, sf_dir, graph)


def context(spark: SparkSession, sf_dir: str, graph: str) -> Context:
    return _context(spark.sparkContext.applicationId, spark, sf_dir, graph)


def oracle(graph: str, p: TreePattern, size: int, body: str, extra: str = "") -> str:
    """WITH graph, bindings and what else body needs."""
    parts = [sqlgen.GRAPHS[graph]()]
    if any(n.bound for n in p.nodes.values()):
        parts.append(f"bindings AS ({bindings_sql('trade4' if graph == 'flags' else graph, p, size, 'duckdb')})")
    if extra:
        parts.append(extra)
    return f"WITH {', '.join(parts)} {body}"


METHODS = ("guided", "kernel", "bulk", "spine")


def run(ctx: Context, p: TreePattern, size: int, k: int, method: str, injective: bool = True) -> DataFrame:
    """The k lightest matches of queries 0 .. size-1. Queries with equal terminals are solved once."""
    if method == "guided" and not any(n.bound for n in p.nodes.values()):  # one query
        cg = ctx.candidates(p, size, injective=injective)
        return search.topk_iso(cg, k) if injective else search.topk(cg, k)
    own, members = ctx.alike(p, size)
    if method == "spine":
        return spread(baselines.spine(ctx.index, p, own, k, injective), members)
    shared = share(ctx.index, p, own, kernel.KERNEL_ROWS) if method in ("bulk", "kernel") else None
    if shared:
        find = baselines.bulk if method == "bulk" else kernel.run
        return spread(find(unswept(p, injective), k, injective=injective, rows=shared.candidates(injective)), members)
    cg = sweep_up(ctx.index, p, own, injective=injective, keep=method == "bulk")  # its candidate rows read each link table twice
    if method == "bulk":
        return spread(baselines.bulk(cg, k, injective), members)
    if method == "kernel":
        return spread(kernel.run(cg, k, injective=injective), members)
    return spread(search.topk_iso(cg, k) if injective else search.topk(cg, k), members)


def unswept(p: TreePattern, injective: bool) -> CandidateGraph:
    """What a search on shared rows, which are reduced in its tasks, has to know of the pattern."""
    return CandidateGraph(p, Algebra.SUM, {}, {}, injective=injective)


COUNTED = ("max_nodes", "total_nodes", "max_partials", "total_partials", "pops", "pushes")


def counted_search(cg: CandidateGraph, k: int | None, method: str, rows: DataFrame | SharedRows) -> DataFrame | None:
    """qid, results and counters of each query's search for the k lightest matches; None for the guided frame search, which
    has none."""
    if method == "bulk":
        return kernel.bulk_counters(cg, k, rows=rows)
    if method == "spine" and 0 < (k or 0) <= baselines.MANY and len(cg.pattern.order) > 1:
        return kernel.spine_counters(cg.pattern, k, rows)
    return None if method == "guided" else kernel.counters(cg, k, {"kernel": "guided"}.get(method, method), rows=rows)


def experiment(spark: SparkSession, sf_dir: str, grid: list[tuple[str, str]], ks: tuple[int | None, ...] = (5,), methods: tuple[str, ...] = METHODS, size: int | None = None, counted: bool = True) -> DataFrame:
    """Times of the sweep (links stored, or reach only where the guided search cuts each level; for queue search and enumeration the down-sweep as well), of the search over stored links, and their sum, with the answers and, if `counted`,
    the mean counters of the queue kernels: a row for each graph, template, method and k. Times are those of a whole batch, of
    which queries with equal terminals are solved once; results and means are over all its queries. What is counted is the
    search that is timed: each method but the guided frame search runs once, and its time includes the counting. Methods on
    shared rows sweep in the tasks that search: their sweep time is that of storing these rows, the rest is search."""
    rows = []
    for graph, template in grid:
        ctx, p = context(spark, sf_dir, graph), pattern(graph, template)
        n = size or BATCH
        own, members = ctx.alike(p, n)
        t0 = time.perf_counter()
        shared = share(ctx.index, p, own, kernel.KERNEL_ROWS)
        links = shared.candidates(True) if shared else None
        down_ms = (time.perf_counter() - t0) * 1e3
        t0 = time.perf_counter()
        lean = shared is not None and counted and None not in ks and not unbound_pairs(p)
        cg = sweep_up(ctx.index, p, own, injective=True, keep=not lean, lean=lean)
        sweep_ms = (time.perf_counter() - t0) * 1e3
        if not shared:
            t0 = time.perf_counter()
            links = stored(kernel.candidate_rows(cg))  # for both queue search and enumeration
            down_ms += (time.perf_counter() - t0) * 1e3
        before = {"guided": sweep_ms, "spine": down_ms if shared else 0.0}
        for k in ks:
            for method in methods:
                t0 = time.perf_counter()
                paths = None if method != "spine" else shared.paths() if shared else stored(kernel.spine_rows(ctx.index, p, own))
                each = counted_search(cg, k, method, links if paths is None else paths) if counted else None
                if each is not None:
                    c = spread(each, members).agg(F.sum("results").alias("found"), *[F.avg(x).alias(x) for x in COUNTED]).first()
                    found = c["found"] or 0
                else:
                    if method == "spine":
                        out = baselines.spine(ctx.index, p, own, k or 1 << 30, known_k=k is not None, rows=paths)
                    elif method == "bulk":
                        out = baselines.bulk(cg, k, rows=links)
                    elif method == "kernel":
                        out = kernel.run(cg, k, rows=links)
                    else:
                        out = search.topk_iso(cg, k) if k else search.upto(cg, 1 << 60, injective=True)
                    found = spread(out, members).count()
                ms = (time.perf_counter() - t0) * 1e3
                row = {"graph": graph, "template": template, "method": method, "k": k, "queries": n, "sweep_ms": before.get(method, down_ms if shared else sweep_ms + down_ms), "search_ms": ms, "results": found}
                rows.append(row if each is None else row | {x: c[x] for x in COUNTED})
    names = ["graph", "template", "method", "k", "queries", "sweep_ms", "search_ms", "results", *COUNTED]
    kinds = "graph string, template string, method string, k int, queries int, sweep_ms double, search_ms double, results long, " + ", ".join(f"{x} double" for x in COUNTED)
    return spark.createDataFrame([tuple(r.get(x) for x in names) for r in rows], kinds).withColumn("total_ms", F.col("sweep_ms") + F.col("search_ms"))


def easy_and_hard(cg: CandidateGraph) -> DataFrame:
    """Queries by number of homomorphic matches: 1-2, 3-99, 100 and more (queries without a match have no row)."""
    n = F.col("n")
    return count_matches(cg).select(F.when(n <= 2, "1-2").when(n < 100, "3-99").otherwise("100+").alias("bucket"), n).groupBy("bucket").agg(F.count("*").alias("queries"), F.sum("n").cast("long").alias("matches"))


def iso_curve(p: TreePattern, matches: DataFrame) -> DataFrame:
    """rank, hom and iso: matches among the first `rank`, and the injective ones of them, for each query."""
    from pyspark.sql import Window

    rows = search.with_iso(p, matches)
    to_here = Window.partitionBy("qid").orderBy("rank").rowsBetween(Window.unboundedPreceding, 0)
    return rows.select("qid", "rank", F.sum(F.col("is_iso").cast("long")).over(to_here).alias("iso"))

