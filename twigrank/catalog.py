"""All queries by name, each over the whole given tables, with SQL twins for DuckDB."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from twigrank.model import Algebra, TreePattern, parse_pattern
from twigrank.functions import relational
from twigrank.operators import baselines, index, kernel, metrics, search, sweep
from twigrank.plans import sqlgen, workloads
from twigrank.plans.workloads import context, oracle, pattern
from twigrank.sources import graphs
from twigrank.streaming import streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def add(name: str, query: Query, sql: str | None = None) -> None:
    def whole(spark: SparkSession, sf_dir: str) -> DataFrame:
        df = query(spark, sf_dir)
        # whole numbers are all BIGINT, as in the twins
        return df.select([F.col(f.name).cast("long").alias(f.name) if isinstance(f.dataType, (T.IntegerType, T.ShortType, T.ByteType)) else F.col(f.name) for f in df.schema])

    QUERIES[name] = whole
    if sql:
        ORACLES[name] = sql


def ranking(name: str, graph: str, p: TreePattern, size: int, k: int | None, method: str = "guided", injective: bool = True, algebra: Algebra = Algebra.SUM, node_weight: bool = False, first: int = 0, make: Callable | None = None, twin: bool = True) -> None:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        ctx = context(spark, sf_dir, graph)
        if make:
            return make(ctx)
        if algebra is not Algebra.SUM or node_weight:
            cg = ctx.candidates(p, size, algebra=algebra, node_weight=node_weight, injective=injective)
            return search.topk_iso(cg, k) if injective else search.topk(cg, k)
        return workloads.run(ctx, p, size, k, method, injective)

    body = sqlgen.top(p, k, algebra, injective, node_weight, first)
    needs_nodes = node_weight or any(n.labels_all or n.labels_any for n in p.nodes.values())
    add(name, query, oracle(graph, p, size, body, sqlgen.nodes() if needs_nodes else "") if twin else None)


TRADE = {t: pattern("trade4", t) for t in workloads.TEMPLATES["trade4"]}
N = workloads.BATCH

# ---- the graphs and the index
for g in ("trade4", "activity", "sparse6", "docs", "talk", "web"):
    add(f"graph_{g}_edges", lambda s, d, g=g: context(s, d, g).index.arcs.where("dir = 1").select("src", "dst", "src_type", "dst_type", "elabel", "w"), f"WITH {sqlgen.GRAPHS[g]()} SELECT src, dst, src_type, dst_type, elabel, w FROM arcs WHERE dir = 1")
    add(f"graph_stats_{g}", lambda s, d, g=g: metrics.graph_stats(context(s, d, g).index.arcs), f"WITH {sqlgen.GRAPHS[g]()} SELECT (SELECT count(DISTINCT src) FROM arcs) AS nodes, (SELECT count(*) FROM edges) AS edges, (SELECT count(DISTINCT src_type) FROM arcs) AS labels, (SELECT count(*) * 1000 FROM edges) // (SELECT count(DISTINCT src) FROM arcs) AS density_milli")
add("graph_knn_edges", lambda s, d: context(s, d, "knn").index.arcs.where("dir = 1").select("src", "dst", "w"))
add("density_by_label_pair", lambda s, d: metrics.label_pairs(context(s, d, "trade4").index.arcs), f"WITH {sqlgen.trade()} SELECT src_type, dst_type, count(*) AS arcs, sum(w)::BIGINT AS total_w FROM arcs GROUP BY ALL")
add("degree_by_label", lambda s, d: metrics.degrees(context(s, d, "trade4").index.arcs), f"WITH {sqlgen.trade()}, deg AS (SELECT src, src_type, dst_type, count(*) AS n FROM arcs GROUP BY ALL) SELECT src_type, dst_type, max(n) AS max_degree, min(n) AS min_degree, count(*) AS nodes FROM deg GROUP BY ALL")


def _some_ids(spark: SparkSession) -> DataFrame:
    return spark.range(20).select((F.col("id") * 37 + 3 * graphs.BASE).alias("node_id"))


for label in ("supplier", None):
    add(f"neighbors_lookup_{label or 'any'}", lambda s, d, label=label: context(s, d, "trade4").index.neighbors(_some_ids(s), label), f"WITH {sqlgen.trade()} SELECT src AS node_id, dst AS neighbor, w FROM arcs WHERE src IN (SELECT range * 37 + {3 * graphs.BASE} FROM range(20))" + (f" AND dst_type = '{label}'" if label else ""))


def _delta(spark: SparkSession, sf_dir: str) -> DataFrame:
    arcs = context(spark, sf_dir, "trade4").index.arcs.where("src_type = 'customer' and dst_type = 'order'")
    orders = graphs.read(spark, sf_dir, "orders").select(graphs.node("customer", F.col("o_custkey")).alias("src"), graphs.node("order", F.col("o_orderkey")).alias("dst"), "o_orderstatus")
    gone = orders.where("o_orderstatus = 'F'")
    fresh = orders.where("o_orderstatus <> 'F'").select("src", "dst", F.lit("customer").alias("src_type"), F.lit("order").alias("dst_type"), F.lit("customer-order").alias("elabel"), F.lit(1).alias("dir"), F.lit(500_000).cast("long").alias("w"))
    return index.updated(index.GraphIndex(arcs), fresh, gone).arcs.drop("dir")


add("index_delta", _delta, f"WITH {sqlgen.trade()}, o AS (SELECT {sqlgen.node('customer', 'o_custkey')} AS src, {sqlgen.node('order', 'o_orderkey')} AS dst, o_orderstatus AS st FROM orders), l AS (SELECT a.src, a.dst, w FROM arcs a WHERE src_type = 'customer' AND dst_type = 'order' AND NOT EXISTS (SELECT 1 FROM o WHERE o.src = a.src AND o.dst = a.dst AND st = 'F') UNION ALL SELECT src, dst, 500000 FROM o WHERE st <> 'F') SELECT src, dst, 'customer' AS src_type, 'order' AS dst_type, 'customer-order' AS elabel, min(w)::BIGINT AS w FROM l GROUP BY src, dst")
add("weight_decay", lambda s, d: graphs.read(s, d, "orders").select("o_orderkey", graphs.decay(F.col("o_orderdate"), graphs.TRADE_DAY, graphs.TRADE_TAU).alias("w")), f"SELECT o_orderkey, {sqlgen.decay('o_orderdate')} AS w FROM orders")
for kind in ("members", "activity"):
    expr = "a.deg + b.deg" if kind == "members" else "a.deg"
    add(f"weight_{kind}", lambda s, d, kind=kind: graphs.weight_by(context(s, d, "trade4").index, kind).select("src", "dst", "w"), f"WITH {sqlgen.trade()}, g AS (SELECT src, count(*) AS deg FROM arcs GROUP BY src) SELECT x.src, x.dst, {expr} AS w FROM arcs x JOIN g a ON a.src = x.src JOIN g b ON b.src = x.dst")
_rank_sql = "r0 AS (SELECT src AS node, 1000000000::BIGINT AS rank FROM g)" + "".join(f", r{i} AS (SELECT x.dst AS node, (sum(floor(r.rank * 85 / 100 / g.deg)::BIGINT) + 150000000)::BIGINT AS rank FROM arcs x JOIN g ON g.src = x.src JOIN r{i - 1} r ON r.node = x.src GROUP BY x.dst)" for i in range(1, 6))
add("weight_pagerank", lambda s, d: graphs.pagerank(context(s, d, "trade4").index.arcs), f"WITH {sqlgen.trade()}, g AS (SELECT src, count(*) AS deg FROM arcs GROUP BY src), {_rank_sql} SELECT node, rank FROM r5")

# ---- the reduction
T5 = TRADE["T5"]


def _cg(s: SparkSession, d: str, t: str = "T5", **options) -> sweep.CandidateGraph:
    return context(s, d, "trade4").candidates(TRADE[t], N, **options)


_arcs = lambda a, b: f"(SELECT src, dst, w FROM arcs WHERE src_type = '{a}' AND dst_type = '{b}')"
_T5 = f"""l AS (SELECT b.qid, b.pnode, a.dst AS c, b.node_id AS d, w FROM bindings b JOIN {_arcs('supplier', 'part')} a ON a.src = b.node_id),
m AS (SELECT qid, pnode, c, min(w) AS m FROM l GROUP BY ALL),
p1 AS (SELECT x.qid, x.c, x.m AS m_s, y.m AS m_s2, x.m + y.m AS floor FROM m x JOIN m y USING (qid, c) WHERE x.pnode = 's' AND y.pnode = 's2'),
p2 AS (SELECT qid, c, m AS m_s3, m AS floor FROM m WHERE pnode = 's3'),
lo AS (SELECT qid, 'p' AS pnode, a.dst AS c, p1.c AS d, a.w, a.w + floor AS wf FROM p1 JOIN {_arcs('part', 'order')} a ON a.src = p1.c UNION ALL SELECT qid, 'p2', a.dst, p2.c, a.w, a.w + floor FROM p2 JOIN {_arcs('part', 'order')} a ON a.src = p2.c),
mo AS (SELECT qid, pnode, c, min(wf) AS m FROM lo GROUP BY ALL),
root AS (SELECT x.qid, x.c, x.m AS m_p, y.m AS m_p2, x.m + y.m AS floor FROM mo x JOIN mo y USING (qid, c) WHERE x.pnode = 'p' AND y.pnode = 'p2')"""
add("sweep_leaf_seed", lambda s, d: sweep.seed(context(s, d, "trade4").index, T5, "s", context(s, d, "trade4").bindings(T5, N)), oracle("trade4", T5, N, "SELECT qid, node_id AS c FROM bindings WHERE pnode = 's'"))
add("sweep_links_T5", lambda s, d: _cg(s, d).link["p"].select("qid", "c", "d", "w", "wf"), oracle("trade4", T5, N, "SELECT qid, c, d, w, wf FROM lo WHERE pnode = 'p'", _T5))
add("sweep_floor_T5", lambda s, d: _cg(s, d).reach["p"].select("qid", "c", "m_s", "m_s2", "floor"), oracle("trade4", T5, N, "SELECT qid, c, m_s, m_s2, floor FROM p1", _T5))
add("sweep_reach_T5", lambda s, d: _cg(s, d).reach["o"].select("qid", "c", "m_p", "m_p2", "floor"), oracle("trade4", T5, N, "SELECT qid, c, m_p, m_p2, floor FROM root", _T5))
add("sweep_down_T5", lambda s, d: sweep.sweep_down(_cg(s, d)).reach["p"].select("qid", "c", "floor"), oracle("trade4", T5, N, "SELECT qid, c, floor FROM p1 WHERE (qid, c) IN (SELECT lo.qid, lo.d FROM lo JOIN root ON lo.qid = root.qid AND lo.c = root.c WHERE pnode = 'p')", _T5))
_after = lambda t, l: f"(SELECT count(*) FROM {t} WHERE (qid, c) IN (SELECT lo.qid, lo.d FROM lo JOIN root ON lo.qid = root.qid AND lo.c = root.c WHERE pnode = '{l}'))"
add("spurious_T5", lambda s, d: metrics.spurious(_cg(s, d)).where("pnode in ('o', 'p', 'p2')"), oracle("trade4", T5, N, f"SELECT 'o' AS pnode, count(*) AS after_up, count(*) AS after_down FROM root UNION ALL SELECT 'p', (SELECT count(*) FROM p1), {_after('p1', 'p')} UNION ALL SELECT 'p2', (SELECT count(*) FROM p2), {_after('p2', 'p2')}", _T5))
for t, p in TRADE.items():
    add(f"count_matches_{t}", lambda s, d, t=t: sweep.count_matches(_cg(s, d, t)).withColumn("n", F.col("n").cast("long")), oracle("trade4", p, N, f"SELECT qid, count(*) AS n FROM ({sqlgen.tree_join(p, injective=False)}) GROUP BY qid"))
add("rk_buckets_T5", lambda s, d: workloads.easy_and_hard(_cg(s, d)), oracle("trade4", T5, N, f"SELECT CASE WHEN n <= 2 THEN '1-2' WHEN n < 100 THEN '3-99' ELSE '100+' END AS bucket, count(*) AS queries, sum(n)::BIGINT AS matches FROM (SELECT qid, count(*) AS n FROM ({sqlgen.tree_join(T5, injective=False)}) GROUP BY qid) GROUP BY 1"))

# ---- the methods on the main graph
for t, p in TRADE.items():
    for method in ("guided", "bulk", "spine", "kernel"):
        ranking(f"{method}_{t}_k5", "trade4", p, N, 5, method)
    ranking(f"batch300_{t}", "trade4", p, N, 1)
    add(f"naive_{t}_k5", lambda s, d, p=p: _naive(s, d, p, N), oracle("trade4", p, N, sqlgen.top(p, 5)))
ranking("guided_hom_T2_k5", "trade4", TRADE["T2"], N, 5, injective=False)
ranking("guided_hom_T5_k5", "trade4", T5, N, 5, injective=False)
ranking("bulk_all_T3", "trade4", TRADE["T3"], N, None, make=lambda ctx: baselines.bulk(ctx.candidates(TRADE["T3"], N), None))
ranking("spine_nok_T4", "trade4", TRADE["T4"], N, 5, make=lambda ctx: baselines.spine(ctx.index, TRADE["T4"], ctx.bindings(TRADE["T4"], N), 5, known_k=False))
ranking("kernel_plain_T3_k5", "trade4", TRADE["T3"], N, 5, make=lambda ctx: kernel.run(ctx.candidates(TRADE["T3"], N), 5, in_hand=False))
ranking("kernel_bulk_T3_k5", "trade4", TRADE["T3"], N, 5, make=lambda ctx: kernel.run(ctx.candidates(TRADE["T3"], N), 5, method="bulk"))
for k in (1, 10, 100, 1000):
    ranking(f"guided_hom_T5_k{k}", "trade4", T5, N, k, injective=False)


def _naive(spark: SparkSession, sf_dir: str, p: TreePattern, size: int) -> DataFrame:
    ctx = context(spark, sf_dir, "trade4")
    ctx.index.arcs.createOrReplaceTempView("arcs_naive")
    ctx.bindings(p, size).createOrReplaceTempView("bindings_naive")
    return baselines.naive(spark, sqlgen.top(p, 5).replace(" arcs e", " arcs_naive e").replace(" bindings b_", " bindings_naive b_"))


def _page2(ctx) -> DataFrame:
    cursor = search.AnyK(ctx.candidates(T5, N))
    cursor.next(5)
    return cursor.next(5)


ranking("page2_T5", "trade4", T5, N, 5, injective=False, first=5, make=_page2)


def _upto(spark: SparkSession, sf_dir: str) -> DataFrame:
    cg = sweep.fixed(_cg(spark, sf_dir))
    best = search.topk(cg, 1).select("qid", F.floor(F.col("weight") * 11 / 10).cast("long").alias("t"))
    return search.upto(cg, best)


add("upto_T5", _upto, oracle("trade4", T5, N, "SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY cost, n0, n1, n2, n3, n4, n5) AS rank, cost AS weight, n0, n1, n2, n3, n4, n5 FROM (SELECT *, min(cost) OVER (PARTITION BY qid) AS low FROM m) WHERE cost <= floor(low * 11 / 10)", f"m AS ({sqlgen.tree_join(T5, injective=False)})"))


ranking("precut_T5_k5", "trade4", T5, N, 5, injective=False, make=lambda ctx: search.topk(search.precut(ctx.candidates(T5, N), 5), 5))


def _cursor(template: str, work: Callable[[search.AnyK], DataFrame]) -> Callable:
    def make(ctx) -> DataFrame:
        p = TRADE[template]
        return work(search.AnyK(ctx.candidates(p, N, injective=True, keep=True), injective=True))

    return make


def _second_page(cursor: search.AnyK) -> DataFrame:
    cursor.next(5)
    return cursor.next(5)


def _after_five(cursor: search.AnyK) -> DataFrame:
    return cursor.next(5).unionByName(cursor.all())


def _digest(rows: DataFrame) -> DataFrame:
    """Millions of ranked rows as a row for each query that tells their number, weights and order."""
    weighed = F.sum(F.col("rank").cast("long") * F.col("weight"))
    return rows.groupBy("qid").agg(F.count("*").alias("matches"), F.sum("weight").alias("total"), weighed.alias("by_rank"))


def _digest_sql(rows: str) -> str:
    return f"SELECT qid, count(*) AS matches, sum(weight)::BIGINT AS total, sum(rank * weight)::BIGINT AS by_rank FROM ({rows}) GROUP BY qid"


for t, limit in (("T2", 8_000), ("T5", 14_000)):
    cheap = f"SELECT * FROM ({sqlgen.top(TRADE[t], None)}) WHERE weight <= {limit}"
    ranking(f"page2_iso_{t}", "trade4", TRADE[t], N, 5, first=5, make=_cursor(t, _second_page))
    add(f"all_{t}", lambda s, d, t=t: _digest(_cursor(t, _after_five)(context(s, d, "trade4"))), oracle("trade4", TRADE[t], N, _digest_sql(sqlgen.top(TRADE[t], None))))
    add(f"until_{t}", lambda s, d, t=t, limit=limit: _cursor(t, lambda cursor: cursor.until(limit))(context(s, d, "trade4")), oracle("trade4", TRADE[t], N, cheap))


# the worked example: two answers of six nodes
PHOTO = parse_pattern("(u3:user)-(g1:group)-(u1:user*), (g1)-(ph:photo*), (u3)-(g2:group)-(u2:user*)")
#: Its edges as (a, type, b, type, weight): fixed values of the example.
PHOTO_EDGES = [
    (5, "user", 2, "group", 2), (5, "user", 3, "group", 4), (2, "group", 8, "user", 2), (2, "group", 9, "photo", 1),
    (3, "group", 8, "user", 2), (3, "group", 9, "photo", 1), (5, "user", 7, "group", 1), (7, "group", 10, "user", 2),
    (1, "group", 8, "user", 1), (1, "group", 9, "photo", 1), (1, "group", 4, "user", 1), (6, "group", 4, "user", 1),
]


def _photo(spark: SparkSession, sf_dir: str) -> DataFrame:
    arcs = [(a, b, ta, tb, "e", w, 1) for a, ta, b, tb, w in PHOTO_EDGES]
    arcs += [(b, a, tb, ta, "e", w, -1) for a, b, ta, tb, _, w, _ in arcs]
    frame = spark.createDataFrame(arcs, "src long, dst long, src_type string, dst_type string, elabel string, w long, dir int")
    bindings = spark.createDataFrame([(0, "u1", 8), (0, "ph", 9), (0, "u2", 10)], "qid int, pnode string, node_id long")
    return search.topk_iso(sweep.sweep_up(index.GraphIndex(frame), PHOTO, bindings, injective=True), 10)


add("worked_example", _photo, "SELECT * FROM (VALUES (0, 1, 8, 5, 2, 8, 9, 7, 10), (0, 2, 10, 5, 3, 8, 9, 7, 10)) t(qid, rank, weight, n0, n1, n2, n3, n4, n5)")
for t in ("T3", "T4"):
    hom = f"SELECT qid, count(*) AS results, '' AS broken FROM ({sqlgen.tree_join(TRADE[t], injective=False)}) GROUP BY qid"
    add(f"guarantees_{t}", lambda s, d, t=t: kernel.verify(_cg(s, d, t)), oracle("trade4", TRADE[t], N, hom))


def _udtf(spark: SparkSession, sf_dir: str) -> DataFrame:
    return kernel.lateral(sweep.sweep_down(_cg(spark, sf_dir, "T1")), 5)


add("udtf_T1_k5", _udtf, oracle("trade4", TRADE["T1"], N, sqlgen.top(TRADE["T1"], 5)))

# ---- weight algebras and richer patterns
for name, algebra in (("heaviest", Algebra.SUM_MAX), ("reliable", Algebra.RELIABILITY), ("bottleneck", Algebra.MAX), ("maxbottleneck", Algebra.MAX_MAX), ("minedge", Algebra.MIN)):
    ranking(f"{name}_T1", "trade4", TRADE["T1"], N, 5, algebra=algebra)
    ranking(f"{name}_T5", "trade4", T5, N, 5, injective=False, algebra=algebra)
ranking("node_weights_T1", "trade4", TRADE["T1"], N, 5, node_weight=True)
ranking("edge_label_T1", "flags", TRADE["T1"].with_edges(p={"elabel": "R"}), N, 5)
ranking("directed_T1", "trade4", TRADE["T1"].with_edges(p={"direction": "out"}, c={"direction": "in"}), N, 5)
ranking("multilabel_T3", "trade4", TRADE["T3"].with_nodes(p={"labels_any": ("size 1", "size 2", "size 3", "size 5", "size 8")}), N, 5)
ranking("alllabels_T1", "trade4", TRADE["T1"].with_nodes(o={"labels_all": ("O",)}), N, 5)
_TEN = tuple(graphs.CODES["supplier"] * graphs.BASE + i for i in range(10))
ranking("idset_T1", "trade4", TRADE["T1"].with_nodes(s={"bound": False, "ids": _TEN}), N, 5)
ranking("free_terminal_T5", "trade4", T5.with_nodes(s3={"bound": False}), N, 5, injective=False)


def _rerooted(ctx) -> DataFrame:
    other = T5.reroot("p")
    rows = search.topk_iso(ctx.candidates(other, N, injective=True), 1)
    return rows.select("qid", "rank", "weight")


add("reroot_T5", lambda s, d: _rerooted(context(s, d, "trade4")), oracle("trade4", T5, N, f"SELECT qid, rank, weight FROM ({sqlgen.top(T5, 1)})"))
add("choose_root_T5", lambda s, d: s.createDataFrame([(sweep.choose_root(context(s, d, "trade4").index, T5.with_nodes(s3={"bound": False})),)], "root string"))
_single = parse_pattern("(c:customer)")
ranking("single_node", "trade4", _single, 1, 50, make=lambda ctx: search.topk(ctx.candidates(_single, 1), 50), twin=False)
ORACLES["single_node"] = f"WITH {sqlgen.trade()} SELECT 0 AS qid, row_number() OVER (ORDER BY src) AS rank, 0 AS weight, src AS n0 FROM (SELECT DISTINCT src FROM arcs WHERE src_type = 'customer') QUALIFY rank <= 50"
_edge = parse_pattern("(p:part)-(s:supplier*)")
ranking("single_edge", "trade4", _edge, N, 5)
T2 = TRADE["T2"]
_hom_T2 = f"m AS ({sqlgen.tree_join(T2, injective=False)})"


def _iso_filter(s: SparkSession, d: str) -> DataFrame:
    rows = search.iso_filter(T2, search.upto(_cg(s, d, "T2"), 1 << 60))
    return rows.groupBy("qid").agg(F.count("*").alias("matches"), F.sum("weight").alias("total"))


def _subgraphs(s: SparkSession, d: str) -> DataFrame:
    rows = search.distinct_subgraphs(T2, search.upto(_cg(s, d, "T2"), 1 << 60))
    return rows.groupBy("qid").agg(F.count("*").alias("subgraphs"), F.sum("weight").alias("total"), F.sum(F.length("edges")).alias("chars"))


_apart = " AND ".join(f"n{i} <> n{j}" for i, j in T2.overlapping_pairs())
add("iso_filter_T2", _iso_filter, oracle("trade4", T2, N, f"SELECT qid, count(*) AS matches, sum(cost)::BIGINT AS total FROM m WHERE {_apart} GROUP BY qid", _hom_T2))
_ends = [(T2.place(e.parent), T2.place(e.child)) for e in T2.edges]
_pairs = ", ".join(f"least(n{a}, n{b}) || '-' || greatest(n{a}, n{b})" for a, b in _ends)
_edge_sets = f"SELECT qid, list_aggregate(list_sort(list_distinct([{_pairs}])), 'string_agg', ' ') AS edges, min(cost) AS weight FROM m GROUP BY ALL"
add("distinct_subgraphs_T2", _subgraphs, oracle("trade4", T2, N, f"SELECT qid, count(*) AS subgraphs, sum(weight)::BIGINT AS total, sum(length(edges))::BIGINT AS chars FROM ({_edge_sets}) GROUP BY qid", _hom_T2))
for t in ("T1", "T2", "T5"):
    p = TRADE[t]
    same = " OR ".join(f"n{i} = n{j}" for i, j in p.overlapping_pairs()) or "false"
    add(f"hom_vs_iso_curve_{t}", lambda s, d, p=p: workloads.iso_curve(p, search.topk(context(s, d, "trade4").candidates(p, N), 200)), oracle("trade4", p, N, f"SELECT qid, rank, (sum(CASE WHEN {same} THEN 0 ELSE 1 END) OVER (PARTITION BY qid ORDER BY rank))::BIGINT AS iso FROM ({sqlgen.top(p, 200, injective=False)})"))

# ---- the methods on the other graphs
#: Templates with tens of millions of matches, which DuckDB would have to enumerate; tests hold their first queries against it.
NO_TWIN = {("activity", "T2"), ("activity", "T5")}
for g in ("trade3", "activity", "sparse6"):
    for t, text in workloads.TEMPLATES[g].items():
        for method, end in (("guided", ""), ("bulk", "_bulk"), ("spine", "_spine")):
            ranking(f"{g}_{t}_k5{end}", g, parse_pattern(text), N, 5, method, twin=(g, t) not in NO_TWIN)
ranking("docs_T3", "docs", pattern("docs", "T3"), N, 5)
ranking("talk_path", "talk", pattern("talk", "path"), N, 5)
ranking("web_path", "web", pattern("web", "path"), N, 5)
add("knn_T2", lambda s, d: workloads.run(context(s, d, "knn"), pattern("knn", "T2"), N, 5, "guided"))

# ---- measures
GRAPHS = ("trade4", "trade3", "activity", "sparse6")
add("metrics_counters", lambda s, d: metrics.counters_by_method(context(s, d, "trade4"), TRADE, N))
add("metrics_gaps", lambda s, d: metrics.answer_gaps(sweep.sweep_down(_cg(s, d))))
add("metrics_anyk_overhead", lambda s, d: metrics.overhead(sweep.sweep_down(_cg(s, d))))
add("metrics_time_to_k", lambda s, d: metrics.time_to_k(sweep.sweep_down(_cg(s, d, injective=True)), (1, 5, 10, 100, 1000, 0)))
add("metrics_speedup", lambda s, d: metrics.speedups(workloads.experiment(s, d, [("trade4", t) for t in TRADE], counted=False)))
add("metrics_easy_hard", lambda s, d: metrics.easy_and_hard(context(s, d, "sparse6"), pattern("sparse6", "T4"), N))
for t, p in TRADE.items():
    add(f"experiment_density_{t}", lambda s, d, p=p: metrics.by_density(context(s, d, "trade4"), p, N))
for g in GRAPHS:
    for t in workloads.TEMPLATES[g]:
        add(f"experiment_{g}_{t}", lambda s, d, g=g, t=t: workloads.experiment(s, d, [(g, t)]))
_edges = [(p.place(e.parent), p.place(e.child)) for p in [TRADE["T4"]] for e in p.edges]
_links = " + ".join(f"count(DISTINCT (n{a}, n{b}))" for a, b in _edges)
_used = f"SELECT qid, {_links} AS links FROM ({sqlgen.tree_join(TRADE['T4'], injective=False)}) GROUP BY qid"
add("candidate_graph_size", lambda s, d: metrics.candidate_size(_cg(s, d, "T4")), oracle("trade4", TRADE["T4"], N, _used))

for name, (query, sql) in relational.ENTRIES.items():
    add(name, query, sql)
for name, (query, sql) in streams.ENTRIES.items():
    add(name, query, sql)


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
