"""Cost and accuracy measures."""

from __future__ import annotations

import time

import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twigrank.operators import kernel, search, sweep
from twigrank.operators.kernel import Candidates, Counters, candidate_rows, exhaustive, guided
from twigrank.operators.sweep import CandidateGraph
from twigrank.plans.storage import stored


def graph_stats(arcs: DataFrame) -> DataFrame:
    """nodes, edges, labels and edges for each node in thousandths."""
    row = arcs.agg(F.countDistinct("src").alias("nodes"), F.sum((F.col("dir") == 1).cast("long")).alias("edges"), F.countDistinct("src_type").alias("labels"))
    return row.select("nodes", "edges", "labels", F.floor(F.col("edges") * 1000 / F.col("nodes")).cast("long").alias("density_milli"))


def label_pairs(arcs: DataFrame) -> DataFrame:
    return arcs.groupBy("src_type", "dst_type").agg(F.count("*").alias("arcs"), F.sum("w").alias("total_w"))


def degrees(arcs: DataFrame) -> DataFrame:
    own = arcs.groupBy("src", "src_type", "dst_type").agg(F.count("*").alias("n"))
    return own.groupBy("src_type", "dst_type").agg(F.max("n").alias("max_degree"), F.min("n").alias("min_degree"), F.count("*").alias("nodes"))


def spurious(cg: CandidateGraph) -> DataFrame:
    return sweep.spurious(cg, sweep.sweep_down(cg))


def candidate_size(cg: CandidateGraph) -> DataFrame:
    """qid, links: candidate rows of each query over all pattern edges."""
    return candidate_rows(cg).where("e >= 0").groupBy("qid").agg(F.count("*").alias("links"))


NAMES = ("pops", "pushes", "max_partials", "max_nodes", "total_partials", "total_nodes", "results", "out_degree", "us")


def counters_by_method(ctx, templates: dict, size: int, k: int = 5) -> DataFrame:
    """Mean counters and search time of the queue search (in hand and plain), of enumeration and of path-first search, for
    each template."""
    out = None
    for t, p in templates.items():
        cg = sweep.sweep_down(ctx.candidates(p, size, injective=True, keep=True))
        kinds = (("guided", "guided", True), ("guided plain", "guided", False), ("bulk", "bulk", True), ("spine", "spine", True))
        for name, method, in_hand in kinds:
            rows = kernel.spine_rows(ctx.index, p, ctx.bindings(p, size)) if method == "spine" else None
            row = kernel.counters(cg, k, method, True, in_hand, rows).agg(F.count("*").alias("queries"), *[F.round(F.avg(x), 2).alias(x) for x in NAMES])
            row = row.select(F.lit(t).alias("template"), F.lit(name).alias("method"), F.lit(k).alias("k"), "*")
            out = row if out is None else out.union(row)
    return out


def easy_and_hard(ctx, pattern, size: int, k: int = 5) -> DataFrame:
    """bucket (1-2, 3-99, 100 and more injective matches), method, queries, and the mean time and counters of each class."""
    cg = sweep.sweep_down(ctx.candidates(pattern, size, injective=True, keep=True))
    n, out = F.col("_n"), None
    bulk = kernel.counters(cg, None, "bulk").select("qid", F.col("results").alias("_n"))
    bucket = F.when(n <= 2, "1-2").when(n < 100, "3-99").otherwise("100+")
    bulk = stored(bulk.where("_n > 0").select("qid", bucket.alias("bucket")))
    for method in ("guided", "bulk", "spine"):
        rows = kernel.spine_rows(ctx.index, pattern, ctx.bindings(pattern, size)) if method == "spine" else None
        own = kernel.counters(cg, k, method, rows=rows).join(bulk, "qid")
        own = own.groupBy("bucket").agg(F.count("*").alias("queries"), *[F.round(F.avg(x), 2).alias(x) for x in ("us", "max_nodes", "total_nodes")])
        own = own.select("bucket", F.lit(method).alias("method"), "queries", "us", "max_nodes", "total_nodes")
        out = own if out is None else out.union(own)
    return out


def time_to_k(cg: CandidateGraph, ks: tuple[int, ...], injective: bool = True) -> DataFrame:
    """k, queries, guided_us, bulk_us: mean time until the k-th answer (or the last, where there are fewer) of the queue search
    and of enumeration over the same candidates; k = 0 stands for all answers."""
    pattern = cg.pattern

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        cand, out = Candidates(pattern, rows), []
        marks = {}
        for name, run in (("guided_us", guided), ("bulk_us", exhaustive)):
            start, times = time.perf_counter(), []
            for _ in run(cand, Counters(), None, injective):
                times.append((time.perf_counter() - start) * 1e6)
            marks[name] = times or [(time.perf_counter() - start) * 1e6]
        for k in ks:
            at = {name: times[min(k, len(times)) - 1 if k else -1] for name, times in marks.items()}
            out.append({"qid": key[0], "k": k, "results": len(marks["guided_us"]), **at})
        return pd.DataFrame(out)

    each = candidate_rows(cg).groupBy("qid").applyInPandas(one, "qid int, k int, results long, guided_us double, bulk_us double")
    return each.groupBy("k").agg(F.count("*").alias("queries"), *[F.round(F.avg(x), 1).alias(x) for x in ("results", "guided_us", "bulk_us")])


def answer_gaps(cg: CandidateGraph, injective: bool = False) -> DataFrame:
    """qid, results, first_us, mean_us, p95_us, max_us: initial latency of the queue search and gaps between answers."""
    pattern = cg.pattern

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        cand, at, gaps = Candidates(pattern, rows), time.perf_counter(), []
        for _ in guided(cand, Counters(), None, injective):
            now = time.perf_counter()
            gaps.append((now - at) * 1e6)
            at = now
        g = pd.Series(gaps or [0.0])
        return pd.DataFrame([{"qid": key[0], "results": len(gaps), "first_us": g.iloc[0], "mean_us": g.mean(), "p95_us": g.quantile(0.95), "max_us": g.max()}])

    return candidate_rows(cg).groupBy("qid").applyInPandas(one, "qid int, results long, first_us double, mean_us double, p95_us double, max_us double")


def overhead(cg: CandidateGraph, injective: bool = False) -> DataFrame:
    """qid, results, guided_ms and bulk_ms for all answers, and the share that the queue search has delivered by the time
    enumeration gives its first (from the same candidates, in one task)."""
    pattern = cg.pattern

    def one(key: tuple, rows: pd.DataFrame) -> pd.DataFrame:
        cand = Candidates(pattern, rows)
        t0, first = time.perf_counter(), None
        for _ in exhaustive(cand, Counters(), None, injective):
            first = first or time.perf_counter() - t0
        bulk_s, t0, by_then, n = time.perf_counter() - t0, time.perf_counter(), 0, 0
        for _ in guided(cand, Counters(), None, injective):
            n += 1
            by_then += time.perf_counter() - t0 <= (first or 0)
        return pd.DataFrame([{"qid": key[0], "results": n, "guided_ms": (time.perf_counter() - t0) * 1e3, "bulk_ms": bulk_s * 1e3, "share_at_bulk_first": by_then / max(n, 1)}])

    return candidate_rows(cg).groupBy("qid").applyInPandas(one, "qid int, results long, guided_ms double, bulk_ms double, share_at_bulk_first double")


def speedups(runs: DataFrame) -> DataFrame:
    """graph, template, k, method, ratio of its total time to that of the guided frame search."""
    own = runs.where("method = 'guided'").select("graph", "template", "k", F.col("total_ms").alias("guided_ms"))
    return runs.join(own, ["graph", "template", "k"]).select("graph", "template", "k", "method", "total_ms", F.round(F.col("total_ms") / F.col("guided_ms"), 3).alias("ratio"))


def by_density(ctx, pattern, size: int, k: int = 5) -> DataFrame:
    """share of edges kept (by a hash of their ends), matches, mean time and counters of the kernels as the graph gets denser."""
    from twigrank.operators.index import GraphIndex

    out = None
    for share in (25, 50, 100):
        keep = F.pmod(F.xxhash64(F.least("src", "dst"), F.greatest("src", "dst")), F.lit(100)) < share
        thin = GraphIndex(ctx.index.arcs.where(keep), ctx.index.nodes)
        bindings = ctx.bindings(pattern, size)
        cg = sweep.sweep_down(sweep.sweep_up(thin, pattern, bindings, injective=True, keep=True))
        for name in ("guided", "bulk", "spine"):
            rows = kernel.spine_rows(thin, pattern, bindings) if name == "spine" else None
            row = kernel.counters(cg, k, name, True, rows=rows).agg(F.count("*").alias("queries"), F.sum("results").alias("results"), *[F.round(F.avg(x), 2).alias(x) for x in ("total_nodes", "max_nodes", "us")])
            row = row.select(F.lit(share).alias("edge_share"), F.lit(name).alias("method"), "*")
            out = row if out is None else out.union(row)
    return out


def prefix_recall(found: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """qid, recall: share of the true first k that `found` has among its first k (1 by contract)."""
    names = ["qid", "rank", "weight", *search.places(truth)]
    top = truth.where(F.col("rank") <= k).select(*names)
    hit = top.join(found.where(F.col("rank") <= k).select(*names).withColumn("hit", F.lit(1)), names, "left")
    return hit.groupBy("qid").agg(F.avg(F.coalesce("hit", F.lit(0))).alias("recall"))

