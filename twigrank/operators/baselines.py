"""The methods that the guided search is compared with."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from twigrank.model import TreePattern
from twigrank.operators import kernel
from twigrank.operators.index import GraphIndex
from twigrank.operators.search import AnyK, answers, expand, open_frontier
from twigrank.operators.shared import SharedRows, share
from twigrank.operators.sweep import CandidateGraph, sweep_down, sweep_up
from twigrank.plans.storage import stored

#: Answers of a query beyond which path-first search keeps them in frames, not in a task.
MANY = 100_000


def bulk(cg: CandidateGraph, k: int | None, injective: bool = True, rows: DataFrame | SharedRows | None = None) -> DataFrame:
    """Enumerate every match of the reduced graph, then rank. With a k the matches are ranked as they are computed, query by
    query, and none is stored but the k least; without one, or where costs don't add up, they are joined and sorted."""
    if k is not None and cg.algebra.adds:
        return kernel.enumerated(cg, k, injective, rows=rows)
    down = sweep_down(cg)
    pairs = cg.pairs() if injective else []
    rows = open_frontier(down)
    for level in range(len(cg.pattern.edges)):
        rows = expand(down, rows, level, pairs)
    return answers(cg, rows, k)


def spine(index: GraphIndex, pattern: TreePattern, bindings: DataFrame, k: int, injective: bool = True, known_k: bool = True, limit: int = kernel.KERNEL_ROWS, rows: DataFrame | SharedRows | None = None) -> DataFrame:
    """Path-first search: query by query on arrays, of which no path is stored but the k least matches; queries with more than
    `limit` candidate rows, patterns without an edge and a k beyond MANY by pages of frames. rows: the stored `spine_rows`, where
    there are such."""
    if k > MANY or len(pattern.order) == 1:
        return spine_pages(index, pattern, bindings, k, injective, known_k=known_k)
    if rows is None:
        shared = share(index, pattern, bindings, limit)
        rows = shared.paths() if shared else stored(kernel.spine_rows(index, pattern, bindings).drop("wf"))
    if isinstance(rows, SharedRows):
        return kernel.path_first(rows, pattern, k, injective, known_k)
    large = stored(kernel.too_large(rows, limit))
    if large.isEmpty():
        return kernel.path_first(rows, pattern, k, injective, known_k)
    few = kernel.path_first(rows.join(large, "qid", "left_anti"), pattern, k, injective, known_k)
    return few.unionByName(spine_pages(index, pattern, bindings.join(large, "qid", "left_semi"), k, injective, known_k=known_k))


def spine_pages(index: GraphIndex, pattern: TreePattern, bindings: DataFrame, k: int, injective: bool = True, page: int = 64, known_k: bool = True, max_pages: int = 40) -> DataFrame:
    """Longest leaf-to-leaf path first: its instances come lightest first, found from the path's own constraints only;
    the branches that hang off it are solved in full at the nodes they hang from, and merged. A query is done when its next
    path instance, with the least weight of each branch added, is no lighter than its k-th match (known_k), or when its
    paths are exhausted."""
    names = pattern.spine()
    path = pattern.reroot(names[0]).restricted(names)
    cursor = AnyK(sweep_up(index, path, bindings, keep=True))
    # branches: subtrees below path nodes, once the whole pattern hangs from the path's first node
    whole = pattern.reroot(names[0])
    sides: list[tuple[str, DataFrame, list[str]]] = []
    for a in names:
        hanging = frozenset(v for v in whole.children(a) if v in names)
        sub = whole.subtree(a, without=hanging)
        if len(sub.order) > 1:
            found = bulk(sweep_up(index, sub, bindings), None, injective)
            cols = {f"n{i}": n for i, n in enumerate(sub.order)}
            found = found.select(*(["qid"] if sub.depends_on_query(a) else []), *[F.col(c).alias(f"x_{n}") for c, n in cols.items()], F.col("weight").alias(f"w_{a}"))
            sides.append((a, stored(found), [n for n in sub.order if n != a]))
    least = None
    for a, rows, _ in sides:
        if "qid" in rows.columns:
            one = rows.groupBy("qid").agg(F.min(f"w_{a}").alias(f"l_{a}"))
            least = one if least is None else least.join(one, "qid")
    final = [f"n{i}" for i in range(len(pattern.order))]
    best, size = None, page
    for _ in range(max_pages):
        rows = stored(cursor.next(size))
        full = rows.withColumnRenamed("weight", "total")
        for i, n in enumerate(path.order):
            full = full.withColumnRenamed(f"n{i}", f"x_{n}")
        for a, side, _ in sides:
            full = full.join(side, [f"x_{a}", *(["qid"] if "qid" in side.columns else [])]).withColumn("total", F.col("total") + F.col(f"w_{a}"))
        full = full.select("qid", F.col("total").alias("weight"), *[F.col(f"x_{n}").alias(f"n{i}") for i, n in enumerate(pattern.order)])
        if injective:
            for i, j in pattern.overlapping_pairs():
                full = full.where(F.col(f"n{i}") != F.col(f"n{j}"))
        best = full if best is None else best.union(full)
        by = Window.partitionBy("qid").orderBy("weight", *final)
        best = stored(best.withColumn("rank", F.row_number().over(by)).where(F.col("rank") <= k).drop("rank"))
        if cursor.exhausted():
            break
        if known_k:
            # queries whose page was full may have more; their next path weighs at least the page's last
            last = rows.groupBy("qid").agg(F.max("weight").alias("at"), F.count("*").alias("n")).where(F.col("n") == size)
            if least is not None:
                last = last.join(least, "qid").withColumn("at", sum((F.col(c) for c in least.columns if c != "qid"), F.col("at")))
            kth = best.groupBy("qid").agg(F.count("*").alias("have"), F.max("weight").alias("kth")).where(F.col("have") >= k)
            open_ = last.join(kth, "qid", "left").where(F.col("kth").isNull() | (F.col("at") <= F.col("kth")))
            if open_.isEmpty():
                break
        size *= 4
    else:
        raise RuntimeError("path pages did not end")
    by = Window.partitionBy("qid").orderBy("weight", *final)
    return best.withColumn("rank", F.row_number().over(by)).select("qid", "rank", "weight", *final)


def naive(spark, sql: str) -> DataFrame:
    """No reduction: the SQL text of the multi-way join, as plans.sqlgen writes it, over views of arcs and bindings."""
    return spark.sql(sql)

