"""The neighbour index: arcs stored by source type, target type and edge label, ordered by source within files."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from twigrank.model import PEdge, TreePattern
from twigrank.plans.storage import rows_at_most, stored
from twigrank.sources.graphs import LabeledGraph

BROADCAST_IDS = 100_000
MAX_LAYERS = 8


@dataclass(frozen=True)
class GraphIndex:
    arcs: DataFrame
    nodes: DataFrame | None = None
    layers: int = 0  # updates that lie over the stored arcs

    def between(self, pattern: TreePattern, e: PEdge) -> DataFrame:
        """c, d, w: arcs that may match a pattern edge, c for the parent. Types and label prune directories. Where two nodes
        have arcs of several labels and the edge demands none, each label is a way of its own."""
        a = self.arcs.where((F.col("src_type") == pattern.nodes[e.parent].ntype) & (F.col("dst_type") == pattern.nodes[e.child].ntype))
        if e.elabel:
            a = a.where(F.col("elabel") == e.elabel)
        if e.direction:
            a = a.where(F.col("dir") == (1 if e.direction == "out" else -1))
        return a.select(F.col("src").alias("c"), F.col("dst").alias("d"), "w")

    def neighbors(self, ids: DataFrame, label: str | None = None) -> DataFrame:
        """node_id, neighbor, w of each id, of one type or all. ids are broadcast if they are few."""
        a = self.arcs if label is None else self.arcs.where(F.col("dst_type") == label)
        few = F.broadcast(ids) if rows_at_most(ids, BROADCAST_IDS) else ids
        return a.join(few, F.col("src") == F.col("node_id")).select("node_id", F.col("dst").alias("neighbor"), "w")


def build_index(graph: LabeledGraph, bucket_table: str | None = None, buckets: int = 64) -> GraphIndex:
    """Bulk build, linear in the arcs. With bucket_table the arcs become a table bucketed by src, so that lookups and
    sweeps join it without an exchange; else they are Parquet files in the shared folder."""
    if bucket_table:
        graph.arcs.write.partitionBy("src_type", "dst_type").bucketBy(buckets, "src").sortBy("src").mode("overwrite").saveAsTable(bucket_table)
        return GraphIndex(graph.arcs.sparkSession.table(bucket_table), graph.nodes)
    return GraphIndex(stored(graph.arcs.select("src", "dst", "w", "dir", "src_type", "dst_type", "elabel"), "src_type", "dst_type", "elabel"), graph.nodes)


KEYS = ["src", "dst", "src_type", "dst_type", "elabel", "dir"]


def updated(index: GraphIndex, inserts: DataFrame, deletes: DataFrame | None = None) -> GraphIndex:
    """The index without the arcs between the ends (src, dst) in deletes, then with inserts (arcs, both ways); parallel arcs
    keep the least weight. Only the arcs of the ends that change are written; the index reads them over those that it had.
    After MAX_LAYERS updates the layers are written as one."""
    fresh = inserts.groupBy(*KEYS).agg(F.min("w").alias("w"))
    ends = fresh.select("src", "dst")
    if deletes is not None:
        ends = ends.union(deletes.select("src", "dst"))
    ends = stored(ends.distinct())
    few = F.broadcast(ends) if rows_at_most(ends, BROADCAST_IDS) else ends
    before = index.arcs.join(few, ["src", "dst"], "left_semi")
    if deletes is not None:
        before = before.join(deletes.select("src", "dst"), ["src", "dst"], "left_anti")
    changed = stored(before.select(*KEYS, "w").unionByName(fresh).groupBy(*KEYS).agg(F.min("w").alias("w")))
    arcs = index.arcs.join(few, ["src", "dst"], "left_anti").select(*KEYS, "w").unionByName(changed)
    if index.layers < MAX_LAYERS:
        return GraphIndex(arcs, index.nodes, index.layers + 1)
    return GraphIndex(stored(arcs, "src_type", "dst_type", "elabel"), index.nodes)
