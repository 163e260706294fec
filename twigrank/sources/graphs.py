"""Labelled, weighted graphs from the given tables.

An edge is two arcs (src, dst) so that the neighbours of a node are one equi-join away. Node ids are a type's code times
10**12 plus the key within the type. Weights are whole millionths, so that ties and sums are the same on every engine.
Parallel arcs of one label collapse to the least weight; arcs with a null end or weight are dropped.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

BASE = 10**12
#: Codes of node types: fixed values, shared with the SQL twins.
CODES = {"customer": 1, "order": 2, "part": 3, "supplier": 4, "nation": 5, "region": 6, "user": 7, "etype": 8, "k": 9, "day": 10, "vec": 11, "doc": 12, "lang": 13, "source": 14, "turn": 15, "role": 16, "page": 17, "host": 18, "target": 19, "quality": 20}
TRADE_DAY, TRADE_TAU, ACTIVITY_DAY, ACTIVITY_TAU = "2001-12-31", 365.0, "2024-02-01", 7.0
ARC = ["src", "dst", "src_type", "dst_type", "elabel", "w"]


@dataclass(frozen=True)
class LabeledGraph:
    """arcs: src, dst, src_type, dst_type, elabel, w (and dir: 1 along the edge, -1 against it).
    nodes: node_id, ntype, labels, nweight; None where a graph needs no node attributes."""

    arcs: DataFrame
    nodes: DataFrame | None = None


def node(ntype: str, key: Column) -> Column:
    return key.cast("long") + F.lit(CODES[ntype] * BASE)


def text_key(x: Column) -> Column:
    """36 bits of a string's md5, the same in every engine."""
    return F.conv(F.substring(F.md5(x.cast("binary")), 1, 9), 16, 10).cast("long")


def decay(ts: Column, day: str, tau: float) -> Column:
    return F.round(F.lit(1e6) * F.exp(-F.datediff(F.lit(day).cast("date"), ts.cast("date")) / F.lit(tau))).cast("long")


def both_ways(edges: DataFrame) -> DataFrame:
    """Arcs of edges a, b, ta, tb, elabel, w: parallel ones collapsed, both directions, nulls dropped."""
    return ways(edges.dropna(subset=["a", "b", "w"]).groupBy("a", "b", "ta", "tb", "elabel").agg(F.min("w").alias("w")))


def ways(least: DataFrame) -> DataFrame:
    """Both arcs of each edge."""
    ways = F.explode(F.array(F.struct(F.col("a").alias("src"), F.col("b").alias("dst"), F.col("ta").alias("src_type"), F.col("tb").alias("dst_type"), F.lit(1).alias("dir")), F.struct(F.col("b").alias("src"), F.col("a").alias("dst"), F.col("tb").alias("src_type"), F.col("ta").alias("dst_type"), F.lit(-1).alias("dir"))))
    return least.select(ways.alias("x"), "elabel", "w").select("x.src", "x.dst", "x.src_type", "x.dst_type", "elabel", "w", "x.dir")


def edge(ta: str, a: Column, tb: str, b: Column, w: Column, elabel: Column | None = None) -> Column:
    return F.struct(node(ta, a).alias("a"), node(tb, b).alias("b"), F.lit(ta).alias("ta"), F.lit(tb).alias("tb"), (F.lit(f"{ta}-{tb}") if elabel is None else elabel).alias("elabel"), w.alias("w"))


def read(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def trade(spark: SparkSession, sf_dir: str, parts: int = 4, flags: bool = False) -> LabeledGraph:
    """Customers, orders, parts and (parts = 4) suppliers. flags: order-part edges bear the return flag as their label.

    One scan of lineitem gives its three edge sets, in one aggregate."""
    orders, lines = read(spark, sf_dir, "orders"), read(spark, sf_dir, "lineitem")
    w = decay(F.col("l_shipdate"), TRADE_DAY, TRADE_TAU)
    per_line = [edge("order", F.col("l_orderkey"), "part", F.col("l_partkey"), w, F.col("l_returnflag") if flags else None)]
    if parts == 4:
        per_line += [edge("part", F.col("l_partkey"), "supplier", F.col("l_suppkey"), w), edge("order", F.col("l_orderkey"), "supplier", F.col("l_suppkey"), w)]
    from_lines = lines.select(F.explode(F.array(*per_line)).alias("e")).select("e.*")
    from_orders = orders.select(edge("customer", F.col("o_custkey"), "order", F.col("o_orderkey"), decay(F.col("o_orderdate"), TRADE_DAY, TRADE_TAU)).alias("e")).select("e.*")
    return LabeledGraph(both_ways(from_orders.union(from_lines)), trade_nodes(spark, sf_dir))


def trade_nodes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nodes with labels (segment, brand, type, size) and weights in cents."""
    cents = lambda c: F.round(F.col(c) * 100).cast("long")
    none = F.array().cast("array<string>")
    rows = [
        ("customer", "c_custkey", F.array("c_mktsegment"), cents("c_acctbal")),
        ("part", "p_partkey", F.array("p_brand", "p_type", F.concat(F.lit("size "), F.col("p_size").cast("string"))), cents("p_retailprice")),
        ("supplier", "s_suppkey", none, cents("s_acctbal")),
    ]
    out = [read(spark, sf_dir, t).select(node(t, F.col(k)).alias("node_id"), F.lit(t).alias("ntype"), labels.alias("labels"), w.alias("nweight")) for t, k, labels, w in rows]
    out.append(read(spark, sf_dir, "orders").select(node("order", F.col("o_orderkey")).alias("node_id"), F.lit("order").alias("ntype"), F.array("o_orderstatus").alias("labels"), F.lit(0).cast("long").alias("nweight")))
    return out[0].union(out[1]).union(out[2]).union(out[3])


def sparse6(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Six types, few edges: each part has its lightest supplier only, each order its lightest part."""
    nation, customer, supplier = (read(spark, sf_dir, t) for t in ("nation", "customer", "supplier"))
    one = F.lit(1_000_000).cast("long")
    full = trade(spark, sf_dir).arcs
    lightest = lambda a, b: (
        full.where((F.col("src_type") == a) & (F.col("dst_type") == b))
        .groupBy("src")
        .agg(F.min(F.struct("w", "dst")).alias("x"))
        .select(F.col("src").alias("a"), F.col("x.dst").alias("b"), F.lit(a).alias("ta"), F.lit(b).alias("tb"), F.lit(f"{a}-{b}").alias("elabel"), F.col("x.w").alias("w"))
    )
    made = [
        nation.select(edge("region", F.col("n_regionkey"), "nation", F.col("n_nationkey"), one).alias("e")).select("e.*"),
        customer.select(edge("nation", F.col("c_nationkey"), "customer", F.col("c_custkey"), one).alias("e")).select("e.*"),
        supplier.select(edge("nation", F.col("s_nationkey"), "supplier", F.col("s_suppkey"), one).alias("e")).select("e.*"),
        full.where("src_type = 'customer' and dst_type = 'order'").select(F.col("src").alias("a"), F.col("dst").alias("b"), F.col("src_type").alias("ta"), F.col("dst_type").alias("tb"), "elabel", "w"),
        lightest("part", "supplier"),
        lightest("order", "part"),
    ]
    out = made[0]
    for x in made[1:]:
        out = out.union(x)
    return LabeledGraph(both_ways(out))


def activity(spark: SparkSession, sf_dir: str, events: DataFrame | None = None) -> LabeledGraph:
    """Users, event types, the number k of an event's properties, and days: small and dense.

    What an event's edges share is computed once, and parallel edges collapse by the number of their kind, without its names."""
    events = read(spark, sf_dir, "events") if events is None else events
    w, k = decay(F.col("ts"), ACTIVITY_DAY, ACTIVITY_TAU), F.get_json_object("props", "$.k").cast("long")
    day = F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date"))
    each = events.select(node("user", F.col("user_id")).alias("user"), node("k", k).alias("k"), node("etype", text_key(F.col("event_type"))).alias("etype"), node("day", day).alias("day"), w.alias("w"))
    kinds = [("user", "k"), ("user", "etype"), ("user", "day"), ("k", "etype")]
    pairs = F.array(*[F.struct(F.lit(i).alias("kind"), F.col(a).alias("a"), F.col(b).alias("b")) for i, (a, b) in enumerate(kinds)])
    least = each.select(F.explode(pairs).alias("e"), "w").select("e.*", "w").dropna(subset=["a", "b", "w"]).groupBy("kind", "a", "b").agg(F.min("w").alias("w"))
    name = lambda names: F.element_at(F.array(*map(F.lit, names)), F.col("kind") + 1)
    return LabeledGraph(ways(least.select("a", "b", name([a for a, _ in kinds]).alias("ta"), name([b for _, b in kinds]).alias("tb"), name([f"{a}-{b}" for a, b in kinds]).alias("elabel"), "w")))


def docs(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    d, labels = read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels")
    one = F.lit(1_000_000).cast("long")
    of = d.select(F.explode(F.array(edge("doc", F.col("doc_id"), "lang", text_key(F.col("lang")), F.col("n_chars").cast("long")), edge("doc", F.col("doc_id"), "source", text_key(F.col("source")), one))).alias("e")).select("e.*")
    return LabeledGraph(both_ways(of.union(labels.select(edge("doc", F.col("doc_id"), "quality", F.col("quality"), one).alias("e")).select("e.*"))))


def talk(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Turns of conversations in a chain, each with its role; a turn's key is conversation * 1000 + turn."""
    c = read(spark, sf_dir, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("t"), "conv_id", "turn", "role", F.length("text").cast("long").alias("n"))
    after = F.lead("t").over(Window.partitionBy("conv_id").orderBy("turn"))
    w_after = F.lead("n").over(Window.partitionBy("conv_id").orderBy("turn"))
    chain = c.select("t", after.alias("next"), (F.col("n") + w_after).alias("w")).where("next is not null").select(edge("turn", F.col("t"), "turn", F.col("next"), F.col("w")).alias("e")).select("e.*")
    return LabeledGraph(both_ways(chain.union(c.select(edge("turn", F.col("t"), "role", text_key(F.col("role")), F.lit(1).cast("long")).alias("e")).select("e.*"))))


def web(spark: SparkSession, sf_dir: str) -> LabeledGraph:
    """Pages, their hosts and the targets of their links."""
    p = read(spark, sf_dir, "pages")
    host = F.regexp_extract("url", "^[a-z]+://([^/?#]+)", 1)
    hrefs = F.regexp_extract_all("html", F.lit('href="([^"]+)"'), F.lit(1))
    of = p.select(edge("page", F.col("page_id"), "host", text_key(host), F.length("url").cast("long")).alias("e")).select("e.*")
    to = p.select("page_id", F.explode(hrefs).alias("t")).select(edge("page", F.col("page_id"), "target", text_key(F.col("t")), F.length("t").cast("long")).alias("e")).select("e.*")
    return LabeledGraph(both_ways(of.union(to)))


def knn(spark: SparkSession, sf_dir: str, neighbours: int = 8, queries: int = 50, planes: int = 0) -> LabeledGraph:
    """One type: each vector whose id is divisible by `queries` and its nearest vectors by cosine.

    planes = 0 compares the stated query set with every vector, exactly; otherwise only vectors that agree with the query
    in the signs of `planes` fixed coordinates sums are compared (approximate, an equi-join).
    """
    v = read(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("x"))
    norm = F.sqrt(F.aggregate("x", F.lit(0.0), lambda a, t: a + t * t))
    v = v.withColumn("x", F.transform("x", lambda t: F.when(norm > 0, t / norm).otherwise(0.0)))
    if planes:
        v = v.withColumn("sign", F.array_join(F.transform(F.sequence(F.lit(0), F.lit(planes - 1)), lambda i: F.when(F.aggregate(F.slice("x", i * 3 + 1, 3), F.lit(0.0), lambda a, t: a + t) > 0, "1").otherwise("0")), ""))
    q = v.where(F.col("vec_id") % queries == 0).select(F.col("vec_id").alias("q"), F.col("x").alias("qx"), *([F.col("sign").alias("qs")] if planes else []))
    on = (F.col("q") != F.col("vec_id")) & (F.col("sign") == F.col("qs") if planes else F.lit(True))
    dot = F.aggregate(F.zip_with("x", "qx", lambda a, b: a * b), F.lit(0.0), lambda a, t: a + t)
    w = F.round((F.lit(1.0) - dot) * 1e6).cast("long")
    near = v.join(q, on).select("q", "vec_id", w.alias("w")).withColumn("k", F.row_number().over(Window.partitionBy("q").orderBy("w", "vec_id"))).where(F.col("k") <= neighbours)
    return LabeledGraph(both_ways(near.select(edge("vec", F.least("q", "vec_id"), "vec", F.greatest("q", "vec_id"), F.col("w")).alias("e")).select("e.*")))


def weight_by(graph: LabeledGraph, kind: str, spark_rounds: int = 5) -> DataFrame:
    """arcs with another weight: 'members' (degree of both ends), 'activity' (degree of the source), 'pagerank' (sum of
    both ends' ranks in billionths, `spark_rounds` rounds in whole numbers)."""
    degree = graph.arcs.groupBy("src").agg(F.count("*").alias("deg"))
    if kind == "pagerank":
        score = pagerank(graph.arcs, spark_rounds).withColumnRenamed("node", "src").withColumnRenamed("rank", "deg")
    else:
        score = degree
    a = graph.arcs.drop("w").join(score, "src")
    if kind == "activity":
        return a.withColumn("w", F.col("deg")).drop("deg")
    return a.join(score.select(F.col("src").alias("dst"), F.col("deg").alias("deg2")), "dst").withColumn("w", F.col("deg") + F.col("deg2")).drop("deg", "deg2")


def pagerank(arcs: DataFrame, rounds: int = 5, scale: int = 10**9) -> DataFrame:
    """(node, rank): each round hands 85 % of a node's rank to its neighbours in equal whole parts, and 15 % of scale."""
    degree = arcs.groupBy("src").agg(F.count("*").alias("deg"))
    rank = degree.select(F.col("src").alias("node"), F.lit(scale).cast("long").alias("rank"))
    for _ in range(rounds):
        share = rank.join(degree, F.col("node") == F.col("src")).select("src", F.floor(F.col("rank") * 85 / 100 / F.col("deg")).cast("long").alias("part"))
        rank = arcs.join(share, "src").groupBy("dst").agg((F.sum("part") + F.lit(scale * 15 // 100)).alias("rank")).withColumnRenamed("dst", "node")
    return rank
