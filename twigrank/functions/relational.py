"""The relational operations around pattern search, each a query over the given tables with its SQL twin."""

from __future__ import annotations

import uuid

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from twigrank.plans.storage import shared_dir
from twigrank.sources.graphs import read

ENTRIES: dict[str, tuple] = {}


def entry(sql: str | None = None):
    def keep(f):
        ENTRIES[f.__name__] = (f, sql)
        return f

    return keep


def cents(c: str):
    return F.round(F.col(c) * 100).cast("long")


_CENTS = "round({} * 100)::BIGINT".format


# ---- joins
def _join(s: SparkSession, d: str, how: str) -> DataFrame:
    c, o = read(s, d, "customer").select("c_custkey", "c_nationkey"), read(s, d, "orders").select("o_orderkey", "o_custkey", "o_orderpriority")
    out = c.join(o, (c.c_custkey == o.o_custkey) & (o.o_orderpriority == "1-URGENT"), how).drop("o_orderpriority")
    return out.select(*[F.coalesce(F.col(x).cast("long"), F.lit(-1)).alias(x) for x in out.columns])


for _how, _sql in (("inner", "JOIN"), ("left", "LEFT JOIN"), ("right", "RIGHT JOIN"), ("full", "FULL JOIN"), ("left_semi", "SEMI JOIN"), ("left_anti", "ANTI JOIN")):
    ENTRIES[f"join_{_how}"] = (lambda s, d, how=_how: _join(s, d, how), f"SELECT coalesce(COLUMNS(*)::BIGINT, -1) FROM (SELECT * {'' if _how.startswith('left_') else 'EXCLUDE (pr) '}FROM (SELECT c_custkey, c_nationkey FROM customer) c {_sql} (SELECT o_orderkey, o_custkey, o_orderpriority AS pr FROM orders) o ON c_custkey = o_custkey AND pr = '1-URGENT')")
_HINTED = "SELECT n_name, count(*) AS customers, sum(round(c_acctbal * 100)::BIGINT)::BIGINT AS cents FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name"
for _hint in ("broadcast", "merge", "shuffle_hash"):
    ENTRIES[f"join_{_hint}"] = (lambda s, d, hint=_hint: read(s, d, "customer").join(read(s, d, "nation").hint(hint), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count("*").alias("customers"), F.sum(cents("c_acctbal")).alias("cents")), _HINTED)


@entry("SELECT r_name, s_name FROM region, (SELECT s_name FROM supplier WHERE s_suppkey < 10)")
def join_cross_small(s, d):
    """Two tables of fixed size: five regions and ten suppliers."""
    return read(s, d, "region").select("r_name").crossJoin(read(s, d, "supplier").where("s_suppkey < 10").select("s_name"))


@entry("SELECT a.n_name AS n1, b.n_name AS n2 FROM nation a JOIN nation b ON a.n_regionkey = b.n_regionkey AND a.n_nationkey < b.n_nationkey")
def join_self_theta(s, d):
    n = read(s, d, "nation")
    a, b = n.alias("a"), n.alias("b")
    return a.join(b, (F.col("a.n_regionkey") == F.col("b.n_regionkey")) & (F.col("a.n_nationkey") < F.col("b.n_nationkey"))).select(F.col("a.n_name").alias("n1"), F.col("b.n_name").alias("n2"))


_PER_UNIT = "l_extendedprice / l_quantity"


@entry(f"WITH b AS (SELECT p_partkey AS band, floor(p_retailprice) AS lo, floor(p_retailprice) + 2 AS hi FROM part) SELECT band, count(*) AS lines FROM b JOIN (SELECT {_PER_UNIT} AS u FROM lineitem) ON u >= lo AND u < hi GROUP BY band")
def join_range(s, d):
    """Unit prices within the price bands of all parts."""
    return _bands(s, d, read(s, d, "part"))


def _bands(s, d, parts):
    """An equi-join on buckets of the price that a band can touch, then the range."""
    width = 10
    bands = parts.select(F.col("p_partkey").alias("band"), F.floor("p_retailprice").alias("lo"), (F.floor("p_retailprice") + 2).alias("hi"))
    bands = bands.withColumn("bucket", F.explode(F.sequence(F.floor(F.col("lo") / width), F.floor(F.col("hi") / width))))
    u = read(s, d, "lineitem").select((F.col("l_extendedprice") / F.col("l_quantity")).alias("u"))
    return u.withColumn("bucket", F.floor(F.col("u") / width)).join(bands, "bucket").where("u >= lo and u < hi").groupBy("band").agg(F.count("*").alias("lines"))


@entry("SELECT e.event_id, s.ts AS signup_ts FROM events e ASOF LEFT JOIN (SELECT user_id, ts FROM events WHERE event_type = 'signup') s ON e.user_id = s.user_id AND e.ts >= s.ts")
def join_asof(s, d):
    """Each event's latest signup of its user, itself included: one sort for each user, no join."""
    w = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, 0)
    e = read(s, d, "events")
    return e.select("event_id", F.max(F.when(F.col("event_type") == "signup", F.col("ts"))).over(w).alias("signup_ts"))


@entry("SELECT p.event_id AS purchase, v.event_id AS viewed FROM events p JOIN events v ON p.user_id = v.user_id AND p.event_type = 'purchase' AND v.event_type = 'view' AND v.ts <= p.ts AND v.ts >= p.ts - INTERVAL 1 HOUR")
def join_interval(s, d):
    """Views in the hour before a purchase: equi-join on user and hour, where a view counts for its hour and the next."""
    e = read(s, d, "events").select("event_id", "user_id", "event_type", "ts", F.date_trunc("hour", F.col("ts").cast("timestamp")).alias("h"))
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), "user_id", F.col("ts").alias("pts"), "h")
    v = e.where("event_type = 'view'").select(F.col("event_id").alias("viewed"), "user_id", F.col("ts").alias("vts"), F.explode(F.array("h", F.col("h") + F.expr("interval 1 hour"))).alias("h"))
    return p.join(v, ["user_id", "h"]).where("vts <= pts and vts >= pts - interval 1 hour").select("purchase", "viewed")


@entry("SELECT c_custkey, o_orderkey FROM customer, LATERAL (SELECT o_orderkey FROM orders WHERE o_custkey = c_custkey ORDER BY o_orderdate DESC, o_orderkey LIMIT 1)")
def join_lateral_latest(s, d):
    o = read(s, d, "orders").groupBy("o_custkey").agg(F.max_by("o_orderkey", F.struct("o_orderdate", -F.col("o_orderkey"))).alias("o_orderkey"))
    return read(s, d, "customer").join(o, F.col("c_custkey") == F.col("o_custkey")).select("c_custkey", "o_orderkey")


# ---- aggregates
@entry(f"SELECT l_returnflag, l_linestatus, count(*) AS n, sum({_CENTS('l_extendedprice')})::BIGINT AS cents, min(l_shipdate) AS first, max(l_shipdate) AS last, (sum(round(l_quantity)::BIGINT) * 1000 // count(*))::BIGINT AS avg_qty_milli FROM lineitem GROUP BY ALL")
def agg_basic(s, d):
    return read(s, d, "lineitem").groupBy("l_returnflag", "l_linestatus").agg(F.count("*").alias("n"), F.sum(cents("l_extendedprice")).alias("cents"), F.min("l_shipdate").alias("first"), F.max("l_shipdate").alias("last"), F.floor(F.sum(F.round("l_quantity").cast("long")) * 1000 / F.count("*")).cast("long").alias("avg_qty_milli"))


@entry("SELECT l_shipdate::DATE AS day, count(DISTINCT l_suppkey) AS suppliers, count(*) FILTER (WHERE l_returnflag = 'R') AS returned, bool_and(l_quantity > 1) AS all_many FROM lineitem GROUP BY 1 HAVING count(*) > 5")
def agg_distinct_filter_having(s, d):
    return read(s, d, "lineitem").groupBy(F.col("l_shipdate").cast("date").alias("day")).agg(F.countDistinct("l_suppkey").alias("suppliers"), F.count_if(F.col("l_returnflag") == "R").alias("returned"), F.bool_and(F.col("l_quantity") > 1).alias("all_many"), F.count("*").alias("n")).where("n > 5").drop("n")


@entry()
def agg_approx_distinct(s, d):
    return read(s, d, "lineitem").groupBy("l_returnflag").agg(F.approx_count_distinct("l_orderkey", 0.02).alias("orders"), F.percentile_approx("l_extendedprice", 0.5, 10_000).alias("median"))


@entry("SELECT p_brand, quantile_disc(round(p_retailprice * 100)::BIGINT, 0.5) AS median_cents FROM part GROUP BY p_brand")
def agg_percentile(s, d):
    return read(s, d, "part").groupBy("p_brand").agg(F.expr("percentile_disc(0.5) WITHIN GROUP (ORDER BY cast(round(p_retailprice * 100) AS bigint))").cast("long").alias("median_cents"))


@entry("SELECT p_brand, arg_min(p_partkey, (p_retailprice, p_partkey)) AS cheapest, arg_max(p_partkey, (p_retailprice, p_partkey)) AS dearest, array_to_string(list_sort(list_distinct(list(p_size))), ' ') AS sizes FROM part GROUP BY p_brand")
def agg_min_by_collect(s, d):
    key = F.struct("p_retailprice", "p_partkey")
    return read(s, d, "part").groupBy("p_brand").agg(F.min_by("p_partkey", key).alias("cheapest"), F.max_by("p_partkey", key).alias("dearest"), F.array_join(F.sort_array(F.collect_set(F.col("p_size"))).cast("array<string>"), " ").alias("sizes"))


@entry("SELECT o_orderpriority, count(*) FILTER (WHERE o_orderstatus = 'F') AS F, count(*) FILTER (WHERE o_orderstatus = 'O') AS O, count(*) FILTER (WHERE o_orderstatus = 'P') AS P FROM orders GROUP BY 1")
def agg_pivot(s, d):
    return read(s, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O", "P"]).count().na.fill(0)


def _cube(s, d) -> DataFrame:
    c = read(s, d, "customer").join(F.broadcast(read(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))  # 25 nations
    return c.join(F.broadcast(read(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("r_name", "c_mktsegment", cents("c_acctbal").alias("cents"))


_CUBE = "FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY {}"
for _kind, _group in (("rollup", "ROLLUP (r_name, c_mktsegment)"), ("cube", "CUBE (r_name, c_mktsegment)")):
    ENTRIES[f"agg_{_kind}"] = (lambda s, d, kind=_kind: getattr(_cube(s, d), kind)("r_name", "c_mktsegment").agg(F.count("*").alias("n"), F.sum("cents").alias("cents")), f"SELECT r_name, c_mktsegment, count(*) AS n, sum({_CENTS('c_acctbal')})::BIGINT AS cents " + _CUBE.format(_group))


@entry(f"SELECT r_name, c_mktsegment, count(*) AS n, sum({_CENTS('c_acctbal')})::BIGINT AS cents " + _CUBE.format("GROUPING SETS ((r_name), (c_mktsegment), ())"))
def agg_grouping_sets(s, d):
    _cube(s, d).createOrReplaceTempView("cube_rows")
    return s.sql("SELECT r_name, c_mktsegment, count(*) AS n, sum(cents) AS cents FROM cube_rows GROUP BY GROUPING SETS ((r_name), (c_mktsegment), ())")


# ---- windows, sorting, sets
@entry("SELECT o_orderkey, row_number() OVER w AS rn, rank() OVER v AS rk, dense_rank() OVER v AS dr, ntile(3) OVER w AS third, lag(o_orderkey, 1, -1) OVER w AS prev, lead(o_orderkey, 1, -1) OVER w AS next, first_value(o_orderkey) OVER w AS first FROM orders WINDOW w AS (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey), v AS (PARTITION BY o_custkey ORDER BY o_orderpriority)")
def window_ranks(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    v = Window.partitionBy("o_custkey").orderBy("o_orderpriority")
    return read(s, d, "orders").select("o_orderkey", F.row_number().over(w).alias("rn"), F.rank().over(v).alias("rk"), F.dense_rank().over(v).alias("dr"), F.ntile(3).over(w).alias("third"), F.lag("o_orderkey", 1, -1).over(w).alias("prev"), F.lead("o_orderkey", 1, -1).over(w).alias("next"), F.first("o_orderkey").over(w).alias("first"))


@entry(f"SELECT o_orderkey, (sum({_CENTS('o_totalprice')}) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey))::BIGINT AS running, (sum({_CENTS('o_totalprice')}) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey ROWS BETWEEN 2 PRECEDING AND CURRENT ROW))::BIGINT AS last3, count(*) OVER (PARTITION BY o_custkey ORDER BY date_diff('day', DATE '1995-01-01', o_orderdate::DATE) RANGE BETWEEN 90 PRECEDING AND CURRENT ROW) AS in_90_days FROM orders")
def window_frames(s, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    day = F.datediff(F.col("o_orderdate").cast("date"), F.lit("1995-01-01").cast("date"))
    r = Window.partitionBy("o_custkey").orderBy(day).rangeBetween(-90, 0)
    return read(s, d, "orders").select("o_orderkey", F.sum(cents("o_totalprice")).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.sum(cents("o_totalprice")).over(w.rowsBetween(-2, 0)).alias("last3"), F.count("*").over(r).alias("in_90_days"))


@entry(f"SELECT l_orderkey, l_linenumber, {_CENTS('l_extendedprice')} AS cents FROM lineitem ORDER BY cents DESC, l_orderkey, l_linenumber LIMIT 100")
def topk_global(s, d):
    return read(s, d, "lineitem").select("l_orderkey", "l_linenumber", cents("l_extendedprice").alias("cents")).orderBy(F.desc("cents"), "l_orderkey", "l_linenumber").limit(100)


@entry(f"SELECT l_suppkey, l_orderkey, l_linenumber FROM lineitem QUALIFY row_number() OVER (PARTITION BY l_suppkey ORDER BY {_CENTS('l_extendedprice')} DESC, l_orderkey, l_linenumber) <= 3")
def topk_group(s, d):
    w = Window.partitionBy("l_suppkey").orderBy(F.desc(cents("l_extendedprice")), "l_orderkey", "l_linenumber")
    return read(s, d, "lineitem").withColumn("k", F.row_number().over(w)).where("k <= 3").select("l_suppkey", "l_orderkey", "l_linenumber")


@entry("SELECT o_orderkey FROM orders ORDER BY o_orderdate, o_orderkey LIMIT 20 OFFSET 40")
def limit_offset(s, d):
    return read(s, d, "orders").orderBy("o_orderdate", "o_orderkey").select("o_orderkey").offset(40).limit(20)


_A, _B = "SELECT c_nationkey % 12 AS x FROM customer", "SELECT s_nationkey AS x FROM supplier WHERE s_nationkey > 5"
for _op, _sql in (("union", "UNION"), ("unionAll", "UNION ALL"), ("intersect", "INTERSECT"), ("intersectAll", "INTERSECT ALL"), ("subtract", "EXCEPT"), ("exceptAll", "EXCEPT ALL")):

    def _set(s, d, op=_op):
        a = read(s, d, "customer").select((F.col("c_nationkey") % 12).alias("x"))
        b = read(s, d, "supplier").where("s_nationkey > 5").select(F.col("s_nationkey").alias("x"))
        return a.union(b).distinct() if op == "union" else getattr(a, op)(b)

    ENTRIES[f"setop_{_op}"] = (_set, f"SELECT x::BIGINT AS x FROM ({_A} {_sql} {_B})")


# ---- functions
@entry("SELECT page_id, lower(regexp_extract(url, '://([^/]+)', 1)) AS host, length(url) AS n, string_split(regexp_extract(url, '://([^/]+)', 1), '.')[-1] AS top, replace(substr(url, 1, 12), '/', '|') AS head, levenshtein(substr(url, 1, 8), 'https://') AS off, url LIKE '%www%' AS www, concat_ws('-', page_id::VARCHAR, 'x') AS tag FROM pages")
def fn_string(s, d):
    host = F.regexp_extract("url", "://([^/]+)", 1)
    return read(s, d, "pages").select("page_id", F.lower(host).alias("host"), F.length("url").alias("n"), F.element_at(F.split(host, r"\."), -1).alias("top"), F.replace(F.substring("url", 1, 12), F.lit("/"), F.lit("|")).alias("head"), F.levenshtein(F.substring("url", 1, 8), F.lit("https://")).alias("off"), F.col("url").like("%www%").alias("www"), F.concat_ws("-", F.col("page_id").cast("string"), F.lit("x")).alias("tag"))


@entry("SELECT o_orderkey, year(o_orderdate) AS y, month(o_orderdate) AS m, date_diff('day', o_orderdate::DATE, DATE '2001-12-31') AS age, date_trunc('month', o_orderdate)::DATE AS first, (o_orderdate::DATE + INTERVAL 10 DAY)::DATE AS due, epoch_us(o_orderdate) AS us FROM orders")
def fn_date(s, d):
    t = F.col("o_orderdate")
    return read(s, d, "orders").select("o_orderkey", F.year(t).alias("y"), F.month(t).alias("m"), F.datediff(F.lit("2001-12-31").cast("date"), t.cast("date")).alias("age"), F.trunc(t.cast("date"), "month").alias("first"), F.date_add(t.cast("date"), 10).alias("due"), F.unix_micros(t.cast("timestamp")).alias("us"))


@entry("SELECT p_partkey, greatest(p_size, 10)::BIGINT AS g, least(p_size, 10)::BIGINT AS l, abs(p_size - 25)::BIGINT AS a, (p_partkey * 7) % 13 AS m, round(ln(p_size + 1) * 1e6)::BIGINT AS ln, pow(p_size, 2)::BIGINT AS sq FROM part")
def fn_math(s, d):
    z = F.col("p_size")
    return read(s, d, "part").select("p_partkey", F.greatest(z, F.lit(10)).alias("g"), F.least(z, F.lit(10)).alias("l"), F.abs(z - 25).alias("a"), F.pmod(F.col("p_partkey") * 7, F.lit(13)).alias("m"), F.round(F.log(z + 1) * 1e6).cast("long").alias("ln"), F.pow(z, F.lit(2)).cast("long").alias("sq"))


@entry("SELECT vec_id, len(embedding) AS n, len(list_filter(embedding, lambda x: x > 0)) AS positive, list_sort(list_transform(embedding, lambda x: round(x * 1000)::BIGINT))[1] AS least, list_contains(list_transform(embedding[1:8], lambda x: x > 0), true) AS any8, len(list_distinct(list_transform(embedding, lambda x: floor(x)::BIGINT))) AS floors FROM embeddings")
def fn_array(s, d):
    e = F.transform("embedding", lambda x: F.round(x.cast("double") * 1000).cast("long"))
    return read(s, d, "embeddings").select("vec_id", F.size("embedding").alias("n"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"), F.sort_array(e)[0].alias("least"), F.array_contains(F.transform(F.slice("embedding", 1, 8), lambda x: x > 0), True).alias("any8"), F.size(F.array_distinct(F.transform("embedding", lambda x: F.floor(x).cast("long")))).alias("floors"))


@entry("SELECT event_id, json_extract(props, '$.k')::BIGINT AS k, json_extract_string(props, '$.k') AS ks, json_extract(props, '$.none') IS NULL AS none FROM events")
def fn_json(s, d):
    k = F.from_json("props", "k long")
    return read(s, d, "events").select("event_id", k["k"].alias("k"), F.get_json_object("props", "$.k").alias("ks"), F.get_json_object("props", "$.none").isNull().alias("none"))


@entry("SELECT o_custkey, count(*) AS orders, coalesce((max(c) FILTER (WHERE st = 'F'))::BIGINT, 0) AS f FROM (SELECT o_custkey, o_orderstatus AS st, count(*) OVER (PARTITION BY o_custkey, o_orderstatus) AS c FROM orders) GROUP BY 1")
def fn_map(s, d):
    per = read(s, d, "orders").groupBy("o_custkey", "o_orderstatus").agg(F.count("*").alias("n"))
    m = per.groupBy("o_custkey").agg(F.map_from_entries(F.collect_list(F.struct("o_orderstatus", "n"))).alias("m"))
    return m.select("o_custkey", F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x).alias("orders"), F.coalesce(F.element_at("m", "F"), F.lit(0)).alias("f"))


@entry("SELECT o_orderkey FROM orders o WHERE o_totalprice BETWEEN 1000 AND 100000 AND o_orderstatus IN ('F', 'O') AND o_orderpriority LIKE '%H%' AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_returnflag = 'R') AND o_custkey IS NOT DISTINCT FROM o_custkey")
def predicates(s, d):
    o = read(s, d, "orders")
    o = o.where(F.col("o_totalprice").between(1000, 100000) & F.col("o_orderstatus").isin("F", "O") & F.col("o_orderpriority").like("%H%") & F.col("o_custkey").eqNullSafe(F.col("o_custkey")))
    r = read(s, d, "lineitem").where("l_returnflag = 'R'").select("l_orderkey")
    return o.join(r, o.o_orderkey == r.l_orderkey, "left_semi").select("o_orderkey")


@entry("SELECT doc_id, name, value FROM (SELECT doc_id, lang, source FROM documents) UNPIVOT (value FOR name IN (lang, source))")
def unpivot_labels(s, d):
    return read(s, d, "documents").select("doc_id", "lang", "source").unpivot("doc_id", ["lang", "source"], "name", "value")


@entry("SELECT p_partkey, {'brand': p_brand, 'size': p_size}.brand AS brand, p_size + 1 AS bigger FROM part")
def project_struct(s, d):
    x = F.struct(F.col("p_brand").alias("brand"), F.col("p_size").alias("size"))
    return read(s, d, "part").withColumn("x", x).select("p_partkey", F.col("x.brand").alias("brand"), (F.col("x.size") + 1).alias("bigger"))


# ---- Python functions, where a user plugs in their own
@entry("SELECT o_orderkey, round(1e6 * exp(-date_diff('day', o_orderdate::DATE, DATE '2001-12-31') / 365.0::DOUBLE))::BIGINT AS w FROM orders")
def udf_vectorised_decay(s, d):
    """A weight function of the user's own, in Arrow batches."""
    import numpy as np

    @F.pandas_udf("long")
    def decay(age: pd.Series) -> pd.Series:
        return np.rint(1e6 * np.exp(-age / 365.0)).astype("int64")

    age = F.datediff(F.lit("2001-12-31").cast("date"), F.col("o_orderdate").cast("date"))
    return read(s, d, "orders").select("o_orderkey", decay(age.cast("double")).alias("w"))


@entry(f"SELECT l_suppkey, string_agg(c::VARCHAR, ' ' ORDER BY c) AS least FROM (SELECT l_suppkey, {_CENTS('l_extendedprice')} AS c FROM lineitem QUALIFY row_number() OVER (PARTITION BY l_suppkey ORDER BY {_CENTS('l_extendedprice')}) <= 3) GROUP BY 1")
def udaf_ksmallest(s, d):
    """The three least of a group: ranked with a group limit before the shuffle, so that no group is gathered whole."""
    w = Window.partitionBy("l_suppkey").orderBy("c")
    rows = read(s, d, "lineitem").select("l_suppkey", cents("l_extendedprice").alias("c")).withColumn("k", F.row_number().over(w)).where("k <= 3")
    return rows.groupBy("l_suppkey").agg(F.array_join(F.sort_array(F.collect_list("c")).cast("array<string>"), " ").alias("least"))


@entry("SELECT user_id, (sum(round(value * 100)::BIGINT))::BIGINT AS cents FROM events GROUP BY 1")
def map_in_arrow(s, d):
    """Partial sums in Arrow batches, then a sum."""
    import pyarrow as pa

    def run(batches):
        for b in batches:
            t = pa.Table.from_batches([b]).group_by("user_id").aggregate([("c", "sum")])
            yield from t.select(["user_id", "c_sum"]).rename_columns(["user_id", "c"]).to_batches()

    part = read(s, d, "events").select("user_id", cents("value").alias("c")).mapInArrow(run, "user_id long, c long")
    return part.groupBy("user_id").agg(F.sum("c").alias("cents"))


# ---- sampling, iteration, similarity
@entry("SELECT o_orderkey FROM orders WHERE (('0x' || substr(md5(o_orderkey::VARCHAR), 1, 8))::BIGINT) % 10 < 3")
def sample_by_hash(s, d):
    """The same thirty per cent in every run and engine."""
    h = F.conv(F.substring(F.md5(F.col("o_orderkey").cast("string").cast("binary")), 1, 8), 16, 10).cast("long")
    return read(s, d, "orders").where(h % 10 < 3).select("o_orderkey")


@entry("WITH RECURSIVE e AS (SELECT n_nationkey AS a, (n_nationkey * 7 + 3) % 25 AS b FROM nation), r(node, hops) AS (SELECT 0, 0 UNION SELECT b, hops + 1 FROM r JOIN e ON a = node WHERE hops < 6) SELECT node::BIGINT AS node, min(hops)::BIGINT AS hops FROM r GROUP BY 1")
def khop_recursive(s, d):
    """Nodes within six hops, by a recursive query."""
    read(s, d, "nation").createOrReplaceTempView("khop_nation")
    return s.sql("WITH RECURSIVE e AS (SELECT n_nationkey AS a, (n_nationkey * 7 + 3) % 25 AS b FROM khop_nation), r(node, hops) AS (SELECT 0, 0 UNION ALL SELECT b, hops + 1 FROM r JOIN e ON a = node WHERE hops < 6) SELECT node, min(hops) AS hops FROM r GROUP BY node")


@entry("SELECT a.n AS node, b.m AS near FROM (SELECT DISTINCT o_custkey AS n, l_partkey AS p FROM orders JOIN lineitem ON o_orderkey = l_orderkey WHERE o_custkey % 50 = 0) a JOIN (SELECT DISTINCT o_custkey AS m, l_partkey AS p FROM orders JOIN lineitem ON o_orderkey = l_orderkey) b USING (p) WHERE a.n <> b.m GROUP BY ALL")
def khop_2(s, d):
    """Two steps of a search: the query set of customers whose key is divisible by 50, against all that share a part."""
    has = read(s, d, "orders").join(read(s, d, "lineitem"), F.col("o_orderkey") == F.col("l_orderkey")).select("o_custkey", "l_partkey").distinct()
    few = has.where("o_custkey % 50 = 0").select(F.col("o_custkey").alias("node"), "l_partkey")
    return few.join(has.select(F.col("o_custkey").alias("near"), "l_partkey"), "l_partkey").where("node <> near").select("node", "near").distinct()


@entry("WITH RECURSIVE e AS (SELECT o_custkey AS a, o_custkey + 500 * (o_orderkey % 3) AS b FROM orders), u AS (SELECT a, b FROM e UNION SELECT b, a FROM e), r(node, c) AS (SELECT a, a FROM u UNION SELECT u.b, r.c FROM r JOIN u ON u.a = r.node) SELECT node, min(c) AS component FROM r GROUP BY node")
def components(s, d):
    """Connected components of a sparse graph of customers: least labels handed on with pointer jumps, to a fixpoint."""
    from twigrank.plans.storage import stored

    e = read(s, d, "orders").select(F.col("o_custkey").alias("a"), (F.col("o_custkey") + 500 * (F.col("o_orderkey") % 3)).alias("b"))
    both = stored(e.union(e.select("b", "a")).distinct())
    labels = stored(both.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("m")).select("node", F.least("node", "m").alias("component")))
    while True:
        near = both.join(labels, F.col("b") == F.col("node")).groupBy("a").agg(F.min("component").alias("m"))
        low = labels.join(near, F.col("node") == F.col("a")).select("node", F.least("component", "m").alias("component"))
        jump = low.select(F.col("node").alias("component"), F.col("component").alias("further"))
        new = stored(low.join(jump, "component", "left").select("node", F.least("component", F.coalesce("further", "component")).alias("component")))
        changed = not new.exceptAll(labels).isEmpty()
        labels = new
        if not changed:
            return labels


# ---- formats
_MATCHES = "SELECT o_orderkey, o_custkey, o_orderstatus FROM orders"


def _round_trip(s: SparkSession, d: str, form: str) -> DataFrame:
    rows = read(s, d, "orders").select("o_orderkey", "o_custkey", "o_orderstatus")
    path = f"{shared_dir(s)}/{form}-{uuid.uuid4().hex}"
    rows.write.format(form).option("header", True).save(path)
    return s.read.schema(rows.schema).format(form).option("header", True).load(path)


for _form in ("parquet", "json", "csv", "orc"):
    ENTRIES[f"sink_roundtrip_{_form}"] = (lambda s, d, form=_form: _round_trip(s, d, form), _MATCHES)


@entry("SELECT o_orderkey, o_orderstatus FROM orders WHERE o_orderstatus = 'F'")
def sink_partitioned(s, d):
    """Written by status, read back with only one directory scanned."""
    path = f"{shared_dir(s)}/by-status-{uuid.uuid4().hex}"
    read(s, d, "orders").select("o_orderkey", "o_orderstatus").repartition("o_orderstatus").write.partitionBy("o_orderstatus").parquet(path)
    return s.read.parquet(path).where("o_orderstatus = 'F'")


@entry("SELECT count(*) AS lines, sum(length(c_name)) ::BIGINT AS chars FROM customer")
def source_text(s, d):
    path = f"{shared_dir(s)}/text-{uuid.uuid4().hex}"
    read(s, d, "customer").select("c_name").write.text(path)
    return s.read.text(path).agg(F.count("*").alias("lines"), F.sum(F.length("value")).alias("chars"))


@entry("SELECT n_name, r_name FROM nation JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA'")
def sql_surface_parameters(s, d):
    for t in ("nation", "region"):
        read(s, d, t).createOrReplaceTempView(f"v_{t}")
    return s.sql("SELECT n_name, r_name FROM v_nation JOIN v_region ON n_regionkey = r_regionkey WHERE r_name = :name", args={"name": "ASIA"})


@entry("SELECT l_partkey, array_to_string(list_sort([n0, n1]), ' ') AS ends FROM (SELECT l_partkey, min(l_orderkey) AS n0, max(l_orderkey) AS n1 FROM lineitem GROUP BY 1)")
def match_as_map(s, d):
    """The generic form of a match: a map from pattern node to graph node."""
    m = read(s, d, "lineitem").groupBy("l_partkey").agg(F.min("l_orderkey").alias("n0"), F.max("l_orderkey").alias("n1"))
    as_map = F.map_from_arrays(F.array(F.lit("first"), F.lit("last")), F.array("n0", "n1"))
    return m.select("l_partkey", F.array_join(F.sort_array(F.map_values(as_map)).cast("array<string>"), " ").alias("ends"))
