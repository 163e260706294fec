"""Edge streams: windows, deduplication, joins, incremental index and continuous answers over the events table.

The stream is the events in the order of arrival: one file for each day, in which every twentieth event comes two days
late; events without a time come on the first day. Each query runs the stream to its end (availableNow) and returns what the sink holds.
"""

from __future__ import annotations

import time
import uuid
from functools import lru_cache

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from twigrank.operators.index import GraphIndex, build_index, updated
from twigrank.plans.storage import shared_dir, stored
from twigrank.sources import graphs
from twigrank.sources.graphs import read

FIRST_DAY, DELAY = "2024-01-01", "1 day"
SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string, arrival int"
ENTRIES: dict[str, tuple] = {}


def arriving(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = read(spark, sf_dir, "events")
    late = F.when(F.col("event_id") % 20 == 0, 2).otherwise(0)
    return e.select("event_id", F.col("ts").cast("timestamp").alias("ts"), "user_id", "event_type", "value", "props", F.coalesce(F.datediff(F.col("ts").cast("date"), F.lit(FIRST_DAY).cast("date")) + late, F.lit(0)).cast("int").alias("arrival"))


@lru_cache(maxsize=16)
def _folder(app: str, spark: SparkSession, sf_dir: str) -> str:
    """One file for each day of arrival, written in that order (file sources read by time of change)."""
    path = f"{shared_dir(spark)}/events-{uuid.uuid4().hex}"
    rows = stored(arriving(spark, sf_dir).repartition(1, "arrival"), "arrival")
    for (day,) in sorted(rows.select("arrival").distinct().collect()):
        part = rows.where(F.col("arrival") == day)
        part.select(*[c.split()[0] for c in SCHEMA.split(", ")]).coalesce(1).write.mode("append").parquet(path)
        time.sleep(0.02)
    return path


def edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = _folder(spark.sparkContext.applicationId, spark, sf_dir)
    return spark.readStream.schema(SCHEMA).option("maxFilesPerTrigger", 8).parquet(path)


def drained(df: DataFrame, mode: str = "append") -> DataFrame:
    """What the stream has written once all its files are read."""
    spark, path = df.sparkSession, f"{shared_dir(df.sparkSession)}/stream-{uuid.uuid4().hex}"
    sink = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", f"{path}-state")
    sink.format("parquet").start(path).awaitTermination()
    return spark.read.schema(df.schema).parquet(path)


def each_batch(df: DataFrame, work) -> None:
    path = f"{shared_dir(df.sparkSession)}/stream-{uuid.uuid4().hex}"
    df.writeStream.foreachBatch(work).trigger(availableNow=True).option("checkpointLocation", path).start().awaitTermination()


#: All events, and the last watermark: windows that end after it are still open when the stream ends. Late ones cross the end of one batch at most, and a batch drops only what an earlier one has emitted
#: by the watermark of those before it, so that none is lost.
_ALL = """WITH e AS (SELECT * FROM events), f AS (SELECT date_trunc('millisecond', max(ts)) - INTERVAL 1 DAY AS last FROM e)"""


def entry(sql: str | None = None):
    def keep(f):
        ENTRIES[f.__name__] = (f, sql)
        return f

    return keep


@entry(f"{_ALL}, t AS (SELECT time_bucket(INTERVAL 1 HOUR, ts) AS h, value FROM e) SELECT h AS start, count(*) AS n, min(round(value * 100)::BIGINT) AS least FROM t, f WHERE h + INTERVAL 1 HOUR <= last GROUP BY h")
def stream_tumbling(s, d):
    """The hourly windows over all events, late ones too."""
    w = edges(s, d).withWatermark("ts", DELAY).groupBy(F.window("ts", "1 hour"))
    return drained(w.agg(F.count("*").alias("n"), F.min(F.round(F.col("value") * 100).cast("long")).alias("least")).select(F.col("window.start").alias("start"), "n", "least"))


@entry(f"{_ALL}, t AS (SELECT time_bucket(INTERVAL 30 MINUTE, ts) - k * INTERVAL 30 MINUTE AS h FROM e, (SELECT unnest([0, 1]) AS k)) SELECT h AS start, count(*) AS n FROM t, f WHERE h + INTERVAL 1 HOUR <= last GROUP BY h")
def stream_sliding(s, d):
    """The sliding windows over all events, late ones too."""
    w = edges(s, d).withWatermark("ts", DELAY).groupBy(F.window("ts", "1 hour", "30 minutes"))
    return drained(w.agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n"))


@entry("SELECT event_type, count(*) AS n, sum(round(value * 100)::BIGINT)::BIGINT AS cents FROM events GROUP BY 1")
def stream_complete_totals(s, d):
    """Running totals of each type, written whole with every batch (output mode complete); the last writing counts."""
    totals = edges(s, d).groupBy("event_type").agg(F.count("*").alias("n"), F.sum(F.round(F.col("value") * 100).cast("long")).alias("cents"))
    last: dict[str, DataFrame] = {}
    path = f"{shared_dir(s)}/stream-{uuid.uuid4().hex}"
    sink = totals.writeStream.outputMode("complete").foreachBatch(lambda batch, _: last.update(rows=stored(batch)))
    sink.trigger(availableNow=True).option("checkpointLocation", path).start().awaitTermination()
    return last["rows"]


#: A user's events with gaps under two hours; a session ends two hours after its last event.
_SESSIONS = (
    "t AS (SELECT *, ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 2 HOUR AS joins FROM e), "
    "g AS (SELECT *, sum(CASE WHEN joins THEN 0 ELSE 1 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS k FROM t), "
    "s AS (SELECT user_id, min(ts) AS start, max(ts) + INTERVAL 2 HOUR AS \"end\", count(*) AS n FROM g GROUP BY user_id, k)"
)


@entry(f"{_ALL}, {_SESSIONS} SELECT user_id, start, \"end\", n FROM s, f WHERE \"end\" <= last")
def stream_session(s, d):
    """Sessions of a user with gaps under two hours."""
    w = edges(s, d).withWatermark("ts", DELAY).groupBy("user_id", F.session_window("ts", "2 hours"))
    return drained(w.agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), F.col("session_window.end").alias("end"), "n"))


@entry()
def stream_late(s, d):
    """Rows that the hourly windows have dropped as late, from the stream's own progress."""
    w = edges(s, d).withWatermark("ts", DELAY).groupBy(F.window("ts", "1 hour"), "event_id").agg(F.count("*").alias("n"))
    path = f"{shared_dir(s)}/stream-{uuid.uuid4().hex}"
    q = w.writeStream.outputMode("append").trigger(availableNow=True).option("checkpointLocation", f"{path}-state").format("parquet").start(path)
    q.awaitTermination()
    late = sum(op["numRowsDroppedByWatermark"] for p in q.recentProgress for op in p["stateOperators"])
    return s.createDataFrame([(late,)], "late long")


@entry("SELECT event_id FROM events")
def stream_dedup(s, d):
    """All events come twice within the watermark's delay, late ones too, once each."""
    twice = edges(s, d).withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1)))).withWatermark("ts", DELAY)
    return drained(twice.dropDuplicatesWithinWatermark(["event_id"]).select("event_id"))


@entry("SELECT event_id, user_id FROM events")
def stream_static_join(s, d):
    """The stream against all users."""
    users = read(s, d, "events").select("user_id").distinct()
    return drained(edges(s, d).join(users, "user_id").select("event_id", "user_id"))


@entry("SELECT p.event_id AS purchase, v.event_id AS viewed FROM events p JOIN events v ON p.user_id = v.user_id AND p.event_type = 'purchase' AND v.event_type = 'view' AND v.ts <= p.ts AND v.ts >= p.ts - INTERVAL 10 MINUTE")
def stream_interval_join(s, d):
    """The same over all events, late ones too."""
    return _viewed_before(edges(s, d))


def _viewed_before(e):
    p = e.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase"), F.col("user_id").alias("pu"), F.col("ts").alias("pts")).withWatermark("pts", DELAY)
    v = e.where("event_type = 'view'").select(F.col("event_id").alias("viewed"), F.col("user_id").alias("vu"), F.col("ts").alias("vts")).withWatermark("vts", DELAY)
    return drained(p.join(v, F.expr("pu = vu and vts <= pts and vts >= pts - interval 10 minutes")).select("purchase", "viewed"))


class Merged:
    """A min-merged edge index that a stream keeps up to date: each batch writes only the arcs that it touches."""

    def __init__(self):
        self.index: GraphIndex | None = None

    @property
    def edges(self) -> DataFrame:
        return self.index.arcs

    def add(self, batch: DataFrame, _: int) -> None:
        new = graphs.activity(batch.sparkSession, "", batch)
        self.index = build_index(new) if self.index is None else updated(self.index, new.arcs)


def _activity_twin() -> str:
    from twigrank.plans import sqlgen

    return sqlgen.activity()


@entry(f"WITH {_activity_twin()} SELECT src, dst, w FROM arcs")
def stream_index_merge(s, d):
    """The activity graph, built edge by edge from the stream; equals the one built at once."""
    merged = Merged()
    each_batch(edges(s, d), merged.add)
    return merged.edges.select("src", "dst", "w")


def _topk_twin() -> str:
    from twigrank.plans import sqlgen, workloads

    p = workloads.pattern("activity", "T3")
    return workloads.oracle("activity", p, workloads.BATCH, sqlgen.top(p, 5))


@entry(_topk_twin())
def stream_topk(s, d):
    """Continuously kept five lightest matches of the star queries: each batch merges its edges and searches again for the
    queries of which a terminal has new edges; the others keep their answers."""
    from twigrank.plans import workloads

    return _kept_best(s, d, workloads.BATCH)


def _kept_best(s, d, size):
    from twigrank.operators import search
    from twigrank.operators.sweep import sweep_up
    from twigrank.plans import workloads

    p = workloads.pattern("activity", "T3")
    bindings = stored(workloads.context(s, d, "activity").bindings(p, size))
    merged, kept = Merged(), {}

    def step(batch: DataFrame, number: int) -> None:
        merged.add(batch, number)
        touched = graphs.activity(batch.sparkSession, "", batch).arcs.select(F.col("src").alias("node_id")).distinct()
        again = stored(bindings.join(touched, "node_id", "left_semi").select("qid").distinct())
        found = search.topk_iso(sweep_up(merged.index, p, bindings.join(again, "qid", "left_semi"), injective=True), 5)
        kept["rows"] = stored(found if "rows" not in kept else kept["rows"].join(again, "qid", "left_anti").unionByName(found))

    each_batch(edges(s, d), step)
    return kept["rows"].withColumn("rank", F.row_number().over(Window.partitionBy("qid").orderBy("weight", "n0", "n1", "n2", "n3")))


@entry("SELECT user_id, string_agg(c::VARCHAR, ' ' ORDER BY c) AS least FROM (SELECT user_id, round(value * 100)::BIGINT AS c FROM events QUALIFY row_number() OVER (PARTITION BY user_id ORDER BY round(value * 100)::BIGINT) <= 3) GROUP BY 1")
def stream_state_kbest(s, d):
    """Three least values of each user in keyed state, updated batch by batch."""
    from pyspark.sql.streaming.state import GroupStateTimeout

    def step(key, frames, state):
        have = list(state.get[0]) if state.exists else []
        for f in frames:
            have += f["c"].astype("int64").tolist()
        have = sorted(have)[:3]
        state.update((have,))
        yield pd.DataFrame({"user_id": [key[0]], "least": [have]})

    rows = edges(s, d).select("user_id", F.round(F.col("value") * 100).cast("long").alias("c"))
    state = rows.groupBy("user_id").applyInPandasWithState(step, "user_id long, least array<long>", "least array<long>", "update", GroupStateTimeout.NoTimeout)
    last: dict[str, DataFrame] = {}

    def sink(batch: DataFrame, number: int) -> None:
        new = batch.withColumn("at", F.lit(number))
        last["rows"] = stored(new if "rows" not in last else last["rows"].join(new.select("user_id"), "user_id", "left_anti").unionByName(new))

    path = f"{shared_dir(s)}/stream-{uuid.uuid4().hex}"
    state.writeStream.outputMode("update").foreachBatch(sink).trigger(availableNow=True).option("checkpointLocation", path).start().awaitTermination()
    return last["rows"].select("user_id", F.array_join(F.col("least").cast("array<string>"), " ").alias("least"))
