"""Sweeps without links, which find the minima of a branch once for all queries that bind the same nodes in it, against the
search on stored links; packed links; arcs of the activity graph against edges that collapse by the names of their types."""

import numpy as np
import pandas as pd
import pytest
from pyspark.sql import functions as F

from tests.conftest import SMALL
from tests.test_shared import OTHERS, batch
from twigrank.operators import enumeration, kernel, pathfirst, search, shared, sweep
from twigrank.plans import workloads
from twigrank.sources import graphs

#: A bound root, a bound node of the type of one below another branch, and a branch that no query binds.
MORE = [*OTHERS, "(u:user)-(d:day*), (u)-(k:k)-(e:etype)", "(k:k)-(u:user)-(d:day*), (k)-(e:etype*)"]


def found(df):
    return sorted(map(tuple, df.select("qid", "rank", "weight", *search.places(df)).collect()))


@pytest.mark.parametrize("text", [workloads.TEMPLATES["activity"]["T1"], workloads.TEMPLATES["activity"]["T4"], *MORE])
def test_search_without_links(spark, text):
    index, p, bindings = batch(spark, text, 12)
    lean = sweep.sweep_up(index, p, bindings, injective=True, lean=True)
    assert not lean.link
    whole = sweep.sweep_up(index, p, bindings, injective=True, keep=True)
    roots = lambda cg: sorted(map(tuple, cg.reach[p.root].select("qid", "c", "floor").collect()))
    assert roots(lean) and roots(lean) == roots(whole)
    assert found(search.topk(lean, 5)) == found(search.topk(whole, 5))


def test_branch_is_swept_once_for_equal_terminals(spark, monkeypatch):
    index, p, bindings = batch(spark, workloads.TEMPLATES["activity"]["T4"], 20)
    seen, same = [], sweep.same_terminals
    monkeypatch.setattr(sweep, "same_terminals", lambda b: seen.append(same(b)) or seen[-1])
    sweep.sweep_up(index, p, bindings, injective=True, lean=True)
    assert len(seen) == 1 and seen[0].count() == 20 and seen[0].select("first").distinct().count() == 5  # event types


def test_experiment_stores_no_links_for_guided_search(spark, monkeypatch):
    ctx, p = workloads.context(spark, SMALL, "activity"), workloads.pattern("activity", "T4")
    monkeypatch.setattr(shared, "GAIN", 0)
    seen, up = [], workloads.sweep_up
    monkeypatch.setattr(workloads, "sweep_up", lambda *a, **b: seen.append(up(*a, **b)) or seen[-1])
    got = {r["method"]: r["results"] for r in workloads.experiment(spark, SMALL, [("activity", "T4")], size=40, methods=("guided", "kernel")).collect()}
    assert seen and not any(cg.link for cg in seen)
    assert set(got.values()) == {workloads.run(ctx, p, 40, 5, "bulk").count()}


@pytest.mark.parametrize("column", [[0], [7, 7, 7], [-5, 300, 2], [10**12, 10**12 + 70_000], [-(1 << 63), (1 << 63) - 1, 0], list(range(1000))])
def test_packed_columns(column):
    x = np.array(column, np.int64)
    assert shared.unpacked(shared.narrowed(x)).tolist() == column
    assert shared.unpacked(shared.narrowed(x)).dtype == np.int64


def test_packed_rows_keep_every_link(monkeypatch):
    monkeypatch.setattr(shared, "PACK", 10)
    parts = [pd.DataFrame({"e": [i % 3 for i in range(n)], "c": range(n), "d": [-i for i in range(n)], "w": [i * i for i in range(n)]}) for n in (7, 0, 40, 1)]
    rows = pd.concat(list(shared.packed(iter(parts))))
    got = [(e, *x) for e, *y in rows[["e", "c", "d", "w"]].itertuples(index=False) for x in zip(*(shared.unpacked(z).tolist() for z in y))]
    assert sorted(got) == sorted(map(tuple, pd.concat(parts).to_numpy().tolist()))
    assert 3 < len(rows) < 20


def test_activity_arcs(spark):
    rows = [(1, "2024-01-03 10:00:00", 5, "view", '{"k": 7}'), (2, "2024-01-05 10:00:00", 5, "view", '{"k": 7}'), (3, "2024-01-04 00:00:00", None, "buy", '{"k": 7}'), (4, None, 6, "buy", '{"k": 1}'), (5, "2024-01-04 00:00:00", 6, None, "{}"), (6, "2024-01-09 00:00:00", 6, "buy", "no json")]
    events = spark.createDataFrame(rows, "event_id long, ts string, user_id long, event_type string, props string").withColumn("ts", F.col("ts").cast("timestamp_ntz"))
    w, k = graphs.decay(F.col("ts"), graphs.ACTIVITY_DAY, graphs.ACTIVITY_TAU), F.get_json_object("props", "$.k").cast("long")
    etype, day = graphs.text_key(F.col("event_type")), F.datediff(F.col("ts").cast("date"), F.lit("2024-01-01").cast("date"))
    user = F.col("user_id")
    pairs = F.array(graphs.edge("user", user, "k", k, w), graphs.edge("user", user, "etype", etype, w), graphs.edge("user", user, "day", day, w), graphs.edge("k", k, "etype", etype, w))
    want, got = graphs.both_ways(events.select(F.explode(pairs).alias("e")).select("e.*")), graphs.activity(spark, "", events).arcs
    assert got.columns == want.columns and got.dtypes == want.dtypes
    assert want.count() > 10 and sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))
    plan = got._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("get_json_object") == 1  # not for each of its edges


def test_counters_of_queue_search_on_packed_links(spark, monkeypatch):
    monkeypatch.setattr(shared, "GAIN", 0)
    monkeypatch.setattr(shared, "PACK", 100)
    index, p, bindings = batch(spark, workloads.TEMPLATES["activity"]["T1"], 6)
    links = shared.share(index, p, bindings, kernel.KERNEL_ROWS).candidates(True)
    rows = lambda df: sorted(map(tuple, df.select("qid", *workloads.COUNTED, "results").collect()))
    assert rows(kernel.counters(sweep.sweep_up(index, p, bindings, injective=True), 5)) == rows(kernel.counters(workloads.unswept(p, True), 5, rows=links))


def test_links_in_order_are_not_sorted_again(monkeypatch):
    p = workloads.pattern("activity", "T4")
    place = {x.child: i for i, x in enumerate(p.preorder_edges())}
    made = np.random.default_rng(5)
    links = [(place["k"], u, k, int(made.integers(1, 9)), 0) for u in range(20) for k in range(100, 110) if (u + k) % 3]
    links += [(place[v], u, b, int(made.integers(1, 9)), 0) for v, b in (("d", 200), ("d2", 201)) for u in range(20)]
    links += [(place["e"], k, 300, int(made.integers(1, 9)), 0) for k in range(100, 110)]
    links += [(-1, -1, u, 0, 0) for u in range(20)]
    rows = pd.DataFrame(links, columns=["e", "c", "d", "w", "wf"])
    kept = rows.sort_values(["e", "c", "d"])
    want, mixed = enumeration.Enumeration(p, kept, [], 7), enumeration.Enumeration(p, rows.sample(frac=1, random_state=1), [], 7)
    paths = [pathfirst.PathFirst(p, x, 7) for x in (kept, rows.sample(frac=1, random_state=2))]
    for x in (want, mixed, *paths):
        x.run()
    assert len(want.best) == 7 and all(x.best == want.best for x in (mixed, *paths))
    monkeypatch.setattr(np, "lexsort", None)
    again = enumeration.Enumeration(p, kept, [], 7)
    again.run()
    assert again.best == want.best and kernel.Candidates(p, kept).out_degree == kernel.Candidates(p, rows).out_degree


def test_order_is_lexicographic():
    order = lambda *columns: pathfirst.in_order(*map(np.array, columns))
    assert order([1, 1, 2], [3, 4, 0]) and order([1, 1, 1], [2, 2, 2]) and order([], []) and order([4], [1])
    assert not order([1, 1, 2], [4, 3, 0]) and not order([2, 1], [0, 5]) and not order([1, 1, 1], [2, 2, 2], [0, 2, 1])
