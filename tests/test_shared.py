"""Rows that tasks reduce from shared links against those that frames give; the same answers and counters from both."""

import pandas as pd
import pytest

from tests.conftest import SMALL
from twigrank.model import parse_pattern
from twigrank.operators import baselines, kernel, search, shared
from twigrank.operators.sweep import sweep_up
from twigrank.plans import workloads

#: A bound node of the type of another, a bound root, and a root beside the longest path.
OTHERS = ["(u:user)-(k:k)-(u2:user*), (k)-(e:etype*)", "(d:day*)-(u:user)-(k:k)-(e:etype*), (u)-(k2:k*)", "(d:day*)-(u:user)-(k:k)-(e:etype*), (u)-(k2:k)-(e2:etype*)"]


def batch(spark, text, n):
    ctx, p = workloads.context(spark, SMALL, "activity"), parse_pattern(text)
    formulas = {"k": "7 * q", "k2": "11 * q + 1", "d": "13 * q", "d2": "17 * q + 3", "e": "q", "e2": "q + 1", "u2": "3 * q"}
    rows = []
    for name in p.order:
        if p.nodes[name].bound:
            ids = sorted(r[0] for r in ctx.index.arcs.where(f"src_type = '{p.nodes[name].ntype}'").select("src").distinct().collect())
            rows += [(q, name, ids[eval(formulas[name], {"q": q}) % len(ids)]) for q in range(n)]  # noqa: S307
    return ctx.index, p, spark.createDataFrame(rows, "qid int, pnode string, node_id long")


@pytest.fixture
def always(monkeypatch):
    monkeypatch.setattr(shared, "GAIN", 0)


def keep(qid, rows):
    return pd.DataFrame({"qid": qid[0], **{x: rows[x] for x in ("e", "c", "d", "w", "wf")}})


@pytest.mark.parametrize("text", [*(workloads.TEMPLATES["activity"][t] for t in ("T4", "T5")), *OTHERS])
def test_same_rows(spark, always, text):
    index, p, bindings = batch(spark, text, 20)
    rows = lambda df: sorted(map(tuple, df.select("qid", "e", "c", "d", "w", "wf").collect()))
    schema = "qid int, e int, c long, d long, w long, wf long"
    got = shared.share(index, p, bindings, kernel.KERNEL_ROWS)
    want = rows(kernel.candidate_rows(sweep_up(index, p, bindings, injective=True)))
    assert want and rows(got.candidates(True).apply(keep, schema)) == want
    assert rows(got.paths().apply(keep, schema)) == rows(kernel.spine_rows(index, p, bindings))


@pytest.mark.parametrize("template, methods", [("T2", ["spine", "bulk"]), ("T4", ["kernel"]), ("T5", ["spine"])])
def test_same_answers_without_links_for_each_query(spark, always, monkeypatch, template, methods):
    ctx, p = workloads.context(spark, SMALL, "activity"), workloads.pattern("activity", template)
    rows = lambda df: sorted(map(tuple, df.select("qid", "rank", "weight", *search.places(df)).collect()))
    want = rows(workloads.run(ctx, p, 40, 5, "guided"))
    for name in ("spine_rows", "candidate_rows"):  # links for each query are not made
        monkeypatch.setattr(kernel, name, None)
    for method in methods:
        assert want and rows(workloads.run(ctx, p, 40, 5, method)) == want


def test_experiment_without_links_for_each_query(spark, always, monkeypatch):
    ctx, p = workloads.context(spark, SMALL, "activity"), workloads.pattern("activity", "T4")
    want = workloads.run(ctx, p, 40, 5, "guided").count()
    for name in ("spine_rows", "candidate_rows"):
        monkeypatch.setattr(kernel, name, None)
    got = {r["method"]: r for r in workloads.experiment(spark, SMALL, [("activity", "T4")], size=40).collect()}
    assert {r["results"] for r in got.values()} == {want} and got["spine"]["pops"] > 0


def test_same_counters(spark, always):
    index, p, bindings = batch(spark, workloads.TEMPLATES["activity"]["T4"], 10)
    rows = lambda df: sorted(map(tuple, df.select("qid", *workloads.COUNTED, "results").collect()))
    cg, got = sweep_up(index, p, bindings, injective=True), shared.share(index, p, bindings, kernel.KERNEL_ROWS)
    links, paths = got.candidates(True), got.paths()
    assert rows(kernel.counters(cg, 5)) == rows(kernel.counters(cg, 5, rows=links))
    assert rows(kernel.bulk_counters(cg, 5)) == rows(kernel.bulk_counters(cg, 5, rows=links))
    assert rows(kernel.counters(cg, 5, "spine", rows=kernel.spine_rows(index, p, bindings))) == rows(kernel.spine_counters(p, 5, paths))


def test_successors_beyond_the_beam_are_not_sorted(spark, monkeypatch):
    index, p, bindings = batch(spark, workloads.TEMPLATES["activity"]["T2"], 3)
    cg, seen, ranked = sweep_up(index, p, bindings, injective=True, keep=True), [], search.ranked
    monkeypatch.setattr(search, "ranked", lambda df, k: seen.append(df) or ranked(df, k))
    rows = lambda df: sorted(map(tuple, df.select("qid", "rank", "weight", *search.places(df)).collect()))
    found = rows(search.topk_iso(cg, 2, beam=16))
    assert found and found == rows(kernel.run(cg, 2))
    assert all("most" in df.columns for df in seen[:3])  # those of the one plan
    assert seen[2].where("most is not null").count() and not seen[2].where("bound > most").count()


def test_little_reach_and_large_queries_keep_links_of_their_own(spark):
    index, p, bindings = batch(spark, workloads.TEMPLATES["activity"]["T2"], 20)
    assert shared.share(index, p, bindings, kernel.KERNEL_ROWS) is None
    rows = lambda df: sorted(map(tuple, df.select("qid", "rank", "weight", *search.places(df)).collect()))
    assert rows(baselines.spine(index, p, bindings, 5, limit=10)) == rows(baselines.spine(index, p, bindings, 5))
