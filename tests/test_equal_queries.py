"""Queries with equal terminals are solved once, and each gets the answers."""

import pytest
from pyspark.sql import functions as F

from tests.conftest import SMALL
from twigrank.operators import search
from twigrank.plans import workloads


@pytest.mark.parametrize("template, differ", [("T1", 30), ("T4", 30), ("T3", 300)])
def test_equal_queries_are_solved_once_and_all_are_answered(spark, template, differ):
    ctx, p = workloads.context(spark, SMALL, "activity"), workloads.pattern("activity", template)
    own, members = ctx.alike(p, 300)
    assert own.select("qid").distinct().count() == members.select("first").distinct().count() == differ
    assert members.count() == 300
    rows = lambda df: sorted(tuple(map(int, r)) for r in df.select("qid", "rank", "weight", *search.places(df)).collect())
    each = rows(search.topk_iso(ctx.candidates(p, 300, injective=True), 5))
    assert each and rows(workloads.run(ctx, p, 300, 5, "guided")) == each


def test_experiment_counts_all_queries(spark):
    got = {r["method"]: r for r in workloads.experiment(spark, SMALL, [("activity", "T1")]).collect()}
    ctx, p = workloads.context(spark, SMALL, "activity"), workloads.pattern("activity", "T1")
    matches = workloads.run(ctx, p, 300, 5, "kernel").groupBy("qid").agg(F.count("*").alias("n"))
    assert {r["results"] for r in got.values()} == {matches.agg(F.sum("n")).first()[0]}
    assert all(r["queries"] == 300 for r in got.values())
