"""The any-k cursor against all matches by DuckDB: pages, thresholds, time limits and single rows, mixed, in both orders."""

import itertools

import pytest

from tests.conftest import SMALL
from twigrank.model import Algebra
from twigrank.operators import search, sweep
from twigrank.operators.kernel import run
from twigrank.plans import sqlgen
from twigrank.plans.workloads import context, oracle, pattern

SIZE = 12
CELLS = [("trade4", "T2", True, Algebra.SUM), ("trade4", "T5", True, Algebra.SUM), ("trade4", "T4", False, Algebra.SUM), ("activity", "T3", True, Algebra.SUM_MAX), ("trade3", "T4", True, Algebra.SUM), ("trade4", "T4", True, Algebra.MAX)]


def truth(duck, graph, p, injective, algebra):
    rows = duck.sql(oracle(graph, p, SIZE, sqlgen.top(p, None, algebra, injective))).fetchall()
    return sorted(tuple(map(int, r)) for r in rows)


def cell(spark, graph, template, injective, algebra):
    p = pattern(graph, template)
    return p, context(spark, SMALL, graph).candidates(p, SIZE, algebra=algebra, injective=injective)


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.mark.parametrize("graph, template, injective, algebra", CELLS)
def test_mixed_calls_give_every_match_once(spark, duck, graph, template, injective, algebra):
    p, cg = cell(spark, graph, template, injective, algebra)
    want = truth(duck, graph, p, injective, algebra)
    assert len(want) > 30
    cursor = search.AnyK(cg, injective)
    first = rows(cursor.next(3))
    assert first == [r for r in want if r[1] <= 3] == rows(search.topk_iso(cg, 3) if injective else search.topk(cg, 3))
    limit = sorted((r[2] for r in want), reverse=algebra.sign < 0)[len(want) // 3]
    second = rows(cursor.until(limit))
    within = lambda w: w * algebra.sign <= limit * algebra.sign
    assert sorted(first + second) == [r for r in want if r[1] <= 3 or within(r[2])]
    third = rows(cursor.next(2))
    given = {q: sum(r[0] == q for r in first + second) for q in {r[0] for r in want}}
    assert third == [r for r in want if given[r[0]] < r[1] <= given[r[0]] + 2]
    fourth = rows(cursor.all())
    assert sorted(first + second + third + fourth) == want
    assert cursor.exhausted() and not cursor.next(1).collect()


def test_rows_of_one_query_come_one_by_one_and_untaken_ones_stay(spark, duck):
    p, ctx = pattern("trade4", "T4"), context(spark, SMALL, "trade4")
    want = [r for r in truth(duck, "trade4", p, True, Algebra.SUM)]
    qid = max({r[0] for r in want}, key=lambda q: sum(r[0] == q for r in want))
    want = [r for r in want if r[0] == qid]
    bindings = ctx.bindings(p, SIZE).where(f"qid = {qid}")
    cursor = search.AnyK(sweep.sweep_up(ctx.index, p, bindings, injective=True), injective=True)
    taken = [tuple(r) for r in itertools.islice(cursor, 5)]
    assert taken == want[:5]
    assert rows(cursor.next(2)) == want[5:7]
    timed = rows(cursor.for_time(0.0, page=2))
    assert timed == want[7:9]
    assert [tuple(r) for r in cursor] == want[9:]


def test_all_matches_by_range_sort(spark, duck):
    p, cg = cell(spark, "trade4", "T4", True, Algebra.SUM)
    assert rows(search.upto(cg, 1 << 60, injective=True)) == truth(duck, "trade4", p, True, Algebra.SUM)


def test_kernel_limits(spark):
    p, cg = cell(spark, "trade4", "T4", True, Algebra.SUM)
    down = sweep.sweep_down(cg)
    want = rows(run(down, 4))
    assert rows(run(down, 4, limit=30)) == want and rows(run(down, None, limit=30)) == rows(run(down, None))
    heavy = sweep.sweep_down(cell(spark, "trade4", "T1", True, Algebra.SUM_MAX)[1])
    assert rows(run(heavy, 4)) == rows(search.topk(heavy, 4))
    with pytest.raises(ValueError):
        run(sweep.sweep_down(cell(spark, "trade4", "T4", True, Algebra.MAX)[1]), 4)
