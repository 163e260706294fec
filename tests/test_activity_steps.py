"""What the activity queries share: links stored once for enumeration, counters of path-first search on arrays."""

import pytest

from tests.conftest import SMALL
from twigrank.operators import kernel
from twigrank.plans import workloads

NAMES = ["qid", "pops", "pushes", "max_partials", "max_nodes", "total_partials", "total_nodes", "results"]


def test_enumeration_reads_stored_links(spark, monkeypatch):
    seen, rows = [], kernel.candidate_rows
    monkeypatch.setattr(kernel, "candidate_rows", lambda cg: seen.append(cg) or rows(cg))
    ctx, p = workloads.context(spark, SMALL, "activity"), workloads.pattern("activity", "T1")
    assert workloads.run(ctx, p, 3, 5, "bulk").count() == 15
    assert seen and all(cg.kept for cg in seen)


@pytest.mark.parametrize("template", ["T2", "T4", "T5"])
def test_counters_are_those_of_the_queue(spark, template):
    ctx, p = workloads.context(spark, SMALL, "activity"), workloads.pattern("activity", template)
    rows = workloads.stored(kernel.spine_rows(ctx.index, p, ctx.alike(p, 5)[0]))
    got = lambda df: sorted(map(tuple, df.select(NAMES).collect()))
    cg = ctx.candidates(p, 5, injective=True)
    each = got(kernel.spine_counters(p, 5, rows))
    assert each and each == got(kernel.counters(cg, 5, "spine", rows=rows))
