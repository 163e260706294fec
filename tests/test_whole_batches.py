"""All 300 assignments of every template, graph and method."""

import pytest

from tests.conftest import SMALL
from twigrank import catalog
from twigrank.plans import sqlgen, workloads

METHODS = {"": "guided", "_bulk": "bulk", "_spine": "spine"}


def test_every_template_graph_and_method_is_there():
    names = catalog.queries()
    cells = [f"{g}_{t}_k5{end}" for g in ("trade3", "activity", "sparse6") for t in workloads.TEMPLATES[g] for end in METHODS]
    cells += [f"{m}_{t}_k5" for t in workloads.TEMPLATES["trade4"] for m in ("guided", "bulk", "spine", "kernel", "naive")]
    cells += [f"experiment_{g}_{t}" for g in catalog.GRAPHS for t in workloads.TEMPLATES[g]]
    assert not [n for n in cells if n not in names]


@pytest.mark.parametrize("method", METHODS)
@pytest.mark.parametrize("graph, template", sorted(catalog.NO_TWIN))
def test_first_queries_of_batches_without_a_twin(spark, duck, graph, template, method):
    p = workloads.pattern(graph, template)
    got = catalog.queries()[f"{graph}_{template}_k5{method}"](spark, SMALL).toPandas()
    want = duck.sql(workloads.oracle(graph, p, 3, sqlgen.top(p, 5))).df()
    cols = sorted(want.columns)
    rows = lambda df: sorted(tuple(map(int, r)) for r in df[cols].itertuples(index=False, name=None))
    assert rows(got[got["qid"] < 3]) == rows(want) and got["qid"].max() >= 200
