"""Path-first search on arrays against the queue: same matches, whatever the pages and chunks; ties cost no pass of their own."""

import random
import time
from dataclasses import asdict

import pandas as pd
import pytest

from tests.conftest import SMALL
from twigrank.model import parse_pattern
from twigrank.operators import baselines, kernel, pathfirst, search
from twigrank.operators.sweep import sweep_down, sweep_up
from twigrank.plans import workloads

TEXTS = ["(a:x)-(b:y)-(c:x)", "(d:x)-(u:y)-(k:z), (d)-(u2:y)-(k2:z)", "(d:x)-(u:y)-(k:z), (u)-(e:w), (d)-(u2:y)-(k2:z)", "(a:x)-(b:y), (a)-(c:y), (a)-(e:y)-(f:x)", "(a:x)-(b:y)-(c:z)-(d:y), (b)-(e:w), (b)-(f:x)-(g:y)"]


def candidates(p, seed, n=5, share=0.8, weights=3):
    rnd, code = random.Random(seed), {t: i * 100_000 for i, t in enumerate("xyzw")}
    ids = lambda v: [code[p.nodes[v].ntype] + i for i in range(n)]
    rows = [(-1, -1, d, 0, 0) for d in ids(p.root)]
    for place, e in enumerate(p.preorder_edges()):
        rows += [(place, c, d, rnd.randrange(weights) - 1, 0) for c in ids(e.parent) for d in ids(e.child) if rnd.random() < share]
    return pd.DataFrame(rows, columns=["e", "c", "d", "w", "wf"]).sample(frac=1, random_state=1)


@pytest.mark.parametrize("text", TEXTS)
@pytest.mark.parametrize("share", [0.8, 0.3, 0.0])
@pytest.mark.parametrize("chunk, page", [(1 << 19, 64), (7, 1), (1, 3)])
def test_same_matches(monkeypatch, text, share, chunk, page):
    monkeypatch.setattr(pathfirst, "CHUNK", chunk)
    monkeypatch.setattr(pathfirst, "PAGE", page)
    p = parse_pattern(text)
    frame = candidates(p, text, share=share)
    for injective in (True, False):
        for k in (1, 5, 1000):
            want = list(kernel.exhaustive(kernel.Candidates(p, frame), kernel.Counters(), k, injective))
            for known_k in (True, False):
                got = pathfirst.PathFirst(p, frame, k, injective, known_k)
                got.run()
                assert [(w, tuple(m)) for w, *m in got.best] == want
            c = kernel.Counters()
            assert list(kernel.spine_first(p, kernel.Candidates(p, frame), c, k, injective)) == want
            found = pathfirst.PathFirst(p, frame, k, injective)
            found.run()
            assert found.counters() == asdict(c)


def test_ties_are_no_square_of_work():
    p = parse_pattern("(a:x)-(b:y)-(c:z)")
    frame = candidates(p, 1, n=80, share=1, weights=1)
    frame = frame[(frame.e != 1) | (frame.d < 200_003)]  # 19,200 paths of one weight
    at = time.perf_counter()
    found = list(kernel.spine_first(p, kernel.Candidates(p, frame), kernel.Counters(), 5))
    assert time.perf_counter() - at < 8
    got = pathfirst.PathFirst(p, frame, 5)
    got.run()
    assert [(w, tuple(m)) for w, *m in got.best] == found


@pytest.mark.parametrize("template", ["T2", "T5"])
def test_arrays_find_what_guided_search_finds(spark, template):
    ctx, p = workloads.context(spark, SMALL, "activity"), workloads.pattern("activity", template)
    own, _ = ctx.alike(p, 20)
    rows = lambda df: sorted(map(tuple, df.select("qid", "rank", "weight", *search.places(df)).collect()))
    cg = sweep_up(ctx.index, p, own, injective=True, keep=True)
    arrays = rows(baselines.spine(ctx.index, p, own, 5))
    assert arrays and arrays == rows(search.topk_iso(cg, 5))
    links = lambda g: sorted(map(tuple, kernel.candidate_rows(g).collect()))
    assert links(cg) == links(sweep_down(cg))


def test_queries_too_large_for_a_task_go_by_pages(spark):
    ctx, p = workloads.context(spark, SMALL, "activity"), workloads.pattern("activity", "T1")
    own, _ = ctx.alike(p, 5)
    rows = lambda df: sorted(map(tuple, df.select("qid", "rank", "weight", *search.places(df)).collect()))
    arrays = rows(baselines.spine(ctx.index, p, own, 5))
    assert arrays and arrays == rows(baselines.spine(ctx.index, p, own, 5, limit=0))
