"""Enumeration on arrays against the depth-first one: same matches, same counters, whatever the chunks."""

import random
from dataclasses import asdict

import numpy as np
import pandas as pd
import pytest

from twigrank.model import parse_pattern
from twigrank.operators import enumeration, kernel


@pytest.mark.parametrize("text", ["(a:x)-(b:y)-(c:x)", "(d:x)-(u:y)-(k:z), (d)-(u2:y)-(k2:z)", "(d:x)-(u:y)-(k:z), (u)-(e:w), (d)-(u2:y)-(k2:z)", "(a:x)-(b:y), (a)-(c:y), (a)-(e:y)-(f:x)", "(a:x)"])
@pytest.mark.parametrize("chunk, block, outer", [(1 << 20, 1 << 18, 1 << 11), (7, 5, 4), (1, 1, 1)])
def test_same_matches_and_counters(monkeypatch, text, chunk, block, outer):
    for name, value in (("CHUNK", chunk), ("BLOCK", block), ("OUTER", outer)):
        monkeypatch.setattr(enumeration, name, value)
    p, rnd = parse_pattern(text), random.Random(text)
    code = {t: i * 100 for i, t in enumerate("xyzw")}
    ids = lambda v: [code[p.nodes[v].ntype] + i for i in range(5)]
    rows = [(-1, -1, d, rnd.randrange(2), 0) for d in ids(p.root)]
    for place, e in enumerate(p.preorder_edges()):
        rows += [(place, c, d, rnd.randrange(3), 0) for c in ids(e.parent) for d in ids(e.child) if rnd.random() < 0.8]
    frame = pd.DataFrame(rows, columns=["e", "c", "d", "w", "wf"]).sample(frac=1, random_state=1)
    for pairs in (p.overlapping_pairs(), []):
        for k in (1, 5, 10_000_000):
            c = kernel.Counters()
            want = list(kernel.exhaustive(kernel.Candidates(p, frame), c, k, bool(pairs)))
            got = enumeration.Enumeration(p, frame, pairs, k)
            got.run()
            assert [(w, tuple(m)) for w, *m in got.best] == want
            assert sum(got.levels) == c.total_partials and got.levels[-1] == c.max_partials
            assert sum(x * i for i, x in enumerate(got.levels, 1)) == asdict(c)["total_nodes"]


@pytest.mark.parametrize("unit", [1, 1 << 30, 1 << 40, -(1 << 31)])
def test_weights_of_any_size(unit):
    p = parse_pattern("(d:x)-(u:y)-(k:z), (d)-(u2:y)-(k2:z)")
    rows = [(-1, -1, d, 0, 0) for d in range(3)]
    rows += [(e, c, 100 * (1 + e % 2) + d, (7 * c + 3 * d + e) % 11 * unit, 0) for e in (0, 2) for c in range(3) for d in range(60)]
    rows += [(e, 100 + d, 200 + e // 2, d % 5 * unit, 0) for e in (1, 3) for d in range(60)]
    frame = pd.DataFrame(rows, columns=["e", "c", "d", "w", "wf"])
    frame.loc[frame.e == 2, "d"] = frame.d[frame.e == 2] % 100 + 100
    want = list(kernel.exhaustive(kernel.Candidates(p, frame), kernel.Counters(), 20, True))
    got = enumeration.Enumeration(p, frame, p.overlapping_pairs(), 20)
    got.run()
    assert len(want) == 20 and [(w, tuple(m)) for w, *m in got.best] == want
    assert list(got.room) == [np.int32 if unit == 1 else np.int64]  # half the memory to go through, where sums fit
