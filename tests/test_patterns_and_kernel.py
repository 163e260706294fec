"""The worked example, random properties against brute force, and the counters' bounds; no Spark needed."""

import itertools
import random

import pandas as pd
import pytest

from twigrank.model import PatternError, parse_pattern
from twigrank.operators.kernel import Candidates, Counters, exhaustive, guided, spine_first, violations

PHOTO = parse_pattern("(u3:user)-(g1:group)-(u1:user*), (g1)-(ph:photo*), (u3)-(g2:group)-(u2:user*)")


def candidates(pattern, labels, arcs):
    """Candidate rows by brute-force floors. labels: node -> set of pattern names it may serve; arcs: {(a, b): w}."""
    floor = {}

    def low(u, c):
        if (u, c) not in floor:
            total = 0
            for v in pattern.children(u):
                ways = [w + low(v, d) for (a, d), w in arcs.items() if a == c and u and d in labels[v] and low(v, d) is not None]
                if not ways:
                    total = None
                    break
                total += min(ways)
            floor[u, c] = total
        return floor[u, c]

    rows = [(-1, -1, c, 0, low(pattern.root, c)) for c in labels[pattern.root] if low(pattern.root, c) is not None]
    for place, e in enumerate(pattern.preorder_edges()):
        rows += [(place, c, d, w, w + low(e.child, d)) for (c, d), w in arcs.items() if c in labels[e.parent] and d in labels[e.child] and low(e.child, d) is not None]
    return Candidates(pattern, pd.DataFrame(rows, columns=["e", "c", "d", "w", "wf"]))


def both(edges):
    return {k: w for (a, b), w in edges.items() for k in ((a, b), (b, a))}


# names of the worked example's nodes as numbers
C1, C2, C3, D1, D2, E1, E2, A, B, FF = range(10)
EDGES = both({(D2, C2): 2, (D2, C3): 4, (C2, A): 2, (C2, B): 1, (C3, A): 2, (C3, B): 1, (D2, E2): 1, (E2, FF): 2, (C1, A): 1, (C1, B): 1, (C1, D1): 1, (E1, D1): 1})
LABELS = {"u3": {D1, D2}, "g1": {C1, C2, C3}, "u1": {A}, "ph": {B}, "g2": {E1, E2}, "u2": {FF}}


def test_worked_example():
    cand, c = candidates(PHOTO, LABELS, EDGES), Counters()
    assert list(guided(cand, c)) == [(8, (D2, C2, A, B, E2, FF)), (10, (D2, C3, A, B, E2, FF))]
    assert (c.pops, c.pushes) == (2, 2)
    plain = Counters()
    assert len(list(guided(cand, plain, in_hand=False))) == 2
    assert (plain.pops, plain.pushes, plain.total_nodes, plain.max_partials) == (11, 11, 41, 2)


def brute(pattern, labels, arcs, injective):
    out = []
    for m in itertools.product(*(sorted(labels[n]) for n in pattern.order)):
        at = dict(zip(pattern.order, m))
        steps = [(at[e.parent], at[e.child]) for e in pattern.edges]
        if all(s in arcs for s in steps) and not (injective and len(set(m)) < len(m)):
            out.append((sum(arcs[s] for s in steps), m))
    return sorted(out)


def test_random_graphs_in_order_with_bounds():
    rng = random.Random(7)
    shapes = ["(a:x)-(b:x)", "(a:x)-(b:x)-(c:x)", "(a:x)-(b:x), (a)-(c:x)", "(a:x)-(b:x)-(c:x), (a)-(d:x)", "(a:x)-(b:x)-(c:x), (b)-(d:x), (a)-(e:x)"]
    for _ in range(250):
        p, n = parse_pattern(rng.choice(shapes)), rng.randint(4, 9)
        arcs = both({(a, b): rng.randint(-2, 5) for a in range(n) for b in range(a) if rng.random() < rng.choice((0.3, 0.6))})
        labels = {u: {x for x in range(n) if rng.random() < 0.7} for u in p.order}
        cand = candidates(p, labels, arcs)
        hom = brute(p, labels, arcs, False)
        c = Counters()
        assert list(guided(cand, c)) == hom
        assert c.pops == len(hom) and c.pushes <= max(len(hom), len(cand.roots)) and c.max_partials <= max(len(hom), 1)
        assert list(guided(cand, Counters(), injective=True)) == brute(p, labels, arcs, True)
        for k in (0, 1, 3):
            c = Counters()
            assert list(guided(cand, c, k)) == hom[:k] and c.pops == min(k, len(hom))
        assert list(exhaustive(cand, Counters())) == hom
        assert violations(cand) == []
        for k in (None, 1, 3):
            assert list(spine_first(p, cand, Counters(), k)) == hom[:k]
            assert list(spine_first(p, cand, Counters(), k, injective=True)) == brute(p, labels, arcs, True)[:k]


def test_broken_guarantees_are_told():
    """Floors that are too high for one branch break the order of bounds; a node that leads nowhere is spurious."""
    rows = [(-1, -1, 1, 0, 2), (0, 1, 2, 1, 1), (0, 1, 3, 2, 2), (1, 1, 4, 1, 1), (1, 1, 5, 3, 3)]
    p = parse_pattern("(a:x)-(b:y), (a)-(c:z)")
    frame = lambda rows: pd.DataFrame(rows, columns=["e", "c", "d", "w", "wf"])
    assert violations(Candidates(p, frame(rows))) == []
    path = parse_pattern("(a:x)-(b:y)-(c:z)")
    dead = [(-1, -1, 1, 0, 2), (0, 1, 2, 1, 2), (0, 1, 3, 1, 3), (1, 2, 4, 1, 1)]
    assert {"no spurious node", "one pop for each match"} & set(violations(Candidates(path, frame(dead))))


def test_patterns():
    p = parse_pattern("(o:order)-(p:part)-(s:supplier*), (o)-[R]->(c:customer)")
    assert p.order == ("o", "p", "s", "c") and p.edge_to("c").elabel == "R" and p.edge_to("c").direction == "out"
    assert p.spine() == ["s", "p", "o", "c"]
    back = p.reroot("c")
    assert back.root == "c" and set(back.order) == set(p.order) and back.edge_to("o").direction == "in"
    assert parse_pattern("(a:x)-(b:y)-(c:x)").overlapping_pairs() == [(0, 2)]
    for bad in ("(a:x)-(b:y), (b)-(a)", "(a:x), (b:y)", "(a)-(b:y)", "(a:x)-(a:x)"):
        with pytest.raises(PatternError):
            parse_pattern(bad)
