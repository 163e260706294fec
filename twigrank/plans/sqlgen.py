"""Plain SQL text for graphs, bindings and tree joins: the twin of every ranking query for DuckDB, and the unreduced
baseline for Spark. It shares nothing with the sweeps but the pattern."""

from __future__ import annotations

from twigrank.model import Algebra, TreePattern
from twigrank.sources.graphs import ACTIVITY_DAY, ACTIVITY_TAU, BASE, CODES, TRADE_DAY, TRADE_TAU


def node(ntype: str, key: str) -> str:
    return f"({key})::BIGINT + {CODES[ntype] * BASE}"


def text_key(x: str) -> str:
    return f"('0x' || substr(md5({x}), 1, 9))::BIGINT"


def decay(ts: str, day: str = TRADE_DAY, tau: float = TRADE_TAU) -> str:
    return f"round(1e6 * exp(-date_diff('day', ({ts})::DATE, DATE '{day}') / {tau}::DOUBLE))::BIGINT"


def edge(ta: str, a: str, tb: str, b: str, w: str, source: str, elabel: str | None = None) -> str:
    return f"SELECT {node(ta, a)} AS a, {node(tb, b)} AS b, '{ta}' AS ta, '{tb}' AS tb, {elabel or f"'{ta}-{tb}'"} AS elabel, {w} AS w FROM {source}"


def both_ways(parts: list[str]) -> str:
    """arcs from edge selects."""
    union = " UNION ALL ".join(parts)
    return (
        f"edges AS (SELECT a, b, ta, tb, elabel, min(w) AS w FROM ({union}) WHERE a IS NOT NULL AND b IS NOT NULL AND w IS NOT NULL GROUP BY ALL), "
        "arcs AS (SELECT a AS src, b AS dst, ta AS src_type, tb AS dst_type, elabel, w, 1 AS dir FROM edges UNION ALL SELECT b, a, tb, ta, elabel, w, -1 FROM edges)"
    )


def trade(parts: int = 4, flags: bool = False) -> str:
    w = decay("l_shipdate")
    own = [edge("customer", "o_custkey", "order", "o_orderkey", decay("o_orderdate"), "orders"), edge("order", "l_orderkey", "part", "l_partkey", w, "lineitem", "l_returnflag" if flags else None)]
    if parts == 4:
        own += [edge("part", "l_partkey", "supplier", "l_suppkey", w, "lineitem"), edge("order", "l_orderkey", "supplier", "l_suppkey", w, "lineitem")]
    return both_ways(own)


def sparse6() -> str:
    w, one = decay("l_shipdate"), "1000000::BIGINT"
    first = lambda a, b, ka, kb: f"SELECT a, b, '{a}' AS ta, '{b}' AS tb, '{a}-{b}' AS elabel, w FROM (SELECT {node(a, ka)} AS a, {node(b, kb)} AS b, min({w}) AS w FROM lineitem GROUP BY 1, 2) QUALIFY row_number() OVER (PARTITION BY a ORDER BY w, b) = 1"
    return both_ways([
        edge("region", "n_regionkey", "nation", "n_nationkey", one, "nation"),
        edge("nation", "c_nationkey", "customer", "c_custkey", one, "customer"),
        edge("nation", "s_nationkey", "supplier", "s_suppkey", one, "supplier"),
        edge("customer", "o_custkey", "order", "o_orderkey", decay("o_orderdate"), "orders"),
        first("part", "supplier", "l_partkey", "l_suppkey"),
        first("order", "part", "l_orderkey", "l_partkey"),
    ])


def activity() -> str:
    w = decay("ts", ACTIVITY_DAY, ACTIVITY_TAU)
    k, e, d = "json_extract(props, '$.k')::BIGINT", text_key("event_type"), "date_diff('day', DATE '2024-01-01', ts::DATE)"
    return both_ways([edge("user", "user_id", "k", k, w, "events"), edge("user", "user_id", "etype", e, w, "events"), edge("user", "user_id", "day", d, w, "events"), edge("k", k, "etype", e, w, "events")])


def docs() -> str:
    one = "1000000::BIGINT"
    return both_ways([edge("doc", "doc_id", "lang", text_key("lang"), "n_chars::BIGINT", "documents"), edge("doc", "doc_id", "source", text_key("source"), one, "documents"), edge("doc", "doc_id", "quality", "quality", one, "labels")])


def talk() -> str:
    c = "(SELECT conv_id * 1000 + turn AS t, role, length(text)::BIGINT AS n, lead(conv_id * 1000 + turn) OVER x AS nx, lead(length(text)::BIGINT) OVER x AS n2 FROM conversations WINDOW x AS (PARTITION BY conv_id ORDER BY turn))"
    return both_ways([edge("turn", "t", "turn", "nx", "n + n2", c), edge("turn", "t", "role", text_key("role"), "1::BIGINT", c)])


def web() -> str:
    h = "(SELECT page_id, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) AS t FROM pages)"
    return both_ways([edge("page", "page_id", "host", text_key("regexp_extract(url, '^[a-z]+://([^/?#]+)', 1)"), "length(url)::BIGINT", "pages"), edge("page", "page_id", "target", text_key("t"), "length(t)::BIGINT", h)])


GRAPHS = {"trade4": trade, "trade3": lambda: trade(3), "flags": lambda: trade(4, True), "sparse6": sparse6, "activity": activity, "docs": docs, "talk": talk, "web": web}


def cost(algebra: Algebra, w: str) -> str:
    if algebra is Algebra.RELIABILITY:
        return f"round(-ln({w} / 1e6) * 1e9)::BIGINT"
    return f"(-{w})" if algebra.value[1] < 0 else w


def tree_join(pattern: TreePattern, algebra: Algebra = Algebra.SUM, injective: bool = True, node_weight: bool = False, arcs: str = "arcs", bindings: str = "bindings") -> str:
    """qid, weight (as a cost), n0..: all matches, one join for each pattern edge."""
    at = pattern.place
    place = {e.child: i for i, e in enumerate(pattern.preorder_edges(), 1)}
    spot = {n: "e1.src" if i == 0 else f"e{i}.dst" for i, n in enumerate(pattern.order)}
    tables, where, costs, qids = [], [], [], []

    def bind(n: str) -> None:
        if pattern.nodes[n].bound:
            tables.append(f"{bindings} b_{n}")
            where.extend([f"b_{n}.pnode = '{n}'", f"b_{n}.node_id = {spot[n]}"] + ([f"b_{n}.qid = {qids[0]}"] if qids else []))
            qids.append(f"b_{n}.qid")

    # edges as a walk from a bound node meets them, so that joins in this order begin with what the queries bind
    start = next((n for n in pattern.order if pattern.nodes[n].bound and pattern.leaves() != [n]), pattern.root)
    bind(start)
    tree = pattern.reroot(start)

    def walk(u: str):
        for v in sorted(tree.children(u), key=lambda v: (not tree.nodes[v].bound, tree.place(v))):
            yield u, v
            yield from walk(v)

    for here, there in walk(start):
        child = there if there in place and pattern.edge_to(there).parent == here else here
        e, i = pattern.edge_to(child), place[child]
        p, c = pattern.nodes[e.parent], pattern.nodes[e.child]
        tables.append(f"{arcs} e{i}")
        where += [f"e{i}.src_type = '{p.ntype}'", f"e{i}.dst_type = '{c.ntype}'"]
        if at(e.parent):
            where.append(f"e{i}.src = e{at(e.parent)}.dst")
        elif i > 1:
            where.append(f"e{i}.src = e1.src")
        if e.elabel:
            where.append(f"e{i}.elabel = '{e.elabel}'")
        if e.direction:
            where.append(f"e{i}.dir = {1 if e.direction == 'out' else -1}")
        bind(there)
    costs = [cost(algebra, f"e{i}.w") for i in range(1, len(pattern.order))]
    for n in pattern.order:
        x = pattern.nodes[n]
        if x.ids is not None:
            where.append(f"{spot[n]} IN ({', '.join(map(str, x.ids))})")
        for label in x.labels_all:
            where.append(f"{spot[n]} IN (SELECT node_id FROM nodes WHERE list_contains(labels, '{label}'))")
        if x.labels_any:
            where.append(f"{spot[n]} IN (SELECT node_id FROM nodes WHERE list_has_any(labels, [{', '.join(repr(y) for y in x.labels_any)}]))")
        if node_weight:
            tables.append(f"(SELECT node_id AS id, nweight FROM nodes) v_{n}")
            where.append(f"v_{n}.id = {spot[n]}")
            costs.append(cost(algebra, f"v_{n}.nweight"))
    if injective:
        own = {n: f"b_{n}.node_id" if pattern.nodes[n].bound else x for n, x in spot.items()}
        where += [f"{own[pattern.order[i]]} <> {own[pattern.order[j]]}" for i, j in pattern.overlapping_pairs()]
    kind = {"sum": "({})", "max": "greatest({})", "min": "least({})"}["min" if algebra is Algebra.MAX_MAX else algebra.value[0]]
    total = kind.format((" + " if algebra.value[0] == "sum" else ", ").join(costs))
    cols = ", ".join(f"{spot[n]} AS n{i}" for i, n in enumerate(pattern.order))
    return f"SELECT {qids[0] if qids else '0'} AS qid, {total} AS cost, {cols} FROM {', '.join(tables)} WHERE {' AND '.join(where)}"


def top(pattern: TreePattern, k: int | None, algebra: Algebra = Algebra.SUM, injective: bool = True, node_weight: bool = False, first: int = 0) -> str:
    """qid, rank, weight, n0.. of the k first matches of each query."""
    names = ", ".join(f"n{i}" for i in range(len(pattern.order)))
    weight = "-cost" if algebra.value[1] < 0 else "cost"
    within = "" if k is None else f" WHERE rank > {first} AND rank <= {first + k}"
    return f"SELECT qid, rank, weight, {names} FROM (SELECT qid, row_number() OVER (PARTITION BY qid ORDER BY cost, {names}) AS rank, {weight} AS weight, {names} FROM ({tree_join(pattern, algebra, injective, node_weight)})){within}"


def nodes() -> str:
    cents = lambda c: f"round({c} * 100)::BIGINT"
    return (
        f"nodes AS (SELECT {node('customer', 'c_custkey')} AS node_id, [c_mktsegment] AS labels, {cents('c_acctbal')} AS nweight FROM customer"
        f" UNION ALL SELECT {node('part', 'p_partkey')}, [p_brand, p_type, 'size ' || p_size], {cents('p_retailprice')} FROM part"
        f" UNION ALL SELECT {node('supplier', 's_suppkey')}, [], {cents('s_acctbal')} FROM supplier"
        f" UNION ALL SELECT {node('order', 'o_orderkey')}, [o_orderstatus], 0 FROM orders)"
    )
