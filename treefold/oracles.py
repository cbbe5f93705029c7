"""DuckDB SQL for the tree workloads and the small-state problems."""

from __future__ import annotations

LEVEL = 1_000_000_000


def _cents(c: str) -> str:
    return f"cast(round({c} * 100) AS BIGINT)"


_EVENTS = f"SELECT event_id AS id, user_id, ts, {_cents('value')} AS w FROM events"
_LINES = f"""SELECT row_number() OVER (ORDER BY l_orderkey, l_partkey, l_suppkey, l_linenumber, l_quantity, l_extendedprice, l_discount, l_tax,
    l_returnflag, l_linestatus, l_shipdate) AS rank, l_orderkey, {_cents('l_extendedprice')} AS w FROM lineitem"""

#: kind -> (SELECT of tree_id, node_id, parent_id, node_w, edge_w; depth expression over id, or None for a search).
TREES: dict[str, tuple[str, str | None]] = {
    "catalog": (
        f"""SELECT 0 AS tree_id, node AS node_id, parent AS parent_id, w AS node_w, w AS edge_w FROM (
            SELECT 0 AS node, NULL AS parent, 1 AS w
            UNION ALL SELECT {LEVEL} + r_regionkey, 0, 1 FROM region
            UNION ALL SELECT {2 * LEVEL} + n_nationkey, {LEVEL} + n_regionkey, 1 FROM nation
            UNION ALL SELECT {3 * LEVEL} + c_custkey, {2 * LEVEL} + c_nationkey, {_cents('abs(c_acctbal)')} FROM customer
            UNION ALL SELECT {4 * LEVEL} + o_orderkey, {3 * LEVEL} + o_custkey, {_cents('o_totalprice')} FROM orders
            UNION ALL SELECT {5 * LEVEL} + rank, {4 * LEVEL} + l_orderkey, w FROM ({_LINES}))""",
        None,
    ),
    "customers": (
        f"""SELECT tree AS tree_id, node AS node_id, parent AS parent_id, w AS node_w, w AS edge_w FROM (
            SELECT c_custkey AS tree, {3 * LEVEL} + c_custkey AS node, NULL AS parent, {_cents('abs(c_acctbal)')} AS w FROM customer
            UNION ALL SELECT o_custkey, {4 * LEVEL} + o_orderkey, {3 * LEVEL} + o_custkey, {_cents('o_totalprice')} FROM orders
            UNION ALL SELECT o_custkey, {5 * LEVEL} + rank, {4 * LEVEL} + l_orderkey, w FROM ({_LINES}) JOIN orders ON o_orderkey = l_orderkey)""",
        f"CASE WHEN node_id < {4 * LEVEL} THEN 0 WHEN node_id < {5 * LEVEL} THEN 1 ELSE 2 END",
    ),
    "chain_all": (f"SELECT 0 AS tree_id, id AS node_id, CASE WHEN id > 0 THEN id - 1 END AS parent_id, w AS node_w, w AS edge_w FROM ({_EVENTS})", "node_id"),
    "chain_user": (
        f"SELECT user_id AS tree_id, id AS node_id, lag(id) OVER (PARTITION BY user_id ORDER BY ts, id) AS parent_id, w AS node_w, w AS edge_w FROM ({_EVENTS})",
        "row_number() OVER (PARTITION BY tree_id ORDER BY node_id) - 1",
    ),
    "heap": (f"SELECT 0 AS tree_id, id AS node_id, CASE WHEN id > 0 THEN (id + 1) // 2 - 1 END AS parent_id, w AS node_w, w AS edge_w FROM ({_EVENTS})", None),
    "random": (f"SELECT 0 AS tree_id, id AS node_id, CASE WHEN id > 0 THEN ((id * 2654435761) % 4294967296) % id END AS parent_id, w AS node_w, w AS edge_w FROM ({_EVENTS})", None),
    "star": (f"SELECT 0 AS tree_id, 0 AS node_id, NULL AS parent_id, 0 AS node_w, 0 AS edge_w UNION ALL SELECT 0, p_partkey + 1, 0, {_cents('p_retailprice')}, {_cents('p_retailprice')} FROM part", None),
    "broom": (
        f"""SELECT 0 AS tree_id, id AS node_id, CASE WHEN id > 0 THEN id - 1 END AS parent_id, w AS node_w, w AS edge_w FROM ({_EVENTS})
            UNION ALL SELECT 0, {5 * LEVEL} + rank, (SELECT max(event_id) FROM events), w, w FROM ({_LINES})""",
        f"CASE WHEN node_id < {LEVEL} THEN node_id ELSE parent_id + 1 END",
    ),
    "caterpillar": (
        f"SELECT 0 AS tree_id, id AS node_id, CASE WHEN id = 0 THEN NULL WHEN id % 2 = 0 THEN id - 2 ELSE id - 1 END AS parent_id, w AS node_w, w AS edge_w FROM ({_EVENTS})",
        "CASE WHEN node_id % 2 = 0 THEN node_id // 2 ELSE (node_id - 1) // 2 + 1 END",
    ),
    "threads": ("SELECT conv_id AS tree_id, conv_id * 1000 + turn AS node_id, lag(conv_id * 1000 + turn) OVER (PARTITION BY conv_id ORDER BY turn) AS parent_id, length(text) AS node_w, 1 AS edge_w FROM conversations", None),
    "corpus": (
        f"""WITH d AS (SELECT doc_id, coalesce(lang, '') AS lang, coalesce(source, '') AS source, coalesce(n_chars, 0) AS w FROM documents),
            l AS (SELECT lang, dense_rank() OVER (ORDER BY lang) AS lid FROM (SELECT DISTINCT lang FROM d)),
            p AS (SELECT lang, source, dense_rank() OVER (ORDER BY lang, source) AS pid FROM (SELECT DISTINCT lang, source FROM d))
            SELECT 0 AS tree_id, node AS node_id, parent AS parent_id, w AS node_w, w AS edge_w FROM (
            SELECT 0 AS node, NULL AS parent, 0 AS w UNION ALL SELECT {LEVEL} + lid, 0, 0 FROM l
            UNION ALL SELECT {2 * LEVEL} + pid, {LEVEL} + lid, 0 FROM p JOIN l USING (lang)
            UNION ALL SELECT {3 * LEVEL} + doc_id, {2 * LEVEL} + pid, w FROM d JOIN p USING (lang, source))""",
        None,
    ),
}


def levels(kind: str) -> str:
    """CTEs tree and lev (tree with depth d)."""
    select, depth = TREES[kind]
    tree = f"tree AS MATERIALIZED (SELECT cast(tree_id AS BIGINT) AS tree_id, cast(node_id AS BIGINT) AS node_id, cast(parent_id AS BIGINT) AS parent_id, cast(node_w AS BIGINT) AS node_w, cast(edge_w AS BIGINT) AS edge_w FROM ({select}))"
    if depth:
        return f"{tree}, lev AS MATERIALIZED (SELECT *, cast({depth} AS BIGINT) AS d FROM tree)"
    return f"""{tree}, lev AS (
        SELECT *, cast(0 AS BIGINT) AS d FROM tree WHERE parent_id IS NULL
        UNION ALL SELECT t.*, lev.d + 1 FROM tree t JOIN lev ON t.tree_id = lev.tree_id AND t.parent_id = lev.node_id)"""


_INF = "1000000000000000"
_WITHIN = ["1 + coalesce(sq, 0)"]
_WITHIN.append(f"least({_WITHIN[0]}, coalesce(sp + near, {_INF}))")
_WITHIN.append(f"least({_WITHIN[1]}, coalesce(sc + far, {_INF}))")
#: problem -> (state columns of a vertex from its children's aggregates, aggregates over children, answer).
#: Aggregates are null for leaves. w is the vertex's weight, e the edge above the child.
RULES: dict[str, tuple[dict[str, str], dict[str, str], str]] = {
    "mis": ({"a": "w + coalesce(sb, 0)", "b": "coalesce(sab, 0)"}, {"sb": "sum(b)", "sab": "sum(greatest(a, b))"}, "greatest(a, b)"),
    "mvc": ({"a": "w + coalesce(sab, 0)", "b": "coalesce(sa, 0)"}, {"sa": "sum(a)", "sab": "sum(least(a, b))"}, "least(a, b)"),
    "mwm": ({"a": "coalesce(sab, 0)", "b": f"coalesce(sab + gain, -{_INF})"}, {"sab": "sum(greatest(a, b))", "gain": "max(e + a - greatest(a, b))"}, "greatest(a, b)"),
    "mds": (
        {"a": "w + coalesce(s3, 0)", "b": f"least(coalesce(s2 + gain, {_INF}), {_INF})", "c": f"least(coalesce(sb, 0), {_INF})"},
        {"s3": "sum(least(a, b, c))", "s2": "sum(least(a, b))", "gain": "min(a - least(a, b))", "sb": "sum(b)"},
        "least(a, b)",
    ),
    "lpath": (
        {"a": "greatest(0, coalesce(p1, 0))", "b": "greatest(0, coalesce(below, 0), coalesce(p1, 0) + coalesce(p2, 0))"},
        {"p1": "max(a + e)", "p2": "coalesce((max(a + e, 2))[2], 0)", "below": "max(b)"},
        "greatest(a, b)",
    ),
    "mids": (
        {"a": "w + coalesce(sbc, 0)", "b": f"least(coalesce(s2 + gain, {_INF}), {_INF})", "c": f"least(coalesce(sb, 0), {_INF})"},
        {"sbc": "sum(least(b, c))", "s2": "sum(least(a, b))", "gain": "min(a - least(a, b))", "sb": "sum(b)"},
        "least(a, b)",
    ),
    "mec": (
        {"a": f"least(coalesce(sn + gain, {_INF}), {_INF})", "b": f"least(coalesce(sa, 0), {_INF})"},
        {"sn": "sum(least(a, e + least(a, b)))", "gain": "min(e + least(a, b) - least(a, e + least(a, b)))", "sa": "sum(a)"},
        "a",
    ),
    "colour3": (
        {"a": "coalesce(sbc, 0)", "b": "w + coalesce(sac, 0)", "c": "w + node_w + coalesce(sab, 0)"},
        {"sbc": "sum(least(b, c))", "sac": "sum(least(a, c))", "sab": "sum(least(a, b))"},
        "least(a, b, c)",
    ),
    # served within two edges: a, b, c have a centre at most 0, 1, 2 edges below; of p and q only the
    # vertex itself, or what lies one edge below too, may still be unserved
    "domination2": (
        {"a": _WITHIN[0], "b": _WITHIN[1], "c": _WITHIN[2], "p": f"least({_WITHIN[2]}, coalesce(sc, 0))", "q": f"least({_WITHIN[2]}, coalesce(sc, 0), coalesce(sp, 0))"},
        {"sq": "sum(q)", "sp": "sum(p)", "sc": "sum(c)", "near": "min(a - p)", "far": "min(b - c)"},
        "c",
    ),
    "height": ({"a": "coalesce(h, -1) + 1"}, {"h": "max(a)"}, "a"),
    "subtree_sum": ({"a": "w + coalesce(s, 0)"}, {"s": "sum(a)"}, "a"),
    "subtree_size": ({"a": "1 + coalesce(s, 0)"}, {"s": "sum(a)"}, "a"),
}
UNIT = {"mcm": "mwm"}


def bottom_up(kind: str, problem: str) -> str:
    """CTEs up to `up`: one row for every vertex with its states."""
    unit = problem in UNIT
    states, aggs, _ = RULES[UNIT.get(problem, problem)]
    w, e = ("1", "1") if unit else ("l.node_w", "edge_w")
    columns = ", ".join(f"cast({x.replace('w + ', w + ' + ', 1) if x.startswith('w + ') else x} AS BIGINT) AS {s}" for s, x in states.items())
    leaf_aggs = ", ".join(f"NULL AS {a}" for a in aggs)
    group = ", ".join(f"{x} AS {a}" for a, x in aggs.items())
    return f"""{levels(kind)}, up AS (
        SELECT l.tree_id, l.node_id, l.parent_id, l.edge_w, l.d, {columns}
        FROM (SELECT * FROM lev WHERE d = (SELECT max(d) FROM lev)) l, (SELECT {leaf_aggs}) c
        UNION ALL
        SELECT l.tree_id, l.node_id, l.parent_id, l.edge_w, l.d, {columns}
        FROM lev l JOIN (SELECT max(d) AS top FROM up) t ON l.d = t.top - 1
        LEFT JOIN (SELECT tree_id, parent_id, {group} FROM (SELECT *, {e} AS e FROM up) GROUP BY tree_id, parent_id) c ON l.tree_id = c.tree_id AND l.node_id = c.parent_id)"""


NAMES = {
    "mwm": "maximum_weight_matching",
    "mcm": "maximum_matching",
    "mvc": "minimum_vertex_cover",
    "mis": "maximum_independent_set",
    "mds": "minimum_dominating_set",
    "lpath": "longest_path",
    "mids": "minimum_independent_dominating_set",
    "mec": "minimum_edge_cover",
    "colour3": "colouring_3",
    "domination2": "domination_2_hops",
    "height": "height",
    "subtree_sum": "subtree_sum",
    "subtree_size": "subtree_size",
}


def answers(kind: str, problem: str) -> str:
    answer = RULES[UNIT.get(problem, problem)][2]
    return f"WITH RECURSIVE {bottom_up(kind, problem)} SELECT tree_id, '{NAMES[problem]}' AS problem, cast({answer} AS BIGINT) AS value FROM up WHERE parent_id IS NULL"


def vertex_values(kind: str, problem: str) -> str:
    answer = RULES[UNIT.get(problem, problem)][2]
    return f"WITH RECURSIVE {bottom_up(kind, problem)} SELECT tree_id, node_id, cast({answer} AS BIGINT) AS value FROM up"


def distances(kind: str) -> str:
    """CTEs up to dist(tree_id, x, y, d): all distances inside every tree of a forest, over common ancestors."""
    return f"""{levels(kind)}, anc AS (
        SELECT tree_id, node_id AS x, node_id AS a, cast(0 AS BIGINT) AS d FROM tree
        UNION ALL SELECT anc.tree_id, anc.x, t.parent_id, anc.d + t.edge_w FROM anc JOIN tree t ON t.tree_id = anc.tree_id AND t.node_id = anc.a WHERE t.parent_id IS NOT NULL),
        dist AS MATERIALIZED (SELECT p.tree_id, p.x AS x, q.x AS y, min(p.d + q.d) AS d FROM anc p JOIN anc q ON p.tree_id = q.tree_id AND p.a = q.a GROUP BY p.tree_id, p.x, q.x)"""


def served(kind: str, total: str) -> str:
    """Least farthest (total 'max') or summed ('sum') distance of every tree's vertices to the nearer of two of them."""
    return f"""WITH RECURSIVE {distances(kind)}
        SELECT tree_id, min(cost)::BIGINT AS value FROM (
            SELECT a.tree_id, {total}(least(a.d, b.d)) AS cost FROM dist a JOIN dist b ON a.tree_id = b.tree_id AND a.y = b.y AND a.x <= b.x GROUP BY a.tree_id, a.x, b.x) GROUP BY tree_id"""


def least_diameter(kind: str, k: int) -> str:
    """Least diameter of k vertices of every tree: those no farther from both ends of a path than it is long; null where there are fewer."""
    return f"""WITH RECURSIVE {distances(kind)}, held AS (
            SELECT e.tree_id, e.x, e.y, any_value(e.d) AS d, count(*) AS n FROM dist e
            JOIN dist a ON a.tree_id = e.tree_id AND a.x = e.x AND a.d <= e.d JOIN dist b ON b.tree_id = e.tree_id AND b.x = e.y AND b.y = a.y AND b.d <= e.d
            WHERE e.x <= e.y GROUP BY e.tree_id, e.x, e.y)
        SELECT t.tree_id, (min(d) FILTER (n >= {k}))::BIGINT AS value FROM (SELECT DISTINCT tree_id FROM tree) t LEFT JOIN held USING (tree_id) GROUP BY t.tree_id"""


def chain_positions(kind: str) -> str:
    """CTEs up to pos(tree_id, i, place, node_w, edge_w, n): vertices of a forest of chains by place, with their distance from the root."""
    return f"""{levels(kind)}, pos AS MATERIALIZED (
        SELECT tree_id, d AS i, coalesce(sum(CASE WHEN d > 0 THEN edge_w END) OVER (PARTITION BY tree_id ORDER BY d), 0)::BIGINT AS place, node_w, edge_w, count(*) OVER (PARTITION BY tree_id) AS n FROM lev)"""


def chain_profiles(kind: str) -> str:
    """CTEs up to prof(tree_id, idx, v): cheapest cut of every chain of a forest with idx vertices on one side."""
    return f"""{chain_positions(kind)}, step AS (
        SELECT tree_id, cast(0 AS BIGINT) AS i, c AS colour, cast(c AS BIGINT) AS b, cast(0 AS BIGINT) AS v FROM pos, (VALUES (0), (1)) t(c) WHERE i = 0
        UNION ALL
        SELECT s.tree_id, s.i + 1, x.c, s.b + x.c, min(s.v + CASE WHEN x.c <> s.colour THEN t.edge_w ELSE 0 END)
        FROM step s JOIN pos t ON t.tree_id = s.tree_id AND t.i = s.i + 1, (VALUES (0), (1)) x(c) GROUP BY s.tree_id, s.i + 1, x.c, s.b + x.c),
        prof AS (SELECT s.tree_id, s.b AS idx, min(s.v) AS v, any_value(p.n) AS n FROM step s JOIN pos p ON p.tree_id = s.tree_id AND p.i = s.i AND s.i = p.n - 1 GROUP BY s.tree_id, s.b)"""


def chain_facilities(kind: str) -> str:
    """Cheapest opening and serving of every chain: stretches of vertices, each served by one of them."""
    return f"""WITH RECURSIVE {chain_positions(kind)}, sums AS (
            SELECT *, sum(place) OVER (PARTITION BY tree_id ORDER BY i)::BIGINT AS s FROM pos
        ), stretch AS MATERIALIZED (
            SELECT a.tree_id, a.i AS lo, b.i AS hi,
                   min(u.node_w + (u.i - a.i + 1) * u.place - (u.s - a.s + a.place) + (b.s - u.s) - (b.i - u.i) * u.place)::BIGINT AS cost
            FROM sums a JOIN sums b ON a.tree_id = b.tree_id AND a.i <= b.i JOIN sums u ON u.tree_id = a.tree_id AND u.i BETWEEN a.i AND b.i
            GROUP BY a.tree_id, a.i, b.i
        ), best AS (
            SELECT tree_id, -1::BIGINT AS i, [0::BIGINT] AS till FROM pos WHERE i = 0
            UNION ALL
            SELECT b.tree_id, b.i + 1, list_append(any_value(b.till), min(b.till[s.lo + 1] + s.cost)) FROM best b JOIN stretch s ON s.tree_id = b.tree_id AND s.hi = b.i + 1 GROUP BY b.tree_id, b.i
        )
        SELECT best.tree_id, till[n + 1] AS value FROM best JOIN (SELECT DISTINCT tree_id, n FROM pos) p ON p.tree_id = best.tree_id AND best.i = p.n - 1"""
