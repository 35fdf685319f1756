"""SQL for DuckDB that gives the rows of the graph queries: the star graph as views, and searches as recursive walks."""

from __future__ import annotations

from ..operators.predicate_space import AUTHORED

B = "1000000000000"

STAR_NODES = f"""
brands AS (SELECT p_brand AS value, row_number() OVER (ORDER BY p_brand) AS key FROM (SELECT DISTINCT p_brand FROM part)),
nodes AS (
    SELECT 1 * {B} + r_regionkey AS node_id, r_name AS name, ['Region'] AS types FROM region
    UNION ALL SELECT 2 * {B} + n_nationkey, n_name, ['Nation'] FROM nation
    UNION ALL SELECT 3 * {B} + c_custkey, c_name, ['Customer', c_mktsegment] FROM customer
    UNION ALL SELECT 4 * {B} + s_suppkey, s_name, ['Supplier'] FROM supplier
    UNION ALL SELECT 5 * {B} + p_partkey, 'Part#' || p_partkey, ['Part', p_type] FROM part
    UNION ALL SELECT 6 * {B} + o_orderkey, 'Order#' || o_orderkey, ['Order', o_orderpriority] FROM orders
    UNION ALL SELECT 7 * {B} + key, value, ['Brand'] FROM brands
)"""

STAR_EDGES = f"""
edges AS (
    SELECT DISTINCT src, predicate, dst FROM (
        SELECT 2 * {B} + n_nationkey AS src, 'inRegion' AS predicate, 1 * {B} + n_regionkey AS dst FROM nation
        UNION ALL SELECT 3 * {B} + c_custkey, 'customerNation', 2 * {B} + c_nationkey FROM customer
        UNION ALL SELECT 4 * {B} + s_suppkey, 'supplierNation', 2 * {B} + s_nationkey FROM supplier
        UNION ALL SELECT 6 * {B} + o_orderkey, 'placedBy', 3 * {B} + o_custkey FROM orders WHERE o_orderkey % 4 <> 0
        UNION ALL SELECT 6 * {B} + o_orderkey, 'originNation', 2 * {B} + c_nationkey FROM orders JOIN customer ON o_custkey = c_custkey WHERE o_orderkey % 4 = 0
        UNION ALL SELECT 6 * {B} + l_orderkey, 'containsPart', 5 * {B} + l_partkey FROM lineitem
        UNION ALL SELECT 6 * {B} + l_orderkey, 'fulfilledBy', 4 * {B} + l_suppkey FROM lineitem
        UNION ALL SELECT 5 * {B} + l_partkey, 'suppliedBy', 4 * {B} + l_suppkey FROM lineitem
        UNION ALL SELECT 5 * {B} + p_partkey, 'hasBrand', 7 * {B} + key FROM part JOIN brands ON p_brand = value
    )
)"""

ADJ = """
adj AS (SELECT src AS node, dst AS nbr, predicate, true AS forward FROM edges UNION ALL SELECT dst, src, predicate, false FROM edges)"""

STAR = f"{STAR_NODES},{STAR_EDGES},{ADJ}"

ACTIVITY = f"""
seen AS (SELECT *, CAST(json_extract_string(props, '$.k') AS BIGINT) AS topic FROM events),
edges AS (SELECT DISTINCT 3 * {B} + user_id AS src, event_type AS predicate, 8 * {B} + topic AS dst FROM seen WHERE topic IS NOT NULL),{ADJ}"""

_rows = ", ".join(f"('{p}', [{', '.join(f'{float(x)}' for x in v)}])" for p, v in AUTHORED.items())
SPACE = f"""
space(predicate, vec) AS (VALUES {_rows}),
sims AS (
    SELECT a.predicate AS a, b.predicate AS b,
        list_sum(list_transform(list_zip(a.vec, b.vec), lambda p: p[1] * p[2]))
        / (sqrt(list_sum(list_transform(a.vec, lambda x: x * x))) * sqrt(list_sum(list_transform(b.vec, lambda x: x * x)))) AS sim
    FROM space a CROSS JOIN space b
)"""

ORDER = f"SELECT 6 * {B} + o_orderkey AS node FROM orders"
SUPPLIER = f"SELECT 4 * {B} + s_suppkey AS node FROM supplier"
CUSTOMER = f"SELECT 3 * {B} + c_custkey AS node FROM customer"
PART = f"SELECT 5 * {B} + p_partkey AS node FROM part"
NATION = f"SELECT 2 * {B} + n_nationkey AS node FROM nation"
TOPIC = f"SELECT DISTINCT 8 * {B} + topic AS node FROM seen WHERE topic IS NOT NULL"


def nation(key: int) -> str:
    return f"SELECT 2 * {B} + {key} AS node"


def named(name: str) -> str:
    return f"SELECT node_id AS node FROM nodes WHERE name = '{name}'"


def of_type(name: str) -> str:
    return f"SELECT node_id AS node FROM nodes WHERE list_contains(types, '{name}')"


def walk(i: int, source: str, stages: list[tuple[str, str]], pivot_pos: int, tau: float, root: int, prune: bool = True, simple: bool = True) -> str:
    """Views of sub-query i: `list_i(pv, psi)`, the best score of each pv, over simple paths of at most `root` edges.

    stages: (query predicate, SQL of the nodes that end it). Products under tau^root cannot come back and are cut.
    """
    cut = tau**root - 1e-12 if prune else -1
    marks = " UNION ALL ".join(f"SELECT {s} AS stage, node FROM ({sql})" for s, (_, sql) in enumerate(stages))
    weights = " UNION ALL ".join(f"SELECT {s} AS stage, b AS predicate, sim AS w FROM sims WHERE a = '{p}' AND sim > 0 AND sim >= {cut}" for s, (p, _) in enumerate(stages))
    last = len(stages) - 1
    return f"""
marks_{i} AS ({marks}),
weights_{i} AS ({weights}),
walk_{i}(node, stage, hops, wp, path, pv, done) AS (
    SELECT CAST(node AS BIGINT), 0, 0, CAST(1 AS DOUBLE), [CAST(node AS BIGINT)], CAST(NULL AS BIGINT), false FROM ({source})
    UNION ALL
    SELECT a.nbr, CASE WHEN m.node IS NOT NULL AND x.stage < {last} THEN x.stage + 1 ELSE x.stage END, x.hops + 1, x.wp * w.w, list_append(x.path, a.nbr),
        CASE WHEN m.node IS NOT NULL AND x.stage + 1 = {pivot_pos} THEN a.nbr ELSE x.pv END, m.node IS NOT NULL AND x.stage = {last}
    FROM walk_{i} x JOIN adj a ON a.node = x.node JOIN weights_{i} w ON w.stage = x.stage AND w.predicate = a.predicate LEFT JOIN marks_{i} m ON m.stage = x.stage AND m.node = a.nbr
    WHERE NOT x.done AND x.hops < {root} AND NOT list_contains(x.path, a.nbr) AND x.wp * w.w >= {cut}
),
list_{i} AS (SELECT pv, max(pow(wp, 1.0 / hops)) AS psi FROM walk_{i} WHERE done AND pow(wp, 1.0 / hops) >= {tau} - 1e-12 GROUP BY pv)"""


def answers(lists: list[str], k: int, graph: str = STAR, complete: bool = True, n: int | None = None) -> str:
    """rank, pivot_id, score of the best k pivots over lists made by `walk`."""
    n = n or len(lists)
    union = " UNION ALL ".join(f"SELECT pv, psi FROM list_{i}" for i in range(n))
    having = f"HAVING count(*) = {n}" if complete else ""
    return f"""WITH RECURSIVE {graph},{SPACE},{",".join(lists)},
total AS (SELECT pv AS pivot_id, round(sum(psi), 9) AS score FROM ({union}) GROUP BY pv {having}),
ranked AS (SELECT CAST(row_number() OVER (ORDER BY score DESC, pivot_id) AS INTEGER) AS rank, pivot_id, score FROM total)
SELECT rank, pivot_id, round(score, 6) AS score FROM ranked WHERE rank <= {k}"""


def many(queries: list[tuple[int, str, str]], target: str, tau: float, root: int, k: int) -> str:
    """Views of many queries of one edge: `ranked_many(q, rank, pv, score)` with the k best of each.

    queries: (number, SQL of the source's id, query predicate); target: SQL of the nodes that end all of them.
    """
    cut = tau**root - 1e-12
    rows = ", ".join(f"({q}, {node}, '{predicate}')" for q, node, predicate in queries)
    return f"""
asked(q, node, pred) AS (VALUES {rows}), ends AS ({target}),
usable AS (SELECT a AS pred, b AS predicate, sim AS w FROM sims WHERE sim > 0 AND sim >= {cut} AND a IN (SELECT pred FROM asked)),
walk_many(q, pred, node, hops, wp, path, done) AS (
    SELECT q, pred, CAST(node AS BIGINT), 0, CAST(1 AS DOUBLE), [CAST(node AS BIGINT)], false FROM asked
    UNION ALL
    SELECT x.q, x.pred, a.nbr, x.hops + 1, x.wp * w.w, list_append(x.path, a.nbr), e.node IS NOT NULL
    FROM walk_many x JOIN adj a ON a.node = x.node JOIN usable w ON w.pred = x.pred AND w.predicate = a.predicate LEFT JOIN ends e ON e.node = a.nbr
    WHERE NOT x.done AND x.hops < {root} AND NOT list_contains(x.path, a.nbr) AND x.wp * w.w >= {cut}
),
scored AS (SELECT q, node AS pv, max(round(pow(wp, 1.0 / hops), 9)) AS score FROM walk_many WHERE done AND pow(wp, 1.0 / hops) >= {tau} - 1e-12 GROUP BY 1, 2),
ranked_many AS (SELECT * FROM (SELECT q, row_number() OVER (PARTITION BY q ORDER BY score DESC, pv) AS rank, pv, score FROM scored) WHERE rank <= {k})"""


def quality(ranked: str, truth: str, ks: tuple[int, ...]) -> str:
    """SELECT of (k, precision, recall, f1): means over the queries of a view `ranked`(q, rank, pv), against SQL of truth(q, node)."""
    grid = ", ".join(f"({k})" for k in ks)
    return f"""SELECT k, round(avg(precision), 6) AS precision, round(avg(recall), 6) AS recall, round(avg(f1), 6) AS f1 FROM (
    SELECT t.q, g.k, coalesce(correct / nullif(returned, 0), 0) AS precision, coalesce(correct / nullif(total, 0), 0) AS recall, coalesce(2.0 * correct / nullif(returned + total, 0), 0) AS f1
    FROM (SELECT q, count(*) AS total FROM ({truth}) GROUP BY 1) t CROSS JOIN (VALUES {grid}) g(k)
    LEFT JOIN (SELECT r.q, h.k, count(*) AS returned, count(y.node) AS correct FROM {ranked} r JOIN (VALUES {grid}) h(k) ON r.rank <= h.k LEFT JOIN ({truth}) y ON y.q = r.q AND y.node = r.pv GROUP BY 1, 2) c ON c.q = t.q AND c.k = g.k
) GROUP BY k"""


def with_star(body: str) -> str:
    return f"WITH RECURSIVE {STAR},{SPACE} {body}"
