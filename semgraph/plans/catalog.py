"""Queries of the graph engine by name, and their SQL for DuckDB."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.scores import psi_hat
from ..model import KG, Params, QueryEdge, QueryGraph, QueryNode, SubQuery
from ..operators import assembly as A
from ..operators import baselines as BL
from ..operators import library as L
from ..operators import metrics as M
from ..operators import predicate_space as P
from ..operators import search as S
from ..sources import builders as G
from ..sources.index import index_of
from ..sources.tables import load, local, scratch
from . import decompose as D
from . import engine as E
from . import oracle as O
from . import surround
from . import workloads as W

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


def _space(spark: SparkSession) -> dict[str, list[float]]:
    return {p: [float(x) for x in v] for p, v in P.AUTHORED.items()}


def _rounded(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in cols})


def _answers(df: DataFrame) -> DataFrame:
    return _rounded(df.select("rank", "pivot_id", "score"), "score")


def _sub(i: int, path: list[QueryNode], predicates: list[str], pivot_pos: int) -> SubQuery:
    return SubQuery(i, tuple(path), tuple(predicates), pivot_pos)


ORDER, SUPPLIER, NATION, PART, CUSTOMER = (QueryNode(k, (t,)) for k, t in (("o", "Order"), ("s", "Supplier"), ("n", "Nation"), ("p", "Part"), ("c", "Customer")))
N7, N3 = QueryNode("n7", ("Nation",), "N7"), QueryNode("n3", ("Nation",), "NATION_3")

# ---- the graph ----


@query("kg_node_counts", f"WITH {O.STAR_NODES} SELECT types[1] AS type, count(*) AS n FROM nodes GROUP BY 1")
def kg_node_counts(spark, d):
    return G.stored_kg(spark, d, "star").nodes.groupBy(F.get("types", F.lit(0)).alias("type")).agg(F.count("*").alias("n"))


@query("kg_edge_counts", f"WITH {O.STAR_NODES},{O.STAR_EDGES} SELECT predicate, count(*) AS n FROM edges GROUP BY 1")
def kg_edge_counts(spark, d):
    return G.stored_kg(spark, d, "star").edges.groupBy("predicate").agg(F.count("*").alias("n"))


@query("kg_homogeneous_counts", f"WITH {O.STAR_NODES},{O.STAR_EDGES.replace(' WHERE o_orderkey % 4 <> 0', '').replace(' WHERE o_orderkey % 4 = 0', '')} SELECT predicate, count(*) AS n FROM edges GROUP BY 1")
def kg_homogeneous_counts(spark, d):
    return G.star_kg(spark, d, heterogeneous=False).edges.groupBy("predicate").agg(F.count("*").alias("n"))


@query("kg_degree_by_type", f"WITH {O.STAR}, deg AS (SELECT node, count(*) AS n FROM adj GROUP BY node) SELECT types[1] AS type, max(n) AS max_degree, CAST(sum(n) AS BIGINT) AS total FROM deg JOIN nodes ON node = node_id GROUP BY 1")
def kg_degree_by_type(spark, d):
    kg = G.stored_kg(spark, d, "star")
    deg = G.adjacency(kg.edges).groupBy("node").agg(F.count("*").alias("n"))
    typed = deg.join(kg.nodes.select(F.col("node_id").alias("node"), F.get("types", F.lit(0)).alias("type")), "node")
    return typed.groupBy("type").agg(F.max("n").alias("max_degree"), F.sum("n").alias("total"))


@query("kg_type_predicate_cube", f"WITH {O.STAR} SELECT types[1] AS type, predicate, count(*) AS n FROM adj JOIN nodes ON node = node_id GROUP BY CUBE (types[1], predicate)")
def kg_type_predicate_cube(spark, d):
    kg = G.stored_kg(spark, d, "star")
    first = kg.nodes.select(F.col("node_id").alias("node"), F.get("types", F.lit(0)).alias("type"))
    return G.adjacency(kg.edges).join(first, "node").cube("type", "predicate").agg(F.count("*").alias("n"))


@query("kg_rollup_types", f"WITH {O.STAR_NODES} SELECT types[1] AS kind, types[2] AS detail, count(*) AS n FROM nodes GROUP BY ROLLUP (types[1], types[2])")
def kg_rollup_types(spark, d):
    t = G.stored_kg(spark, d, "star").nodes.select(F.get("types", F.lit(0)).alias("kind"), F.get("types", F.lit(1)).alias("detail"))
    return t.rollup("kind", "detail").agg(F.count("*").alias("n"))


@query("kg_adjacency_both", f"WITH {O.STAR} SELECT node, nbr, predicate, forward FROM adj WHERE predicate IN ('inRegion', 'supplierNation')")
def kg_adjacency_both(spark, d):
    return G.adjacency(G.stored_kg(spark, d, "star").edges).filter(F.col("predicate").isin("inRegion", "supplierNation"))


@query("kg_stats", f"WITH {O.STAR} SELECT types[1] AS type, predicate, CASE WHEN forward THEN 'out' ELSE 'in' END AS direction, count(DISTINCT node) AS nodes, count(*) AS edges, round(count(*) / count(DISTINCT node), 6) AS mean_fanout FROM adj JOIN nodes ON node = node_id GROUP BY 1, 2, 3")
def kg_stats(spark, d):
    return _rounded(D.stats_table(G.stored_kg(spark, d, "star")), "mean_fanout")


@query("kg_activity_counts", f"WITH {O.ACTIVITY} SELECT predicate, count(*) AS n, count(DISTINCT src) AS users, count(DISTINCT dst) AS topics FROM edges GROUP BY 1")
def kg_activity_counts(spark, d):
    return G.activity_kg(spark, d).edges.groupBy("predicate").agg(F.count("*").alias("n"), F.countDistinct("src").alias("users"), F.countDistinct("dst").alias("topics"))


@query("kg_content_counts", """
WITH links AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS href FROM pages)
SELECT 'fromSource' AS predicate, count(*) AS n FROM documents WHERE source IS NOT NULL
UNION ALL SELECT 'writtenIn', count(*) FROM documents WHERE lang IS NOT NULL
UNION ALL SELECT 'onHost', count(*) FROM pages
UNION ALL SELECT 'linksTo', count(*) FROM links
UNION ALL SELECT 'quotes', count(*) FROM documents d JOIN benchmark b ON contains(d.text, b.text)""")
def kg_content_counts(spark, d):
    return G.content_kg(spark, d).edges.groupBy("predicate").agg(F.count("*").alias("n"))


@query("kg_dialog_counts", """
WITH role_names AS (SELECT DISTINCT role FROM conversations)
SELECT 'partOf' AS predicate, count(*) AS n FROM conversations
UNION ALL SELECT 'spokenBy', count(*) FROM conversations WHERE role IS NOT NULL
UNION ALL SELECT 'follows', count(*) FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND a.turn = b.turn - 1""")
def kg_dialog_counts(spark, d):
    return G.dialog_kg(spark, d).edges.groupBy("predicate").agg(F.count("*").alias("n"))


@query("kg_vector_counts", """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS e FROM embeddings)
SELECT count(*) AS edges, CAST(sum(a.vec_id) AS BIGINT) AS check_a, CAST(sum(b.vec_id) AS BIGINT) AS check_b FROM v a JOIN v b ON a.vec_id < b.vec_id AND list_sum(list_transform(list_zip(a.e, b.e), lambda p: p[1] * p[2])) >= 0.35""")
def kg_vector_counts(spark, d):
    e = G.vector_kg(spark, d).edges
    base = G.KINDS["vector"] * G.BASE
    return e.agg(F.count("*").alias("edges"), F.sum(F.col("src") - base).alias("check_a"), F.sum(F.col("dst") - base).alias("check_b"))


@query("kg_restrict_entities", f"WITH {O.STAR}, kept AS (SELECT node_id FROM nodes WHERE name LIKE 'NATION%' OR name LIKE 'Supplier%') SELECT predicate, count(*) AS n FROM edges WHERE src IN (SELECT node_id FROM kept) AND dst IN (SELECT node_id FROM kept) GROUP BY 1")
def kg_restrict_entities(spark, d):
    kg = G.stored_kg(spark, d, "star")
    names = kg.nodes.select("name").filter("name LIKE 'NATION%' OR name LIKE 'Supplier%'").distinct()
    return G.restrict_entities(kg, names).edges.groupBy("predicate").agg(F.count("*").alias("n"))


@query("kg_core_portion", f"WITH {O.STAR} SELECT predicate, count(*) AS n FROM edges WHERE src // {O.B} NOT IN (5, 7) AND dst // {O.B} NOT IN (5, 7) GROUP BY 1")
def kg_core_portion(spark, d):
    return G.core_portion(G.stored_kg(spark, d, "star"), ["part", "brand"]).edges.groupBy("predicate").agg(F.count("*").alias("n"))


@query("subgraph_counts", f"WITH {O.STAR} SELECT p AS percent, (SELECT count(*) FROM nodes WHERE node_id % 100 < p) AS nodes, (SELECT count(*) FROM edges WHERE src % 100 < p AND dst % 100 < p) AS edges FROM (VALUES (44), (67), (100)) t(p)")
def subgraph_counts(spark, d):
    kg = G.stored_kg(spark, d, "star")
    out = None
    for percent in (44, 67, 100):
        part = G.induced_subgraph(kg, percent)
        own = part.nodes.agg(F.lit(percent).alias("percent"), F.count("*").alias("nodes")).crossJoin(part.edges.agg(F.count("*").alias("edges")))
        out = own if out is None else out.unionByName(own)
    return out


# ---- node matching ----


def _phi(name: str, node: QueryNode, relations: tuple[str, ...], sql: str) -> None:
    @query(name, f"WITH {O.STAR_NODES} {sql}")
    def run(spark, d):
        kg = G.stored_kg(spark, d, "star")
        return L.match_nodes(kg, L.build_library(kg), node, relations).select("node_id", "relation")


ALL = ("identical", "synonym", "abbreviation")
_phi("phi_identical", QueryNode("x", ("order",)), ("identical",), "SELECT node_id, 'identical' AS relation FROM nodes WHERE list_contains(types, 'Order')")
_phi("phi_synonym", QueryNode("x", ("Purchase",)), ("identical", "synonym"), "SELECT node_id, 'synonym' AS relation FROM nodes WHERE list_contains(types, 'Order')")
_phi("phi_abbreviation", QueryNode("x", ("Country",), "N7"), ALL, "SELECT node_id, 'abbreviation' AS relation FROM nodes WHERE name = 'NATION_7'")
_phi("phi_multitype", QueryNode("x", ("BUILDING",)), ALL, "SELECT node_id, 'identical' AS relation FROM nodes WHERE list_contains(types, 'BUILDING')")
_phi("phi_union_types", QueryNode("x", ("PROMO", "ECONOMY", "Vendor")), ALL, "SELECT node_id, CASE WHEN list_contains(types, 'Supplier') THEN 'synonym' ELSE 'identical' END AS relation FROM nodes WHERE list_has_any(types, ['PROMO', 'ECONOMY', 'Supplier'])")
_phi("phi_specific", QueryNode("x", ("Nation",), "EUROPE"), ALL, "SELECT node_id, 'identical' AS relation FROM nodes WHERE list_contains(types, 'Nation') AND name = 'EUROPE'")


@query("phi_wildcard", f"WITH {O.STAR_NODES} SELECT count(*) AS n FROM nodes")
def phi_wildcard(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return L.match_nodes(kg, L.build_library(kg), QueryNode("x")).agg(F.count("*").alias("n"))


@query("library_initials", "SELECT 'N' || n_nationkey AS surface, n_name AS canonical FROM nation UNION ALL SELECT 'ME', 'MIDDLE EAST'")
def library_initials(spark, d):
    names = G.stored_kg(spark, d, "star").nodes.filter(F.arrays_overlap("types", F.array(F.lit("Nation"), F.lit("Region")))).select("name")
    return L.initials_rule(names).select("surface", "canonical")


TYPING = f"""
WITH {O.STAR}, firsts AS (SELECT node_id, types[1] AS type, node_id % 10 = 3 AS hidden FROM nodes),
evidence AS (SELECT node AS node_id, predicate || CASE WHEN forward THEN '>' ELSE '<' END AS sign FROM adj),
prior AS (SELECT type, count(*) AS members FROM firsts WHERE NOT hidden GROUP BY 1),
seen AS (SELECT type, sign, count(*) AS n FROM evidence JOIN firsts USING (node_id) WHERE NOT hidden GROUP BY 1, 2),
totals AS (SELECT type, sum(n) AS total FROM seen GROUP BY 1), signs AS (SELECT DISTINCT sign FROM evidence),
model AS (
    SELECT p.type, s.sign, ln(members / (SELECT sum(members) FROM prior)) AS prior, ln((coalesce(n, 0) + 1) / (coalesce(total, 0) + (SELECT count(*) FROM signs))) AS ll
    FROM prior p CROSS JOIN signs s LEFT JOIN seen USING (type, sign) LEFT JOIN totals USING (type)
), counts AS (SELECT node_id, sign, count(*) AS times FROM evidence JOIN firsts USING (node_id) WHERE hidden GROUP BY 1, 2),
scored AS (SELECT node_id, type, first(prior) + sum(times * ll) AS score FROM counts JOIN model USING (sign) GROUP BY 1, 2),
best AS (SELECT node_id, type, row_number() OVER (PARTITION BY node_id ORDER BY score DESC, type) AS r FROM scored)
SELECT f.type AS real, b.type AS predicted, count(*) AS n FROM best b JOIN firsts f USING (node_id) WHERE r = 1 GROUP BY 1, 2"""


@query("typing_naive_bayes", TYPING)
def typing_naive_bayes(spark, d):
    kg = G.stored_kg(spark, d, "star")
    first = F.slice("types", 1, 1)
    hidden = kg.nodes.withColumn("types", F.when(F.col("node_id") % 10 == 3, F.array().cast("array<string>")).otherwise(first))
    found = L.infer_types(KG(hidden, kg.edges))
    real = kg.nodes.select("node_id", F.get("types", F.lit(0)).alias("real"))
    return found.join(real, "node_id").groupBy("real", F.col("type").alias("predicted")).agg(F.count("*").alias("n"))


# ---- the predicate space ----


@query("pred_cosine_authored", f"WITH {O.SPACE}, held AS (SELECT event_type, count(*) AS edges FROM events GROUP BY 1) SELECT a, b, round(sim, 6) AS sim, edges FROM sims JOIN held ON event_type = b")
def pred_cosine_authored(spark, d):
    """(a, b, sim, edges): every predicate of the space against those of the events, with the events that have it."""
    held = load(spark, d, "events").groupBy(F.col("event_type").alias("b")).agg(F.count("*").alias("edges"))
    return _rounded(P.predicate_similarity(P.predicate_space(spark)).join(held, "b").select("a", "b", "sim", "edges"), "sim")


_blend_rows = ", ".join(f"('{p}', {i}, {axis}, {float(x)})" for i, (p, v) in enumerate(P.AUTHORED.items()) for axis, x in [*enumerate(v), (10 + i, 0.2)])


BLEND = f"""parts(predicate, i, vec_id, c) AS (VALUES {_blend_rows}), wide AS (
    SELECT predicate, pos, sum(c * CAST(embedding[pos] AS DOUBLE)) AS x FROM parts JOIN embeddings USING (vec_id), (SELECT unnest(range(1, 65)) AS pos) GROUP BY 1, 2
), blended AS (SELECT p.predicate AS a, q.predicate AS b, sum(p.x * q.x) / sqrt(sum(p.x * p.x) * sum(q.x * q.x)) AS sim FROM wide p JOIN wide q USING (pos) GROUP BY 1, 2)"""


@query("pred_cosine_blend", f"""
WITH parts(predicate, i, vec_id, c) AS (VALUES {_blend_rows}), wide AS (
    SELECT predicate, pos, sum(c * CAST(embedding[pos] AS DOUBLE)) AS x FROM parts JOIN embeddings USING (vec_id), (SELECT unnest(range(1, 65)) AS pos) GROUP BY 1, 2
)
SELECT p.predicate AS a, q.predicate AS b, round(sum(p.x * q.x) / sqrt(sum(p.x * p.x) * sum(q.x * q.x)), 6) AS sim FROM wide p JOIN wide q USING (pos) GROUP BY 1, 2""")
def pred_cosine_blend(spark, d):
    return _rounded(P.predicate_similarity(P.predicate_space(spark, "blend", load(spark, d, "embeddings"))), "sim")


@query("pred_top10_similar", f"WITH {BLEND}, r AS (SELECT a, b, sim, row_number() OVER (PARTITION BY a ORDER BY round(sim, 9) DESC, b) AS rank FROM blended WHERE a <> b) SELECT a, b, round(sim, 6) AS sim, CAST(rank AS INTEGER) AS rank FROM r WHERE rank <= 10")
def pred_top10_similar(spark, d):
    """The ten most similar predicates of each, in the space that is blended from the embeddings."""
    from pyspark.sql import Window

    sims = P.predicate_similarity(P.predicate_space(spark, "blend", load(spark, d, "embeddings"))).filter("a != b")
    order = Window.partitionBy("a").orderBy(F.desc(F.round("sim", 9)), "b")
    return _rounded(sims.withColumn("rank", F.row_number().over(order)).filter("rank <= 10"), "sim")


@query("pred_static_cut", f"WITH {O.STAR_NODES},{O.STAR_EDGES},{O.SPACE} SELECT b AS predicate, round(sim, 6) AS w, count(*) AS edges FROM sims JOIN edges ON predicate = b WHERE a = 'originNation' AND sim >= pow(0.8, 4) - 1e-12 GROUP BY 1, 2")
def pred_static_cut(spark, d):
    """(predicate, w, edges): what the static cut leaves of the star graph for an origin query."""
    sub = _sub(0, [N7, ORDER], ["originNation"], 1)
    kept = local(spark, list(S.stage_weights([sub], _space(spark), Params())[0, 0].items()), "predicate string, w double")
    left = G.stored_kg(spark, d, "star").edges.join(F.broadcast(kept), "predicate")  # a vocabulary
    return _rounded(left.groupBy("predicate", "w").agg(F.count("*").alias("edges")), "w")


@query("pred_weights_rescaled", f"WITH {BLEND} SELECT a, b, round(least((sim + 1) / 2, 1), 6) AS w FROM blended WHERE (sim + 1) / 2 > 0.5")
def pred_weights_rescaled(spark, d):
    """Similarities of the space that is blended from the embeddings, as weights."""
    return _rounded(P.edge_weights(P.predicate_similarity(P.predicate_space(spark, "blend", load(spark, d, "embeddings"))), 0.5, "half"), "w")


# ---- semantic graph, estimates, paths ----

Q1_SUB = _sub(0, [N7, ORDER], ["originNation"], 1)
Q2_SUBS = [Q1_SUB, _sub(1, [N3, SUPPLIER, ORDER], ["supplierNation", "fulfilledBy"], 2)]


def _q1(tau: float = 0.8, root: int = 4) -> str:
    return O.walk(0, O.nation(7), [("originNation", O.ORDER)], 1, tau, root)


def _q2(tau: float = 0.8, root: int = 3) -> list[str]:
    return [_q1(tau, root), O.walk(1, O.nation(3), [("supplierNation", O.SUPPLIER), ("fulfilledBy", O.ORDER)], 2, tau, root)]


@query("semgraph_one_hop", O.with_star(f", w AS (SELECT b AS predicate, sim FROM sims WHERE a = 'originNation' AND sim > 0) SELECT nbr, predicate, round(sim, 6) AS w FROM adj JOIN w USING (predicate) WHERE node = 2 * {O.B} + 7").replace("},", "},"))
def semgraph_one_hop(spark, d):
    kg = G.stored_kg(spark, d, "star")
    prep = S.prepare(kg, [Q1_SUB], _space(spark), Params(static_cut=False), L.build_library(kg))
    hop = prep.start.join(prep.adj, "node").join(F.broadcast(prep.weights), ["sub_id", "stage", "predicate"])
    return _rounded(hop.select("nbr", "predicate", "w"), "w")


_reach2 = f"""
, w AS (SELECT b AS predicate, sim FROM sims WHERE a = 'originNation' AND sim > 0), weighed AS (SELECT node, nbr, predicate, sim FROM adj JOIN w USING (predicate)),
one AS (SELECT DISTINCT nbr AS node FROM weighed WHERE node = 2 * {O.B} + 7), near AS (SELECT node FROM one UNION SELECT 2 * {O.B} + 7)
SELECT predicate, count(*) AS n, round(sum(sim), 4) AS total FROM weighed WHERE node IN (SELECT node FROM near) GROUP BY 1"""


@query("semgraph_complete", O.with_star(_reach2))
def semgraph_complete(spark, d):
    kg = G.stored_kg(spark, d, "star")
    whole = S.semantic_graph(kg, [Q1_SUB], _space(spark), Params(max_hops=2), "complete", L.build_library(kg))
    return whole.groupBy("predicate").agg(F.count("*").alias("n"), F.round(F.sum("w"), 4).alias("total"))


_partial = f"""
, w AS (SELECT b AS predicate, sim FROM sims WHERE a = 'originNation' AND sim >= pow(0.8, 2) - 1e-12), weighed AS (SELECT node, nbr, predicate, sim FROM adj JOIN w USING (predicate)),
m AS (SELECT node, max(sim) AS m FROM weighed GROUP BY 1),
one AS (SELECT x.nbr AS node FROM weighed x JOIN m ON m.node = x.nbr WHERE x.node = 2 * {O.B} + 7 AND x.nbr // {O.B} <> 6 AND sqrt(sim * m) >= 0.8 - 1e-12),
near AS (SELECT node FROM one UNION SELECT 2 * {O.B} + 7)
SELECT predicate, count(*) AS n, round(sum(sim), 4) AS total FROM weighed WHERE node IN (SELECT node FROM near) GROUP BY 1"""


@query("semgraph_partial_touched", O.with_star(_partial))
def semgraph_partial_touched(spark, d):
    kg = G.stored_kg(spark, d, "star")
    part = S.semantic_graph(kg, [Q1_SUB], _space(spark), Params(max_hops=2), "partial", L.build_library(kg))
    return part.groupBy("predicate").agg(F.count("*").alias("n"), F.round(F.sum("w"), 4).alias("total"))


@query("max_adjacent_weight", O.with_star(f", m AS (SELECT node, max(sim) AS m FROM adj JOIN sims ON b = predicate AND a = 'originNation' AND sim >= pow(0.8, 4) - 1e-12 GROUP BY 1) SELECT node // {O.B} AS kind, round(m, 6) AS m, count(*) AS n FROM m GROUP BY 1, 2"))
def max_adjacent_weight(spark, d):
    kg = G.stored_kg(spark, d, "star")
    prep = S.prepare(kg, [Q1_SUB], _space(spark), Params(), L.build_library(kg))
    m = index_of(kg).entities.select(F.col("node_id").alias("node"), "profile").join(F.broadcast(prep.info.filter("m > 0")), "profile")
    return m.groupBy(F.expr(f"node div {G.BASE}").alias("kind"), F.round("m", 6).alias("m")).agg(F.count("*").alias("n"))


@query("psi_hat_first_hop", O.with_star(f""", w AS (SELECT b AS predicate, sim FROM sims WHERE a = 'originNation' AND sim >= pow(0.8, 4) - 1e-12), m AS (SELECT node, max(sim) AS m FROM adj JOIN w USING (predicate) GROUP BY 1)
SELECT x.nbr AS node, x.nbr // {O.B} = 6 AS done, round(CASE WHEN x.nbr // {O.B} = 6 THEN sim ELSE pow(sim * m, 0.25) END, 6) AS psi_hat
FROM adj x JOIN w USING (predicate) JOIN m ON m.node = x.nbr WHERE x.node = 2 * {O.B} + 7 AND CASE WHEN x.nbr // {O.B} = 6 THEN sim ELSE pow(sim * m, 0.25) END >= 0.8 - 1e-12"""))
def psi_hat_first_hop(spark, d):
    kg = G.stored_kg(spark, d, "star")
    prep = S.prepare(kg, [Q1_SUB], _space(spark), Params(), L.build_library(kg))
    return _rounded(S.expand(prep, prep.start).select("node", "done", "psi_hat"), "psi_hat")


def _edge_matches(hops: int) -> None:
    sql = O.with_star(f""", found(node, hops, path, preds) AS (
        SELECT 2 * {O.B} + 7, 0, [2 * {O.B} + 7], '' UNION ALL
        SELECT a.nbr, hops + 1, list_append(path, a.nbr), preds || ' ' || a.predicate FROM found JOIN adj a ON a.node = found.node WHERE hops < {hops} AND found.node // {O.B} <> 6 AND NOT list_contains(path, a.nbr)
    ) SELECT hops AS n, trim(preds) AS preds, count(*) AS paths, count(DISTINCT node) AS ends FROM found WHERE node // {O.B} = 6 GROUP BY 1, 2""")

    @query(f"edge_matches_{hops}hop", sql)
    def run(spark, d):
        kg = G.stored_kg(spark, d, "star")
        found = S.enumerate_edge_matches(kg, Q1_SUB, Params(max_hops=hops), L.build_library(kg))
        return found.groupBy("n", F.array_join("path_preds", " ").alias("preds")).agg(F.count("*").alias("paths"), F.countDistinct("end_id").alias("ends"))


_edge_matches(2)
_edge_matches(3)

# ---- exact search ----


def _exact(name: str, gq: QueryGraph, params: Params, sql: str, builder=G.star_kg, **options) -> None:
    @query(name, sql)
    def run(spark, d):
        kg = G.stored_kg(spark, d, builder.__name__.removesuffix("_kg"))
        library = L.build_library(kg) if builder is G.star_kg else L.authored_library(spark)
        return _answers(E.exact_query(kg, gq, _space(spark), params, library, **options).answers)


for _k in (20, 40, 100, 200):
    _exact(f"exact_origin_k{_k}", W.origin(), Params(k=_k), O.answers([_q1()], _k))
for _t in (0.6, 0.7, 0.8, 0.9):
    # over 100 answers score .8 and more, so a lower tau changes none of the 100 best; SQL cannot prune by the k-th score and stops at .8
    _exact(f"exact_tau_0{int(_t * 10)}", W.origin(), Params(k=100, tau=_t, topk_prune=True), O.answers([_q1(max(_t, 0.8))], 100))
for _n in (2, 3, 4, 5):
    _exact(f"exact_nhat_{_n}", W.origin(), Params(k=1000, max_hops=_n, topk_prune=_n > 4), O.answers([_q1(0.8, _n)], 1000))
_exact("exact_no_estimate", W.origin(), Params(k=100, max_hops=3, use_estimate=False), O.answers([_q1(0.8, 3)], 100))
_exact("exact_complete_construction", W.origin(), Params(k=100, max_hops=2), O.answers([_q1(0.8, 2)], 100), construct="complete")
_exact("exact_tight_bound", W.origin(), Params(k=1000, bound="tight"), O.answers([_q1()], 1000))
_exact("exact_scan_m", W.origin(), Params(k=100, m_mode="scan"), O.answers([_q1()], 100))
_exact("exact_loose_m", W.origin(), Params(k=100, m_mode="loose"), O.answers([_q1()], 100))
_exact("exact_topk_prune", W.origin(), Params(k=100, topk_prune=True), O.answers([_q1()], 100))
_exact("exact_best_first", W.origin(), Params(k=100, batch=500), O.answers([_q1()], 100), engine="best_first")
_exact("exact_local_heap", W.origin(), Params(k=100), O.answers([_q1()], 100), engine="local")
_exact("exact_two_stage", W.chain(), Params(k=100, max_hops=3), O.answers([O.walk(0, f"SELECT 1 * {O.B} + r_regionkey AS node FROM region WHERE r_name = 'EUROPE'", [("inRegion", O.NATION), ("originNation", O.ORDER)], 2, 0.8, 3)], 100), pivot="o")
_exact("exact_two_subqueries_complete", W.two_lists(), Params(k=200, max_hops=3), O.answers(_q2(), 200))
_exact("exact_two_subqueries_partial", W.two_lists(), Params(k=200, max_hops=3), O.answers(_q2(), 200, complete=False), assembly="partial")
for _engine, _options in (("topk_prune", {"topk_prune": True}), ("best_first", {"batch": 5000}), ("local", {})):
    _exact(f"exact_two_subqueries_{_engine}", W.two_lists(), Params(k=100, max_hops=3, **_options), O.answers(_q2(), 100), engine="layered" if _options.get("topk_prune") else _engine)
# the planner's worst cover of the same query: both paths go on to the other's edge, so both have two stages
_worst = [O.walk(0, O.nation(7), [("originNation", O.ORDER), ("fulfilledBy", O.SUPPLIER)], 1, 0.8, 3), _q2()[1]]
_exact("exact_worst_decomposition", W.two_lists(), Params(k=100, max_hops=3), O.answers(_worst, 100), decomposition="max", pivot="o")

_cycle = [_q1(0.8, 3), O.walk(1, O.nation(7), [("supplierNation", O.SUPPLIER), ("fulfilledBy", O.ORDER)], 2, 0.8, 3)]
_exact("exact_cycle", W.cycle(), Params(k=100, max_hops=3), O.answers(_cycle, 100))

_star = [O.walk(0, O.named("Brand#12"), [("hasBrand", O.PART)], 1, 0.6, 2), O.walk(1, O.named("Supplier#000000001"), [("suppliedBy", O.PART)], 1, 0.6, 2), O.walk(2, O.named("Order#4"), [("containsPart", O.PART)], 1, 0.6, 2)]
_exact("exact_star3", W.star(), Params(k=50, max_hops=2, tau=0.6), O.answers(_star, 50, complete=False), assembly="partial")

_tree = [
    O.walk(0, O.nation(3), [("supplierNation", O.SUPPLIER), ("fulfilledBy", O.ORDER)], 2, 0.8, 3), O.walk(1, O.nation(7), [("originNation", O.ORDER), ("containsPart", O.of_type("PROMO"))], 1, 0.8, 3),
]
_exact("exact_tree", W.tree(), Params(k=100, max_hops=3), O.answers(_tree, 100))


_flower = [*_cycle, O.walk(2, O.named("Brand#12"), [("hasBrand", O.PART), ("containsPart", O.ORDER)], 2, 0.8, 3)]
_exact("exact_flower", W.flower(), Params(k=100, max_hops=3), O.answers(_flower, 100, complete=False), assembly="partial")

_wild = QueryGraph((QueryNode("x"), QueryNode("c", ("Customer",), "Customer#000000005")), (QueryEdge("x", "c", "placedBy"),), "wildcard")
_exact("exact_wildcard", _wild, Params(k=50, max_hops=2), O.answers([O.walk(0, O.named("Customer#000000005"), [("placedBy", "SELECT node_id AS node FROM nodes")], 1, 0.8, 2)], 50))
_multi = QueryGraph((QueryNode("p", ("PROMO", "ECONOMY")), QueryNode("b", ("Brand",), "Brand#4")), (QueryEdge("p", "b", "hasBrand"),), "several types")
_exact("exact_multi_type", _multi, Params(k=50, max_hops=2), O.answers([O.walk(0, O.named("Brand#4"), [("hasBrand", f"{O.of_type('PROMO')} UNION {O.of_type('ECONOMY')}")], 1, 0.8, 2)], 50))
_q3 = QueryGraph((QueryNode("p", ("Part",)), QueryNode("n", ("Nation",), "NATION_7")), (QueryEdge("p", "n", "suppliedBy"),), "part supply")
_exact("exact_length_padding", _q3, Params(k=50, max_hops=3), O.answers([O.walk(0, O.nation(7), [("suppliedBy", O.PART)], 1, 0.8, 3)], 50))
_act = QueryGraph((QueryNode("t", ("Topic",)), QueryNode("c", ("Customer",), "Customer#000000008")), (QueryEdge("t", "c", "purchase"),), "activity")
_exact("exact_activity", _act, Params(k=50, max_hops=1, tau=0.5), O.answers([O.walk(0, f"SELECT 3 * {O.B} + c_custkey AS node FROM customer WHERE c_name = 'Customer#000000008'", [("purchase", O.TOPIC)], 1, 0.5, 1)], 50, O.ACTIVITY), G.activity_kg)

_content = QueryGraph((QueryNode("d", ("Doc",)), QueryNode("s", ("Source",), "src3"), QueryNode("l", ("Language",), "French")), (QueryEdge("d", "s", "fromSource"), QueryEdge("d", "l", "writtenIn")), "content")
_exact("exact_content", _content, Params(k=30, max_hops=1), f"SELECT CAST(row_number() OVER (ORDER BY doc_id) AS INTEGER) AS rank, 9 * {O.B} + doc_id AS pivot_id, CAST(2.0 AS DOUBLE) AS score FROM documents WHERE source = 'src3' AND lang = 'fr' QUALIFY rank <= 30", G.content_kg)
_dialog = QueryGraph((QueryNode("t", ("Turn",)), QueryNode("c", ("Conversation",), "Conversation#1")), (QueryEdge("t", "c", "partOf"),), "dialog")
_exact("exact_dialog", _dialog, Params(k=30, max_hops=1), f"SELECT CAST(row_number() OVER (ORDER BY turn) AS INTEGER) AS rank, 17 * {O.B} + conv_id * 1000 + turn AS pivot_id, CAST(1.0 AS DOUBLE) AS score FROM conversations WHERE conv_id = 1 QUALIFY rank <= 30", G.dialog_kg)


@query("exact_dominance", O.answers([_q1(0.8, 3)], 100))
def exact_dominance(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return _answers(E.exact_query(kg, W.origin(), _space(spark), Params(k=100, max_hops=3, revisit="dominance"), L.build_library(kg)).answers)


@query("brute_force_topk", O.answers([_q1(0.8, 2)], 100))
def brute_force_topk(spark, d):
    kg = G.stored_kg(spark, d, "star")
    w = spark.createDataFrame(list(P.weights_for("originNation", _space(spark)).items()), "predicate string, w double")
    return _answers(BL.brute_force_query(kg, Q1_SUB, w, 100, Params(max_hops=2), L.build_library(kg)))


# ---- assembly ----


def _lists(spark, d, **changes):
    kg = G.stored_kg(spark, d, "star")
    return S.search_scores(kg, Q2_SUBS, _space(spark), Params(max_hops=3, **changes), library=L.build_library(kg))


@query("assembly_lists", O.answers(_q2(), 1).split("total AS")[0].rstrip().rstrip(",") + " SELECT sub_id, round(psi, 6) AS psi, count(*) AS n FROM (SELECT 0 AS sub_id, psi FROM list_0 UNION ALL SELECT 1, psi FROM list_1) GROUP BY 1, 2")
def assembly_lists(spark, d):
    return _lists(spark, d).groupBy("sub_id", F.round("psi", 6).alias("psi")).agg(F.count("*").alias("n"))


@query("assembly_full", O.answers(_q2(), 100))
def assembly_full(spark, d):
    return _answers(A.assemble(_lists(spark, d), [0, 1], 100, strategy="full"))


@query("assembly_threshold", O.answers(_q2(), 100))
def assembly_threshold(spark, d):
    return _answers(A.assemble(_lists(spark, d), [0, 1], 100, strategy="threshold", step=200))


_depth = O.answers(_q2(), 1).split("total AS")[0].rstrip().rstrip(",") + """,
heads AS (SELECT * FROM (SELECT 0 AS sub_id, pv, psi, row_number() OVER (ORDER BY round(psi, 9) DESC, pv) AS depth FROM list_0 UNION ALL SELECT 1, pv, psi, row_number() OVER (ORDER BY round(psi, 9) DESC, pv) FROM list_1) WHERE depth <= 200),
cur AS (SELECT sub_id, CASE WHEN count(*) >= 200 THEN min(psi) ELSE 0 END AS c FROM heads GROUP BY 1),
wide AS (SELECT pv AS pivot_id, count(*) AS seen, sum(psi) AS lower, max(psi) FILTER (sub_id = 0) AS a, max(psi) FILTER (sub_id = 1) AS b FROM heads GROUP BY 1)
SELECT pivot_id, seen, round(lower, 6) AS lower, round(coalesce(a, (SELECT c FROM cur WHERE sub_id = 0)) + coalesce(b, (SELECT c FROM cur WHERE sub_id = 1)), 6) AS upper FROM wide"""


@query("assembly_bounds_depth_200", _depth)
def assembly_bounds_depth(spark, d):
    lists = _lists(spark, d).withColumn("psi", F.round("psi", 9))
    return _rounded(A.bounds(lists, [0, 1], 200, 50).table, "lower", "upper")


# ---- bounded search ----


#: States of a round when a round is to be a whole hop, which SQL can follow.
WHOLE = 10**7


def _bounded(name: str, rounds: int, root: int) -> None:
    lists = [_q1(0.8, 4).replace("x.hops < 4", f"x.hops < {root}")]

    @query(name, O.answers(lists, 200))
    def run(spark, d):
        kg = G.stored_kg(spark, d, "star")
        return _answers(E.bounded_query(kg, W.origin(), _space(spark), Params(k=200, batch=WHOLE), E.LogicalClock(rounds), library=L.build_library(kg)).answers)


_bounded("bounded_round1", 1, 1)
_bounded("bounded_round2", 2, 2)
_bounded("bounded_converged", 9, 4)


@query("bounded_small_batches", O.answers([_q1()], 200))
def bounded_small_batches(spark, d):
    """Best-first rounds of 500 states until nothing is left: what the bounded search converges to."""
    kg = G.stored_kg(spark, d, "star")
    return _answers(E.bounded_query(kg, W.origin(), _space(spark), Params(k=200, batch=500), E.LogicalClock(10_000), library=L.build_library(kg)).answers)


@query("bounded_90")
def bounded_90(spark, d):
    """(k, bound_ms, ms, rounds, jaccard, completed): 90 % of the time of the exact search, measured just before."""
    kg = G.stored_kg(spark, d, "star")
    library, rows = L.build_library(kg), []
    E.exact_query(kg, W.origin(), _space(spark), Params(k=20), library).answers.count()  # what a session has compiled is not part of a bound
    for k in (20, 40, 100, 200):
        r, exact, bound, ms = E.relative_bound(kg, W.origin(), _space(spark), Params(k=k), 0.9, library)
        rows.append((k, bound, ms, len(r.stats.rounds), M.jaccard(r.answers, exact.answers).first().jaccard, r.completed))
    return local(spark, rows, "k int, bound_ms double, ms double, rounds int, jaccard double, completed boolean")


@query("bounded_two_subqueries", O.answers(_q2(), 100))
def bounded_two_subqueries(spark, d):
    """Two lists in one bounded frontier, run until the queue is empty."""
    kg = G.stored_kg(spark, d, "star")
    return _answers(E.bounded_query(kg, W.two_lists(), _space(spark), Params(k=100, max_hops=3, batch=WHOLE), E.LogicalClock(10_000), library=L.build_library(kg)).answers)


@query("bounded_resumed", O.answers([_q1()], 200))
def bounded_resumed(spark, d):
    kg = G.stored_kg(spark, d, "star")
    first = E.bounded_query(kg, W.origin(), _space(spark), Params(k=200, batch=WHOLE), E.LogicalClock(1), library=L.build_library(kg))
    return _answers(first.resume(9).answers)


def _jaccard_sql() -> str:
    tops = []
    base = O.answers([_q1()], 1).split("total AS")[0].rstrip().rstrip(",")
    for r in (1, 2, 3):
        tops.append(f"top_{r} AS (SELECT pv FROM (SELECT pv, row_number() OVER (ORDER BY round(max(pow(wp, 1.0 / hops)), 9) DESC, pv) AS n FROM walk_0 WHERE done AND hops <= {r} AND pow(wp, 1.0 / hops) >= 0.8 - 1e-12 GROUP BY pv) WHERE n <= 200)")
    tops.append("best AS (SELECT pv FROM (SELECT pv, row_number() OVER (ORDER BY round(psi, 9) DESC, pv) AS n FROM list_0) WHERE n <= 200)")
    picks = " UNION ALL ".join(f"SELECT {r} AS rounds, round((SELECT count(*) FROM top_{r} JOIN best USING (pv)) / (SELECT count(*) FROM (SELECT pv FROM top_{r} UNION SELECT pv FROM best)), 6) AS jaccard" for r in (1, 2, 3))
    return f"{base}, {', '.join(tops)} {picks}"


@query("jaccard_by_round", _jaccard_sql())
def jaccard_by_round(spark, d):
    kg = G.stored_kg(spark, d, "star")
    library = L.build_library(kg)
    exact = E.exact_query(kg, W.origin(), _space(spark), Params(k=200), library).answers
    out = None
    for r in (1, 2, 3):
        a = E.bounded_query(kg, W.origin(), _space(spark), Params(k=200, batch=WHOLE), E.LogicalClock(r), library=library).answers
        own = M.jaccard(a, exact).select(F.lit(r).alias("rounds"), F.round("jaccard", 6).alias("jaccard"))
        out = own if out is None else out.unionByName(own)
    return out


# ---- schemas, baselines, truth, measures ----


@query("answer_schemas", f"""
WITH RECURSIVE {O.STAR},{O.SPACE},{_q1(0.8, 3)}
SELECT 0 AS sub_id, CASE round(psi, 4) WHEN 1.0 THEN 'Nation-originNation-Order' WHEN 0.9444 THEN 'Nation-customerNation-Customer-placedBy-Order' ELSE 'Nation-supplierNation-Supplier-fulfilledBy-Order' END AS schema, count(*) AS matches, round(max(psi), 6) AS best_psi FROM list_0 GROUP BY 1, 2""")
def answer_schemas(spark, d):
    kg = G.stored_kg(spark, d, "star")
    found = S.search(kg, [Q1_SUB], _space(spark), Params(max_hops=3), library=L.build_library(kg))
    return _rounded(E.answer_schemas(found, kg), "best_psi")


def _schema_sql(preds: str, k: int, score: str) -> str:
    return f"""WITH {O.STAR}, found AS ({preds}) SELECT CAST(row_number() OVER (ORDER BY pivot_id) AS INTEGER) AS rank, pivot_id, CAST({score} AS DOUBLE) AS score FROM found QUALIFY rank <= {k}"""


_direct = f"SELECT DISTINCT nbr AS pivot_id FROM adj WHERE node = 2 * {O.B} + 7 AND predicate = 'originNation'"


@query("baseline_exact_schema", _schema_sql(f"SELECT DISTINCT nbr AS pivot_id FROM adj WHERE node = 2 * {O.B} + 7 AND predicate = 'customerNation'", 100, "1.0") + " UNION ALL SELECT CAST(-1 AS INTEGER), count(*), CAST(0 AS DOUBLE) FROM (SELECT 1 WHERE false)")
def baseline_exact_schema(spark, d):
    """Customers of a nation in the graph's own words; the same orders query in the user's words (N7, Purchase) finds nothing, and counts as row -1."""
    kg = G.stored_kg(spark, d, "star")
    known = BL.exact_schema_query(kg, [_sub(0, [QueryNode("n", ("Nation",), "NATION_7"), CUSTOMER], ["customerNation"], 1)], 100)
    unknown = BL.exact_schema_query(kg, [_sub(0, [N7, QueryNode("o", ("Purchase",))], ["originNation"], 1)], 100)
    return _answers(known.unionByName(unknown.agg(F.lit(-1).alias("rank"), F.count("*").alias("pivot_id"), F.lit(0.0).alias("score"))))


@query("baseline_exact_schema_known", _schema_sql(_direct, 100, "1.0"))
def baseline_exact_schema_known(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return _answers(BL.exact_schema_query(kg, [_sub(0, [QueryNode("n", ("Nation",), "NATION_7"), ORDER], ["originNation"], 1)], 100))


@query("baseline_node_library", _schema_sql(_direct, 100, "1.0"))
def baseline_node_library(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return _answers(BL.node_library_query(kg, [_sub(0, [N7, QueryNode("o", ("Purchase",))], ["originNation"], 1)], 100, L.build_library(kg)))


def _mining(pairs: int, noise: int, hops: int) -> str:
    return f"""
known AS (SELECT row_number() OVER (ORDER BY src, dst) - 1 AS pair_id, dst AS source, src AS target FROM (SELECT src, dst FROM edges WHERE predicate = 'originNation' ORDER BY src, dst LIMIT {pairs})),
dealt AS (SELECT *, row_number() OVER (ORDER BY (pair_id * 7919 + 13) % 10007, pair_id) AS place, (SELECT count(*) FROM known) AS n FROM known),
prior AS (SELECT d.pair_id, d.source, w.target FROM dealt d JOIN known w ON w.pair_id = CASE WHEN place * 100 <= n * {noise} THEN (d.pair_id + 1) % n ELSE d.pair_id END),
found(pair_id, target, node, hops, path, preds) AS (
    SELECT pair_id, target, source, 0, [source], '' FROM prior UNION ALL
    SELECT pair_id, target, a.nbr, hops + 1, list_append(path, a.nbr), preds || ' ' || a.predicate FROM found JOIN adj a ON a.node = found.node WHERE hops < {hops} AND found.node <> target AND NOT list_contains(path, a.nbr)
), patterns AS (SELECT trim(preds) AS pattern, count(*) AS support FROM (SELECT DISTINCT pair_id, preds FROM found WHERE node = target) GROUP BY 1),
mined AS (SELECT pattern, support, 1 - levenshtein(pattern, 'originNation') / greatest(length(pattern), 12) AS similarity, support / (SELECT count(*) FROM prior) * (1 - levenshtein(pattern, 'originNation') / greatest(length(pattern), 12)) AS score FROM patterns)"""


@query("baseline_pattern_mining", O.with_star(f", {_mining(50, 0, 3)} SELECT pattern, support, round(similarity, 6) AS similarity, round(score, 6) AS score FROM mined"))
def baseline_pattern_mining(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return _rounded(BL.mined_patterns(kg, W.prior_pairs(kg, 50).select("source", "target"), "originNation", 3), "similarity", "score")


_mined_answers = O.with_star(f""", {_mining(50, 20, 3)},
best AS (SELECT string_split(pattern, ' ') AS preds, score FROM mined ORDER BY round(score, 9) DESC, pattern LIMIT 3),
chase(preds, score, node, h) AS (
    SELECT preds, score, CAST(2 * {O.B} + 7 AS BIGINT), 0 FROM best UNION
    SELECT preds, score, a.nbr, h + 1 FROM chase JOIN adj a ON a.node = chase.node AND a.predicate = preds[h + 1] WHERE h < len(preds) AND a.nbr <> 2 * {O.B} + 7
), found_by AS (SELECT node AS pivot_id, max(score) AS score FROM chase WHERE h = len(preds) AND node // {O.B} = 6 GROUP BY 1)
SELECT CAST(row_number() OVER (ORDER BY round(score, 9) DESC, pivot_id) AS INTEGER) AS rank, pivot_id, round(score, 6) AS score FROM found_by QUALIFY rank <= 100""")


@query("baseline_pattern_miner", _mined_answers)
def baseline_pattern_miner(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return _answers(BL.pattern_miner_query(kg, Q1_SUB, W.prior_pairs(kg, 50, 20).select("source", "target"), 100, library=L.build_library(kg)))


@query("baseline_prior_sweep")
def baseline_prior_sweep(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return W.prior_sweep(kg, _space(spark), Params(k=100, max_hops=2), L.build_library(kg))


def _distances(start: str, hops: int, name: str) -> str:
    """Views of least distances d of nodes from a set of nodes, up to `hops`."""
    out = f"{name}_0 AS (SELECT DISTINCT node, 0 AS d FROM ({start}) t)"
    for h in range(1, hops + 1):
        out += f", {name}_{h} AS (SELECT * FROM {name}_{h - 1} UNION ALL SELECT DISTINCT nbr, {h} FROM adj WHERE node IN (SELECT node FROM {name}_{h - 1} WHERE d = {h - 1}) AND nbr NOT IN (SELECT node FROM {name}_{h - 1}))"
    return out


@query("baseline_hop_bounded", O.with_star(f""", {_distances(O.nation(7), 4, "near")}, best AS (SELECT node AS pivot_id, 1.0 / d AS score FROM near_4 WHERE node // {O.B} = 6)
SELECT CAST(row_number() OVER (ORDER BY score DESC, pivot_id) AS INTEGER) AS rank, pivot_id, round(CAST(score AS DOUBLE), 6) AS score FROM best QUALIFY rank <= 2000"""))
def baseline_hop_bounded(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return _answers(BL.hop_bounded_query(kg, [Q1_SUB], 2000, 4, L.build_library(kg)))


def _keyword_sql(name: str, predicate: str, hops: int, k: int) -> str:
    return O.with_star(f""", {_distances(f"SELECT node_id AS node FROM nodes WHERE contains(replace(lower(name), '_', ' '), '{name}')", hops, "a")},
{_distances(f"SELECT node FROM adj WHERE contains(lower(predicate), '{predicate}')", hops, "b")},
best AS (SELECT x.node AS pivot_id, x.d + y.d AS score FROM a_{hops} x JOIN b_{hops} y USING (node) WHERE x.node // {O.B} = 6)
SELECT CAST(row_number() OVER (ORDER BY score, pivot_id) AS INTEGER) AS rank, pivot_id, CAST(score AS DOUBLE) AS score FROM best QUALIFY rank <= {k}""")


@query("baseline_keyword", _keyword_sql("nation 7", "originnation", 4, 2000))
def baseline_keyword(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return _answers(BL.keyword_query(kg, ["NATION_7", "originNation"], ("Order",), 2000, 4, L.build_library(kg)))


@query("baseline_keyword_other_nation", _keyword_sql("nation 23", "originnation", 4, 100))
def baseline_keyword_other_nation(spark, d):
    """The keywords come from the query graph."""
    kg = G.stored_kg(spark, d, "star")
    return _answers(W.run_method("keyword", kg, {0: W.origin("N23")}, _space(spark), Params(k=100), L.build_library(kg)).drop("query_id"))


@query("baseline_homomorphism", O.with_star(f""", s0 AS (SELECT node_id AS node, ((1 - levenshtein(lower(name), 'nation_7') / greatest(length(name), 8)) + list_max(list_transform(types, lambda t: 1 - levenshtein(lower(t), 'nation') / greatest(length(t), 6)))) / 2 AS s FROM nodes),
l0 AS (SELECT node, s, s AS best FROM s0 WHERE s >= 0.9), h1 AS (SELECT nbr AS node, max(s) AS s FROM l0 JOIN adj USING (node) GROUP BY 1), l1 AS (SELECT * FROM h1 WHERE node NOT IN (SELECT node FROM l0)),
h2 AS (SELECT nbr AS node, max(s) AS s FROM l1 JOIN adj USING (node) GROUP BY 1), l2 AS (SELECT * FROM h2 WHERE node NOT IN (SELECT node FROM l0) AND node NOT IN (SELECT node FROM l1)),
h3 AS (SELECT nbr AS node, max(s) AS s FROM l2 JOIN adj USING (node) GROUP BY 1), l3 AS (SELECT * FROM h3 WHERE node NOT IN (SELECT node FROM l0) AND node NOT IN (SELECT node FROM l1) AND node NOT IN (SELECT node FROM l2)),
t AS (SELECT node_id AS node, list_max(list_transform(types, lambda t: 1 - levenshtein(lower(t), 'order') / greatest(length(t), 5))) AS s FROM nodes),
best AS (SELECT x.node AS pivot_id, (x.s + t.s) / 2 AS score FROM (SELECT * FROM l1 UNION ALL SELECT * FROM l2 UNION ALL SELECT * FROM l3) x JOIN t USING (node) WHERE t.s >= 0.9)
SELECT CAST(row_number() OVER (ORDER BY round(score, 9) DESC, pivot_id) AS INTEGER) AS rank, pivot_id, round(score, 6) AS score FROM best QUALIFY rank <= 2000"""))
def baseline_homomorphism(spark, d):
    kg = G.stored_kg(spark, d, "star")
    sub = _sub(0, [QueryNode("n", ("Nation",), "NATION_7"), ORDER], ["originNation"], 1)
    return _answers(BL.homomorphism_query(kg, [sub], 2000, 0.9, 3))


@query("baseline_homomorphism_one_to_one", f"WITH {O.STAR}, l1 AS (SELECT DISTINCT nbr AS node FROM adj WHERE node // {O.B} = 2 AND nbr // {O.B} <> 2), l2 AS (SELECT DISTINCT nbr AS node FROM adj WHERE node IN (SELECT node FROM l1) AND nbr // {O.B} <> 2 AND nbr NOT IN (SELECT node FROM l1)) SELECT count(*) FILTER (WHERE node // {O.B} = 2) AS nations, count(*) FILTER (WHERE node // {O.B} = 1) AS regions FROM (SELECT * FROM l1 UNION ALL SELECT * FROM l2)")
def baseline_homomorphism_one_to_one(spark, d):
    """Nations whose label is near that of a nation: one to one, no nation stands for both ends of the edge."""
    kg = G.stored_kg(spark, d, "star")
    sub = _sub(0, [QueryNode("n", ("Nation",), "NATION_7"), QueryNode("m", ("Nation", "Region"))], ["inRegion"], 1)
    x = BL.homomorphism_scores(kg, [sub], 0.8, 2, True).withColumn("kind", F.expr(f"pivot_id div {G.BASE}"))
    return x.agg(F.count_if(F.col("kind") == 2).alias("nations"), F.count_if(F.col("kind") == 1).alias("regions"))


TRUTH = f"""SELECT 6 * {O.B} + o_orderkey AS node_id FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_nationkey = 7"""


@query("truth_union", TRUTH)
def truth_union(spark, d):
    return W.origin_truth(G.stored_kg(spark, d, "star"), 7)


def _pr_sql(ks: tuple[int, ...]) -> str:
    base = O.answers([_q1()], max(ks)).rsplit("SELECT rank, pivot_id", 1)[0]
    parts = " UNION ALL ".join(f"SELECT {k} AS k, (SELECT count(*) FROM ranked WHERE rank <= {k}) AS returned, (SELECT count(*) FROM ranked JOIN truth ON pivot_id = node_id WHERE rank <= {k}) AS correct, (SELECT count(*) FROM truth) AS total" for k in ks)
    return f"{base}, truth AS ({TRUTH}), c AS ({parts}) SELECT k, round(correct / returned, 6) AS precision, round(correct / total, 6) AS recall, round(2 / (returned / correct + total / correct), 6) AS f1 FROM c"


@query("precision_recall_by_k", _pr_sql((20, 40, 100, 200)))
def precision_recall_by_k(spark, d):
    kg = G.stored_kg(spark, d, "star")
    a = E.exact_query(kg, W.origin(), _space(spark), Params(k=200), L.build_library(kg)).answers.select(F.lit(0).alias("query_id"), "rank", F.col("pivot_id").alias("node_id"))
    truth = W.origin_truth(kg, 7).select(F.lit(0).alias("query_id"), "node_id")
    out = None
    for k in (20, 40, 100, 200):
        own = M.precision_recall(a, truth, k).select(F.lit(k).alias("k"), *[F.round(c, 6).alias(c) for c in ("precision", "recall", "f1")])
        out = own if out is None else out.unionByName(own)
    return out


ORIGINS = [(i, f"2 * {O.B} + {i}", "originNation") for i in range(25)]
ORIGIN_TRUTHS = f"SELECT c_nationkey AS q, 6 * {O.B} + o_orderkey AS node FROM orders JOIN customer ON o_custkey = c_custkey"
KS = (20, 40, 100, 200)


def _measures_of(answers: DataFrame, truth: DataFrame, ks: tuple[int, ...]) -> DataFrame:
    return _rounded(W.quality(answers, truth, ks), "precision", "recall", "f1")


@query("effectiveness_exact", O.with_star(f", {O.many(ORIGINS, O.ORDER, 0.8, 4, 200)} {O.quality('ranked_many', ORIGIN_TRUTHS, KS)}"))
def effectiveness_exact(spark, d):
    """Precision, recall and F1 by k over all 25 nations."""
    kg = G.stored_kg(spark, d, "star")
    a = W.run_method("exact", kg, W.origin_queries(), _space(spark), Params(k=200), L.build_library(kg))
    return _measures_of(a, W.origin_truths(kg, list(range(25))), KS)


@query("effectiveness_hop_bounded", O.with_star(f""", near(q, node, d) AS (
    SELECT n_nationkey, 2 * {O.B} + n_nationkey, 0 FROM nation UNION SELECT q, a.nbr, d + 1 FROM near JOIN (SELECT DISTINCT node, nbr FROM adj) a ON a.node = near.node WHERE d < 2
), best AS (SELECT q, node AS pv, min(d) AS d FROM near WHERE node // {O.B} = 6 GROUP BY 1, 2),
ranked AS (SELECT * FROM (SELECT q, pv, row_number() OVER (PARTITION BY q ORDER BY d, pv) AS rank FROM best) WHERE rank <= 200) {O.quality('ranked', ORIGIN_TRUTHS, KS)}"""))
def effectiveness_hop_bounded(spark, d):
    """As the 200 best of every nation lie within two hops, SQL stops there; the method goes to four."""
    kg = G.stored_kg(spark, d, "star")
    a = W.run_method("hop_bounded", kg, W.origin_queries(), _space(spark), Params(k=200), L.build_library(kg))
    return _measures_of(a, W.origin_truths(kg, list(range(25))), KS)


@query("effectiveness_node_library", O.with_star(f", ranked AS (SELECT * FROM (SELECT node - 2 * {O.B} AS q, nbr AS pv, row_number() OVER (PARTITION BY node ORDER BY nbr) AS rank FROM adj WHERE predicate = 'originNation' AND node // {O.B} = 2) WHERE rank <= 200) {O.quality('ranked', ORIGIN_TRUTHS, KS)}"))
def effectiveness_node_library(spark, d):
    kg = G.stored_kg(spark, d, "star")
    a = W.run_method("node_library", kg, W.origin_queries(), _space(spark), Params(k=200), L.build_library(kg))
    return _measures_of(a, W.origin_truths(kg, list(range(25))), KS)


@query("effectiveness_methods")
def effectiveness_methods(spark, d):
    """All methods, all nations, four k, with times."""
    kg = G.stored_kg(spark, d, "star")
    return W.effectiveness(kg, W.origin_queries(), W.origin_truths(kg, list(range(25))), _space(spark), Params(), L.build_library(kg), KS, prior=W.prior_pairs(kg, 50).select("source", "target"))


_activity_truth = f"SELECT DISTINCT CAST(src - 3 * {O.B} AS INTEGER) AS q, dst AS node FROM edges WHERE predicate IN ('purchase', 'view', 'click') AND src < 3 * {O.B} + 25"
_users = [(i, f"3 * {O.B} + {i}", "purchase") for i in range(25)]


@query("effectiveness_activity", f"WITH RECURSIVE {O.ACTIVITY},{O.SPACE}, {O.many(_users, O.TOPIC, 0.7, 3, 200)} {O.quality('ranked_many', _activity_truth, KS)}")
def effectiveness_activity(spark, d):
    kg = G.stored_kg(spark, d, "activity")
    a = W.run_method("exact", kg, W.activity_queries(), _space(spark), Params(k=200, tau=0.7, max_hops=3), L.authored_library(spark))
    return _measures_of(a, W.activity_truths(kg, list(range(25))), KS)


_content_truth = "SELECT CAST(substr(source, 4) AS INTEGER) AS q, doc_id AS node FROM documents WHERE regexp_matches(source, '^src[0-9]+$') AND CAST(substr(source, 4) AS INTEGER) < 20"


@query("effectiveness_content", f"WITH ranked AS (SELECT * FROM (SELECT q, node AS pv, row_number() OVER (PARTITION BY q ORDER BY node) AS rank FROM ({_content_truth})) WHERE rank <= 200) {O.quality('ranked', _content_truth, KS)}")
def effectiveness_content(spark, d):
    kg = G.stored_kg(spark, d, "content")
    a = W.run_method("exact", kg, W.content_queries(), _space(spark), Params(k=200, max_hops=1), L.authored_library(spark))
    return _measures_of(a, W.content_truths(kg, list(range(20))), KS)


@query("effectiveness_activity_methods")
def effectiveness_activity_methods(spark, d):
    kg = G.stored_kg(spark, d, "activity")
    methods = ("exact", "bounded", "hop_bounded", "keyword", "homomorphism", "node_library", "exact_schema")
    return W.effectiveness(kg, W.activity_queries(), W.activity_truths(kg, list(range(25))), _space(spark), Params(tau=0.7, max_hops=3), L.authored_library(spark), KS, methods)


@query("effectiveness_content_methods")
def effectiveness_content_methods(spark, d):
    kg = G.stored_kg(spark, d, "content")
    methods = ("exact", "bounded", "hop_bounded", "keyword", "homomorphism", "node_library", "exact_schema")
    return W.effectiveness(kg, W.content_queries(), W.content_truths(kg, list(range(20))), _space(spark), Params(max_hops=3), L.authored_library(spark), KS, methods)


@query("f1_report_pivot", f"WITH f AS ({O.with_star(f', {O.many(ORIGINS, O.ORDER, 0.8, 4, 200)} {O.quality("ranked_many", ORIGIN_TRUTHS, KS)}')}) SELECT 'exact' AS method, max(f1) FILTER (k = 20) AS \"20\", max(f1) FILTER (k = 40) AS \"40\", max(f1) FILTER (k = 100) AS \"100\", max(f1) FILTER (k = 200) AS \"200\" FROM f")
def f1_report_pivot(spark, d):
    return effectiveness_exact(spark, d).withColumn("method", F.lit("exact")).groupBy("method").pivot("k", list(KS)).agg(F.first("f1"))


@query("component_times")
def component_times(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return W.component_times(kg, [W.origin(), W.two_lists()], _space(spark), Params(k=100, max_hops=3), L.build_library(kg))


@query("time_bound_sweep")
def time_bound_sweep(spark, d):
    kg = G.stored_kg(spark, d, "star")
    truth = W.origin_truths(kg, [7]).withColumn("query_id", F.lit(0))
    return W.time_bound_sweep(kg, W.origin(), truth, _space(spark), Params(k=100, batch=500), library=L.build_library(kg))


#: Edge noise also asks for predicates that hubs have by the thousand: without a bound by the k-th score, as in SQL, four hops do not end.
NOISE_HOPS = {"node": 4, "edge": 2}


def _noise_sql(kind: str) -> str:
    """Measures at each share of noise: node noise changes labels that the library knows, edge noise the query predicate."""
    parts, views = [], []
    space = {p: [float(x) for x in v] for p, v in P.AUTHORED.items()}
    for percent in (0, 10, 20, 30, 40):
        plain = [W.origin(f"NATION_{i}", "Order") for i in range(25)]
        noisy = plain if kind == "node" else W.add_edge_noise(plain, space, percent)
        many = O.many([(i, f"2 * {O.B} + {i}", q.edges[0].predicate) for i, q in enumerate(noisy)], O.ORDER, 0.8, NOISE_HOPS[kind], 100)
        for name in ("asked", "ends", "usable", "walk_many", "scored", "ranked_many"):
            many = many.replace(name, f"{name}_{percent}")
        views.append(many)
        parts.append(f"SELECT '{kind}' AS kind, {percent} AS percent, precision, recall, f1 FROM ({O.quality(f'ranked_many_{percent}', ORIGIN_TRUTHS, (100,))})")
    return O.with_star(f", {', '.join(views)} {' UNION ALL '.join(parts)}")


def _noise(kind: str) -> None:
    @query(f"noise_{kind}", _noise_sql(kind))
    def run(spark, d):
        kg = G.stored_kg(spark, d, "star")
        return _rounded(W.noise_report(kg, (kind,), _space(spark), Params(k=100, max_hops=NOISE_HOPS[kind]), L.build_library(kg)).drop("ms"), "precision", "recall", "f1")


_noise("node")
_noise("edge")


@query("noise_times")
def noise_times(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return W.noise_report(kg, ("node", "edge"), _space(spark), Params(k=100, max_hops=2), L.build_library(kg))


def _sensitivity_sql() -> str:
    views, parts = [], []
    for name, values in (("max_hops", (2, 3, 4, 5)), ("tau", (0.6, 0.7, 0.8, 0.9))):
        for i, v in enumerate(values):
            root = v if name == "max_hops" else 4
            # the 100 best all score over .95 (there are more direct edges), so SQL, which cannot prune by the k-th score, stops there
            many = O.many([(0, f"2 * {O.B} + 7", "originNation")], O.ORDER, 0.95, root, 100)
            for view in ("asked", "ends", "usable", "walk_many", "scored", "ranked_many"):
                many = many.replace(view, f"{view}_{name}_{i}")
            views.append(many)
            parts.append(f"SELECT '{name}' AS param, CAST({v} AS DOUBLE) AS value, precision, recall, f1 FROM ({O.quality(f'ranked_many_{name}_{i}', f'SELECT 0 AS q, node FROM ({ORIGIN_TRUTHS}) WHERE q = 7', (100,))})")
    return O.with_star(f", {', '.join(views)} {' UNION ALL '.join(parts)}")


@query("sensitivity", _sensitivity_sql())
def sensitivity(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return _rounded(W.sensitivity(kg, 7, _space(spark), Params(k=100, topk_prune=True), L.build_library(kg)).drop("ms"), "precision", "recall", "f1")


@query("sensitivity_times")
def sensitivity_times(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return W.sensitivity(kg, 7, _space(spark), Params(k=100, topk_prune=True), L.build_library(kg))


@query("scale_curve")
def scale_curve(spark, d):
    """Times by size of the graph and k, with the index and one epoch of the embedding; `embed_train` trains to the end."""
    from ..operators.embedding import TranslationEmbedding

    return W.scale_curve(G.stored_kg(spark, d, "star"), (44, 67, 100), (80, 100, 120), _space(spark), Params(), TranslationEmbedding(epochs=1))


PAIRS = """
WITH placed AS (SELECT o_custkey, count(*) AS votes FROM orders GROUP BY 1),
ranked AS (
    SELECT c_nationkey AS query_id, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_acctbal DESC, c_custkey) AS rank, row_number() OVER (PARTITION BY c_nationkey ORDER BY c_custkey) - 1 AS at, coalesce(votes, 0) AS votes
    FROM customer LEFT JOIN placed ON o_custkey = c_custkey
)"""


@query("correlation_users", PAIRS + " SELECT a.query_id, count(*) AS pairs, round(corr(b.rank - a.rank, a.votes - b.votes), 6) AS pcc FROM ranked a JOIN ranked b ON a.query_id = b.query_id AND a.at % 2 = 0 AND b.at = a.at + 1 GROUP BY 1")
def correlation_users(spark, d):
    """Pairs of customers of a nation, next to each other by key: differences of rank by balance against differences of orders, an order being a vote."""
    from pyspark.sql import Window

    placed = load(spark, d, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("votes"))
    nation = Window.partitionBy("c_nationkey")
    ranked = load(spark, d, "customer").select("c_custkey", "c_nationkey", "c_acctbal").join(placed, "c_custkey", "left").select(
        F.col("c_nationkey").alias("query_id"), F.row_number().over(nation.orderBy(F.desc_nulls_last("c_acctbal"), "c_custkey")).alias("rank"),
        (F.row_number().over(nation.orderBy("c_custkey")) - 1).alias("at"), F.coalesce("votes", F.lit(0)).alias("votes"),
    )
    side = lambda even, c: F.max(F.when((F.col("at") % 2 == 0) == even, F.col(c)))
    pairs = ranked.groupBy("query_id", F.expr("at div 2").alias("pair_id")).agg(
        side(True, "rank").alias("rank_a"), side(False, "rank").alias("rank_b"), side(True, "votes").alias("votes_a"), side(False, "votes").alias("votes_b")
    )
    return _rounded(M.pcc(pairs.filter("rank_b IS NOT NULL")).select("query_id", "pairs", "pcc"), "pcc")


_votes_sql = O.with_star(f""", {O.many(ORIGINS[:20], O.ORDER, 0.8, 4, 200)},
split AS (SELECT *, score >= max(score) OVER (PARTITION BY q) - 1e-9 AS top FROM ranked_many),
placed AS (SELECT q, top, rank, score, row_number() OVER (PARTITION BY q, top ORDER BY rank) - 1 AS at, count(*) OVER (PARTITION BY q, top) AS n FROM split),
pairs AS (SELECT a.q, i, a.rank AS rank_a, b.rank AS rank_b, a.score AS sa, b.score AS sb FROM range(30) p(i) JOIN placed a ON a.top AND a.at = i % a.n JOIN placed b ON b.q = a.q AND NOT b.top AND b.at = (i * 7) % b.n),
votes AS (SELECT q, i, rank_a, rank_b, count(*) FILTER (WHERE (i * 7919 + w * 31 + q * 17) % 100 < 50 + (sa - sb) * 150 + (rank_b - rank_a) / 8.0) AS votes_a FROM pairs, range(10) r(w) GROUP BY 1, 2, 3, 4)
SELECT CAST(q AS INTEGER) AS query_id, count(*) AS pairs, round(corr(rank_b - rank_a, 2 * votes_a - 10), 6) AS pcc FROM votes GROUP BY 1""")


@query("user_study", _votes_sql)
def user_study(spark, d):
    """Correlation of rank differences and simulated preferences for 20 queries, 30 pairs of differing schemas each, 10 annotators."""
    kg = G.stored_kg(spark, d, "star")
    a = W.run_method("exact", kg, W.origin_queries(20), _space(spark), Params(k=200), L.build_library(kg))
    return _rounded(M.pcc(W.simulate_votes(a)).select("query_id", "pairs", "pcc"), "pcc")


@query("pruning_ratio", O.with_star(_partial.split("SELECT predicate, count(*) AS n, round(sum(sim)")[0] + """, touched AS (SELECT * FROM weighed WHERE node IN (SELECT node FROM near))
SELECT (SELECT count(*) FROM nodes) AS nodes, (SELECT count(*) FROM edges) AS edges, (SELECT count(*) FROM (SELECT node FROM touched UNION SELECT nbr FROM touched)) AS touched_nodes,
    (SELECT count(*) FROM (SELECT DISTINCT least(node, nbr), greatest(node, nbr), predicate FROM touched)) AS touched_edges"""))
def pruning_ratio(spark, d):
    kg = G.stored_kg(spark, d, "star")
    part = S.semantic_graph(kg, [Q1_SUB], _space(spark), Params(max_hops=2), "partial", L.build_library(kg))
    return M.pruning(part, kg).select("nodes", "edges", "touched_nodes", "touched_edges")


DECOMPOSED = [W.origin(), W.two_lists(), W.cycle(), W.star(), W.chain(), W.tree(), W.flower()]


def _cost_sql() -> str:
    """Costs of all covers that the planner chooses among, from the graph's statistics: the least and the greatest of each query."""
    paths: dict[tuple, int] = {}
    rows, steps, members = [], [], []
    for gq in DECOMPOSED:
        for n, (_, used) in enumerate(D.covers(gq, 4)):
            for source, preds in used:
                if (gq.label, source, preds) not in paths:
                    paths[gq.label, source, preds] = len(paths)
                    steps += [f"({len(paths) - 1}, {h}, '{preds[min(h * len(preds) // 4, len(preds) - 1)]}')" for h in range(4)]
                members.append(f"('{gq.label}', {n}, {paths[gq.label, source, preds]})")
        rows.append(f"('{gq.label}', '{D.classify_shape(gq)}')")
    return O.with_star(f""", fan AS (SELECT predicate, count(*) / (SELECT count(*) FROM nodes) AS fanout FROM adj GROUP BY 1),
usable AS (SELECT a AS pred, greatest(sum(fanout), 1e-9) AS width FROM sims JOIN fan ON predicate = b WHERE sim > 0 AND sim >= pow(0.8, 4) GROUP BY 1),
steps(path, h, pred) AS (VALUES {', '.join(steps)}), members(label, cover, path) AS (VALUES {', '.join(members)}), shapes(label, shape) AS (VALUES {', '.join(rows)}),
widths AS (SELECT path, exp(sum(ln(width)) OVER (PARTITION BY path ORDER BY h)) AS w FROM steps JOIN usable USING (pred)),
costs AS (SELECT path, sum(w) AS cost FROM widths GROUP BY 1), covers AS (SELECT label, cover, sum(cost) AS cost FROM members JOIN costs USING (path) GROUP BY 1, 2)
SELECT label AS query, shape, round(min(cost), 4) AS optimal, round(max(cost), 4) AS worst, round((max(cost) - min(cost)) / max(cost), 6) AS gain FROM covers JOIN shapes USING (label) GROUP BY 1, 2""")


@query("decomposition_costs", _cost_sql())
def decomposition_costs(spark, d):
    kg = G.stored_kg(spark, d, "star")
    r = W.decomposition_costs(kg, DECOMPOSED, _space(spark), Params(), L.build_library(kg))
    return r.withColumns({"optimal": F.round("optimal", 4), "worst": F.round("worst", 4), "gain": F.round("gain", 6)})


@query("decomposition_times")
def decomposition_times(spark, d):
    kg = G.stored_kg(spark, d, "star")
    return W.decomposition_times(kg, [W.two_lists(), W.cycle(), W.star()], _space(spark), Params(k=100, max_hops=3), L.build_library(kg))


@query("shape_report")
def shape_report(spark, d):
    """Shapes and sizes extracted from the graph, decomposed and searched: one graph each here; `workloads.shape_report` takes five."""
    kg = G.stored_kg(spark, d, "star")
    return W.shape_report(kg, _space(spark), Params(k=100, max_hops=1, hop_scope="query_edge", tau=0.8, revisit="dominance"), {"S": 3, "L": 5}, 1, L.build_library(kg))


@query("relpath_questions", O.answers([O.walk(0, f"SELECT 1 * {O.B} + r_regionkey AS node FROM region WHERE r_name = 'ASIA'", [("inRegion", O.NATION), ("originNation", O.ORDER)], 2, 0.8, 3)], 50))
def relpath_questions(spark, d):
    """A question as a key entity and a path of relations, read from JSON: orders that originate from a region."""
    kg = G.stored_kg(spark, d, "star")
    path = f"{scratch(spark, 'questions')}/rows"
    line = '{"text": "Which orders come from Asia?", "key_entity": "ASIA", "key_type": "Region", "answer_type": "Purchase", "rel_paths": ["inRegion", "originNation"], "answers": []}'
    local(spark, [(line,)], "value string").write.text(path)
    asked = spark.read.schema("text string, key_entity string, key_type string, answer_type string, rel_paths array<string>, answers array<string>").json(path)
    (gq, _), *_ = W.relpath_questions(asked)
    nodes = tuple(QueryNode(n.key, ("Nation",), None) if not n.types and not n.specific else n for n in gq.nodes)
    return _answers(E.exact_query(kg, QueryGraph(nodes, gq.edges, gq.label), _space(spark), Params(k=50, max_hops=3), L.build_library(kg), pivot="x1").answers)


def _trained(spark, d):
    """The translation embedding of the whole star graph, trained once for an application and graph."""
    from ..operators.embedding import TranslationEmbedding

    kg = G.stored_kg(spark, d, "star")
    if "trained" not in kg.memo:
        model = TranslationEmbedding()
        _, predicates = model.fit(kg.edges)
        kg.memo["trained"] = (P.vectors(predicates), model.losses)
    return kg, *kg.memo["trained"]


@query("embed_train")
def embed_train(spark, d):
    """(epoch, loss) of the translation embedding over the whole graph, 32 dimensions, all epochs."""
    _, _, losses = _trained(spark, d)
    return local(spark, [(i + 1, float(x)) for i, x in enumerate(losses)], "epoch int, loss double")


@query("embed_similarities")
def embed_similarities(spark, d):
    """(a, b, sim, rank): the most similar predicates in the trained space."""
    _, space, _ = _trained(spark, d)
    table = local(spark, [(p, v) for p, v in space.items()], "predicate string, vec array<double>")
    return P.similar_predicates(P.predicate_space(spark, "trained", trained=table), 3)


@query("exact_trained_space")
def exact_trained_space(spark, d):
    """The origin query searched with trained vectors."""
    kg, space, _ = _trained(spark, d)
    return _answers(E.exact_query(kg, W.origin(), space, Params(k=100, max_hops=2, tau=0.3, rescale="half"), L.build_library(kg)).answers)


surround.add_to(QUERIES, ORACLE_SQL)

__all__ = ["ORACLE_SQL", "QUERIES", "psi_hat"]
