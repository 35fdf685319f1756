"""The experiments re-expressed on the given tables: query graphs, truths, noise, shapes, sweeps."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import KG, Params, QueryEdge, QueryGraph, QueryNode
from ..operators import baselines as B
from ..operators import metrics as M
from ..operators import search as S
from ..operators.library import build_library
from ..operators.predicate_space import weights_for
from ..sources.builders import BASE, KINDS, induced_subgraph
from ..sources.index import index_of
from ..sources.tables import keep, local
from . import decompose as D
from . import engine as E


def origin(nation: str = "N7", target: str = "Purchase", predicate: str = "originNation") -> QueryGraph:
    """Orders that originate from a nation."""
    return QueryGraph((QueryNode("o", (target,)), QueryNode("n", ("Nation",), nation)), (QueryEdge("o", "n", predicate),), f"origin {nation}").validate()


def two_lists(origin_nation: str = "N7", supplier_nation: str = "NATION_3") -> QueryGraph:
    """Orders from one nation that a supplier of another fulfilled."""
    nodes = (QueryNode("o", ("Order",)), QueryNode("n", ("Nation",), origin_nation), QueryNode("s", ("Supplier",)), QueryNode("m", ("Nation",), supplier_nation))
    return QueryGraph(nodes, (QueryEdge("o", "n", "originNation"), QueryEdge("s", "m", "supplierNation"), QueryEdge("o", "s", "fulfilledBy")), "two lists").validate()


def cycle(nation: str = "N7") -> QueryGraph:
    nodes = (QueryNode("o", ("Order",)), QueryNode("n", ("Nation",), nation), QueryNode("s", ("Supplier",)))
    return QueryGraph(nodes, (QueryEdge("o", "n", "originNation"), QueryEdge("o", "s", "fulfilledBy"), QueryEdge("s", "n", "supplierNation")), "cycle").validate()


def star(brand: str = "Brand#12", supplier: str = "Supplier#000000001", order: str = "Order#4") -> QueryGraph:
    nodes = (QueryNode("p", ("Part",)), QueryNode("b", ("Brand",), brand), QueryNode("s", ("Supplier",), supplier), QueryNode("o", ("Order",), order))
    return QueryGraph(nodes, (QueryEdge("p", "b", "hasBrand"), QueryEdge("p", "s", "suppliedBy"), QueryEdge("o", "p", "containsPart")), "star").validate()


def chain(region: str = "EU") -> QueryGraph:
    nodes = (QueryNode("r", ("Region",), region), QueryNode("n", ("Nation",)), QueryNode("o", ("Order",)))
    return QueryGraph(nodes, (QueryEdge("n", "r", "inRegion"), QueryEdge("o", "n", "originNation")), "chain").validate()


def tree() -> QueryGraph:
    """Two lists with a leaf behind the pivot."""
    base = two_lists()
    return QueryGraph((*base.nodes, QueryNode("p", ("PROMO",))), (*base.edges, QueryEdge("o", "p", "containsPart")), "tree").validate()


def flower() -> QueryGraph:
    """A cycle with a petal through a part and a named brand."""
    base = cycle()
    nodes = (*base.nodes, QueryNode("p", ("Part",)), QueryNode("b", ("Brand",), "Brand#12"))
    return QueryGraph(nodes, (*base.edges, QueryEdge("o", "p", "containsPart"), QueryEdge("p", "b", "hasBrand")), "flower").validate()


def origin_truth(kg: KG, nation_key: int) -> DataFrame:
    """(node_id): orders of the right schemas: the direct edge, and by way of the customer."""
    source = kg.nodes.sparkSession.createDataFrame([(KINDS["nation"] * BASE + nation_key,)], "node_id long")
    return B.union_of_schemas(kg, source, [("originNation",), ("customerNation", "placedBy")], "Order")


def relpath_questions(questions: DataFrame) -> list[tuple[QueryGraph, list[str]]]:
    """Query graphs and answers of rows {text, key_entity, key_type, answer_type, rel_paths, answers}: a question set is small and stays on the driver."""
    out = []
    for r in questions.limit(100_000).collect():
        keys = [f"x{i}" for i in range(len(r.rel_paths))]
        nodes = [QueryNode("k", (r.key_type,), r.key_entity)] + [QueryNode(k, (r.answer_type,) if i == len(keys) - 1 else ()) for i, k in enumerate(keys)]
        edges = [QueryEdge(a, b, p) for a, b, p in zip(["k", *keys], keys, r.rel_paths)]
        out.append((QueryGraph(tuple(nodes), tuple(edges), r.text).validate(), list(r.answers or [])))
    return out


METHODS = ("exact", "bounded", "pattern_miner", "hop_bounded", "keyword", "homomorphism", "node_library", "exact_schema")


def origin_queries(n: int = 25) -> dict[int, QueryGraph]:
    return {i: origin(f"N{i}") for i in range(n)}


def _truths(kg: KG, names: DataFrame, schemas: list[tuple[str, ...]], target: str) -> DataFrame:
    """(query_id, node_id): the union over schemas for each source of names(query_id, node_id): what full knowledge would find."""
    adj = index_of(kg).adj.select("node", "nbr", "predicate")
    ends = kg.nodes.filter(F.array_contains("types", target)).select("node_id")
    out = None
    for preds in schemas:
        x = names.select("query_id", F.col("node_id").alias("node"))
        for p in preds:
            x = x.join(adj.filter(F.col("predicate") == p), "node").select("query_id", F.col("nbr").alias("node")).distinct()
        own = x.select("query_id", F.col("node").alias("node_id")).join(ends, "node_id", "left_semi").select("query_id", "node_id")
        out = own if out is None else out.unionByName(own)
    return out.distinct()


def origin_truths(kg: KG, keys: list[int]) -> DataFrame:
    names = local(kg.nodes.sparkSession, [(k, KINDS["nation"] * BASE + k) for k in keys], "query_id int, node_id long")
    return _truths(kg, names, [("originNation",), ("customerNation", "placedBy")], "Order")


def activity_queries(n: int = 25) -> dict[int, QueryGraph]:
    """Topics that a user purchased, for the first users."""
    return {i: QueryGraph((QueryNode("t", ("Topic",)), QueryNode("c", ("Customer",), f"Customer#{i:09d}")), (QueryEdge("t", "c", "purchase"),), f"activity {i}").validate() for i in range(n)}


def activity_truths(kg: KG, keys: list[int]) -> DataFrame:
    """A purchase, or what comes before one: a view or a click of the topic."""
    names = local(kg.nodes.sparkSession, [(k, KINDS["customer"] * BASE + k) for k in keys], "query_id int, node_id long")
    return _truths(kg, names, [("purchase",), ("view",), ("click",)], "Topic")


def content_queries(n: int = 20) -> dict[int, QueryGraph]:
    """Documents of a source."""
    return {i: QueryGraph((QueryNode("d", ("Doc",)), QueryNode("s", ("Source",), f"src{i}")), (QueryEdge("d", "s", "fromSource"),), f"content {i}").validate() for i in range(n)}


def content_truths(kg: KG, keys: list[int]) -> DataFrame:
    sources = kg.nodes.filter(F.array_contains("types", "Source")).select("node_id", F.regexp_extract("name", "^src([0-9]+)$", 1).cast("int").alias("query_id"))
    return _truths(kg, sources.filter(F.col("query_id").isin(keys)).select("query_id", "node_id"), [("fromSource",)], "Document")


def run_method(method: str, kg: KG, queries: dict[int, QueryGraph], space: dict, params: Params, library: DataFrame, bound_ms: float | None = None, prior: DataFrame | None = None) -> DataFrame:
    """(query_id, rank, pivot_id, score) of all queries by a method: each hop or level is one job for all of them.

    `bounded` needs `bound_ms` for the whole batch; `pattern_miner` needs prior(source, target) pairs.
    """
    if method == "exact":
        return E.exact_many(kg, queries, space, params, library)[0]
    if method == "bounded":
        return E.bounded_many(kg, queries, space, params, E.ExecutionClock(bound_ms), library)
    subs, owner = E.plan_many(kg, queries, space, params, library)
    top = lambda scores: E.answers_of_many(scores, owner, params.k)
    if method == "exact_schema":
        return top(B.exact_schema_scores(kg, subs, library))
    if method == "node_library":
        return top(B.exact_schema_scores(kg, subs, library, ("identical", "synonym", "abbreviation")))
    if method == "hop_bounded":
        return top(B.hop_bounded_scores(kg, subs, params.max_hops, library, params.k if len(owner) == len(queries) else None))
    if method == "pattern_miner":
        patterns = B.best_patterns(B.mined_patterns(kg, prior, subs[0].predicates[0], min(params.max_hops, 3)))
        return top(B.pattern_miner_scores(kg, subs, patterns, library, k=params.k))
    if method == "homomorphism":
        return top(B.homomorphism_scores(kg, subs, 0.6, params.max_hops))
    if method == "keyword":
        labels = S.resolve_labels(library, sorted({(t, "type") for q in queries.values() for n in q.nodes for t in n.types} | {(n.name, "name") for q in queries.values() for n in q.nodes if n.specific}), params.relations, index_of(kg).memo)
        asked = {i: B.keyword_terms(q, labels) for i, q in queries.items()}
        scores = B.keyword_scores(kg, {i: t for i, (t, _) in asked.items()}, {i: keys for i, (_, keys) in asked.items()}, params.max_hops, params.k)
        own = scores.select(F.col("query_id").alias("sub_id"), "pivot_id", F.col("score").alias("psi"))
        return E.answers_of_many(own, {i: i for i in queries}, params.k, ascending=True)
    raise ValueError(method)


def quality(answers: DataFrame, truth: DataFrame, ks: tuple[int, ...]) -> DataFrame:
    """(k, precision, recall, f1): means over queries at each k."""
    spark = answers.sparkSession
    named = answers.select("query_id", "rank", F.col("pivot_id").alias("node_id"))
    grid = F.broadcast(local(spark, [(k,) for k in ks], "k int"))
    total = truth.groupBy("query_id").agg(F.count("*").alias("total")).crossJoin(grid)  # a row for each query and k
    hits = named.join(truth.withColumn("right", F.lit(1)), ["query_id", "node_id"], "left").crossJoin(grid).filter("rank <= k")
    counted = hits.groupBy("query_id", "k").agg(F.count("*").alias("returned"), F.sum(F.coalesce("right", F.lit(0))).alias("correct"))
    own = total.join(counted, ["query_id", "k"], "left").na.fill(0, ["returned", "correct"])
    own = own.selectExpr("k", "IF(returned > 0, correct / returned, 0D) AS precision", "IF(total > 0, correct / total, 0D) AS recall", "IF(correct > 0, 2 * correct / (returned + total), 0D) AS f1")
    return own.groupBy("k").agg(*[F.avg(c).alias(c) for c in ("precision", "recall", "f1")])


def effectiveness(kg: KG, queries: dict[int, QueryGraph], truth: DataFrame, space: dict, params: Params, library: DataFrame, ks: tuple[int, ...] = (20, 40, 100, 200), methods: tuple[str, ...] = METHODS, prior: DataFrame | None = None) -> DataFrame:
    """(method, k, precision, recall, f1, ms): means over the queries; ms is a query's share of the batch. The bounded method has 90 % of the
    time that the exact one took.
    """
    spark = kg.nodes.sparkSession
    truth, _ = keep(truth, "truth")
    rows, took = [], {}
    for m in methods:
        bound = 0.9 * took["exact"] if m == "bounded" else None
        (answers, _), took[m] = M.timed(lambda m=m, bound=bound: keep(run_method(m, kg, queries, space, params.but(k=max(ks)), library, bound, prior), "answers"))
        rows += [(m, r.k, r.precision, r.recall, r.f1, took[m] / len(queries)) for r in quality(answers, truth, ks).orderBy("k").collect()]
    return local(spark, rows, "method string, k int, precision double, recall double, f1 double, ms double")


def prior_pairs(kg: KG, n: int, noise_percent: int = 0) -> DataFrame:
    """(pair_id, source, target): the first n direct originNation edges as prior knowledge, some with a wrong target."""
    known = kg.edges.filter("predicate = 'originNation'").orderBy("src", "dst").limit(n)
    numbered = known.select((F.row_number().over(Window.orderBy("src", "dst")) - 1).alias("pair_id"), F.col("dst").alias("source"), F.col("src").alias("target"))
    return B.prior_with_noise(numbered, noise_percent)


def prior_sweep(kg: KG, space: dict, params: Params, library: DataFrame, percents: tuple[int, ...] = (0, 10, 20, 30, 40), pairs: int = 50) -> DataFrame:
    """(percent, precision, recall, f1): the pattern miner as more of its prior knowledge is wrong."""
    queries = origin_queries()
    truth, _ = keep(origin_truths(kg, list(queries)), "truth")
    subs, owner = E.plan_many(kg, queries, space, params, library)
    rows, held, known = [], {}, {}
    for percent in percents:
        patterns = tuple(B.best_patterns(B.mined_patterns(kg, prior_pairs(kg, pairs, percent), subs[0].predicates[0], min(params.max_hops, 3))))
        if patterns not in known:  # the same patterns with the same scores have the same answers
            known[patterns] = quality(E.answers_of_many(B.pattern_miner_scores(kg, subs, patterns, library, held=held), owner, params.k), truth, (params.k,)).first()
        r = known[patterns]
        rows.append((percent, r.precision, r.recall, r.f1))
    return local(kg.nodes.sparkSession, rows, "percent int, precision double, recall double, f1 double")


def component_times(kg: KG, queries: list[QueryGraph], space: dict, params: Params, library: DataFrame | None = None) -> DataFrame:
    """(query, variant, component, ms, states, edges): partial against complete construction, search with against without estimate."""
    rows = []
    for gq in queries:
        for variant, options, p in (
            ("partial, estimate", {}, params), ("complete, estimate", {"construct": "complete"}, params), ("partial, no estimate", {}, params.but(use_estimate=False)),
        ):
            r = E.exact_query(kg, gq, space, p, library, measured=True, **options)
            produced = sum(x["produced"] for x in r.stats.rounds)
            rows += [(gq.label, variant, c, float(ms), produced, r.stats.edges_weighted) for c, ms in r.stats.component_ms.items()]
    return local(kg.nodes.sparkSession, rows, "query string, variant string, component string, ms double, states long, edges long")


def time_bound_sweep(kg: KG, gq: QueryGraph, truth: DataFrame, space: dict, params: Params, shares: tuple[int, ...] = (20, 30, 40, 50, 60, 70, 80, 90), runs: int = 2, library: DataFrame | None = None) -> DataFrame:
    """(percent, bound_ms, min_ms, avg_ms, max_ms, overshoot_ms, precision, recall, f1, jaccard, completed): bounds as shares of the time of the exact search, which is
    the best of two runs.
    """
    spark = kg.nodes.sparkSession
    exact, best = None, None
    for _ in range(2):
        (exact, _), ms = M.timed(lambda: keep(E.exact_query(kg, gq, space, params, library).answers, "exact"))
        best = ms if best is None else min(best, ms)
    truth, _ = keep(truth, "truth")
    rows, times = [], []
    for share in shares:
        bound, own = best * share / 100, []
        for _ in range(runs):
            result, ms = M.timed(lambda bound=bound: (r := E.bounded_query(kg, gq, space, params, E.ExecutionClock(bound), library=library), keep(r.answers, "bounded")[0]))
            own.append(ms)
        times += [(share, ms) for ms in own]
        answers = result[1].withColumn("query_id", F.lit(0))
        q = quality(answers, truth, (params.k,)).first()
        rows.append((share, bound, q.precision, q.recall, q.f1, M.jaccard(answers, exact).first().jaccard, result[0].completed))
    spread = M.spread_of_times(local(spark, times, "bound int, ms double")).withColumnRenamed("bound", "percent").drop("overshoot_ms")
    facts = local(spark, rows, "percent int, bound_ms double, precision double, recall double, f1 double, jaccard double, completed boolean")
    return facts.join(spread, "percent").withColumn("overshoot_ms", F.col("max_ms") - F.col("bound_ms"))


def decomposition_costs(kg: KG, queries: list[QueryGraph], space: dict, params: Params, library: DataFrame | None = None) -> DataFrame:
    """(query, shape, optimal, worst, gain) on the cost model."""
    stats = D.collect_stats(kg)
    rows = []
    longest = params.max_hops if params.hop_scope == "match" else D.MOST_EDGES
    for gq in queries:
        counts = D.source_counts(kg, gq, library, params)
        cost = lambda source, preds, counts=counts: D.path_cost(counts[source], preds, stats, space, params)
        best, worst = D.decompose(gq, cost, longest=longest)[2], D.decompose(gq, cost, objective="max", longest=longest)[2]
        rows.append((gq.label, D.classify_shape(gq), best, worst, M.decomposition_gain(best, worst)))
    return local(kg.nodes.sparkSession, rows, "query string, shape string, optimal double, worst double, gain double")


def decomposition_times(kg: KG, queries: list[QueryGraph], space: dict, params: Params, library: DataFrame | None = None, runs: int = 2) -> DataFrame:
    """(query, shape, optimal_ms, worst_ms, gain): run times of both decompositions, the best of some runs each.

    Where a query has one cover only, both objectives name the same search: it is timed once, and nothing is gained.
    """
    rows = []
    for gq in queries:
        ms, covers = {}, {}
        for objective in ("min", "max"):
            cover = frozenset((s.path, s.predicates, s.pivot_pos) for s in E.plan_subs(kg, gq, space, params, library, objective))
            if cover not in covers:
                own = [M.timed(lambda objective=objective, gq=gq: E.exact_query(kg, gq, space, params, library, decomposition=objective).answers.count())[1] for _ in range(runs)]
                covers[cover] = min(own)
            ms[objective] = covers[cover]
        rows.append((gq.label, D.classify_shape(gq), ms["min"], ms["max"], M.decomposition_gain(ms["min"], ms["max"])))
    return local(kg.nodes.sparkSession, rows, "query string, shape string, optimal_ms double, worst_ms double, gain double")


def simulate_votes(answers: DataFrame, n_pairs: int = 30, annotators: int = 10) -> DataFrame:
    """(query_id, pair_id, rank_a, rank_b, votes_a, votes_b) for answers(query_id, rank, score): annotators prefer the better score, with noise by hash.

    The answers of a pair differ in score, that is in the schema they were found by: pair i takes answer i mod n of those with the
    best score and answer (7 i) mod m of the rest. A query whose answers all score alike has no pairs.
    """
    spark = answers.sparkSession
    best = Window.partitionBy("query_id")
    split = answers.withColumn("top", F.col("score") >= F.max("score").over(best) - 1e-9)
    place = Window.partitionBy("query_id", "top")
    split = split.select("query_id", "top", "rank", "score", (F.row_number().over(place.orderBy("rank")) - 1).alias("at"), F.count("*").over(place).alias("n"))
    pairs = F.broadcast(local(spark, [(i,) for i in range(n_pairs)], "pair_id int"))
    a = split.filter("top").crossJoin(pairs).filter("at = pair_id % n").select("query_id", "pair_id", F.col("rank").alias("rank_a"), F.col("score").alias("sa"))
    b = split.filter("NOT top").crossJoin(pairs).filter("at = (pair_id * 7) % n").select("query_id", "pair_id", F.col("rank").alias("rank_b"), F.col("score").alias("sb"))
    ask = a.join(b, ["query_id", "pair_id"]).withColumn("annotator", F.explode(F.sequence(F.lit(0), F.lit(annotators - 1))))
    # the odds grow with the distance of scores and of ranks
    odds = "50 + (sa - sb) * 150 + (rank_b - rank_a) / 8"
    votes = ask.groupBy("query_id", "pair_id", "rank_a", "rank_b").agg(F.expr(f"CAST(sum(CASE WHEN (pair_id * 7919 + annotator * 31 + query_id * 17) % 100 < {odds} THEN 1 ELSE 0 END) AS INT) AS votes_a"))
    return votes.withColumn("votes_b", F.lit(annotators) - F.col("votes_a"))


def noisy_of(n: int, percent: int) -> set[int]:
    """Which of n queries are noisy: the first by a hash order, so that the share is exact (rounded to whole queries)."""
    order = sorted(range(n), key=lambda i: ((i * 7919 + 13) % 10007, i))
    return set(order[: round(n * percent / 100)])


def add_node_noise(queries: list[QueryGraph], surfaces: dict[str, list[str]], percent: int) -> list[QueryGraph]:
    """Types and names replaced by surfaces of the library in a share of the queries."""
    out, noisy = [], noisy_of(len(queries), percent)
    for i, gq in enumerate(queries):
        pick = lambda label, i=i: surfaces[label][i % len(surfaces[label])] if surfaces.get(label) else label
        nodes = tuple(QueryNode(n.key, tuple(pick(t) for t in n.types), pick(n.name) if n.name else None) for n in gq.nodes)
        out.append(QueryGraph(nodes, gq.edges, gq.label) if i in noisy else gq)
    return out


def add_edge_noise(queries: list[QueryGraph], space: dict[str, list[float]], percent: int, m: int = 10) -> list[QueryGraph]:
    """Predicates replaced by the one at rank 1 + i mod m of their most similar in a share of the queries."""
    out, noisy, near = [], noisy_of(len(queries), percent), {}
    for i, gq in enumerate(queries):
        edges = []
        for e in gq.edges:
            if e.predicate not in near:
                w = weights_for(e.predicate, space, -2.0)
                near[e.predicate] = sorted((p for p in w if p != e.predicate), key=lambda p, w=w: (-round(w[p], 9), p))[:m]
            edges.append(QueryEdge(e.a, e.b, near[e.predicate][i % len(near[e.predicate])]))
        out.append(QueryGraph(gq.nodes, tuple(edges), gq.label) if i in noisy else gq)
    return out


def noise_report(kg: KG, kinds: tuple[str, ...], space: dict, params: Params, library: DataFrame, percents: tuple[int, ...] = (0, 10, 20, 30, 40), n_queries: int = 25) -> DataFrame:
    """(kind, percent, precision, recall, f1, ms) means over origin queries."""
    plain = [origin(f"NATION_{i}", "Order") for i in range(n_queries)]
    surfaces = {"Order": ["Purchase", "Sale"], **{f"NATION_{i}": [f"N{i}"] for i in range(25)}}
    truth, _ = keep(origin_truths(kg, list(range(n_queries))), "truth")
    rows = []
    for kind in kinds:
        for percent in percents:
            noisy = add_node_noise(plain, surfaces, percent) if kind == "node" else add_edge_noise(plain, space, percent)
            (answers, _), ms = M.timed(lambda noisy=noisy: keep(E.exact_many(kg, dict(enumerate(noisy)), space, params, library)[0], "answers"))
            m = quality(answers, truth, (params.k,)).first()
            rows.append((kind, percent, m.precision, m.recall, m.f1, ms / n_queries))
    return local(kg.nodes.sparkSession, rows, "kind string, percent int, precision double, recall double, f1 double, ms double")


def scale_curve(kg: KG, percents: tuple[int, ...], ks: tuple[int, ...], space: dict, params: Params, embed=None) -> DataFrame:
    """(percent, nodes, edges, k, ms, index_s, embed_s, embed_mb) over induced subgraphs; ms is the best of two runs."""
    rows = []
    for percent in percents:
        part = induced_subgraph(kg, percent)
        nodes, edges = part.nodes.count(), part.edges.count()
        _, index_ms = M.timed(lambda part=part: index_of(part))
        library = build_library(part)
        seconds, mb = 0.0, 0.0
        if embed is not None:
            _, ms = M.timed(lambda part=part: embed.fit(part.edges)[0].count())
            seconds, mb = ms / 1000, M.embedding_bytes(nodes, embed.dim) / 1e6
        for k in ks:
            own = [M.timed(lambda part=part, k=k, library=library: E.exact_query(part, origin(), space, params.but(k=k), library).answers.count())[1] for _ in range(2)]
            rows.append((percent, nodes, edges, k, min(own), index_ms / 1000, seconds, mb))
    return local(kg.nodes.sparkSession, rows, "percent int, nodes long, edges long, k int, ms double, index_s double, embed_s double, embed_mb double")


def sensitivity(kg: KG, nation_key: int, space: dict, params: Params, library: DataFrame, n_hats: tuple[int, ...] = (2, 3, 4, 5), taus: tuple[float, ...] = (0.6, 0.7, 0.8, 0.9)) -> DataFrame:
    """(param, value, precision, recall, f1, ms)."""
    truth, _ = keep(origin_truths(kg, [nation_key]).withColumn("query_id", F.lit(0)), "truth")
    rows = []
    for name, values in (("max_hops", n_hats), ("tau", taus)):
        for v in values:
            p = params.but(**{name: v})
            (answers, _), ms = M.timed(lambda p=p: keep(E.exact_query(kg, origin(f"N{nation_key}"), space, p, library).answers, "answers"))
            m = quality(answers.withColumn("query_id", F.lit(0)), truth, (p.k,)).first()
            rows.append((name, float(v), m.precision, m.recall, m.f1, ms))
    return local(kg.nodes.sparkSession, rows, "param string, value double, precision double, recall double, f1 double, ms double")


SHAPES = ("chain", "star", "tree", "cycle", "flower")


def extract_query_graphs(kg: KG, shape: str, n_edges: int, n_graphs: int = 5, seed: int = 0, fan: int = 12) -> list[QueryGraph]:
    """Query graphs of a shape and size, extracted from the graph itself: instances of nodes and edges whose names make the specific nodes.

    Seeds and steps are drawn by hash, with `fan` neighbours of a node at most in a draw (a random extraction, like the reference's).
    Cycles close where two walks from a seed meet; flowers are cycles with leaves at the seed. All graphs of a call grow in the same jobs.
    """
    spark = kg.nodes.sparkSession
    index = index_of(kg)
    draw = lambda *c: F.xxhash64(*c, F.lit(f"{shape}-{n_edges}-{seed}"))
    names = kg.nodes.select("node_id", "name", F.get("types", F.lit(0)).alias("type"))
    seeds = names.filter("type = 'Order'") if shape in ("cycle", "flower") else names.filter("type IN ('Order', 'Part', 'Customer')")
    graph_ids = [r.node_id for r in seeds.orderBy(draw("node_id"), "node_id").limit(n_graphs * (4 if shape in ("cycle", "flower") else 1)).collect()]

    def around(pairs: list[tuple[int, int]], few: int) -> dict[tuple[int, int], list[tuple[str, int]]]:
        """(graph, node) -> some (predicate, neighbour) by hash."""
        asked = F.broadcast(local(spark, sorted(set(pairs)), "g int, node long"))
        rows = index.adj.select("node", "nbr", "predicate").join(asked, "node").withColumn("r", F.row_number().over(Window.partitionBy("g", "node").orderBy(draw("g", "node", "nbr", "predicate"), "nbr"))).filter(F.col("r") <= few)
        out: dict[tuple[int, int], list[tuple[str, int]]] = {}
        for r in rows.orderBy("g", "node", "r").collect():
            out.setdefault((r.g, r.node), []).append((r.predicate, r.nbr))
        return out

    edges: dict[int, list[tuple[int, str, int]]] = {g: [] for g in range(len(graph_ids))}
    nodes: dict[int, list[int]] = {g: [i] for g, i in enumerate(graph_ids)}

    def grow(g: int, at: int, near: dict) -> None:
        for predicate, nbr in near.get((g, at), []):
            if nbr not in nodes[g]:
                nodes[g].append(nbr)
                edges[g].append((at, predicate, nbr))
                return

    if shape in ("cycle", "flower"):
        length = n_edges if shape == "cycle" else max(3, n_edges - 2)
        rows = local(spark, [(g, i) for g, i in enumerate(graph_ids)], "g int, node long")
        half = rows.select("g", "node", F.array("node").alias("path"), F.array().cast("array<string>").alias("preds"))
        walks = [half]
        for _ in range((length + 1) // 2):
            x = walks[-1].join(index.adj.select("node", "nbr", "predicate"), "node").filter("NOT array_contains(path, nbr)")
            x = x.withColumn("r", F.row_number().over(Window.partitionBy("g", "path").orderBy(draw("g", "node", "nbr", "predicate"), "nbr"))).filter(F.col("r") <= fan * 4)
            walks.append(keep(x.select("g", F.col("nbr").alias("node"), F.concat("path", F.array("nbr")).alias("path"), F.concat("preds", F.array("predicate")).alias("preds")), "extract")[0])
        a, b = walks[(length + 1) // 2], walks[length // 2].select("g", "node", F.col("path").alias("path_b"), F.col("preds").alias("preds_b"))
        met = a.join(b, ["g", "node"]).filter("size(array_intersect(path, path_b)) = 2 AND (size(path) != 2 OR size(path_b) != 2)")
        one = met.groupBy("g").agg(F.min_by(F.struct("path", "preds", "path_b", "preds_b"), F.struct(draw("path", "path_b"), "path", "path_b")).alias("c")).select("g", "c.*").collect()
        for r in one:
            for path, preds in ((r.path, r.preds), (r.path_b, r.preds_b)):
                edges[r.g] += [(x, p, y) for x, p, y in zip(path, preds, path[1:])]
                nodes[r.g] += [n for n in path[1:] if n not in nodes[r.g]]
        if shape == "flower":
            near = around([(g, graph_ids[g]) for g in edges if edges[g]], fan * 4)
            for g in edges:
                while edges[g] and len(edges[g]) < n_edges:
                    before = len(edges[g])
                    grow(g, graph_ids[g], near)
                    if len(edges[g]) == before:
                        break
    else:
        for at in range(n_edges):
            where = {g: nodes[g][-1] if shape == "chain" else nodes[g][0] if shape == "star" or at < 3 else nodes[g][1 + at % (len(nodes[g]) - 1)] for g in nodes if len(edges[g]) == at}
            near = around(list(where.items()), fan)
            for g, node in where.items():
                grow(g, node, near)
    whole = [g for g in edges if len(edges[g]) == (n_edges if shape != "cycle" else n_edges)][:n_graphs]
    facts = {r.node_id: r for r in names.filter(F.col("node_id").isin(sorted({n for g in whole for n in nodes[g]}) or [0])).collect()}
    out: list[QueryGraph] = []
    for i, g in enumerate(whole):
        degree = {n: sum(n in (a, b) for a, _, b in edges[g]) for n in nodes[g]}
        leaves = [n for n in nodes[g][1:] if degree[n] == 1]
        if shape == "chain":
            chosen = {nodes[g][-1]} | ({nodes[g][0]} if n_edges > 3 else set())
        elif shape in ("cycle", "flower"):
            chosen = {nodes[g][length // 2 + 1 if length > 3 else 1], *leaves[:3]}
        else:
            chosen = set(leaves[:4])
        query_nodes = tuple(QueryNode(f"q{n}", (facts[n].type,), facts[n].name if n in chosen else None) for n in nodes[g])
        out.append(QueryGraph(query_nodes, tuple(QueryEdge(f"q{a}", f"q{b}", p) for a, p, b in edges[g]), f"{shape}-{n_edges}-{i}").validate())
    return out


def shape_report(kg: KG, space: dict, params: Params, sizes: dict[str, int], n_graphs: int = 5, library: DataFrame | None = None, shapes: tuple[str, ...] = SHAPES) -> DataFrame:
    """(shape, size, queries, edges, specific, subs, answers, found, decompose_ms, construct_ms, search_ms, assemble_ms): means over extracted graphs that are searched; `found` is the
    share whose own extracted pivot instance is among the answers' scores of 1 per sub-query.
    """
    rows = []
    for shape in shapes:
        for size, n_edges in sizes.items():
            least = {"star": 3, "tree": 4, "cycle": 3, "flower": 5}.get(shape, 1)
            graphs = extract_query_graphs(kg, shape, max(least, n_edges), n_graphs)
            if not graphs:
                continue
            own = []
            for gq in graphs:
                p = params.but(max_hops=max(params.max_hops, 1)) if params.hop_scope == "query_edge" else params
                r = E.exact_query(kg, gq, space, p, library, measured=True)
                best = r.answers.agg(F.count("*").alias("n"), F.max("score").alias("s")).first()
                own.append((len(gq.edges), sum(n.specific for n in gq.nodes), len(r.subs), best.n, float(best.s is not None and best.s >= len(r.subs) - 1e-6), r.stats.component_ms))
            mean = lambda i, own=own: sum(x[i] for x in own) / len(own)
            ms = [sum(x[5].get(c, 0.0) for x in own) / len(own) for c in ("decompose", "construct", "search", "assemble")]
            rows.append((shape, size, len(own), mean(0), mean(1), mean(2), mean(3), mean(4), *ms))
    return local(kg.nodes.sparkSession, rows, "shape string, size string, queries int, edges double, specific double, subs double, answers double, found double, decompose_ms double, construct_ms double, search_ms double, assemble_ms double")


def queries_as_json(queries: list[QueryGraph]) -> list[str]:
    return [json.dumps(json.loads(q.to_json())) for q in queries]
