"""Re-creations of the compared method classes on the same tables; all return (rank, pivot_id, score).

Each takes a graph, sub-queries and k. The `_scores` forms serve the sub-queries of many queries at once: (sub_id, pivot_id, psi), where psi is the
method's own score.
"""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model import KG, Params, QueryGraph, QueryNode, SubQuery
from ..sources.builders import adjacency
from ..sources.index import SLOTS, index_of
from ..sources.tables import keep, local
from . import search as S
from .search import enumerate_edge_matches


def ranked(scored: DataFrame, k: int, ascending: bool = False) -> DataFrame:
    order = F.asc("score") if ascending else F.desc("score")
    top = scored.orderBy(order, "pivot_id").limit(k)
    return top.withColumn("rank", F.row_number().over(Window.orderBy(order, "pivot_id"))).select("rank", "pivot_id", "score")


def identity_weights(subs: list[SubQuery]) -> dict[tuple[int, int], dict[str, float]]:
    """Every query edge takes its own predicate and no other."""
    return {(s.sub_id, i): {p: 1.0} for s in subs for i, p in enumerate(s.predicates)}


def exact_schema_scores(kg: KG, subs: list[SubQuery], library: DataFrame | None = None, relations: tuple[str, ...] = ("identical",)) -> DataFrame:
    """(sub_id, pivot_id, psi = 1): matches whose every query edge is one edge of the same predicate. As in a join, a node may stand for two query nodes;
    states that end alike are one, so a level is as large as the graph at most.
    """
    one_each = Params(tau=0.0, max_hops=1, hop_scope="query_edge", use_estimate=False, revisit="dominance", relations=relations)
    return S.layered(S.prepare(kg, subs, {}, one_each, library, maps=identity_weights(subs))).scores


def _joined(scores: DataFrame, n_subs: int, k: int, ascending: bool = False) -> DataFrame:
    """The k best pivots that every sub-query has."""
    total = scores.groupBy("pivot_id").agg(F.sum("psi").alias("score"), F.count("*").alias("n")).filter(F.col("n") == n_subs)
    return ranked(total.select("pivot_id", "score"), k, ascending)


def exact_schema_query(kg: KG, subs: list[SubQuery], k: int, library: DataFrame | None = None, relations: tuple[str, ...] = ("identical",)) -> DataFrame:
    """Every query edge is one edge of the graph with the same predicate; labels must be those of the graph."""
    return _joined(exact_schema_scores(kg, subs, library, relations), len(subs), k)


def node_library_query(kg: KG, subs: list[SubQuery], k: int, library: DataFrame) -> DataFrame:
    """As exact_schema_query, with node labels through the library; edges still match one to one."""
    return exact_schema_query(kg, subs, k, library, ("identical", "synonym", "abbreviation"))


def _levels(near: DataFrame, states: DataFrame, max_hops: int, size: int | None = None, settled=None) -> DataFrame:
    """(sub_id, node, degree, profile, pivot_id, value, h) of nodes by least distance from states(sub_id, node, degree, pivot_id, value).

    A node keeps its least distance, and the best value at it, so that a level is as large as the graph at most. `settled(level)` gives
    the sub-queries that need no further level.
    """
    keys = ["sub_id", "node", "pivot"]
    level = states.withColumn("pivot", F.coalesce("pivot_id", F.lit(-1)))
    seen, out = level.select(*keys), []
    edges = near.select("node", "slot", F.col("nbr"), "profile", F.col("degree").alias("nbr_degree"))
    for h in range(1, max_hops + 1):
        if size is not None and size <= S.BROADCAST_STATES:
            x = edges.drop("slot").join(F.broadcast(level.select("sub_id", "node", "pivot", "value")), "node")
        else:
            x = level.select("sub_id", "node", "pivot", "value", F.expr(f"explode(sequence(0, {SLOTS} - 1)) AS slot")).join(edges, ["node", "slot"])
        x = x.groupBy("sub_id", F.col("nbr").alias("node"), F.col("nbr_degree").alias("degree"), "profile", "pivot").agg(F.max("value").alias("value"))
        level, told = keep(x.join(seen, keys, "left_anti"), "level", F.count("*").alias("n"))
        size = told["n"]
        if not size:
            break
        seen = seen.unionByName(level.select(*keys))
        out.append(level.withColumn("h", F.lit(h)))
        if settled is not None and h < max_hops:
            over = settled(out[-1])
            level = level.filter(~F.col("sub_id").isin(sorted(over) or [-1]))
    found = out[0]
    for o in out[1:]:
        found = found.unionByName(o)
    return found.withColumn("pivot_id", F.when(F.col("pivot") >= 0, F.col("pivot"))).drop("pivot")


def _stagewise(prep: S.Prepared, states: DataFrame, max_hops: int, ends, gain, size: int | None = None, settled=None) -> DataFrame:
    """(sub_id, pivot_id, value): chase each sub-query's edges by distance. `ends(stage, levels)` keeps the nodes that may end a stage, with
    `gained`; `gain` is the SQL of a state's new value.
    """
    out = None
    for i in range(max(s.stages for s in prep.subs)):
        found = ends(i, _levels(prep.adj, states, max_hops, size, settled))
        at = [s.sub_id for s in prep.subs if i + 1 == s.pivot_pos]
        pivot = F.when(F.col("sub_id").isin(at or [-1]), F.col("node")).otherwise(F.col("pivot_id"))
        states = found.withColumns({"pivot_id": pivot, "value": F.expr(gain)}).groupBy("sub_id", "node", "degree", "pivot_id").agg(F.max("value").alias("value"))
        over = [s.sub_id for s in prep.subs if s.stages == i + 1]
        own = states.filter(F.col("sub_id").isin(over or [-1])).groupBy("sub_id", "pivot_id").agg(F.max("value").alias("value"))
        out = own if out is None else out.unionByName(own)
        states, size = states.filter(~F.col("sub_id").isin(over or [-1])), None
    return out


def _any_edge(kg: KG, subs: list[SubQuery], params: Params, library: DataFrame | None) -> S.Prepared:
    """A query that takes every predicate alike."""
    every = {p: 1.0 for r in (index_of(kg).profile_rows() or []) for p in r[2]} or {r.predicate: 1.0 for r in kg.edges.select("predicate").distinct().collect()}
    return S.prepare(kg, subs, {}, params.but(tau=0.0), library, maps={(s.sub_id, i): every for s in subs for i in range(s.stages)})


def hop_bounded_scores(kg: KG, subs: list[SubQuery], max_hops: int = 4, library: DataFrame | None = None, k: int | None = None) -> DataFrame:
    """(sub_id, pivot_id, psi): sums of 1 / hops over query edges, each of which takes any path of at most `max_hops` edges.

    `k`: only the k best pivots of each sub-query and their ties are wanted. Where all have one edge, what a further level finds scores less than
    what is there, so a sub-query that has k pivots goes no further.
    """
    prep = _any_edge(kg, subs, Params(max_hops=max_hops), library)

    def ends(stage: int, found: DataFrame) -> DataFrame:
        x = found.withColumn("stage", F.lit(stage)).withColumnRenamed("node", "nbr")
        x, at_end = S._with_ends(prep, x)
        return x.filter(at_end).withColumnRenamed("nbr", "node")

    counts: dict[int, int] = {}

    def settled(level: DataFrame) -> list[int]:
        for r in ends(0, level).groupBy("sub_id").count().collect():
            counts[r.sub_id] = counts.get(r.sub_id, 0) + r["count"]
        return [s for s, n in counts.items() if n >= k]

    states = prep.start.select("sub_id", "node", "degree", "pivot_id", F.lit(0.0).alias("value"))
    return _stagewise(prep, states, max_hops, ends, "value + 1D / h", S.MOST_NAMED if prep.start_span else None, settled if k and all(s.stages == 1 for s in subs) else None).withColumnRenamed("value", "psi")


def hop_bounded_query(kg: KG, subs: list[SubQuery], k: int, max_hops: int = 4, library: DataFrame | None = None) -> DataFrame:
    """Each query edge matches any path of at most `max_hops` edges; only lengths rank."""
    return _joined(hop_bounded_scores(kg, subs, max_hops, library, k if len(subs) == 1 else None), len(subs), k)


def mined_patterns(kg: KG, pairs: DataFrame, query_predicate: str, max_hops: int = 3, min_support: int = 1) -> DataFrame:
    """(pattern, support, similarity, score): predicate sequences between given pairs (source, target), by support share and string edit distance.

    Paths from the source meet paths from the target half way, so neither side goes the whole length from a hub. Prior pairs are a
    small table that a user gives.
    """
    adj = index_of(kg).adj.select("node", "nbr", "predicate")
    pairs = pairs.select("source", "target").withColumn("pair", F.monotonically_increasing_id())
    pairs, told = keep(pairs, "prior", F.count("*").alias("n"))

    def walk(start: str, other: str, hops: int, meet: list[DataFrame] | None = None) -> list[DataFrame]:
        x = pairs.select("pair", F.col(other).alias("other"), F.col(start).alias("node"), F.array(start).alias("path"), F.array().cast("array<string>").alias("preds"))
        out = [x]
        for h in range(1, hops + 1):
            x = x.join(adj, "node").filter("NOT array_contains(path, nbr) AND node != other").select("pair", "other", F.col("nbr").alias("node"), F.concat("path", F.array("nbr")).alias("path"), F.concat("preds", F.array("predicate")).alias("preds"))
            if meet and h == hops:  # a hub's last step is only stored where the other side has come
                x = x.join(S._union([m.select("pair", "node") for m in meet]).distinct(), ["pair", "node"], "left_semi").select(*out[0].columns)
            x, _ = keep(x, "walk")
            out.append(x)
        return out

    back = walk("target", "source", max_hops // 2)
    ahead = walk("source", "target", (max_hops + 1) // 2, back)
    found = None
    for n in range(1, max_hops + 1):
        a, b = ahead[(n + 1) // 2], back[n // 2].select("pair", "node", F.col("path").alias("path_b"), F.col("preds").alias("preds_b"))
        met = a.join(b, ["pair", "node"]).filter("size(array_intersect(path, path_b)) = 1")
        own = met.select("pair", F.array_join(F.concat("preds", F.reverse("preds_b")), " ").alias("pattern")).distinct()
        found = own if found is None else found.unionByName(own)
    supported = found.distinct().groupBy("pattern").agg(F.count("*").alias("support")).filter(F.col("support") >= min_support)
    lengths = F.greatest(F.length("pattern"), F.lit(len(query_predicate)))
    near = 1 - F.levenshtein("pattern", F.lit(query_predicate)) / lengths
    return supported.select("pattern", "support", near.alias("similarity"), (F.col("support") / told["n"] * near).alias("score"))


def pattern_miner_scores(kg: KG, subs: list[SubQuery], patterns: list[tuple[str, float]], library: DataFrame | None = None, relations: tuple[str, ...] = ("identical", "synonym", "abbreviation"), held: dict[str, DataFrame] | None = None, k: int | None = None) -> DataFrame:
    """(sub_id, pivot_id, psi): what mined patterns (predicates, score) find from the sources of sub-queries of one edge. `held` keeps what a pattern finds, for
    further calls with the same sub-queries. `k`: only the k best pivots of each sub-query and their ties are wanted, so one that has k from better patterns
    takes no other.
    """
    out, left = None, list(subs)
    for i, (pattern, score) in enumerate(patterns):
        if k and i and score < patterns[i - 1][1] - S.TIE:  # patterns come best first
            over = {r.sub_id for r in out.groupBy("sub_id").agg(F.countDistinct("pivot_id").alias("n")).filter(F.col("n") >= k).collect()}
            left = [s for s in subs if s.sub_id not in over]
        if not left:
            break
        preds = tuple(pattern.split(" "))
        longer = [replace(s, path=(s.path[0], *[QueryNode(f"x{i}") for i in range(len(preds) - 1)], s.path[-1]), predicates=preds, pivot_pos=len(preds)) for s in left]
        ends = held.get(pattern) if held is not None else None
        if ends is None:
            ends = exact_schema_scores(kg, longer, library, relations).select("sub_id", "pivot_id")
            if held is not None or k:
                ends = keep(ends, "pattern")[0]
            if held is not None:
                held[pattern] = ends
        own = ends.select("sub_id", "pivot_id", F.lit(float(score)).alias("psi"))
        out = own if out is None else out.unionByName(own)
    if out is None:
        return kg.nodes.sparkSession.createDataFrame([], "sub_id int, pivot_id long, psi double")
    return out.groupBy("sub_id", "pivot_id").agg(F.max("psi").alias("psi"))


def best_patterns(patterns: DataFrame, top_patterns: int = 3) -> list[tuple[str, float]]:
    return [(r.pattern, r.score) for r in patterns.orderBy(F.desc(F.round("score", 9)), "pattern").limit(top_patterns).collect()]


def pattern_miner_query(kg: KG, sub: SubQuery, prior_pairs: DataFrame, k: int, top_patterns: int = 3, min_support: int = 1, max_hops: int = 3, library: DataFrame | None = None) -> DataFrame:
    """Mine predicate sequences between prior instance pairs, then answer with the best; a wrong prior gives wrong patterns."""
    best = best_patterns(mined_patterns(kg, prior_pairs, sub.predicates[0], max_hops, min_support), top_patterns)
    return _joined(pattern_miner_scores(kg, [sub], best, library, k=k), 1, k)


def prior_with_noise(pairs: DataFrame, noise_percent: int) -> DataFrame:
    """Prior pairs of which a share has another pair's target: pairs(pair_id, source, target), pair_id from 0.

    The noisy ones are the first by a hash order, so the share is exact for any number of pairs. Prior knowledge is a small table.
    """
    by_hash = Window.orderBy(F.expr("(pair_id * 7919 + 13) % 10007"), "pair_id")
    dealt = pairs.select("*", F.row_number().over(by_hash).alias("place"), F.count("*").over(Window.partitionBy()).alias("n"))
    moved = pairs.select(F.col("pair_id").alias("other"), F.col("target").alias("wrong"))
    noisy = F.col("place") * 100 <= F.col("n") * noise_percent
    return dealt.withColumn("other", F.when(noisy, (F.col("pair_id") + 1) % F.col("n")).otherwise(F.col("pair_id"))).join(moved, "other").select("pair_id", "source", F.col("wrong").alias("target"))


def keyword_scores(kg: KG, terms: dict[int, list[str]], answer_keys: dict[int, set[str]], max_hops: int = 4, k: int | None = None) -> DataFrame:
    """(query_id, pivot_id, score): sums of the distances from a node of an answer type to every keyword's group.

    A keyword's group holds the nodes whose name or type contains it and the ends of edges whose predicate does. Distances are found
    once for a keyword, whatever the number of queries that use it. `k`: only the k best pivots of each query and their ties are wanted. What a level
    has not reached scores more than its number, so a keyword whose queries all have k pivots up to it goes no further.
    """
    spark = kg.nodes.sparkSession
    words = sorted({w for own in terms.values() for w in own})
    index = index_of(kg)
    plain = lambda c: F.regexp_replace(F.lower(c), r"[_\s]+", " ")
    hit = F.filter(F.array(*[F.lit(i) for i in range(len(words))]), lambda i: plain(F.col("name")).contains(F.get(F.array(*[F.lit(w) for w in words]), i)) | F.exists("types", lambda t: plain(t).contains(F.get(F.array(*[F.lit(w) for w in words]), i))))
    by_label = kg.nodes.select("node_id", F.explode(hit).alias("sub_id")).select("sub_id", F.col("node_id").alias("node"))
    predicates = sorted({p for r in (index.profile_rows() or []) for p in r[2]}) or [r.predicate for r in kg.edges.select("predicate").distinct().collect()]
    on_edge = [(i, p) for i, w in enumerate(words) for p in predicates if w in p.lower()]
    by_edge = index.adj.filter(F.col("predicate").isin([p for _, p in on_edge] or [""])).join(F.broadcast(local(spark, on_edge, "sub_id int, predicate string")), "predicate").select("sub_id", "node")
    first = by_label.unionByName(by_edge).distinct().join(index.entities.select(F.col("node_id").alias("node"), "degree", "profile"), "node")
    first, told = keep(first, "keywords", F.count("*").alias("n"))
    states = first.select("sub_id", "node", "degree", F.lit(None).cast("long").alias("pivot_id"), F.lit(0.0).alias("value"))
    at = {w: i for i, w in enumerate(words)}
    asked = F.broadcast(local(spark, [(q, at[w], len(set(own))) for q, own in terms.items() for w in sorted(set(own))], "query_id int, sub_id int, groups long"))
    kinds = F.broadcast(local(spark, [(q, p) for q, wanted in answer_keys.items() for p, keys, _ in index.profile_rows() or [] if keys & wanted], "query_id int, profile long"))
    dist = [first.select("sub_id", "node", "profile", F.lit(0.0).alias("d"))]

    def complete() -> DataFrame:
        whole = S._union(dist).join(asked, "sub_id").join(kinds, ["query_id", "profile"]).groupBy("query_id", "node", "groups").agg(F.sum("d").alias("score"), F.count("*").alias("n"))
        return whole.filter("n = groups").select("query_id", F.col("node").alias("pivot_id"), "score")

    def settled(level: DataFrame) -> list[int]:
        dist.append(level.select("sub_id", "node", "profile", F.col("h").cast("double").alias("d")))
        over = {r.query_id for r in complete().filter(F.col("score") <= len(dist) - 1).groupBy("query_id").count().filter(F.col("count") >= k).collect()}
        return [i for w, i in at.items() if all(q in over for q, own in terms.items() if w in own)]

    near = _levels(index.adj, states, max_hops, told["n"], settled if k else None)
    dist[1:] = [near.select("sub_id", "node", "profile", F.col("h").cast("double").alias("d"))]
    return complete()


def keyword_terms(gq: QueryGraph, labels: dict[tuple[str, str], dict[str, str]]) -> tuple[list[str], set[str]]:
    """(keywords, answer types) of a query graph: names of its specific nodes and its predicates; types of its first target."""
    names = [sorted(labels[n.name, "name"], key=lambda k: (labels[n.name, "name"][k] == "identical", k))[0] for n in gq.nodes if n.specific]
    target = next(n for n in gq.nodes if not n.specific)
    return [*names, *[e.predicate.lower() for e in gq.edges]], {k for t in target.types for k in labels[t, "type"]}


def keyword_query(kg: KG, keywords: list[str], answer_types: tuple[str, ...], k: int, max_hops: int = 3, library: DataFrame | None = None) -> DataFrame:
    """Keywords match names, types and predicates by containment; answers are near to all groups: the least sum of distances."""
    labels = S.resolve_labels(library if library is not None else S.authored_library(kg.nodes.sparkSession), [(t, "type") for t in answer_types], ("identical", "synonym", "abbreviation"), {})
    found = keyword_scores(kg, {0: [w.lower().replace("_", " ") for w in keywords]}, {0: {x for t in answer_types for x in labels[t, "type"]}}, max_hops, k)
    return ranked(found.select("pivot_id", "score"), k, ascending=True)


def homomorphism_scores(kg: KG, subs: list[SubQuery], threshold: float = 0.5, max_hops: int = 4, one_to_one: bool = False) -> DataFrame:
    """(sub_id, pivot_id, psi): mean label similarity, by edit distance, of the nodes that a sub-query's nodes map to; a query edge takes any path.

    Similarities of types belong to profiles, a vocabulary; those of names are found for the few specific query nodes. `one_to_one` keeps
    a pivot from standing for the source as well.
    """
    spark = kg.nodes.sparkSession
    index = index_of(kg)
    prep = _any_edge(kg, subs, Params(max_hops=max_hops), None)
    best = lambda words, c: F.array_max(F.array(*[1 - F.levenshtein(F.lower(c), F.lit(x.lower())) / F.greatest(F.length(c), F.lit(len(x))) for x in words]))

    def by_type(q: QueryNode) -> DataFrame:
        s = F.coalesce(F.array_max(F.transform("types", lambda t: best(list(q.types), t))), F.lit(0.0)) if q.types else F.lit(1.0)
        return index.profiles.select("profile", s.alias("s_type"))

    def similar(q: QueryNode) -> DataFrame:
        """(node, degree, s) of a specific query node."""
        named = kg.nodes.select(F.col("node_id").alias("node"), best([q.name], F.col("name")).alias("s_name"))
        least = 2 * threshold - 1 if q.types else threshold  # the other half is one at most
        own = named.filter(F.col("s_name") >= least).join(index.entities.select(F.col("node_id").alias("node"), "degree", "profile"), "node").join(by_type(q), "profile")
        s = (F.col("s_name") + F.col("s_type")) / 2 if q.types else F.col("s_name")
        return own.select("node", "degree", s.alias("s")).filter(F.col("s") >= threshold)

    # a sub-query with a node that no type of the graph is like has no match: it is not walked
    asked = {q for s in subs for q in s.path[1:] if q.types and not q.specific}
    lost = {q for q in asked if not by_type(q).filter(F.col("s_type") >= threshold).limit(1).count()}
    live = [s for s in subs if not lost & set(s.path[1:])]
    if not live:
        return spark.createDataFrame([], "sub_id int, pivot_id long, psi double")

    states, forms = None, {}
    for s in live:
        forms.setdefault(s.path[0], []).append(s.sub_id)
    for q, ids in forms.items():
        own = similar(q).select(F.explode(F.array(*[F.lit(i) for i in ids])).alias("sub_id"), "node", "degree", F.lit(None).cast("long").alias("pivot_id"), F.col("s").alias("value"))
        states = own if states is None else states.unionByName(own)
    states, told = keep(states, "similar", F.count("*").alias("n"))

    def ends(stage: int, found: DataFrame) -> DataFrame:
        out = None
        groups: dict[QueryNode, list[int]] = {}
        for s in subs:
            if s.stages > stage:
                groups.setdefault(s.path[stage + 1], []).append(s.sub_id)
        for q, ids in groups.items():
            mine = found.filter(F.col("sub_id").isin(ids))
            if q.specific:
                own = mine.join(similar(q).select("node", F.col("s").alias("gained")), "node")
            else:
                own = mine.join(F.broadcast(by_type(q).filter(F.col("s_type") >= threshold).select("profile", F.col("s_type").alias("gained"))), "profile")
            own = own.select("sub_id", "node", "degree", "pivot_id", "value", "h", "gained")
            out = own if out is None else out.unionByName(own)
        return out

    found = _stagewise(prep, states, max_hops, ends, "value + gained", told["n"])
    if one_to_one:
        found = found.join(states.select("sub_id", F.col("node").alias("pivot_id")).distinct(), ["sub_id", "pivot_id"], "left_anti")
    stages = local(spark, [(s.sub_id, s.stages + 1) for s in subs], "sub_id int, nodes int")
    return found.join(F.broadcast(stages), "sub_id").select("sub_id", "pivot_id", F.round(F.col("value") / F.col("nodes"), 9).alias("psi"))


def homomorphism_query(kg: KG, subs: list[SubQuery], k: int, threshold: float = 0.5, max_hops: int = 4, one_to_one: bool = False) -> DataFrame:
    """Nodes match if their labels are similar; a query edge matches any path that is not empty; semantics plays no part."""
    return _joined(homomorphism_scores(kg, subs, threshold, max_hops, one_to_one), len(subs), k)


def union_of_schemas(kg: KG, source: DataFrame, schemas: list[tuple[str, ...]], target_type: str) -> DataFrame:
    """(node_id): what a user with full knowledge would find: the union over predicate sequences from source(node_id)."""
    adj = adjacency(kg.edges).select("node", "nbr", "predicate")
    ends = kg.nodes.filter(F.array_contains("types", target_type)).select("node_id")
    out = None
    for preds in schemas:
        x = source.select(F.col("node_id").alias("node"))
        for p in preds:
            x = x.join(adj.filter(F.col("predicate") == p), "node").select(F.col("nbr").alias("node")).distinct()
        own = x.select(F.col("node").alias("node_id")).join(ends, "node_id", "left_semi")
        out = own if out is None else out.unionByName(own)
    return out.distinct()


def brute_force_query(kg: KG, sub: SubQuery, weights: DataFrame, k: int, params: Params, library: DataFrame | None = None) -> DataFrame:
    """Every simple path within the hop limit, scored at the end; weights(predicate, w)."""
    paths = enumerate_edge_matches(kg, sub, params, library).withColumn("id", F.monotonically_increasing_id())
    table = F.map_from_entries(F.collect_list(F.struct("predicate", "w")))
    one = weights.agg(table.alias("t"))
    scored = paths.crossJoin(F.broadcast(one)).withColumn("ws", F.transform("path_preds", lambda p: F.coalesce(F.element_at("t", p), F.lit(0.0))))
    product = F.aggregate("ws", F.lit(1.0), lambda s, x: s * x)
    best = scored.select(F.col("end_id").alias("pivot_id"), F.pow(product, 1.0 / F.col("n")).alias("score")).filter(F.col("score") >= params.tau - 1e-12)
    return ranked(best.groupBy("pivot_id").agg(F.max("score").alias("score")), k)


__all__ = [n for n in dir() if n.endswith("_query") or n in ("mined_patterns", "prior_with_noise", "ranked", "union_of_schemas", "QueryGraph")]
