"""Semantic search of sub-queries: all states of a frontier expand at once, under admissible bounds.

A state is a partial path with its weight product. One hop joins the frontier with the adjacency on the node, weighs the
edges by broadcast (stage, predicate) weights, and joins what is known of the neighbours' profiles: stages they end and
the best weight at them, which give the bound. A frontier that was counted as small is broadcast to the adjacency; a larger
one is shuffled on (node, slot), so that hubs are split. The engines differ in which states expand when:

* layered: every state, one join a hop (`eager` stores each hop and can prune by the k-th best score);
* best_first: the best `batch` states each round, until k scores beat every estimate left;
* local: a heap search in one task over a neighbourhood that was pruned and counted before.

An engine returns its lists with, for each sub-query, a bound on the scores that the list may lack: none where it is whole.
A query of several sub-queries goes on until its k best answers beat what the bounds still allow.
"""

from __future__ import annotations

import contextlib
import heapq
import time
from collections.abc import Callable
from dataclasses import dataclass, field, replace

from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, Observation, Window
from pyspark.sql import functions as F

from ..model import KG, Params, QueryNode, SubQuery
from ..sources.builders import adjacency
from ..sources.index import SLOTS, index_of
from ..sources.tables import cut, keep, local
from .library import authored_library, match_nodes, resolve_labels
from .predicate_space import weights_for

EPS = 1e-12
#: Scores that differ by less count as equal where lists are cut off, so that ties are always whole.
TIE = 1e-8
#: Rows of broadcast vocabularies: (sub-query, stage, predicate) weights and (sub-query, stage, profile) facts.
MOST_WEIGHTS = 1_000_000
#: States of a frontier that are broadcast (some 300 bytes each).
BROADCAST_STATES = 100_000
#: Adjacency rows of a round beyond which they are dealt to all tasks; a task then weighs about as many.
SPREAD_ROWS = 200_000
#: Source and named nodes of a query that the driver holds.
MOST_NAMED = 10_000
MOST_LOCAL_EDGES = 2_000_000
#: Sub-queries that a round measures one by one.
MOST_MEASURED = 50
#: Places up to which Spark cuts ranked rows off before it shuffles them (`spark.sql.optimizer.windowGroupLimitThreshold`).
MOST_PLACES = 1000


@dataclass
class Stats:
    """What a search did: per round the rows produced, kept and matched; milliseconds of each component; edges weighed; entries read."""

    rounds: list[dict] = field(default_factory=list)
    component_ms: dict[str, float] = field(default_factory=dict)
    edges_weighted: int = 0
    accesses: int = 0
    random_accesses: int = 0
    list_rows: int = 0
    searches: int = 0
    early: dict[int, int] = field(default_factory=dict)

    def add(self, component: str, began: float) -> None:
        self.component_ms[component] = self.component_ms.get(component, 0.0) + (time.monotonic() - began) * 1000


@dataclass
class Found:
    """Lists of matches, and for a sub-query whose list is not whole a score that every match it lacks stays under."""

    matches: DataFrame
    missing: dict[int, float] = field(default_factory=dict)
    scores: DataFrame | None = None  # (sub_id, pivot_id, psi) of the matches, where that is cheaper to have


@dataclass
class Prepared:
    """Tables of one query: adjacency of usable predicates, weights, facts of profiles, named ends, first states."""

    kg: KG
    subs: list[SubQuery]
    params: Params
    adj: DataFrame
    weights: DataFrame
    info: DataFrame
    named: DataFrame | None
    start: DataFrame
    start_span: tuple[int, int] | None
    start_fanout: int | None
    weight_maps: dict[tuple[int, int], dict[str, float]]
    most: float
    small_info: bool = True
    adjacent: DataFrame | None = None  # (sub_id, stage, nbr, m): only with m_mode='scan'

    @property
    def hops(self) -> int:
        return max(self.params.root(s) for s in self.subs)


def stage_weights(subs: list[SubQuery], space: dict[str, list[float]], params: Params) -> dict[tuple[int, int], dict[str, float]]:
    """Weights of each (sub, stage), without those that no match above tau can hold."""
    out = {}
    held: dict[str, dict[str, float]] = {}
    for s in subs:
        floor = max(params.weight_floor, params.tau ** params.root(s) - EPS if params.static_cut and params.tau > 0 else 0.0)
        for i, p in enumerate(s.predicates):
            if p not in held:
                held[p] = weights_for(p, space, params.weight_floor, params.rescale)
            out[s.sub_id, i] = {k: w for k, w in held[p].items() if w >= floor}
    return out


def _labels(kg: KG, nodes: list[QueryNode], library: DataFrame | None, params: Params) -> dict[tuple[str, str], dict[str, str]]:
    index = index_of(kg)
    if library is None:
        library = index.memo.setdefault("authored", authored_library(kg.edges.sparkSession))
    asked = {(t, "type") for n in nodes for t in n.types} | {(n.name, "name") for n in nodes if n.specific}
    return resolve_labels(library, sorted(asked), params.relations, index.memo)


def _wanted(q: QueryNode, labels: dict) -> set[str] | None:
    """Normal forms of types that a query node takes; None: any."""
    return {k for t in q.types for k in labels[t, "type"]} if q.types else None


def named_nodes(kg: KG, q: QueryNode, labels: dict) -> DataFrame:
    """(node_id, profile, degree) of a query node: names are looked up first, then types by profile."""
    index = index_of(kg)
    out = index.entities.select("key", "node_id", "profile", "degree")
    if q.specific:
        out = out.filter(F.col("key").isin(sorted(labels[q.name, "name"]) or ["\x00"]))
    out = out.drop("key")
    wanted = _wanted(q, labels)
    if wanted is None:
        return out
    held = index.profile_rows()
    if held is None:
        good = index.profiles.filter(F.arrays_overlap("keys", F.array(*[F.lit(w) for w in sorted(wanted) or [""]]))).select("profile")
        return out.join(good, "profile", "left_semi").select("node_id", "profile", "degree")
    return out.filter(F.col("profile").isin([p for p, keys, _ in held if keys & wanted] or [0]))


def _named_alike(kg: KG, nodes: list[QueryNode], labels: dict) -> dict[QueryNode, list[tuple[int, int]]] | None:
    """(node_id, degree) of the graph's nodes that each query node stands for, from one scan; None where they are too many for the driver."""
    if not nodes:
        return {}
    index, held = index_of(kg), index_of(kg).profile_rows()
    if held is None or not all(q.specific for q in nodes):
        asked = _union([named_nodes(kg, q, labels).select(F.lit(i).alias("i"), "node_id", "degree") for i, q in enumerate(nodes)])
        rows = asked.limit(MOST_NAMED + 1).collect()
        return {q: sorted({(r.node_id, r.degree) for r in rows if r.i == i}) for i, q in enumerate(nodes)} if len(rows) <= MOST_NAMED else None
    keys = sorted({k for q in nodes for k in labels[q.name, "name"]})
    rows = index.entities.filter(F.col("key").isin(keys or ["\x00"])).select("key", "node_id", "profile", "degree").limit(MOST_NAMED + 1).collect()
    if len(rows) > MOST_NAMED:
        return None
    kinds, out = {p: types for p, types, _ in held}, {}
    for q in nodes:
        wanted = _wanted(q, labels)
        out[q] = sorted({(r.node_id, r.degree) for r in rows if r.key in labels[q.name, "name"] and (wanted is None or kinds.get(r.profile, frozenset()) & wanted)})
    return out


def named_alike(kg: KG, nodes: list[QueryNode], library: DataFrame | None, params: Params) -> dict[QueryNode, list[tuple[int, int]]] | None:
    """(node_id, degree) of the graph's nodes that each query node stands for; looked up once for a graph and library. None: too many for the driver."""
    known = index_of(kg).memo.setdefault(("sources", id(library), params.relations), {"library": library})
    new = [q for q in nodes if q not in known]
    if new:
        found = _named_alike(kg, new, _labels(kg, new, library, params))
        if found is None:
            return None
        known.update(found)
    return {q: known[q] for q in nodes}


def prepare(kg: KG, subs: list[SubQuery], space: dict[str, list[float]], params: Params, library: DataFrame | None = None, adj: DataFrame | None = None, maps: dict | None = None) -> Prepared:
    """Resolve labels, weights and profiles of a query. `adj` replaces the stored adjacency, `maps` the weights of the space."""
    spark = kg.edges.sparkSession
    index = index_of(kg)
    labels = _labels(kg, [n for s in subs for n in s.path], library, params)
    maps = maps if maps is not None else stage_weights(subs, space, params)
    rows = [(s, i, p, float(w)) for (s, i), m in maps.items() for p, w in m.items()]
    if len(rows) > MOST_WEIGHTS:
        raise ValueError("too many predicate weights to broadcast")
    weights = local(spark, rows, "sub_id int, stage int, predicate string, w double")
    used = sorted({p for m in maps.values() for p in m})
    near = (adj if adj is not None else index.adj).filter(F.col("predicate").isin(used or [""]))
    info, small = _facts(kg, subs, maps, labels)
    # nodes that only their name makes an end of a stage
    named = None
    for s in subs:
        for i, q in enumerate(s.path[1:]):
            if q.specific:
                own = named_nodes(kg, q, labels).select(F.lit(s.sub_id).alias("sub_id"), F.lit(i).alias("stage"), F.col("node_id").alias("nbr"))
                named = own if named is None else named.unionByName(own)
    if named is not None:
        held = named.limit(MOST_NAMED + 1).collect()
        if len(held) <= MOST_NAMED:
            named = F.broadcast(local(spark, [tuple(r) for r in held], "sub_id int, stage int, nbr long"))
    sources: dict[QueryNode, list[int]] = {}
    for s in subs:
        sources.setdefault(s.path[0], []).append(s.sub_id)
    known = named_alike(kg, list(sources), library, params)
    span, fanout = None, None
    if known is not None:  # the usual case: a name is one node or a few
        rows = [(i, n, degree) for q, ids in sources.items() for i in ids for n, degree in known[q]]
        start = local(spark, rows, "sub_id int, source_id long, degree long")
        span = (min((r[1] for r in rows), default=0), max((r[1] for r in rows), default=0))
        fanout = sum(r[2] for r in rows)
    else:
        start = _union([named_nodes(kg, q, labels).select(F.explode(F.array(*[F.lit(i) for i in ids])).alias("sub_id"), F.col("node_id").alias("source_id"), "degree") for q, ids in sources.items()]).distinct()
    start = start.selectExpr(
        "sub_id", "source_id", "source_id AS node", "degree", "0 AS stage", "0 AS hops", "0 AS stage_hops", "1D AS w_prod", "1D AS psi_hat", "array(source_id) AS path_nodes",
        "CAST(array() AS array<string>) AS path_preds", "CAST(NULL AS BIGINT) AS pivot_id", "false AS done",
    )
    most = max((w for m in maps.values() for w in m.values()), default=1.0)
    prep = Prepared(kg, subs, params, near, weights, info, named, start, span, fanout, maps, most, small)
    if params.m_mode == "scan":
        prep.adjacent = near.join(F.broadcast(weights), "predicate").groupBy("sub_id", "stage", F.col("node").alias("nbr")).agg(F.max("w").alias("m"))
    return prep


def _facts(kg: KG, subs: list[SubQuery], maps: dict, labels: dict) -> tuple[DataFrame, bool]:
    """(sub_id, stage, profile, ends, m, m_next), small: whether nodes of a profile may end the stage, and the best weight at them in it
    and in the next. A vocabulary: broadcast where it was counted as small, else joined.
    """
    spark = kg.edges.sparkSession
    index = index_of(kg)
    schema = "sub_id int, stage int, profile long, ends boolean, m double, m_next double"
    held = index.profile_rows()
    rows: list[tuple] | None = [] if held is not None else None
    if held is not None and len(held) * sum(s.stages for s in subs) <= MOST_WEIGHTS:
        same: dict = {}  # sub-queries of the same form share their facts
        for s in subs:
            for i in range(s.stages):
                q = s.path[i + 1]
                form = (q, tuple(sorted(maps[s.sub_id, i].items())), tuple(sorted(maps.get((s.sub_id, i + 1), {}).items())))
                if form not in same:
                    wanted, here, then = _wanted(q, labels), maps[s.sub_id, i], maps.get((s.sub_id, i + 1), {})
                    facts = []
                    for profile, keys, preds in held:
                        ends = wanted is None or bool(keys & wanted)
                        m, n = max((here.get(p, 0.0) for p in preds), default=0.0), max((then.get(p, 0.0) for p in preds), default=0.0)
                        if ends or m > 0 or n > 0:
                            facts.append((profile, ends, float(m), float(n)))
                    same[form] = facts
                rows += [(s.sub_id, i, *f) for f in same[form]]
        return local(spark, rows, schema), True
    out = None
    best = lambda m: F.coalesce(F.array_max(F.transform("preds", lambda p: F.coalesce(F.element_at(F.create_map(*[F.lit(x) for kv in m.items() for x in kv]), p), F.lit(0.0)))), F.lit(0.0)) if m else F.lit(0.0)
    for s in subs:
        for i in range(s.stages):
            wanted = _wanted(s.path[i + 1], labels)
            ends = F.lit(True) if wanted is None else F.arrays_overlap("keys", F.array(*[F.lit(w) for w in sorted(wanted) or [""]]))
            own = index.profiles.select(F.lit(s.sub_id).alias("sub_id"), F.lit(i).alias("stage"), "profile", ends.alias("ends"), best(maps[s.sub_id, i]).alias("m"), best(maps.get((s.sub_id, i + 1), {})).alias("m_next"))
            out = own if out is None else out.unionByName(own)
    return keep(out, "facts")[0], False


def by_sub(prep: Prepared, value: Callable[[SubQuery], float]) -> str:
    """SQL of a literal that depends on the sub-query; one literal where all agree."""
    show = lambda v: f"{v!r}D" if isinstance(v, float) else str(v)
    values = {s.sub_id: value(s) for s in prep.subs}
    common = max(set(values.values()), key=list(values.values()).count)
    others = "".join(f" WHEN sub_id IN ({', '.join(str(i) for i, x in values.items() if x == v)}) THEN {show(v)}" for v in sorted(set(values.values()) - {common}))
    return f"(CASE{others} ELSE {show(common)} END)" if others else show(common)


def step(prep: Prepared, states: DataFrame, size: int | None = None, span: tuple[int, int] | None = None, within: DataFrame | None = None) -> DataFrame:
    """States joined with their usable edges, weighed. `size`: how many states there are at most, if that is known; `span`: their least and
    greatest node, which prunes files of the adjacency; `within`(pivot_id): the only neighbours asked for.
    """
    near = prep.adj.withColumnRenamed("degree", "nbr_degree")
    if span is not None:
        near = near.filter(f"node = {span[0]}" if span[0] == span[1] else f"node BETWEEN {span[0]} AND {span[1]}")
    if within is not None:
        near = near.join(F.broadcast(within.withColumnRenamed("pivot_id", "nbr")), "nbr", "left_semi")
    states = states.filter("NOT done")
    if size is not None and size <= BROADCAST_STATES:
        x = near.drop("slot").join(F.broadcast(states), "node")
    else:
        x = states.withColumn("slot", F.expr(f"explode(sequence(0, {SLOTS} - 1))")).join(near, ["node", "slot"])
    return x.join(F.broadcast(prep.weights), ["sub_id", "stage", "predicate"])


def _with_ends(prep: Prepared, x: DataFrame) -> tuple[DataFrame, str]:
    """Rows with the facts of the neighbour's profile, and SQL that tells whether the neighbour ends the state's stage."""
    x = x.join(F.broadcast(prep.info) if prep.small_info else prep.info, ["sub_id", "stage", "profile"], "left")
    named = [f"(sub_id = {s.sub_id} AND stage = {i})" for s in prep.subs for i, q in enumerate(s.path[1:]) if q.specific]
    if not named:
        return x, "coalesce(ends, false)"
    x = x.join(prep.named.withColumn("is_named", F.lit(True)), ["sub_id", "stage", "nbr"], "left")
    return x, f"(CASE WHEN {' OR '.join(named)} THEN coalesce(is_named, false) ELSE coalesce(ends, false) END)"


def _next_weight(prep: Prepared) -> str:
    """SQL of m(u), the best weight at the neighbour for its stage, after a move on to the next stage where `moves`."""
    if prep.params.m_mode == "scan":
        return "coalesce(m, 0D)"
    if prep.params.m_mode == "loose":
        best = {k: max(own.values(), default=0.0) for k, own in prep.weight_maps.items()}
        return "(CASE " + " ".join(f"WHEN sub_id = {s} AND stage + CAST(moves AS INT) = {i} THEN {v!r}D" for (s, i), v in best.items()) + " ELSE 0D END)"
    return "coalesce(CASE WHEN moves THEN m_next ELSE m END, 0D)"


def expand(prep: Prepared, states: DataFrame, theta: dict[int, float] | None = None, size: int | None = None, span: tuple[int, int] | None = None, weighed=None, fanout: int | None = None, within: DataFrame | None = None) -> DataFrame:
    """One hop of states that are not done: new states and matches (done, with psi as psi_hat), bounded and pruned.

    States that have fewer hops left than edges of the query are dropped. `fanout`: the adjacency rows of the states, if known. States that wait at the same few nodes meet their edges in one task, so
    where there are many rows these are dealt to all tasks before they are weighed. `theta` cuts off states that stay below the k-th score by more than a tie. `weighed` observes the edges that were weighed.
    Expressions are SQL text: a hop is planned in a few calls.
    """
    p = prep.params
    root, last = by_sub(prep, lambda s: p.root(s)), by_sub(prep, lambda s: s.stages - 1)
    x = step(prep, states, size, span, within)
    if weighed is not None:
        x = x.observe(weighed, F.count("*").alias("edges"))
    kept = ["nbr != source_id" if p.revisit == "dominance" else "NOT array_contains(path_nodes, nbr)", f"hops < {root}"]
    if p.hop_scope == "query_edge":
        kept.append(f"stage_hops < {p.max_hops}")
    if p.use_estimate and p.tau > 0:  # before anything is known of the neighbour: its weight is one at most
        kept.append(f"w_prod * w >= {by_sub(prep, lambda s: p.tau ** p.root(s) - EPS)}")
    if "only" in states.columns:  # see `undominated`
        kept.append("(only IS NULL OR nbr = only)")
    x = x.filter(" AND ".join(kept))
    if fanout is not None and fanout > SPREAD_ROWS:
        x = x.repartition(max(states.sparkSession.sparkContext.defaultParallelism, fanout // SPREAD_ROWS), "nbr", "path_nodes")
    x, at_end = _with_ends(prep, x)
    x = x.selectExpr("*", f"{at_end} AS at_end").selectExpr("*", f"at_end AND stage < {last} AS moves", f"at_end AND stage = {last} AS ends_all", f"at_end AND stage + 1 = {by_sub(prep, lambda s: s.pivot_pos)} AS at_pivot")
    if p.through_target:  # a neighbour that ends a stage also stays in it
        x = x.withColumn("passes", F.expr("explode(CASE WHEN at_end THEN array(false, true) ELSE array(false) END)"))
        x = x.withColumns({c: F.expr(f"{c} AND NOT passes") for c in ("moves", "ends_all", "at_pivot")})
    if p.m_mode == "scan":
        x = x.drop("m").withColumn("to", F.expr("stage + CAST(moves AS INT)")).join(prep.adjacent.withColumnRenamed("stage", "to"), ["sub_id", "to", "nbr"], "left")
    m = _next_weight(prep)
    if not p.use_estimate:
        estimate = "1D"
    elif p.bound == "tight":
        most = f"{float(prep.most)!r}D"
        estimate = f"coalesce(array_max(transform(sequence(hops + 2, greatest(hops + 2, {root})), n -> power(w_prod * w * {m} * power({most}, n - hops - 2), 1D / n))), 0D)"
    else:
        estimate = f"power(w_prod * w * {m}, 1D / {root})"
    x = x.selectExpr(
        "sub_id", "source_id", "nbr AS node", "nbr_degree AS degree", "stage + CAST(moves AS INT) AS stage", "hops + 1 AS hops", "CASE WHEN moves THEN 0 ELSE stage_hops + 1 END AS stage_hops", "w_prod * w AS w_prod",
        f"CASE WHEN ends_all THEN power(w_prod * w, 1D / (hops + 1)) ELSE {estimate} END AS psi_hat", "concat(path_nodes, array(nbr)) AS path_nodes", "concat(path_preds, array(predicate)) AS path_preds",
        "CASE WHEN at_pivot THEN nbr ELSE pivot_id END AS pivot_id", "ends_all AS done",
    )
    good = [f"(done OR hops + {last} + 1 - stage <= {root})", f"psi_hat >= {float(p.tau - EPS)!r}D"]
    if theta:
        good.append("psi_hat >= CASE " + " ".join(f"WHEN sub_id = {s} THEN {float(t - TIE)!r}D" for s, t in theta.items()) + " ELSE 0D END")
    x = x.filter(" AND ".join(good))
    if p.revisit == "dominance":  # of walks that agree in all that their future depends on, the greatest product stays
        keys = ["sub_id", "source_id", "node", "degree", "stage", "hops", "stage_hops", "pivot_id", "done"]
        rest = ["w_prod", "psi_hat", "path_nodes", "path_preds"]
        best = F.max_by(F.struct(*rest), F.struct("w_prod", F.transform("path_nodes", lambda n: -n)))
        x = x.groupBy(keys).agg(best.alias("b")).select(*keys, *[F.col(f"b.{c}").alias(c) for c in rest])
    return x.select(*[c for c in states.columns if c != "only"])


def undominated(prep: Prepared, states: DataFrame) -> DataFrame:
    """States with one hop left, as few as find the same best match of every pivot.

    Of states that agree in all but their path, the best one serves every neighbour that its path does not hold. For each node v
    on its path the best state without v serves v: it is kept with `only` = v. A group leaves no more states than a path has nodes.
    """
    keys = ["sub_id", "node", "degree", "stage", "hops", "stage_hops", "pivot_id"]
    rest = ["source_id", "w_prod", "psi_hat", "path_nodes", "path_preds"]
    ahead = F.struct("w_prod", F.transform("path_nodes", lambda n: -n))
    best = states.groupBy(keys).agg(F.max_by(F.struct(*rest), ahead).alias("b"))
    first = best.select(*keys, *[F.col(f"b.{c}").alias(c) for c in rest], F.lit(None).cast("long").alias("only"))
    same = " AND ".join(f"s.{c} <=> f.{c}" for c in keys)
    other = states.alias("s").join(best.select(*keys, F.col("b.path_nodes").alias("held")).alias("f"), F.expr(same))
    other = other.select(*[f"s.{c}" for c in [*keys, *rest]], F.expr("explode(array_except(f.held, s.path_nodes)) AS only"))
    spare = other.groupBy(*keys, "only").agg(F.max_by(F.struct(*rest), ahead).alias("b")).select(*keys, *[F.col(f"b.{c}").alias(c) for c in rest], "only")
    return first.unionByName(spare).withColumn("done", F.lit(False)).select(*prep.start.columns, "only")


def best_matches(done: DataFrame) -> DataFrame:
    """(sub_id, pivot_id, psi, n, source_id, end_id, path_nodes, path_preds): the best path of each sub-query and pivot."""
    rank = F.struct(F.col("psi_hat"), -F.col("hops"), F.transform("path_nodes", lambda n: -n))
    best = F.max_by(F.struct(F.col("psi_hat").alias("psi"), F.col("hops").alias("n"), "source_id", F.col("node").alias("end_id"), "path_nodes", "path_preds"), rank)
    return done.groupBy("sub_id", "pivot_id").agg(best.alias("b")).select("sub_id", "pivot_id", "b.*")


def kth_scores(done: DataFrame, subs: list[SubQuery], k: int) -> dict[int, float]:
    """The k-th best score of each sub-query over distinct pivots; absent while there are fewer than k. One job: a top-k for each."""
    best = done.groupBy("sub_id", "pivot_id").agg(F.max("psi_hat").alias("psi"))
    if k <= MOST_PLACES:  # the matches are read once, and tasks send on the k best of each sub-query
        place = F.row_number().over(Window.partitionBy("sub_id").orderBy(F.desc("psi")))
        top = best.withColumn("place", place).filter(F.col("place") <= k).select("sub_id", "psi")
    else:
        top = None
        for s in subs:
            own = best.filter(F.col("sub_id") == s.sub_id).select("sub_id", "psi").orderBy(F.desc("psi")).limit(k)
            top = own if top is None else top.unionByName(own)
    return {r.sub_id: r.low for r in top.groupBy("sub_id").agg(F.count("*").alias("n"), F.min("psi").alias("low")).collect() if r.n >= k}


def _measures(prep: Prepared) -> list[Column]:
    """What one round tells: rows, matches, the span of the nodes that are left, the rows their edges make at most, and by sub-query its matches, their best
    score and the best estimate left.
    """
    left = "CASE WHEN NOT done THEN node END"
    by = [e for s in prep.subs[:MOST_MEASURED] for e in (f"count_if(done AND sub_id = {s.sub_id}) AS d{s.sub_id}", f"max(CASE WHEN done AND sub_id = {s.sub_id} THEN psi_hat END) AS b{s.sub_id}", f"max(CASE WHEN NOT done AND sub_id = {s.sub_id} THEN psi_hat END) AS u{s.sub_id}")]
    return [F.expr(e) for e in ("count(*) AS n", "count_if(done) AS d", f"min({left}) AS low", f"max({left}) AS high", "coalesce(sum(CASE WHEN NOT done THEN degree END), 0) AS fanout", *by)]


def store_round(prep: Prepared, fresh: DataFrame, fanout: int | None) -> tuple[DataFrame, dict]:
    """(the rows of a round, its measures): stored in the shared folder, or held by the driver where `fanout`, the adjacency rows of
    the states that were expanded, proves them to be few; a round then costs one small job.
    """
    ways = 2 if prep.params.through_target else 1
    if fanout is None or fanout * ways > BROADCAST_STATES:
        return keep(fresh, "round", *_measures(prep))
    rows = fresh.toArrow()
    done, node, degree, sub, psi = (rows.column(c).to_numpy() for c in ("done", "node", "degree", "sub_id", "psi_hat"))
    done = done.astype(bool)
    left = node[~done]
    seen = {"n": rows.num_rows, "d": int(done.sum()), "low": int(left.min()) if left.size else None, "high": int(left.max()) if left.size else None, "fanout": int(degree[~done].sum())}
    for s in prep.subs[:MOST_MEASURED]:
        own, more = psi[done & (sub == s.sub_id)], psi[~done & (sub == s.sub_id)]
        seen |= {f"d{s.sub_id}": own.size, f"b{s.sub_id}": float(own.max()) if own.size else None, f"u{s.sub_id}": float(more.max()) if more.size else None}
    return fresh.sparkSession.createDataFrame(rows, fresh.schema), seen


def _observed(watch: Observation, name: str) -> int:
    """A count that was observed; none where Spark found a join's other side empty and dropped the watched rows from the plan."""
    try:
        return watch.get[name]
    except Py4JJavaError:
        return 0


def _union(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def _below(floors: dict[int, float]) -> str:
    """SQL: the row reaches the floor of its sub-query."""
    return "psi_hat >= CASE " + " ".join(f"WHEN sub_id = {s} THEN {float(t - TIE)!r}D" for s, t in floors.items()) + " ELSE 0D END"


def joint_floors(done: DataFrame, subs: list[SubQuery], k: int, best: dict[int, float]) -> dict[int, float]:
    """The score in each list below which no pivot is among the k best sums; none while fewer than k pivots stand in all lists.

    The k-th sum of what was found holds from below. `best` bounds the scores that a list has or may still get: a pivot with less than the k-th sum
    without the best of all other lists stays under that sum, whatever the others give it.
    """
    lists = done.groupBy("sub_id", "pivot_id").agg(F.max("psi_hat").alias("psi"))
    sums = lists.groupBy("pivot_id").agg(F.sum("psi").alias("score"), F.count("*").alias("parts")).filter(F.col("parts") == len(subs))
    low = sums.select("score").orderBy(F.desc("score")).limit(k).agg(F.count("*").alias("n"), F.min("score").alias("low")).first()
    return {s.sub_id: low.low - sum(b for t, b in best.items() if t != s.sub_id) for s in subs} if low.n == k else {}


def _standing(done: list[DataFrame], shut: set[int]) -> DataFrame | None:
    """(pivot_id) of pivots in all of the lists that nothing can be added to: an answer stands in each. None where they are too many to broadcast."""
    rows = _union(done).filter(F.col("sub_id").isin(sorted(shut))).select("sub_id", "pivot_id").distinct()
    named, seen = keep(rows.groupBy("pivot_id").agg(F.count("*").alias("n")).filter(F.col("n") == len(shut)).select("pivot_id"), "pivots", F.count("*").alias("n"))
    return named if seen["n"] <= BROADCAST_STATES else None


def layered(prep: Prepared, stats: Stats | None = None, k_list: int | None = None, joint: int | None = None) -> Found:
    """All matches, one join a hop. Eager mode stores each hop and stops when no state is left; `topk_prune` cuts at the k_list-th score.

    `joint`: the lists are to be added up, and only the k best sums of pivots that stand in all of them are asked for. What cannot be part of these
    is left out of the lists and not expanded; all that these pivots have is found.
    """
    p = prep.params
    if not (p.eager or p.topk_prune or stats is not None):
        states, done = prep.start, []
        for _ in range(prep.hops):
            fresh = expand(prep, states)
            done.append(fresh.filter("done"))
            states = fresh.filter("NOT done")
        return _found(done, {})
    states, size, span, fanout, done = prep.start, MOST_NAMED if prep.start_span else None, prep.start_span, prep.start_fanout, []
    theta: dict[int, float] = {}
    joint = joint if p.eager and not p.topk_prune and 1 < len(prep.subs) <= MOST_MEASURED else None
    shut, within = set(), None
    top, held = dict.fromkeys([s.sub_id for s in prep.subs], 0.0), dict.fromkeys([s.sub_id for s in prep.subs], 0)
    h = 0
    while h < prep.hops:
        began = time.monotonic()
        weighed = Observation() if stats is not None else None
        h += 1
        if h == prep.hops and h > 1:
            return _last_hop(prep, states, done, theta, span, weighed, stats, k_list, within, shut)
        fresh = expand(prep, states, theta, size, span, weighed, fanout)
        fresh, seen = store_round(prep, fresh, fanout)
        done.append(fresh.filter("done"))
        states, size, fanout = fresh.filter("NOT done"), seen["n"] - seen["d"], seen["fanout"]
        span = (seen["low"], seen["high"]) if size else None
        if stats is not None:
            edges = _observed(weighed, "edges")
            stats.edges_weighted += edges
            stats.rounds.append({"round": h, "edges": edges, "produced": seen["n"], "matched": seen["d"], "left": size, "ms": (time.monotonic() - began) * 1000})
        if not size:
            break
        if joint:
            for s in top:
                top[s], held[s] = max(top[s], seen[f"b{s}"] or 0.0), held[s] + seen[f"d{s}"]
            if min(held.values()) >= joint:
                theta = joint_floors(_union(done), prep.subs, joint, {s: max(b, seen[f"u{s}"] or 0.0) for s, b in top.items()}) or theta
                done = [d.filter(_below(theta)) for d in done] if theta else done
        if p.topk_prune:
            theta = kth_scores(_union(done), prep.subs, k_list or p.k)
        closed = {s for s in top if joint and (seen[f"u{s}"] is None or seen[f"u{s}"] < theta.get(s, 0.0) - TIE)}
        if len(closed) == len(prep.subs):
            break  # no estimate reaches its floor
        if closed - shut:
            shut |= closed
            within = _standing(done, shut)
            if within is not None:
                done = [d.join(F.broadcast(within), "pivot_id", "left_semi") for d in done]
                states = states.join(F.broadcast(within.withColumn("stands", F.lit(True))), "pivot_id", "left").filter("pivot_id IS NULL OR stands").select(*prep.start.columns)
        if theta or within is not None:  # states that were stored before the k best were known
            states = states.filter(_below(theta)) if theta else states
            left = states.selectExpr("count(*) AS n", "min(node) AS low", "max(node) AS high", "coalesce(sum(degree), 0) AS fanout").first()
            size, span, fanout = left.n, (left.low, left.high), left.fanout
            if not size:
                break
    return _found(done, {s: t - TIE for s, t in theta.items()})


def _last_hop(prep: Prepared, states: DataFrame, done: list[DataFrame], theta: dict[int, float], span: tuple[int, int] | None, weighed: Observation | None, stats: Stats | None, k_list: int | None, within: DataFrame | None = None, shut: set[int] = frozenset()) -> Found:
    """The lists, with the hop after which nothing is left to expand.

    Its rows are the most by far and all are matches. So the states are reduced first, and its rows are summed up to the best score of a pivot where
    they arise: neither they nor their paths are stored. Paths are found again if they are asked for. `within`: pivots asked for, if not all; the lists in
    `shut` get no more.
    """
    p, began = prep.params, time.monotonic()
    if p.revisit == "simple_path" and not p.through_target:
        states, seen = keep(undominated(prep, states), "states", *[F.expr(e) for e in ("count(*) AS n", "min(node) AS low", "max(node) AS high")])
        size, span = seen["n"], (seen["low"], seen["high"]) if seen["n"] else None
    else:
        size = None
    ends = within if within is not None and all(s.pivot_pos == s.stages for s in prep.subs if s.sub_id not in shut) else None
    rows, told = expand(prep, states, theta, size, span, weighed, within=ends).filter("done"), Observation()
    watched = rows.observe(told, F.count("*").alias("n")) if stats is not None else rows
    best = lambda df: df.groupBy("sub_id", "pivot_id").agg(F.max("psi_hat").alias("psi_hat"))
    last, _ = keep(best(watched), "scores")
    found = _union([*[d.select("sub_id", "pivot_id", "psi_hat") for d in done], last])
    if stats is not None:
        edges, n = _observed(weighed, "edges"), _observed(told, "n")
        stats.edges_weighted += edges
        stats.rounds.append({"round": prep.hops, "edges": edges, "produced": n, "matched": n, "left": 0, "ms": (time.monotonic() - began) * 1000})
    if p.topk_prune:
        theta = kth_scores(found, prep.subs, k_list or p.k)
    matches = best_matches(_union([*done, expand(prep, states, theta, size, span, within=ends).filter("done")]))
    return Found(matches, {s: t - TIE for s, t in theta.items()}, best(found).withColumnRenamed("psi_hat", "psi"))


def _found(done: list[DataFrame], missing: dict[int, float]) -> Found:
    rows = _union(done)
    return Found(best_matches(rows), missing, rows.groupBy("sub_id", "pivot_id").agg(F.max("psi_hat").alias("psi")))


class Queue:
    """States to expand, best first, as stored segments of which only what lies under an upper estimate is left.

    A pop takes all states whose estimate reaches that of the batch-th best, so ties go together and nothing is written anew; many
    segments are written into one.
    """

    def __init__(self, prep: Prepared, batch: int) -> None:
        self.batch = batch
        self.subs = [s.sub_id for s in prep.subs]
        self.segments: list[list] = [[prep.start, {}]]

    def _left(self) -> DataFrame:
        return _union([df.filter("NOT done" + "".join(f" AND (sub_id != {s} OR psi_hat < {u!r}D)" for s, u in upper.items())) for df, upper in self.segments])

    def pop(self, floors: dict[int, float]) -> tuple[DataFrame | None, int, dict[int, float], tuple | None, int | None]:
        """(the best states, how many, for each sub-query the estimate that all its others stay under, the span of their nodes, rows of their edges).
        States that cannot reach the k-th score of their sub-query stay, for a longer list, but are not taken.
        """
        if not self.segments:
            return None, 0, {}, None, None
        left = self._left()
        for s, t in floors.items():
            left = left.filter(f"sub_id != {s} OR psi_hat >= {float(t - TIE)!r}D")
        best = left.select("psi_hat").orderBy(F.desc("psi_hat")).limit(self.batch).agg(F.min("psi_hat").alias("low")).first().low
        if best is None:
            return None, 0, {}, None, None
        taken = left.filter(F.col("psi_hat") >= best)
        seen = taken.selectExpr("count(*) AS n", "min(node) AS low", "max(node) AS high", "sum(degree) AS fanout").first()
        return taken, seen.n, {s: max(best, floors[s] - TIE) if s in floors else best for s in self.subs}, (seen.low, seen.high), seen.fanout

    def push(self, popped: dict[int, float], fresh: DataFrame, some: bool) -> None:
        """What a round made; the states it took are gone."""
        self.segments = [[df, {s: min(u, upper.get(s, u)) for s, u in popped.items()}] for df, upper in self.segments]
        if some:
            self.segments.append([fresh, {}])
        if len(self.segments) > 12:
            self.segments = [[keep(self._left(), "queue")[0], {}]]


def best_first(prep: Prepared, stats: Stats | None = None, k_list: int | None = None, on_round: Callable | None = None, state: dict | None = None, guard: Callable | None = None) -> Found:
    """Rounds that expand the best `batch` states; exact when no estimate left reaches the k-th score of its sub-query.

    `on_round(matches by sub-query)` may stop the search after a round, and `guard` makes a context that may cancel one; `state` takes what
    a later call goes on from.
    `on_discovery` marks nodes when they are first reached, whatever their score, and so may lose the best match.
    """
    p = prep.params
    k = k_list or p.k
    if p.revisit == "on_discovery":
        return _literal(prep, stats, k)
    state = state if state is not None else {}
    queue: Queue = state.setdefault("queue", Queue(prep, p.batch))
    done: list[DataFrame] = state.setdefault("done", [])
    early: dict[int, int] = state.setdefault("early", {s.sub_id: 0 for s in prep.subs})
    state["completed"] = False
    theta: dict[int, float] = kth_scores(_union(done), prep.subs, k) if done and on_round is None else {}
    single = len(prep.subs) == 1  # with several lists, a longer one may be asked for later: nothing above tau is dropped
    while True:
        began = time.monotonic()
        seen = None
        with guard() if guard is not None else contextlib.nullcontext():
            taken, n, low, span, fanout = queue.pop(theta)
            if taken is None:
                state["completed"] = True
                break
            fresh, seen = store_round(prep, expand(prep, taken, theta if single else None, n, span), fanout)
        if seen is None:  # cancelled: its states are still in the queue
            break
        queue.push(low, fresh, seen["n"] > seen["d"])
        if seen["d"]:
            done.append(fresh.filter("done"))
            for s in prep.subs[:MOST_MEASURED]:
                early[s.sub_id] += seen[f"d{s.sub_id}"]
            if len(done) > 12:
                done[:] = [keep(_union(done), "done")[0]]
            if on_round is None:
                theta = kth_scores(_union(done), prep.subs, k)
        if stats is not None:
            stats.rounds.append({"round": len(stats.rounds) + 1, "popped": n, "produced": seen["n"], "matched": sum(early.values()), "left": seen["n"] - seen["d"], "ms": (time.monotonic() - began) * 1000})
        if on_round is not None and on_round(early):
            break
    return _found(done or [prep.start.limit(0)], {s: t - TIE for s, t in theta.items()})


def _literal(prep: Prepared, stats: Stats | None, k: int) -> Found:
    """Best first where a node counts as seen once it is discovered: what it costs is decided before its score is looked at."""
    p = prep.params
    looser = replace(prep, params=p.but(tau=0.0, revisit="simple_path"))
    columns = prep.start.columns
    queue, done, visited = cut(prep.start), cut(prep.start.limit(0)), cut(prep.start.select("sub_id", "source_id", "node"))
    theta: dict[int, float] = {}
    while True:
        began = time.monotonic()
        rest = queue
        for s, t in theta.items():
            rest = rest.filter((F.col("sub_id") != s) | (F.col("psi_hat") > t + EPS))
        taken = cut(rest.orderBy(F.desc("psi_hat"), F.size("path_nodes"), "path_nodes").limit(p.batch))
        n = taken.count()
        if not n:
            break
        fresh = expand(looser, taken, None, n).join(visited, ["sub_id", "source_id", "node"], "left_anti")
        first = F.max_by(F.struct(*columns), F.struct("psi_hat", F.transform("path_nodes", lambda v: -v)))
        fresh = cut(fresh.groupBy("sub_id", "source_id", "node").agg(first.alias("b")).select("b.*"))
        visited = cut(visited.unionByName(fresh.select("sub_id", "source_id", "node")))
        good = fresh.filter(F.col("psi_hat") >= p.tau - EPS)
        done = cut(done.unionByName(good.filter("done")))
        keys = ["sub_id", "path_nodes", "path_preds", "stage"]
        queue = cut(queue.join(taken.select(keys), keys, "left_anti").select(columns).unionByName(good.filter("NOT done")))
        theta = kth_scores(done, prep.subs, k)
        if stats is not None:
            stats.rounds.append({"round": len(stats.rounds) + 1, "popped": n, "produced": fresh.count(), "matched": done.count(), "left": queue.count(), "ms": (time.monotonic() - began) * 1000})
    return _found([done], {})


def local_heap(prep: Prepared, stats: Stats | None = None, k_list: int | None = None) -> Found:
    """A heap search in one task for each sub-query over the edges that any state can use; these are counted first.

    Where they are more than a task should hold, the layered engine searches them, with the same lists and nothing missing from them.
    """
    p = prep.params
    if p.revisit != "simple_path" or p.hop_scope != "match" or p.through_target:
        raise ValueError("the local engine takes simple paths, a limit on the whole match, and ends at targets")
    hood = reachable(prep, MOST_LOCAL_EDGES)
    own, seen = keep(hood, "hood", F.count("*").alias("n")) if hood is not None else (None, {"n": 0})
    if own is None or seen["n"] > MOST_LOCAL_EDGES:
        return layered(prep, stats, k_list)
    first = prep.start.select(F.col("sub_id").alias("sub"), "source_id")
    subs = {s.sub_id: s for s in prep.subs}
    k = k_list or p.k

    def run(key, a, b):
        import pandas as pd

        sub = subs[int(key[0])]
        root, last = p.root(sub), sub.stages - 1
        around: dict[tuple, list] = {}
        best_at: dict[tuple, float] = {}
        ends = set()
        for stage, node, nbr, pred, w, end in zip(a.stage, a.node, a.nbr, a.predicate, a.w, a.at_end):
            around.setdefault((stage, node), []).append((nbr, pred, w))
            best_at[stage, node] = max(best_at.get((stage, node), 0.0), w)
            if end:
                ends.add((stage, nbr))
        best: dict[int, tuple] = {}
        pops, kth = 0, None
        heap = [(-1.0, (int(s),), (), 1.0, 0, None) for s in b.source_id]
        heapq.heapify(heap)
        low = 0.0
        while heap:
            estimate, path, preds, w, stage, pivot = heapq.heappop(heap)
            pops += 1
            if len(best) >= k and pops % 64 == 0:  # a bound that is late only delays the stop
                kth = heapq.nlargest(k, (x[0] for x in best.values()))[-1]
            if kth is not None and -estimate < kth - TIE:
                low = -estimate
                break
            for nbr, pred, x in around.get((stage, path[-1]), ()):
                if nbr in path:
                    continue
                prod, n = w * x, len(path)
                to, at = stage, pivot
                if (stage, nbr) in ends:
                    at = nbr if stage + 1 == sub.pivot_pos else pivot
                    if stage == last:
                        score = prod ** (1 / n)
                        if score >= p.tau - EPS and score > best.get(at, (0.0,))[0]:
                            best[at] = (score, n, path[0], nbr, [*path, nbr], [*preds, pred])
                        continue
                    to = stage + 1
                if n < root:
                    score = (prod * best_at.get((to, nbr), 0.0)) ** (1 / root)
                    if score >= p.tau - EPS:
                        heapq.heappush(heap, (-score, (*path, nbr), (*preds, pred), prod, to, at))
        rows = [(sub.sub_id, e, s, n, src, end, nodes, preds, low) for e, (s, n, src, end, nodes, preds) in best.items()]
        return pd.DataFrame(rows, columns=["sub_id", "pivot_id", "psi", "n", "source_id", "end_id", "path_nodes", "path_preds", "low"])

    schema = "sub_id int, pivot_id long, psi double, n int, source_id long, end_id long, path_nodes array<long>, path_preds array<string>, low double"
    out, _ = keep(own.groupBy("sub_id").cogroup(first.groupBy("sub")).applyInPandas(run, schema), "lists")
    missing = {}
    if len(prep.subs) > 1:
        missing = {r.sub_id: r.low for r in out.groupBy("sub_id").agg(F.max("low").alias("low")).collect() if r.low > 0}
    return Found(out.drop("low"), missing)


def reachable(prep: Prepared, most: int | None = None) -> DataFrame | None:
    """(sub_id, stage, node, nbr, predicate, w, at_end): edges that a state within the hop limit and the product bound can touch, by best products of
    (stage, node), hop after hop. None where one hop alone has over `most` of them.
    """
    p = prep.params
    floor, last, root = by_sub(prep, lambda s: p.tau ** p.root(s) - EPS if p.tau > 0 else 0.0), by_sub(prep, lambda s: s.stages - 1), by_sub(prep, lambda s: p.root(s))
    front, size, span = prep.start, MOST_NAMED if prep.start_span else None, prep.start_span
    touched = []
    for h in range(1, prep.hops + 1):
        x = step(prep, front.select("sub_id", "node", "degree", "stage", "w_prod", "done"), size, span).filter(f"w_prod * w >= {floor} AND {h} <= {root}")
        x, at_end = _with_ends(prep, x)
        x, seen = keep(x.selectExpr("sub_id", "stage", "node", "nbr", "nbr_degree", "predicate", "w", "w_prod * w AS w_prod", f"{at_end} AS at_end"), "reach", *[F.expr(e) for e in ("count(*) AS n", "min(nbr) AS low", "max(nbr) AS high")])
        touched.append(x.select("sub_id", "stage", "node", "nbr", "predicate", "w", "at_end"))
        if most is not None and seen["n"] > most:
            return None
        if not seen["n"]:
            break
        front = x.selectExpr("sub_id", "nbr AS node", "nbr_degree AS degree", f"stage + CAST(at_end AND stage < {last} AS INT) AS stage", f"at_end AND stage = {last} AS done", "w_prod").groupBy("sub_id", "node", "degree", "stage", "done").agg(F.max("w_prod").alias("w_prod"))
        size, span = seen["n"], (seen["low"], seen["high"])
    return _union(touched).distinct()


ENGINES = {"layered": layered, "best_first": best_first, "local": local_heap}


def search(kg: KG, subs: list[SubQuery], space: dict[str, list[float]], params: Params, engine: str = "layered", library: DataFrame | None = None, stats: Stats | None = None) -> DataFrame:
    """Matches of all sub-queries, in one frontier keyed by sub_id: the best path of each pivot, with psi >= tau.

    With `topk_prune` and in the engines best_first and local, a list holds the k best of its sub-query and their ties at least.
    """
    return ENGINES[engine](prepare(kg, subs, space, params, library), stats).matches


def search_scores(kg: KG, subs: list[SubQuery], space: dict[str, list[float]], params: Params, engine: str = "layered", library: DataFrame | None = None, stats: Stats | None = None) -> DataFrame:
    """(sub_id, pivot_id, psi): the lists of `search` without their paths, which cost far more than the scores."""
    found = ENGINES[engine](prepare(kg, subs, space, params, library), stats)
    return found.scores if found.scores is not None else found.matches.select("sub_id", "pivot_id", "psi")


def semantic_graph(kg: KG, subs: list[SubQuery], space: dict[str, list[float]], params: Params, mode: str = "partial", library: DataFrame | None = None) -> DataFrame:
    """(sub_id, stage, node, nbr, predicate, w and the index columns of nbr): all edges within the hop limit (`complete`), or those that the search touches
    (`partial`).
    """
    prep = prepare(kg, subs, space, params.but(static_cut=mode != "complete", eager=False), library)
    columns = ["sub_id", "stage", "node", "slot", "nbr", "profile", "degree", "predicate", "w"]
    weighed = prep.adj.join(F.broadcast(prep.weights), "predicate").select(*columns)
    if mode == "complete":
        front, size = prep.start.select("sub_id", "node").distinct(), None
        seen = front
        edges = weighed.select("sub_id", "node", "nbr")
        for _ in range(prep.hops - 1):
            front = edges.join(F.broadcast(front) if size is not None and size <= BROADCAST_STATES else front, ["sub_id", "node"]).select("sub_id", F.col("nbr").alias("node")).distinct()
            front, told = keep(front.join(seen, ["sub_id", "node"], "left_anti"), "reach", F.count("*").alias("n"))
            seen, size = seen.unionByName(front), told["n"]
            if not size:
                break
        return weighed.join(seen, ["sub_id", "node"], "left_semi").select(*columns)
    states, size, span, fanout, touched = prep.start, MOST_NAMED if prep.start_span else None, prep.start_span, prep.start_fanout, []
    for _ in range(prep.hops):
        own = states.select("sub_id", "stage", "node").distinct()
        touched.append(weighed.join(F.broadcast(own) if size is not None and size <= BROADCAST_STATES else own, ["sub_id", "stage", "node"]).select(*columns))
        fresh, seen = store_round(prep, expand(prep, states, None, size, span), fanout)
        states, size, fanout = fresh.filter("NOT done"), seen["n"] - seen["d"], seen["fanout"]
        span = (seen["low"], seen["high"])
        if not size:
            break
    return _union(touched).distinct()


def enumerate_edge_matches(kg: KG, sub: SubQuery, params: Params, library: DataFrame | None = None) -> DataFrame:
    """(source_id, end_id, n, path_nodes, path_preds): every simple path within the hop limit, without weights: the straightforward way."""
    adj = adjacency(kg.edges)
    ends = match_nodes(kg, library, sub.path[-1], params.relations).select(F.col("node_id").alias("nbr"), F.lit(True).alias("target"))
    x = match_nodes(kg, library, sub.path[0], params.relations).select(F.col("node_id").alias("source_id"), F.col("node_id").alias("node"), F.array("node_id").alias("path_nodes"), F.array().cast("array<string>").alias("path_preds"))
    out = None
    for n in range(1, params.max_hops + 1):
        x = x.join(adj.select("node", "nbr", "predicate"), "node").filter(~F.array_contains("path_nodes", F.col("nbr"))).join(ends, "nbr", "left")
        x = x.select("source_id", F.col("nbr").alias("node"), F.concat("path_nodes", F.array("nbr")).alias("path_nodes"), F.concat("path_preds", F.array("predicate")).alias("path_preds"), "target")
        own = x.filter("target").select("source_id", F.col("node").alias("end_id"), F.lit(n).alias("n"), "path_nodes", "path_preds")
        out = own if out is None else out.unionByName(own)
        x = x.filter("target IS NULL").drop("target")
    return out
