"""Queries end to end: exact search, bounded search, what they return and what they cost."""

from __future__ import annotations

import contextlib
import threading
import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import KG, Params, QueryGraph, SubQuery
from ..operators import search as S
from ..operators.assembly import assemble
from ..sources.tables import keep, local
from . import decompose as D


@dataclass
class QueryResult:
    answers: DataFrame
    matches: DataFrame
    subs: list[SubQuery]
    stats: S.Stats
    completed: bool = True
    resume: Callable[[float], QueryResult] | None = None


def plan_subs(kg: KG, gq: QueryGraph, space: dict[str, list[float]], params: Params, library: DataFrame | None = None, objective: str = "min", stats: D.GraphStats | None = None, pivot: str | None = None) -> list[SubQuery]:
    """Sub-queries of the least (or greatest) estimated cost; a single edge needs no statistics."""
    if len(gq.edges) == 1:
        return D.decompose(gq, lambda *_: 1.0, pivot)[0]
    longest = params.max_hops if params.hop_scope == "match" else D.MOST_EDGES
    stats = stats or D.collect_stats(kg)
    counts = D.source_counts(kg, gq, library, params)
    return D.decompose(gq, lambda source, preds: D.path_cost(counts[source], preds, stats, space, params), pivot, objective, longest)[0]


def exact_query(
    kg: KG, gq: QueryGraph, space: dict[str, list[float]], params: Params = Params(), library: DataFrame | None = None, engine: str = "layered", assembly: str = "complete", strategy: str = "threshold",
    construct: str = "partial", decomposition: str = "min", subs: list[SubQuery] | None = None, graph_stats: D.GraphStats | None = None, measured: bool = False, pivot: str | None = None,
) -> QueryResult:
    """The k best answers. `construct='complete'` weighs the whole neighbourhood before it searches.

    Where an engine cuts its lists off (top-k pruning, best first, local heap), the search goes on with longer lists until the bounds
    of what is missing prove the answers. The layered engine leaves what cannot be among the k best sums out of its lists, if the answers are to be complete
    (`strategy='full'` adds whole lists up). `measured` stores each component's result, so that its time is its own.
    """
    stats = S.Stats()
    began = time.monotonic()
    subs = subs or plan_subs(kg, gq, space, params, library, decomposition, graph_stats, pivot)
    stats.add("decompose", began)
    began = time.monotonic()
    if construct == "complete":
        whole = S.semantic_graph(kg, subs, space, params, "complete", library)
        adj = whole.select("node", "slot", "nbr", "profile", "degree", "predicate").distinct()
        adj, seen = keep(adj, "semantic-graph", F.count("*").alias("n"))
        stats.edges_weighted += seen["n"]
        prep = S.prepare(kg, subs, space, params.but(static_cut=False), library, adj)
    else:
        prep = S.prepare(kg, subs, space, params, library)
    stats.add("construct", began)
    ids, state = [s.sub_id for s in subs], {}
    factor = params.fetch_factor if len(subs) > 1 else 1
    joint = engine == "layered" and strategy == "threshold" and assembly == "complete" and len(subs) > 1 and not params.topk_prune
    while True:
        began = time.monotonic()
        options = {"state": state} if engine == "best_first" else {"joint": params.k} if joint else {}
        found = S.ENGINES[engine](prep, stats if measured else None, params.k * factor, **options)
        stats.searches += 1
        matches = found.matches
        lists = found.scores if found.scores is not None else matches
        if measured or len(subs) > 1:  # scores alone: the paths of whole lists are never stored
            lists, seen = keep(lists, "lists", F.count("*").alias("n"))
            stats.list_rows = seen["n"]
        stats.add("search", began)
        began = time.monotonic()
        answers = assemble(lists, ids, params.k, assembly, strategy, stats=stats, truncated=found.missing if len(subs) > 1 and not joint else None, stored=True, size=stats.list_rows or None)
        if answers is not None and measured:
            answers, _ = keep(answers, "answers")
        stats.add("assemble", began)
        if answers is not None:
            return QueryResult(answers, matches, subs, stats)
        factor *= 4


class Deadline:
    """Cancels the jobs of a block when its time is over; `over` tells whether that happened. The block's partial work is dropped."""

    def __init__(self, spark: SparkSession, ms: float) -> None:
        self.context, self.ms, self.over = spark.sparkContext, ms, False
        self.tag = f"deadline-{uuid.uuid4().hex}"

    def __enter__(self) -> Deadline:
        self.context.addJobTag(self.tag)
        self.stopped = threading.Event()

        def watch() -> None:
            wait = max(self.ms, 0.0) / 1000
            while not self.stopped.wait(wait):
                self.over, wait = True, 0.02
                self.context.cancelJobsWithTag(self.tag)

        self.thread = threading.Thread(target=watch, daemon=True)
        self.thread.start()
        return self

    def __exit__(self, kind, error, trace) -> bool:
        self.stopped.set()
        self.thread.join()
        self.context.removeJobTag(self.tag)
        return self.over and kind is not None and issubclass(kind, Exception)


class ExecutionClock:
    """Tells when to assemble: longest search time plus the matches' assembly time reach the alert share of the bound."""

    def __init__(self, bound_ms: float, alert_ratio: float = 0.8, assembly_ms_per_match: float = 0.01) -> None:
        self.bound_ms, self.alert_ratio, self.per_match = bound_ms, alert_ratio, assembly_ms_per_match
        self.began = time.monotonic()
        self.estimate_ms = 0.0

    def elapsed(self) -> float:
        return (time.monotonic() - self.began) * 1000

    def should_assemble(self, elapsed_ms: list[float], early: list[int]) -> bool:
        self.estimate_ms = max(elapsed_ms, default=0.0) + sum(early) * self.per_match
        return self.estimate_ms >= self.bound_ms * self.alert_ratio

    def tick(self, early: dict[int, int]) -> bool:
        """After a round: all sub-queries share a frontier, so their search times are one."""
        return self.should_assemble([self.elapsed()] * len(early), list(early.values()))

    def left(self, early: dict[int, int]) -> float:
        """Milliseconds until the alert, within which the next round must end."""
        return self.bound_ms * self.alert_ratio - sum(early.values()) * self.per_match - self.elapsed()

    def again(self, extra: float) -> ExecutionClock:
        return ExecutionClock(extra, self.alert_ratio, self.per_match)


class LogicalClock:
    """Stops after a number of rounds: the same outcome on every machine."""

    def __init__(self, rounds: int) -> None:
        self.rounds = rounds
        self.seen = 0

    def tick(self, early: dict[int, int]) -> bool:
        self.seen += 1
        return self.seen >= self.rounds

    def left(self, early: dict[int, int]) -> None:
        return None

    def again(self, extra: float) -> LogicalClock:
        return LogicalClock(int(extra))


def bounded_query(
    kg: KG, gq: QueryGraph, space: dict[str, list[float]], params: Params = Params(), clock: ExecutionClock | LogicalClock | None = None, time_bound_ms: float = 1000.0, alert_ratio: float = 0.8,
    assembly_ms_per_match: float = 0.01, library: DataFrame | None = None, assembly: str = "complete", subs: list[SubQuery] | None = None,
) -> QueryResult:
    """Approximate answers within a time bound: every target counts as soon as it is discovered; more time refines.

    Rounds take the `batch` best states. Under an execution clock a round that is still running at the alert is cancelled and the
    answers are those of the rounds before (the first round always ends). `result.resume(extra)` goes on from the queue that was left.
    `completed` tells that nothing was left to expand.
    """
    clock = clock or ExecutionClock(time_bound_ms, alert_ratio, assembly_ms_per_match)
    subs = subs or plan_subs(kg, gq, space, params, library)
    prep = S.prepare(kg, subs, space, params.but(topk_prune=False), library)
    return _bounded_rounds(prep, clock, S.Stats(), assembly, {})


def _bounded_rounds(prep: S.Prepared, clock, stats: S.Stats, assembly: str, state: dict) -> QueryResult:
    spark = prep.kg.edges.sparkSession

    def guard():
        wait = clock.left(state["early"])
        return Deadline(spark, wait) if wait is not None and stats.rounds else contextlib.nullcontext()

    found = S.best_first(prep, stats, prep.params.k, on_round=clock.tick, state=state, guard=guard)
    stats.early = dict(state["early"])
    answers = assemble(found.scores, [s.sub_id for s in prep.subs], prep.params.k, assembly, stats=stats)
    # what a later call goes on from; this result keeps its own
    later = {"queue": state["queue"], "done": state["done"], "early": state["early"]}
    resume = lambda extra: _bounded_rounds(prep, clock.again(extra), stats, assembly, later)
    return QueryResult(answers, found.matches, prep.subs, stats, state["completed"], resume)


def relative_bound(kg: KG, gq: QueryGraph, space: dict[str, list[float]], params: Params, ratio: float = 0.9, library: DataFrame | None = None, **options) -> tuple[QueryResult, QueryResult, float, float]:
    """(bounded result, exact result, bound in ms, its time in ms): the bound is a share of the time that the exact search takes, measured just before."""
    began = time.monotonic()
    exact = exact_query(kg, gq, space, params, library, **options)
    exact.answers, _ = keep(exact.answers, "exact")
    bound = (time.monotonic() - began) * 1000 * ratio
    began = time.monotonic()
    result = bounded_query(kg, gq, space, params, ExecutionClock(bound), library=library, **options)
    result.answers, _ = keep(result.answers, "bounded")
    return result, exact, bound, (time.monotonic() - began) * 1000


def plan_many(kg: KG, queries: dict[int, QueryGraph], space: dict[str, list[float]], params: Params, library: DataFrame | None = None, objective: str = "min") -> tuple[list[SubQuery], dict[int, int]]:
    """(sub-queries, query of each) of many queries, which one frontier can serve."""
    subs, owner = [], {}
    for query_id, gq in queries.items():
        for s in plan_subs(kg, gq, space, params, library, objective):
            owner[len(subs)] = query_id
            subs.append(replace(s, sub_id=len(subs)))
    return subs, owner


def answers_of_many(scores: DataFrame, owner: dict[int, int], k: int, mode: str = "complete", ascending: bool = False) -> DataFrame:
    """(query_id, rank, pivot_id, score): the k best pivots of each query from scores(sub_id, pivot_id, psi) of its sub-queries."""
    spark = scores.sparkSession
    parts: dict[int, int] = {}
    for q in owner.values():
        parts[q] = parts.get(q, 0) + 1
    table = local(spark, [(s, q, parts[q]) for s, q in owner.items()], "sub_id int, query_id int, of long")
    own = scores.join(F.broadcast(table), "sub_id")
    total = own.groupBy("query_id", "pivot_id", "of").agg(F.round(F.sum("psi"), 9).alias("score"), F.count("*").alias("parts"))
    if mode == "complete":
        total = total.filter("parts = of")
    order = Window.partitionBy("query_id").orderBy(F.asc("score") if ascending else F.desc("score"), "pivot_id")
    return total.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "pivot_id", "score")


def exact_many(kg: KG, queries: dict[int, QueryGraph], space: dict[str, list[float]], params: Params = Params(), library: DataFrame | None = None, decomposition: str = "min", mode: str = "complete", stats: S.Stats | None = None) -> tuple[DataFrame, S.Found]:
    """(answers(query_id, rank, pivot_id, score), lists) of many queries at once: each hop is one job for all.

    Where each query is one sub-query, its k best scores are its answers: what the bound proves to stay below them is not expanded, and the lists
    lack it. Lists that are added up are whole.
    """
    subs, owner = plan_many(kg, queries, space, params, library, decomposition)
    found = S.layered(S.prepare(kg, subs, space, params.but(topk_prune=len(owner) == len(queries)), library), stats)
    return answers_of_many(found.scores, owner, params.k, mode), found


def bounded_many(kg: KG, queries: dict[int, QueryGraph], space: dict[str, list[float]], params: Params, clock: ExecutionClock | LogicalClock, library: DataFrame | None = None) -> DataFrame:
    """(query_id, rank, pivot_id, score) of many queries within one bound."""
    subs, owner = plan_many(kg, queries, space, params, library)
    prep = S.prepare(kg, subs, space, params.but(topk_prune=False), library)
    rounds, state = [0], {}

    def guard():
        rounds[0] += 1
        wait = clock.left(state["early"])
        return Deadline(kg.edges.sparkSession, wait) if wait is not None and rounds[0] > 1 else contextlib.nullcontext()

    return answers_of_many(S.best_first(prep, None, params.k, on_round=clock.tick, state=state, guard=guard).scores, owner, params.k)


def answer_schemas(matches: DataFrame, kg: KG) -> DataFrame:
    """(sub_id, schema, matches, best_psi): type-predicate-type strings of the matched paths."""
    first = kg.nodes.select("node_id", F.get("types", F.lit(0)).alias("type"))
    steps = matches.select("sub_id", "pivot_id", "psi", "path_preds", F.posexplode("path_nodes").alias("at", "node_id")).join(first, "node_id")
    grouped = steps.groupBy("sub_id", "pivot_id").agg(F.first("psi").alias("psi"), F.first("path_preds").alias("path_preds"), F.sort_array(F.collect_list(F.struct("at", "type"))).alias("t"))
    kinds = F.transform("t", lambda x: x["type"])
    schema = F.concat(F.get(kinds, F.lit(0)), F.array_join(F.zip_with("path_preds", F.slice(kinds, 2, F.size("t")), lambda p, t: F.concat(F.lit("-"), p, F.lit("-"), t)), ""))
    return grouped.select("sub_id", "psi", schema.alias("schema")).groupBy("sub_id", "schema").agg(F.count("*").alias("matches"), F.max("psi").alias("best_psi"))


def present(result: QueryResult, kg: KG) -> DataFrame:
    """Answers with names and the path of each sub-query."""
    names = kg.nodes.select(F.col("node_id").alias("pivot_id"), "name")
    parts = result.matches.join(F.broadcast(result.answers.select("pivot_id")), "pivot_id", "left_semi")  # k rows
    grouped = parts.groupBy("pivot_id").agg(F.sort_array(F.collect_list(F.struct("sub_id", "psi", "path_nodes", "path_preds"))).alias("parts"))
    return result.answers.join(grouped, "pivot_id", "left").join(names, "pivot_id", "left").select("rank", "pivot_id", "name", "score", "parts")
