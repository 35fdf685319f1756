"""Accuracy and cost measures as DataFrames."""

from __future__ import annotations

import time
from collections.abc import Callable
from typing import Any

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def precision_recall(answers: DataFrame, truth: DataFrame, k: int | None = None) -> DataFrame:
    """(query_id, returned, correct, total, precision, recall, f1) for answers(query_id, rank, node_id) and truth(query_id, node_id).

    F1 is that of the query; averages over queries are taken afterwards.
    """
    top = answers.filter(F.col("rank") <= k) if k else answers
    right = truth.select("query_id", "node_id", F.lit(1).alias("right"))
    hits = top.join(right, ["query_id", "node_id"], "left").groupBy("query_id").agg(F.count("*").alias("returned"), F.sum(F.coalesce("right", F.lit(0))).alias("correct"))
    all_right = truth.groupBy("query_id").agg(F.count("*").alias("total"))
    both = all_right.join(hits, "query_id", "full_outer").select("query_id", *[F.coalesce(c, F.lit(0)).alias(c) for c in ("returned", "correct", "total")])
    share = lambda a, b: F.when(F.col(b) > 0, F.col(a) / F.col(b)).otherwise(0.0)
    out = both.withColumns({"precision": share("correct", "returned"), "recall": share("correct", "total")})
    return out.withColumn("f1", F.when((F.col("precision") > 0) & (F.col("recall") > 0), 2 / (1 / F.col("precision") + 1 / F.col("recall"))).otherwise(0.0))


def mean_over_queries(per_query: DataFrame) -> DataFrame:
    return per_query.agg(*[F.avg(c).alias(c) for c in ("precision", "recall", "f1")])


def jaccard(a: DataFrame, b: DataFrame, key: str = "pivot_id") -> DataFrame:
    """(shared, either, jaccard) of two answer sets; 1 if both are empty."""
    x = a.select(key).distinct().withColumn("a", F.lit(1))
    y = b.select(key).distinct().withColumn("b", F.lit(1))
    both = x.join(y, key, "full_outer").agg(F.sum(F.when(F.col("a").isNotNull() & F.col("b").isNotNull(), 1).otherwise(0)).alias("shared"), F.count("*").alias("either"))
    return both.select(F.coalesce("shared", F.lit(0)).alias("shared"), "either", F.when(F.col("either") > 0, F.col("shared") / F.col("either")).otherwise(1.0).alias("jaccard"))


def pcc(pair_votes: DataFrame) -> DataFrame:
    """(query_id, pairs, pcc, class): Pearson correlation of rank differences and vote differences.

    pair_votes(query_id, pair_id, rank_a, rank_b, votes_a, votes_b). strong from .5, medium from .3, small from .1.
    """
    x, y = (F.col("rank_b") - F.col("rank_a")).cast("double"), (F.col("votes_a") - F.col("votes_b")).cast("double")
    d = pair_votes.select("query_id", x.alias("x"), y.alias("y"))
    m = d.groupBy("query_id").agg(F.count("*").alias("pairs"), F.avg("x").alias("mx"), F.avg("y").alias("my"), F.avg(F.col("x") * F.col("y")).alias("mxy"), F.avg(F.col("x") ** 2).alias("mxx"), F.avg(F.col("y") ** 2).alias("myy"))
    spread = F.sqrt(F.col("mxx") - F.col("mx") ** 2) * F.sqrt(F.col("myy") - F.col("my") ** 2)
    r = F.when(spread > 0, (F.col("mxy") - F.col("mx") * F.col("my")) / spread)
    return m.select("query_id", "pairs", r.alias("pcc")).withColumn("class", correlation_class("pcc"))


def correlation_class(c: str):
    return F.when(F.col(c) >= 0.5, "strong").when(F.col(c) >= 0.3, "medium").when(F.col(c) >= 0.1, "small").otherwise("none")


def pruning(touched: DataFrame, kg) -> DataFrame:
    """(nodes, edges, touched_nodes, touched_edges, node_pruning, edge_pruning) for touched(node, nbr, predicate) rows of either direction."""
    ids = touched.select("node").unionByName(touched.select(F.col("nbr").alias("node"))).distinct().agg(F.count("*").alias("touched_nodes"))
    pairs = touched.select(F.least("node", "nbr").alias("a"), F.greatest("node", "nbr").alias("b"), "predicate").distinct().agg(F.count("*").alias("touched_edges"))
    total = kg.nodes.agg(F.count("*").alias("nodes")).crossJoin(kg.edges.agg(F.count("*").alias("edges"))).crossJoin(ids).crossJoin(pairs)  # one row each
    return total.withColumns({"node_pruning": 1 - F.col("touched_nodes") / F.col("nodes"), "edge_pruning": 1 - F.col("touched_edges") / F.col("edges")})


def timed(fn: Callable[[], Any]) -> tuple[Any, float]:
    began = time.monotonic()
    out = fn()
    return out, (time.monotonic() - began) * 1000


def decomposition_gain(optimal: float, worst: float) -> float:
    """Share of the worst cost that the optimum saves."""
    return (worst - optimal) / worst if worst else 0.0


def embedding_bytes(rows: int, dim: int) -> int:
    return rows * dim * 8


def spread_of_times(times: DataFrame) -> DataFrame:
    """(bound, min_ms, avg_ms, max_ms, overshoot_ms) of times(bound, ms)."""
    return times.groupBy("bound").agg(F.min("ms").alias("min_ms"), F.avg("ms").alias("avg_ms"), F.max("ms").alias("max_ms"), (F.max("ms") - F.first("bound")).alias("overshoot_ms"))
