"""Assembly of sub-query matches at the pivot: threshold algorithm on ranked lists, or a full join."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources.tables import keep

EPS = 1e-9
#: List entries that the driver reads; deeper lists are bounded as tables.
MOST_READ = 500_000
MOST_DEPTH = 2**31 - 1
#: Pivots that go into a plan as literals.
MOST_LITERALS = 2_000


@dataclass(frozen=True)
class Bounds:
    """State of a threshold assembly at one access depth."""

    depth: int
    table: DataFrame  # pivot_id, seen, lower, upper
    kth_lower: float
    best_other: float
    accesses: int
    exhausted: bool

    @property
    def can_stop(self) -> bool:
        return self.exhausted or self.kth_lower >= self.best_other - EPS


def full_join(matches: DataFrame, n_subs: int, k: int | None = None, mode: str = "complete") -> DataFrame:
    """(pivot_id, score, parts): all pivots by sum of psi; complete mode wants every sub-query."""
    out = matches.groupBy("pivot_id").agg(F.round(F.sum("psi"), 9).alias("score"), F.count("*").alias("parts"))
    if mode == "complete":
        out = out.filter(F.col("parts") == n_subs)
    return out.orderBy(F.desc("score"), "pivot_id").limit(k) if k else out


def list_heads(matches: DataFrame, subs: list[int], depth: int) -> DataFrame:
    """The first `depth` entries of each list, by psi: a top-k each, never a sort of a whole list in one task."""
    out = None
    for s in subs:
        own = matches.filter(F.col("sub_id") == s).select("sub_id", "pivot_id", "psi").orderBy(F.desc("psi"), "pivot_id").limit(depth)
        out = own if out is None else out.unionByName(own)
    return out


def bounds(matches: DataFrame, subs: list[int], depth: int, k: int, mode: str = "complete", truncated: dict[int, float] | None = None) -> Bounds:
    """Lower and upper bounds of every pivot seen down to `depth`.

    A list that was not read to its end stands, for pivots unseen in it, for its last score read; one that was, for 0, or for the score
    where the search was cut off (`truncated`). Pivots unseen in every list are bounded by the sum of these.
    """
    heads, _ = keep(list_heads(matches, subs, depth) if depth < MOST_DEPTH else matches.select("sub_id", "pivot_id", "psi"), "heads")
    ends = {r.sub_id: (r.n, r.low) for r in heads.groupBy("sub_id").agg(F.count("*").alias("n"), F.min("psi").alias("low")).collect()}
    current = {}
    for s in subs:
        n, low = ends.get(s, (0, 0.0))
        current[s] = low if n >= depth else (truncated or {}).get(s, 0.0)
    exhausted = all(ends.get(s, (0, 0))[0] < depth for s in subs) and not truncated
    wide = heads.groupBy("pivot_id").agg(F.count("*").alias("seen"), F.sum("psi").alias("lower"), *[F.max(F.when(F.col("sub_id") == s, F.col("psi"))).alias(f"s{s}") for s in subs])
    table = wide.select("pivot_id", "seen", "lower", sum((F.coalesce(F.col(f"s{s}"), F.lit(current[s])) for s in subs), F.lit(0.0)).alias("upper"))
    eligible = table.filter(F.col("seen") == len(subs)) if mode == "complete" else table
    top = eligible.orderBy(F.desc("lower"), "pivot_id").limit(k)
    chosen = top.collect()
    kth = chosen[-1].lower if len(chosen) == k else 0.0
    picked = matches.sparkSession.createDataFrame([(r.pivot_id,) for r in chosen], "pivot_id long")
    others = table.join(F.broadcast(picked), "pivot_id", "left_anti")  # k rows
    seen_other = others.agg(F.max("upper").alias("u")).first().u or 0.0
    unseen = sum(current.values())
    accesses = sum(n for n, _ in ends.values())
    best_other = max(seen_other, unseen)
    if len(chosen) < k and not exhausted:
        best_other = max(best_other, kth + 1)
    return Bounds(depth, table, kth, best_other, accesses, exhausted)


def ranked_lists(matches: DataFrame, subs: list[int]) -> dict[int, list[tuple[int, float, int]]]:
    """(sub_id, psi, pivot_id) of each list by rank, from one read: for lists of at most `MOST_READ` entries."""
    import numpy as np

    rows = matches.select("sub_id", "psi", "pivot_id").toArrow()
    sub, psi, pivot = (rows.column(c).to_numpy() for c in ("sub_id", "psi", "pivot_id"))
    order = np.lexsort((pivot, -psi, sub))
    sub, psi, pivot = sub[order], psi[order], pivot[order]
    cut = lambda s: slice(*np.searchsorted(sub, [s, s + 1]))
    return {s: list(zip(sub[cut(s)].tolist(), psi[cut(s)].tolist(), pivot[cut(s)].tolist())) for s in subs}


def read_lists(matches: DataFrame, subs: list[int], k: int, mode: str, depth: int, truncated: dict[int, float], stats=None, size: int | None = None) -> tuple[list[int] | None, float]:
    """Sorted access from the driver: (pivots that may be among the k best, score of the k-th), or None where the lists do not prove them.

    Each round reads on from where the last one ended in every list, twice as deep, and closes the bounds: a pivot that a list has not
    shown yet has there the last score read at most; a list that is read to its end holds no other, or, where the search was cut off,
    none above `truncated`. In complete mode a pivot that a whole list lacks is no answer. Lists whose `size` is known to be small are fetched at once.
    """
    held = ranked_lists(matches, subs) if size is not None and size <= MOST_READ else None
    at: dict[int, tuple[float, int] | None] = {s: None for s in subs}
    ended = dict.fromkeys(subs, False)
    seen: dict[int, dict[int, float]] = {}
    read = 0
    while True:
        batch = None
        for s in (s for s in subs if not ended[s] and held is None):
            own = matches.filter(F.col("sub_id") == s)
            if at[s] is not None:
                psi, pivot = at[s]
                own = own.filter((F.col("psi") < psi) | ((F.col("psi") == psi) & (F.col("pivot_id") > pivot)))
            own = own.select("sub_id", "pivot_id", "psi").orderBy(F.desc("psi"), "pivot_id").limit(depth - read)
            batch = own if batch is None else batch.unionByName(own)
        if held is not None:
            rows = [r for s in subs for r in held[s][read:depth]]
        else:
            rows = sorted(((r.sub_id, r.psi, r.pivot_id) for r in batch.collect()), key=lambda r: (r[0], -r[1], r[2])) if batch is not None else []
        fresh = dict.fromkeys(subs, 0)
        for s, psi, pivot in rows:
            seen.setdefault(pivot, {})[s] = psi
            at[s] = (psi, pivot)
            fresh[s] += 1
        for s in subs:
            ended[s] = ended[s] or fresh[s] < depth - read
        if stats is not None:
            stats.accesses += len(rows)
        most = {s: truncated.get(s, 0.0) if ended[s] else at[s][0] for s in subs}
        closed = [s for s in subs if ended[s] and s not in truncated]
        lost = lambda own: mode == "complete" and any(s not in own for s in closed)
        lower = {p: sum(own.values()) for p, own in seen.items() if mode != "complete" or len(own) == len(subs)}
        chosen = sorted(lower, key=lambda p: (-lower[p], p))[:k]
        kth = lower[chosen[-1]] if len(chosen) == k else 0.0
        upper = {p: 0.0 if lost(own) else sum(own.get(s, most[s]) for s in subs) for p, own in seen.items()}
        top = set(chosen)
        other = max((u for p, u in upper.items() if p not in top), default=0.0)
        unseen = 0.0 if mode == "complete" and closed else sum(most.values())
        if len(closed) == len(subs) or max(other, unseen) <= (kth + EPS if len(chosen) == k else 0.0):
            return [p for p, u in upper.items() if u >= kth - EPS and u > 0], kth
        if all(ended.values()):
            return None, kth
        read, depth = depth, depth * 2
        if depth * len(subs) > MOST_READ:
            return None, -1.0


def assemble(
    matches: DataFrame, subs: list[int], k: int, mode: str = "complete", strategy: str = "threshold", step: int | None = None, stats=None, truncated: dict[int, float] | None = None, stored: bool = False, size: int | None = None,
) -> DataFrame | None:
    """(rank, pivot_id, score): the k best pivots by sum of psi, ties by id.

    `truncated` bounds what cut-off lists lack; None is returned where the lists do not prove the answers, so that the search must go on.
    """
    from pyspark.sql import Window

    truncated = truncated or {}
    if len(subs) == 1 or (strategy == "full" and not truncated):
        out = full_join(matches, len(subs), k, mode)
    else:
        if not stored:
            matches, _ = keep(matches, "lists")
        near, kth = read_lists(matches, subs, k, mode, step or 2 * k, truncated, stats, size)
        if near is None and kth < 0:  # deeper than a driver should hold: bounds as tables
            b = bounds(matches, subs, MOST_DEPTH, k, mode, truncated)
            if truncated and not b.can_stop:
                return None
            out = full_join(matches, len(subs), k, mode)
        elif near is None:
            return None
        else:  # candidates that may still tie with the k-th keep their place by id: exact scores by random access
            if stats is not None:
                stats.random_accesses += len(near) * len(subs)
            if len(near) <= MOST_LITERALS:
                chosen = matches.filter(F.col("pivot_id").isin(near))
            else:
                chosen = matches.join(F.broadcast(matches.sparkSession.createDataFrame([(p,) for p in near], "pivot_id long")), "pivot_id", "left_semi")
            out = full_join(chosen, len(subs), k, mode)
    return out.select("pivot_id", "score").withColumn("rank", F.row_number().over(Window.orderBy(F.desc("score"), "pivot_id"))).select("rank", "pivot_id", "score")
