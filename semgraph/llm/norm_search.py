"""Exact top-k inner products by norm buckets with local cosine thresholds.

Vectors are grouped by length into buckets. A block of the longest gives each query a lower bound of its k-th
score, so a query skips buckets whose longest vector cannot reach it. In a bucket the bound becomes a cosine
threshold: where it is high, candidates must lie in feasible ranges of the query's largest coordinates
(coordinate pruning); where it is low, those too short to reach the bound go (length pruning). Products of what
is left are verified as whole numbers.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .vectors import CELL_ROWS, best_of, dimension, distinct_queries, matrix, read_vectors, search_cells

SEED_ROWS = 1024
MOST_BUCKETS = 4096
#: Local cosine thresholds from here on use coordinates, below it lengths.
COORDINATE_FROM = 0.6
FOCUS = 5
LONG_MAX = 2**63 - 1


def products(x: np.ndarray, q: np.ndarray) -> np.ndarray:
    """Inner products of rows of whole numbers with one such vector, exact; beyond 64 bits they stop at the ends of long."""
    if len(x) == 0:
        return np.zeros(0, np.int64)
    if float(np.abs(x).max()) * float(np.abs(q).max(initial=0)) * x.shape[1] < 2**53:
        return (x @ q).astype(np.int64)
    whole = [int(v) for v in q]
    sums = [sum(int(a) * b for a, b in zip(row, whole)) for row in x]
    return np.array([max(-LONG_MAX - 1, min(LONG_MAX, s)) for s in sums], np.int64)


def candidates(x: np.ndarray, norms: np.ndarray, unit: np.ndarray, q: np.ndarray, q_norm: float, bound: float) -> np.ndarray:
    """Rows of a bucket (norms descending) that may reach `bound` with q."""
    if q_norm == 0 or bound <= 0:
        return np.arange(len(x)) if bound <= 0 else np.zeros(0, np.int64)
    reach = int(np.searchsorted(-norms, -bound / q_norm * (1 - 1e-12), "right"))  # longer than the bound asks for
    local = bound / (q_norm * norms[0])
    if local > 1 + 1e-9 or not reach:
        return np.zeros(0, np.int64)
    if local < COORDINATE_FROM:
        return np.arange(reach)
    ok = np.ones(reach, bool)
    direction = q / q_norm
    local = min(local, 1.0)
    for f in np.argsort(-np.abs(direction))[:FOCUS]:
        c = direction[f]
        spread = np.sqrt(max(0.0, (1 - c * c) * (1 - local * local))) + 1e-9
        low, high = c * local - spread, c * local + spread
        # the feasible arc ends at the axis itself where the axis lies within the threshold's cone
        if c > local:
            high = 1.0
        if -c > local:
            low = -1.0
        ok &= (unit[:reach, f] >= low) & (unit[:reach, f] <= high)
    return np.flatnonzero(ok)


def top_products(table: DataFrame, id_col: str, vec_col: str, is_query, k: int = 10, scale: int = 1024) -> DataFrame:
    """(query_id, rank, vec_id, score long): the k greatest whole-number inner products of each query row, exact.

    Components become floor(scale * x). `is_query` is a condition on column id; a query does not meet rows of its
    own id. Vectors that are null, of another length than most, or hold null or non-finite components take
    no part, nor do null ids; zero vectors do, with score 0. Repeated ids are one query each (the least vector),
    but candidates each. Ties go to the smaller id. An empty table gives an empty result.
    """
    spark = table.sparkSession
    dim = dimension(table, vec_col)
    empty = "query_id long, rank int, vec_id long, score long"
    if not dim:
        return spark.createDataFrame([], empty)

    def measure(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            n = np.sqrt((matrix(b.column(1), dim) ** 2).sum(1)) if b.num_rows else np.zeros(0)
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(n)], ["id", "vec", "norm"])

    vectors = read_vectors(table, id_col, vec_col, dim, scale, zeros=True).mapInArrow(measure, "id long, vec binary, norm double")
    rows = vectors.count()
    if not rows:
        return spark.createDataFrame([], empty)
    seeds = vectors.orderBy(F.desc("norm"), "id", "vec").limit(SEED_ROWS).collect()
    seed = spark.sparkContext.broadcast((np.array([r.id for r in seeds], np.int64), np.frombuffer(b"".join(r.vec for r in seeds), np.float64).reshape(-1, dim)))
    n_buckets = int(min(MOST_BUCKETS, -(-rows // CELL_ROWS)))
    cuts = vectors.agg(F.percentile_approx("norm", [i / n_buckets for i in range(1, n_buckets)] or [0.5], 10_000).alias("c")).first().c if n_buckets > 1 else []
    edges = sorted(set(cuts))
    bucket = F.lit(0)
    if edges:
        listed = F.array(*[F.lit(float(e)) for e in edges])
        bucket = F.aggregate(listed, F.lit(0), lambda acc, e: acc + (F.col("norm") > e).cast("int"))
    dealt = vectors.withColumn("cell", bucket)
    stats = dealt.groupBy("cell").agg(F.count("*").alias("n"), F.max("norm").alias("longest")).collect()  # a row for each bucket
    parts = {r.cell: -(-r.n // CELL_ROWS) for r in stats}
    longest = spark.sparkContext.broadcast([(r.cell, parts[r.cell], r.longest) for r in sorted(stats, key=lambda r: -r.cell)])
    many = F.create_map(*[F.lit(x) for c, n in parts.items() for x in (c, n)])
    cells = dealt.withColumn("part", F.pmod(F.xxhash64("id"), many[F.col("cell")].cast("long")).cast("int")).drop("norm")

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seed_ids, seed_x = seed.value
        for b in batches:
            cell, part, at, bounds = [], [], [], []
            for i, (own, q) in enumerate(zip(b.column(0).to_pylist(), matrix(b.column(1), dim) if b.num_rows else ())):
                s = products(seed_x[seed_ids != own], q)
                bound = float(np.partition(s, len(s) - k)[len(s) - k]) if len(s) >= k else float("-inf")
                norm = float(np.sqrt((q**2).sum()))
                for c, n, most in longest.value:
                    if bound <= 0 or norm * most >= bound * (1 - 1e-12):
                        for p in range(n):
                            cell.append(c)
                            part.append(p)
                            at.append(i)
                            bounds.append(bound)
            pick = pa.array(at, pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(cell, pa.int32()), pa.array(part, pa.int32()), b.column(0).take(pick), b.column(1).take(pick), pa.array(bounds, pa.float64())], ["cell", "part", "id", "vec", "bound"])

    queries = distinct_queries(vectors.select("id", "vec"), is_query)
    sent = queries.mapInArrow(send, "cell int, part int, id long, vec binary, bound double")

    def meet(ids, x, q_ids, q, bounds):
        norms = np.sqrt((x**2).sum(1))
        order = np.argsort(-norms, kind="stable")
        ids, x, norms = ids[order], x[order], norms[order]
        unit = x / np.where(norms == 0, 1, norms)[:, None]
        out = [], [], []
        for i, query in enumerate(q_ids):
            pick = candidates(x, norms, unit, q[i], float(np.sqrt((q[i] ** 2).sum())), float(bounds[i]))
            pick = pick[ids[pick] != query]
            score = products(x[pick], q[i])
            keep = score >= bounds[i]
            pick, score = pick[keep], score[keep]
            few = best_of(score, k)
            best = few[np.lexsort((ids[pick][few], -score[few]))[:k]]
            for c, v in zip(out, (np.full(len(best), query), ids[pick][best], score[best])):
                c.append(v)
        yield tuple(np.concatenate(c) for c in out)

    return search_cells(cells, sent, dim, meet, k, "long")
