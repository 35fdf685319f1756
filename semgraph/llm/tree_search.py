"""Approximate nearest neighbours: a hierarchical k-means tree walked best bin first.

The tree is fitted on a bounded sample and broadcast (its leaves are bounded too); every row is indexed.
A query walks the tree with a priority queue of nodes by inner product with their centres, which puts all leaves
in the order of their visits. How many are visited is calibrated: for some queries the true neighbours are found by
brute force, and visits widen until the wanted share of these lies in visited leaves.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .vectors import CELL_ROWS, best_of, dimension, distinct_queries, matrix, read_vectors, search_cells

#: Rows the tree is fitted on, children of a node, least number of leaves, rows a leaf is meant to hold, most leaves.
SAMPLE_ROWS = 10_000
BRANCHES = 8
LEAST_LEAVES = 64
LEAF_ROWS = 16_384
MOST_LEAVES = 4096
#: Queries that calibrate, and the recall they must reach.
CALIBRATION_QUERIES = 64
TARGET_RECALL = 0.95


def _kmeans(x: np.ndarray, k: int, rng: np.random.Generator, rounds: int = 8) -> tuple[np.ndarray, np.ndarray]:
    centres = x[rng.choice(len(x), k, replace=False)]
    for _ in range(rounds):
        near = (x @ centres.T - (centres**2).sum(1) / 2).argmax(1)
        for j in range(k):
            if (near == j).any():
                centres[j] = x[near == j].mean(0)
    return centres, (x @ centres.T - (centres**2).sum(1) / 2).argmax(1)


class Tree:
    """Nodes in arrays: centre, children of inner nodes, number of leaves."""

    def __init__(self, sample: np.ndarray, leaves: int, seed: int = 0) -> None:
        rng = np.random.default_rng(seed)
        self.centre: list[np.ndarray] = [sample.mean(0)]
        self.children: list[list[int]] = [[]]
        open_nodes = [(0, np.arange(len(sample)))]
        n_leaves = 1
        while open_nodes and n_leaves < leaves:
            open_nodes.sort(key=lambda o: len(o[1]))
            node, rows = open_nodes.pop()
            k = min(BRANCHES, leaves - n_leaves + 1, len(rows))
            if k < 2 or len(np.unique(sample[rows], axis=0)) < k:
                continue
            centres, near = _kmeans(sample[rows].copy(), k, rng)
            for j in range(k):
                if (near == j).any() or j == 0:
                    self.children[node].append(len(self.centre))
                    self.centre.append(centres[j])
                    self.children.append([])
                    open_nodes.append((len(self.centre) - 1, rows[near == j]))
            n_leaves += len(self.children[node]) - 1
        self.leaf = {n: i for i, n in enumerate(n for n, c in enumerate(self.children) if not c)}
        self.table = np.array(self.centre)

    def assign(self, x: np.ndarray) -> np.ndarray:
        """The leaf of each row: the nearest child at each level."""
        out = np.zeros(len(x), np.int32)
        todo = [(0, np.arange(len(x)))]
        while todo:
            node, rows = todo.pop()
            kids = self.children[node]
            if not kids:
                out[rows] = self.leaf[node]
            elif len(rows):
                c = self.table[kids]
                near = (x[rows] @ c.T - (c**2).sum(1) / 2).argmax(1)
                todo += [(kid, rows[near == j]) for j, kid in enumerate(kids)]
        return out

    def visits(self, query: np.ndarray, most: int | None = None) -> list[int]:
        """Leaves in the order in which the best bin comes first."""
        near = -(self.table @ query)
        queue, out = [(near[0], 0)], []
        while queue and (most is None or len(out) < most):
            _, node = heapq.heappop(queue)
            if self.children[node]:
                for kid in self.children[node]:
                    heapq.heappush(queue, (near[kid], kid))
            else:
                out.append(self.leaf[node])
        return out


def fit_tree(vectors: DataFrame, dim: int, rows: int, sample_rows: int = SAMPLE_ROWS) -> Tree:
    sample = vectors.orderBy(F.xxhash64("id"), "id", "vec").limit(sample_rows).select("vec").collect()
    leaves = int(min(MOST_LEAVES, max(LEAST_LEAVES, rows // LEAF_ROWS), max(1, rows // 4)))
    return Tree(np.frombuffer(b"".join(r.vec for r in sample), np.float64).reshape(-1, dim), leaves)


def calibrate(vectors: DataFrame, queries: DataFrame, tree, dim: int, k: int, target: float = TARGET_RECALL, n_queries: int = CALIBRATION_QUERIES) -> int:
    """Leaves to visit so that the calibration queries find `target` of their k true neighbours."""
    rows = queries.orderBy(F.xxhash64("id"), "id").limit(n_queries).collect()
    if not rows:
        return 1
    spark = vectors.sparkSession
    asked = spark.sparkContext.broadcast((np.array([r.id for r in rows], np.int64), np.frombuffer(b"".join(r.vec for r in rows), np.float64).reshape(-1, dim)))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q = asked.value
        held = [(np.zeros(0, np.int64), np.zeros(0), np.zeros(0, np.int32)) for _ in ids]
        for b in batches:
            if not b.num_rows:
                continue
            own, x = b.column(0).to_numpy(), matrix(b.column(1), dim)
            leaf, scores = tree.value.assign(x), q @ x.T
            for i, query in enumerate(ids):
                ok = own != query
                v, s, f = (np.concatenate(p) for p in zip(held[i], (own[ok], scores[i, ok], leaf[ok])))
                best = np.lexsort((v, -s))[:k]
                held[i] = v[best], s[best], f[best]
        for i, query in enumerate(ids.tolist()):
            v, s, f = held[i]
            yield pa.RecordBatch.from_arrays([pa.array([query] * len(v), pa.int64()), pa.array(v), pa.array(s), pa.array(f)], ["query", "vec_id", "score", "leaf"])

    best = Window.partitionBy("query").orderBy(F.desc("score"), "vec_id")
    truth = vectors.mapInArrow(run, "query long, vec_id long, score double, leaf int").withColumn("r", F.row_number().over(best)).filter(F.col("r") <= k).select("query", "leaf").collect()
    place = {r.id: {leaf: n for n, leaf in enumerate(tree.value.visits(asked.value[1][i]))} for i, r in enumerate(rows)}
    depth = np.array([place[t.query][t.leaf] for t in truth])
    visits = 1
    while len(depth) and (depth < visits).mean() < target:
        visits += 1
    return visits


def nearest(table: DataFrame, id_col: str, vec_col: str, is_query, k: int = 20, target: float = TARGET_RECALL, visits: int | None = None) -> DataFrame:
    """(query_id, rank, vec_id, score): the k greatest inner products found for each query row.

    `is_query` is a condition on column id. A query does not meet rows of its own id. Vectors that are null,
    zero, of another length than most, or hold null or non-finite components take no part, nor do null ids.
    Repeated ids are one query each (the least vector), but candidates each. Ties go to the smaller id. An
    empty table gives an empty result. Scores are sums of products in double precision.
    """
    spark = table.sparkSession
    dim = dimension(table, vec_col)
    if not dim:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    vectors = read_vectors(table, id_col, vec_col, dim)
    rows = vectors.count()
    if not rows:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    queries = distinct_queries(vectors, is_query)
    tree = spark.sparkContext.broadcast(fit_tree(vectors, dim, rows))
    visits = visits or calibrate(vectors, queries, tree, dim, k, target)

    def index(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            leaf = tree.value.assign(matrix(b.column(1), dim)) if b.num_rows else np.zeros(0, np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(leaf), b.column(0), b.column(1)], ["cell", "id", "vec"])

    indexed = vectors.mapInArrow(index, "cell int, id long, vec binary")
    sizes = {r.cell: r["count"] for r in indexed.groupBy("cell").count().collect()}  # a row for each leaf at most
    parts = spark.sparkContext.broadcast({c: -(-n // CELL_ROWS) for c, n in sizes.items()})
    many = F.create_map(*[F.lit(x) for c, n in sizes.items() for x in (c, -(-n // CELL_ROWS))])
    cells = indexed.withColumn("part", F.pmod(F.xxhash64("id"), many[F.col("cell")].cast("long")).cast("int"))

    def send(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            cell, part, at = [], [], []
            for i, q in enumerate(matrix(b.column(1), dim) if b.num_rows else ()):
                for c in tree.value.visits(q, visits):
                    for p in range(parts.value.get(c, 0)):
                        cell.append(c)
                        part.append(p)
                        at.append(i)
            pick = pa.array(at, pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(cell, pa.int32()), pa.array(part, pa.int32()), b.column(0).take(pick), b.column(1).take(pick), pa.array([0.0] * len(at), pa.float64())], ["cell", "part", "id", "vec", "bound"])

    sent = queries.mapInArrow(send, "cell int, part int, id long, vec binary, bound double")

    def meet(ids, x, q_ids, q, _bounds):
        scores = q @ x.T
        scores[q_ids[:, None] == ids[None, :]] = -np.inf
        out = [], [], []
        for i, query in enumerate(q_ids):
            pick = best_of(scores[i], k, 1e-9 * (1 + abs(scores[i]).max(where=np.isfinite(scores[i]), initial=0)))
            pick = pick[scores[i, pick] > -np.inf]
            exact = (x[pick] * q[i]).sum(1)  # the same order of addition for every row, so equal vectors tie
            best = np.lexsort((ids[pick], -exact))[:k]
            for c, v in zip(out, (np.full(len(best), query), ids[pick][best], exact[best])):
                c.append(v)
        yield tuple(np.concatenate(c) for c in out)

    return search_cells(cells, sent, dim, meet, k, "double")
