"""What the two vector searches share: reading vectors, and meeting queries with vectors cell by cell."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

#: Vectors of a cell held in a task; larger cells are split.
CELL_ROWS = 4096
QUERIES_AT_ONCE = 512


def dimension(table: DataFrame, vec_col: str) -> int:
    """The most common length of the vectors (ties: the greater), 0 if there are none."""
    found = table.filter(F.size(vec_col) > 0).groupBy(F.size(vec_col).alias("d")).count().orderBy(F.desc("count"), F.desc("d")).first()
    return found.d if found else 0


def read_vectors(table: DataFrame, id_col: str, vec_col: str, dim: int, scale: int | None = None, zeros: bool = False) -> DataFrame:
    """(id long, vec binary): doubles of every usable row; with `scale`, floor(scale * x) of each.

    Left out: null ids; vectors that are null, of another length than `dim`, or hold null or non-finite
    components; zero vectors unless `zeros`.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            flat = b.column(1).flatten().cast(pa.float64())
            x = flat.to_numpy(zero_copy_only=False).reshape(-1, dim) if len(flat) else np.zeros((0, dim))
            ok = np.isfinite(x).all(1)
            if scale:
                x = np.floor(x * scale)
            if not zeros:
                ok &= (x != 0).any(1)
            x = np.ascontiguousarray(x[ok])
            ids = b.column(0).filter(pa.array(ok))
            yield pa.RecordBatch.from_arrays([ids, pa.array([r.tobytes() for r in x], pa.binary())], ["id", "vec"])

    plain = F.transform(F.col(vec_col), lambda x: F.coalesce(x.cast("double"), F.lit(float("nan"))))  # null components fail the finite test
    rows = table.filter(F.col(id_col).isNotNull() & (F.size(vec_col) == dim)).select(F.col(id_col).cast("long").alias("id"), plain.alias("v"))
    return rows.mapInArrow(run, "id long, vec binary")


def matrix(column: pa.Array, dim: int) -> np.ndarray:
    return np.frombuffer(b"".join(column.to_pylist()), np.float64).reshape(-1, dim)


def distinct_queries(vectors: DataFrame, condition) -> DataFrame:
    """Query rows, one for each id (of repeated ids the least vector)."""
    return vectors.filter(condition).groupBy("id").agg(F.min("vec").alias("vec"))


#: (vectors, queries, bounds of the queries) -> for each query, rows of vectors to verify.
Meet = Callable[[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray], Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]]


def search_cells(vectors: DataFrame, queries: DataFrame, dim: int, meet: Meet, k: int, score_type: str) -> DataFrame:
    """(query_id, rank, vec_id, score) from (cell, part, id, vec) and (cell, part, id, vec, bound).

    Rows of a cell's part come to a task in order, vectors first; the task holds these (CELL_ROWS about) and a block
    of queries, and emits the best k of each query. A window keeps the best k over all cells.
    """
    cols = ["cell", "part", "kind", "id", "vec", "bound"]
    both = vectors.withColumns({"kind": F.lit(0), "bound": F.lit(0.0)}).select(cols).unionByName(queries.withColumn("kind", F.lit(1)).select(cols))
    kind = pa.int64() if score_type == "long" else pa.float64()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, ids, vecs, ready = None, [], [], None
        asked: list[tuple[int, bytes, float]] = []

        def answer() -> Iterator[pa.RecordBatch]:
            nonlocal ready, asked
            if asked and vecs:
                if ready is None:
                    ready = np.array(ids, np.int64), np.frombuffer(b"".join(vecs), np.float64).reshape(-1, dim)
                q = np.array([a[0] for a in asked], np.int64)
                m = np.frombuffer(b"".join(a[1] for a in asked), np.float64).reshape(-1, dim)
                for query, vec, score in meet(ready[0], ready[1], q, m, np.array([a[2] for a in asked])):
                    yield pa.RecordBatch.from_arrays([pa.array(query), pa.array(vec), pa.array(score, kind)], ["query_id", "vec_id", "score"])
            asked = []

        for b in batches:
            for cell, part, is_query, i, vec, bound in zip(*(c.to_pylist() for c in b.columns)):
                if (cell, part) != now:
                    yield from answer()
                    now, ids, vecs, ready = (cell, part), [], [], None
                if is_query:
                    asked.append((i, vec, bound))
                    if len(asked) == QUERIES_AT_ONCE:
                        yield from answer()
                else:
                    ids.append(i)
                    vecs.append(vec)
        yield from answer()

    dealt = both.repartition("cell", "part").sortWithinPartitions("cell", "part", "kind", "id")
    found = dealt.mapInArrow(run, f"query_id long, vec_id long, score {score_type}")
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    ranked = found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)
    return ranked.select("query_id", "rank", "vec_id", "score")


def best_of(scores: np.ndarray, k: int, slack: float = 0.0) -> np.ndarray:
    """Positions of the k greatest and of all that tie with the least of them (within `slack`)."""
    if len(scores) <= k:
        return np.arange(len(scores))
    least = np.partition(scores, len(scores) - k)[len(scores) - k]
    return np.flatnonzero(scores >= least - slack)
