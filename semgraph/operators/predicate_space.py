"""The predicate space: vectors of predicates, their similarities, weights for query predicates."""

from __future__ import annotations

import math

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions.scores import cosine_sim
from ..model import PREDICATE_VECTORS
from .library import norm

#: Authored vectors on the axes geo, trade, catalog, activity, content, taxonomy.
AUTHORED = {
    "originNation": (0.75, 0.65, 0, 0, 0, 0), "customerNation": (0.9, 0.4, 0, 0, 0, 0), "supplierNation": (0.85, 0.3, 0.3, 0, 0, 0), "inRegion": (0.5, 0, 0, 0, 0, 0.9),
    "placedBy": (0.45, 0.85, 0, 0, 0, 0), "containsPart": (0, 0.6, 0.75, 0, 0, 0), "fulfilledBy": (0.35, 0.75, 0.35, 0, 0, 0), "suppliedBy": (0.3, 0.6, 0.65, 0, 0, 0),
    "hasBrand": (0, 0.2, 1, 0, 0, 0.2), "click": (0, 0.1, 0.2, 1, 0, 0), "view": (0, 0.1, 0.3, 1, 0, 0), "purchase": (0, 0.7, 0.2, 0.7, 0, 0), "signup": (0.1, 0.1, 0, 1, 0, 0),
    "error": (0, -0.2, 0, 1, 0, 0), "fromSource": (0, 0, 0, 0.1, 1, 0), "writtenIn": (0.5, 0, 0, 0, 0.9, 0), "linksTo": (0, 0, 0, 0.3, 1, 0), "onHost": (0.1, 0, 0, 0.2, 1, 0.1),
    "quotes": (0, 0, 0.1, 0, 1, 0.3), "partOf": (0, 0, 0, 0.3, 0.7, 0.5), "spokenBy": (0, 0, 0, 0.6, 0.6, 0), "follows": (0, 0, 0, 0.5, 0.8, 0.1),
}


def predicate_space(spark: SparkSession, provider: str = "authored", embeddings: DataFrame | None = None, trained: DataFrame | None = None) -> DataFrame:
    """(predicate, vec): authored, blended from the embeddings table, or trained."""
    if provider == "authored":
        return spark.createDataFrame([(p, [float(x) for x in v]) for p, v in AUTHORED.items()], PREDICATE_VECTORS)
    if provider == "blend":
        return _blend(spark, embeddings)
    if provider == "trained":
        return trained
    raise ValueError(f"no predicate space is called {provider}")


def _blend(spark: SparkSession, embeddings: DataFrame) -> DataFrame:
    """Vectors 0 to 5 of the table are the axes; a fifth of vector 10 + i sets predicate i apart."""
    vectors = embeddings.select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v")).filter("vec_id < 100")
    rows = [(p, i, axis, float(x)) for i, (p, v) in enumerate(AUTHORED.items()) for axis, x in enumerate(v)] + [(p, i, 10 + i, 0.2) for i, p in enumerate(AUTHORED)]
    parts = spark.createDataFrame(rows, "predicate string, i int, vec_id long, c double").join(vectors, "vec_id")
    scaled = parts.select("predicate", F.posexplode(F.transform("v", lambda x: x * F.col("c"))).alias("at", "x"))
    summed = scaled.groupBy("predicate", "at").agg(F.sum("x").alias("x")).groupBy("predicate").agg(F.sort_array(F.collect_list(F.struct("at", "x"))).alias("s"))
    vec = summed.select("predicate", F.transform("s", lambda t: t["x"]).alias("vec"))
    return vec.select("predicate", F.transform("vec", lambda x: x / F.sqrt(F.aggregate("vec", F.lit(0.0), lambda s, y: s + y * y))).alias("vec"))


def predicate_similarity(space: DataFrame) -> DataFrame:
    """(a, b, sim) of all pairs: a vocabulary against itself, never data."""
    a, b = space.select(F.col("predicate").alias("a"), F.col("vec").alias("va")), space.select(F.col("predicate").alias("b"), F.col("vec").alias("vb"))
    return a.crossJoin(F.broadcast(b)).select("a", "b", cosine_sim("va", "vb").alias("sim"))


def edge_weights(sim: DataFrame, floor: float = 0.0, rescale: str | None = None) -> DataFrame:
    """(a, b, w): similarities as weights in (0, 1]; those at or under the floor are left out."""
    w = (F.col("sim") + 1) / 2 if rescale == "half" else F.col("sim")
    return sim.select("a", "b", F.least(w, F.lit(1.0)).alias("w")).filter(F.col("w") > floor)


def similar_predicates(space: DataFrame, m: int = 10) -> DataFrame:
    """(a, b, sim, rank): the m most similar other predicates of each."""
    order = Window.partitionBy("a").orderBy(F.desc("sim"), "b")
    return predicate_similarity(space).filter("a != b").withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= m)


def vectors(space: DataFrame) -> dict[str, list[float]]:
    """The space on the driver: a vocabulary, thousands of rows at most."""
    rows = space.limit(100_001).collect()
    if len(rows) > 100_000:
        raise ValueError("a predicate vocabulary of over 100,000 entries is not held on the driver")
    return {r.predicate: list(r.vec) for r in rows}


def resolve_predicate(label: str, space: dict[str, list[float]], synonyms: dict[str, str] | None = None, vector: list[float] | None = None) -> list[float]:
    """The vector of a query predicate: its own, that of a synonym, or the user's; else the predicate with the nearest name."""
    if vector is not None:
        return list(vector)
    if label in space:
        return space[label]
    plain = {k.lower().replace("_", ""): v for k, v in space.items()}
    wanted = (synonyms or {}).get(label, label).lower().replace("_", "").replace(" ", "")
    if wanted in plain:
        return plain[wanted]
    raise KeyError(f"the predicate {label} is in neither the vocabulary nor the synonyms; give its vector")


def weights_for(label: str, space: dict[str, list[float]], floor: float = 0.0, rescale: str | None = None, **resolve) -> dict[str, float]:
    """predicate -> weight for one query predicate."""
    q = resolve_predicate(label, space, **resolve)
    out = {}
    for p, v in space.items():
        norms = math.sqrt(sum(x * x for x in q)) * math.sqrt(sum(x * x for x in v))
        sim = sum(x * y for x, y in zip(q, v)) / norms if norms else 0.0
        w = min((sim + 1) / 2 if rescale == "half" else sim, 1.0)
        if w > floor:
            out[p] = w
    return out


__all__ = ["AUTHORED", "edge_weights", "norm", "predicate_similarity", "predicate_space", "resolve_predicate", "similar_predicates", "vectors", "weights_for"]
