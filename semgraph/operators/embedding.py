"""Embedding of predicates: a generic contract, and translation embedding by full-batch gradient descent in DataFrames."""

from __future__ import annotations

import math
from dataclasses import dataclass
from typing import Protocol

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model import PREDICATE_VECTORS
from ..sources.tables import drop, keep

#: Bytes of entity vectors that every task may hold; where there are more, triples join them.
MOST_HELD = 320_000_000
#: Triples that a task gets, one for each of its entities on them, about; 15 bytes each.
TASK_TRIPLES = 3_500_000
#: Ends of triples at one entity, at least, from which its gradient is summed by all tasks.
HUB_ENDS = 100_000
#: Entities that are broadcast to number the ends of triples; where there are more, they are joined.
MOST_NUMBERED = 2_000_000
#: Entity vectors of a stored row, and triples that are dealt out or weighed at once.
VECTORS, DEALT, WEIGHED = 1_000, 500_000, 2_048
#: Bytes of a batch that a task of Spark and its Python worker each hold beside all vectors.
BATCH_CONF, BATCH = "spark.sql.execution.arrow.maxBytesPerBatch", "4m"


class EmbeddingModel(Protocol):
    """t is about g(h, r): fit gives (entity vectors, predicate vectors)."""

    def fit(self, edges: DataFrame) -> tuple[DataFrame, DataFrame]: ...


@dataclass
class TranslationEmbedding:
    """g(h, r) = h + r, margin ranking loss against corrupted triples, L1 or L2.

    Entities are a table and stay one: each epoch joins the triples with the vectors of their ends, makes gradients as
    arrays, sums them by entity and by predicate in one aggregate and updates by a join. Predicate vectors are few: they are
    broadcast each epoch. Corrupted ends are chosen by hash, so results repeat. Where the vectors of all entities are small enough
    for a task, each task reads them whole and finds the gradients of its own entities, so that only numbers of entities are shuffled.
    """

    dim: int = 32
    margin: float = 1.0
    rate: float = 0.05
    epochs: int = 10
    norm: int = 2
    negatives: int = 1
    seed: int = 0

    def start(self, ids: DataFrame, key: str, *others: str) -> DataFrame:
        """Unit vectors from hashes of id, axis and seed; other columns stay."""
        bound = 6 / math.sqrt(self.dim)
        draw = lambda i: (F.pmod(F.xxhash64(F.col(key), i, F.lit(self.seed)), F.lit(2_000_003)) / 2_000_003.0 * 2 - 1) * bound
        raw = ids.select(key, *others, F.transform(F.sequence(F.lit(1), F.lit(self.dim)), draw).alias("vec"))
        return raw.select(key, *others, _unit("vec").alias("vec"))

    def fit(self, edges: DataFrame) -> tuple[DataFrame, DataFrame]:
        spark = edges.sparkSession
        edges, _ = keep(edges.select("src", "predicate", "dst"), "triples")  # packed by column, where a checkpoint is not
        tasks = max(spark.sparkContext.defaultParallelism, edges.rdd.getNumPartitions())
        ids = edges.select(F.col("src").alias("id")).unionByName(edges.select(F.col("dst").alias("id"))).distinct()
        entities, _ = keep(self._numbered(ids), "entities")
        n = entities.count()
        predicates = {r.predicate: np.array(r.vec) for r in self.start(edges.select("predicate").distinct(), "predicate").collect()}
        self.losses: list[float] = []
        if 0 < n * self.dim * 8 <= MOST_HELD:
            return self._fit_held(edges, entities, predicates, n)
        vectors, _ = keep(self.start(entities.select("id"), "id"), "vectors")
        for epoch in range(self.epochs):
            table = spark.createDataFrame([(p, [float(x) for x in v]) for p, v in predicates.items()], PREDICATE_VECTORS)
            # a triple costs far more work than bytes, and the join may follow the few files of the entities
            pairs = self._pairs(edges, entities, n, epoch).repartition(tasks, "src", "dst")
            total, _ = keep(self._gradients(pairs, vectors, table), "gradients")
            moved = vectors.join(total.where("predicate IS NULL").select("id", "g"), "id", "left").select("id", _unit(F.when(F.col("g").isNull(), F.col("vec")).otherwise(F.zip_with("vec", "g", lambda v, g: v - self.rate * g))).alias("vec"))
            by_predicate = total.where("predicate IS NOT NULL").collect()
            vectors, _ = keep(moved, "vectors")
            for r in by_predicate:
                predicates[r.predicate] = predicates[r.predicate] - self.rate * min(r.n, 50) / r.n * np.array(r.g)
            self.losses.append(sum(r.loss for r in by_predicate) / max(1, sum(r.n for r in by_predicate)))
            del pairs, total, moved
            _let_go(spark)
        return vectors, spark.createDataFrame([(p, [float(x) for x in v]) for p, v in predicates.items()], PREDICATE_VECTORS)

    def _fit_held(self, edges: DataFrame, entities: DataFrame, predicates: dict[str, np.ndarray], n: int) -> tuple[DataFrame, DataFrame]:
        """The same steps with the vectors of all entities in every task: a triple is no longer widened by three vectors.

        Entity i belongs to block i mod the number of blocks. Each epoch a triple, as numbers, goes to the blocks of its ends and of the
        entity that replaces one of them. The task of a block reads all vectors from their files, sums the gradients of its own entities and
        stores their new vectors; sums of predicates, and of hubs, come from the one task where a triple is at home.
        """
        spark = edges.sparkSession
        names = sorted(predicates)
        triples, rows = self._triples(edges, entities, names, n)
        cores = spark.sparkContext.defaultParallelism
        blocks = cores * max(1, -(-3 * rows // (cores * TASK_TRIPLES)))
        hubs = self._hubs(triples, max(HUB_ENDS, rows // (4 * blocks)), entities)
        at = np.array(sorted(hubs), np.int64)
        at_hubs = np.array([hubs[i] for i in at]).reshape(len(at), self.dim) if len(at) else np.zeros((0, self.dim))
        vectors, _ = keep(self.start(entities.repartition(cores), "id", "at").mapInArrow(_packed, VECTORS_SCHEMA), "vectors")
        owners = spark.range(0, blocks, 1, 1).selectExpr("CAST(id AS INT) AS block", "CAST(NULL AS BINARY) AS data", "true AS owner")
        for epoch in range(self.epochs):
            r = np.array([predicates[p] for p in names])
            dealt = triples.mapInArrow(_dealt(blocks, n, epoch, at), "block int, data binary")
            own = owners.unionByName(dealt.withColumn("owner", F.lit(False))).repartitionById(blocks, F.col("block"))
            none = spark.range(0, 1, 1, 1).selectExpr("CAST(NULL AS BINARY) AS at", "CAST(NULL AS BINARY) AS vec", "false AS known")
            every = vectors.filter("vec IS NOT NULL").select("at", "vec", F.lit(True).alias("known")).unionByName(none).coalesce(1)
            # each task streams all vectors past the rows of its block, which it holds: triples come beside the empty row, vectors beside
            # the owner's. To ask whether `data` is null would copy it.
            met = every.join(own.hint("shuffle_replicate_nl"), F.col("owner") == F.col("known"))
            met = met.select("block", "at", F.coalesce("data", "vec").alias("data"))
            step = _held_step(blocks, n, self.dim, r, at, at_hubs, self.margin, self.norm, self.rate)
            before, usual = vectors, spark.conf.get(BATCH_CONF)
            spark.conf.set(BATCH_CONF, BATCH)
            try:
                vectors, _ = keep(met.mapInArrow(step, VECTORS_SCHEMA), "vectors")
            finally:
                spark.conf.set(BATCH_CONF, usual)
            sums = np.sum([np.frombuffer(x.sums) for x in vectors.filter("sums IS NOT NULL").select("sums").collect()], axis=0)
            loss, count, sums = sums[: len(names)], sums[len(names) : 2 * len(names)], sums[2 * len(names) :].reshape(-1, self.dim)
            for i, name in enumerate(names):
                if count[i]:
                    predicates[name] = predicates[name] - self.rate * min(count[i], 50) / count[i] * sums[i]
            at_hubs = _unit_rows(at_hubs - self.rate * sums[len(names) :])
            self.losses.append(float(loss.sum() / max(1, count.sum())))
            drop(before)
            del before, dealt, own, every, met
            _let_go(spark)
        rows = vectors.filter("vec IS NOT NULL").select("at", "vec").mapInArrow(_unpacked(self.dim, at, at_hubs), "at long, vec array<double>")
        return entities.join(rows, "at").select("id", "vec"), spark.createDataFrame([(p, [float(x) for x in y]) for p, y in predicates.items()], PREDICATE_VECTORS)

    def _triples(self, edges: DataFrame, entities: DataFrame, names: list[str], n: int) -> tuple[DataFrame, int]:
        """(s, p, t, h): triples as numbers of entities and predicates, with the hash of all that is the same in every epoch; their count."""
        spark = edges.sparkSession
        known = spark.createDataFrame(list(zip(names, range(len(names)))), "predicate string, p int")
        of = (lambda c: F.broadcast(entities.select(F.col("id").alias(c), F.col("at").cast("int").alias(f"{c}_at")))) if n <= MOST_NUMBERED else (lambda c: entities.select(F.col("id").alias(c), F.col("at").cast("int").alias(f"{c}_at")))
        drawn = edges.select("*", F.explode(F.sequence(F.lit(1), F.lit(self.negatives))).alias("draw")) if self.negatives != 1 else edges.withColumn("draw", F.lit(1))
        numbered = drawn.join(F.broadcast(known), "predicate").join(of("src"), "src").join(of("dst"), "dst")
        numbered = numbered.select(F.col("src_at").alias("s"), "p", F.col("dst_at").alias("t"), F.xxhash64("src", "predicate", "dst", "draw", F.lit(self.seed)).alias("h"))
        triples, seen = keep(numbered.repartition(spark.sparkContext.defaultParallelism * max(1, edges.rdd.getNumPartitions() // spark.sparkContext.defaultParallelism)), "numbered", F.count("*").alias("n"))
        return triples, seen["n"]

    def _hubs(self, triples: DataFrame, ends: int, entities: DataFrame) -> dict[int, list[float]]:
        """Numbers and first vectors of the entities with more than `ends` ends of triples."""
        by_end = triples.select(F.col("s").alias("at")).unionByName(triples.select(F.col("t").alias("at")))
        hubs = by_end.groupBy("at").count().filter(F.col("count") > ends).select(F.col("at").cast("long").alias("at"))
        return {r.at: r.vec for r in self.start(entities.join(F.broadcast(hubs), "at"), "id", "at").collect()}

    def _numbered(self, ids: DataFrame) -> DataFrame:
        """(id, at): entities with numbers from 0 that hashes can point at."""
        dealt, _ = keep(ids.withColumn("pid", F.spark_partition_id()), "dealt")
        from pyspark.sql import Window

        own = dealt.withColumn("own", F.row_number().over(Window.partitionBy("pid").orderBy("id")) - 1)
        sizes = dealt.groupBy("pid").agg(F.count("*").alias("n"))
        first = sizes.select("pid", (F.sum("n").over(Window.orderBy("pid")) - F.col("n")).alias("first"))
        return own.join(F.broadcast(first), "pid").select("id", (F.col("first") + F.col("own")).cast("long").alias("at"))

    def _pairs(self, edges: DataFrame, entities: DataFrame, n: int, epoch: int) -> DataFrame:
        """Each triple with the entity that replaces its head or its tail in the corrupted one."""
        return self._drawn(edges, n, epoch).join(entities.withColumnRenamed("id", "other"), "at").select("src", "predicate", "dst", "other", "head")

    def _drawn(self, edges: DataFrame, n: int, epoch: int) -> DataFrame:
        """(src, predicate, dst, at, head): each triple with the number of an entity, and whether it replaces the head."""
        drawn = edges.select("*", F.explode(F.sequence(F.lit(1), F.lit(self.negatives))).alias("draw"))
        h = F.xxhash64("src", "predicate", "dst", "draw", F.lit(self.seed), F.lit(epoch))
        return drawn.select("src", "predicate", "dst", F.pmod(h, F.lit(n)).cast("long").alias("at"), (F.pmod(F.shiftright(h, 40), F.lit(2)) == 0).alias("head"))

    def _gradients(self, pairs: DataFrame, vectors: DataFrame, table: DataFrame) -> DataFrame:
        """(predicate, id, g, loss, n): sums for each entity (its predicate is null) and each predicate (its id is null).

        One aggregate holds both, so that gradients of single triples are summed before a shuffle and never stored.
        """
        x = pairs.join(F.broadcast(table.withColumnRenamed("vec", "v_pred")), "predicate")
        for c in ("src", "dst", "other"):
            x = x.join(vectors.select(F.col("id").alias(c), F.col("vec").alias(f"v_{c}")), c)
        gap = lambda a, b: F.zip_with(F.zip_with(a, "v_pred", lambda p, q: p + q), b, lambda p, q: p - q)
        head_2, tail_2 = F.when(F.col("head"), F.col("v_other")).otherwise(F.col("v_src")), F.when(F.col("head"), F.col("v_dst")).otherwise(F.col("v_other"))
        x = x.select("src", "predicate", "dst", "other", "head", gap("v_src", "v_dst").alias("d"), gap(head_2, tail_2).alias("e"))
        if self.norm == 1:
            size = lambda c: F.aggregate(c, F.lit(0.0), lambda s, v: s + F.abs(v))
            slope = lambda c, _: F.transform(c, lambda v: F.signum(v))
        else:
            size = lambda c: F.sqrt(F.aggregate(c, F.lit(1e-12), lambda s, v: s + v * v))
            slope = lambda c, n: F.transform(c, lambda v: v / F.col(n))
        x = x.withColumns({"nd": size("d"), "ne": size("e")})
        x = x.withColumn("loss", F.greatest(F.lit(0.0), F.lit(self.margin) + F.col("nd") - F.col("ne")))
        x = x.withColumns({"gd": slope("d", "nd"), "ge": slope("e", "ne")})
        minus = lambda c: F.transform(c, lambda v: -v)
        less = F.zip_with("gd", "ge", lambda a, b: a - b)
        part = lambda predicate, id_, g, loss: F.struct(predicate.alias("predicate"), id_.alias("id"), g.alias("g"), loss.alias("loss"))
        entity = lambda c, g: part(F.lit(None).cast("string"), F.col(c), g, F.lit(0.0))
        # a corrupted triple shares one end with its own: that end takes both gradients
        moved = F.array(
            part(F.col("predicate"), F.lit(None).cast("long"), less, F.col("loss")),
            entity("src", F.when(F.col("head"), F.col("gd")).otherwise(less)),
            entity("dst", F.when(F.col("head"), minus(less)).otherwise(minus("gd"))),
            entity("other", F.when(F.col("head"), minus("ge")).otherwise(F.col("ge"))),
        )
        still = F.array(part(F.col("predicate"), F.lit(None).cast("long"), F.transform("gd", lambda _: F.lit(0.0)), F.col("loss")))
        parts = x.select(F.explode(F.when(F.col("loss") > 0, moved).otherwise(still)).alias("x")).select("x.*")
        # a sum for each axis is a hash aggregate; one of whole vectors would sort all parts
        summed = parts.groupBy("predicate", "id").agg(*[F.sum(F.col("g")[i]).alias(f"g{i}") for i in range(self.dim)], F.sum("loss").alias("loss"), F.count("*").alias("n"))
        return summed.select("predicate", "id", F.array(*[f"g{i}" for i in range(self.dim)]).alias("g"), "loss", "n")


def _last_hash(h: np.ndarray, epoch: int) -> np.ndarray:
    """What Spark's xxhash64 makes of more columns and an int, from its hash of the columns before."""
    p1, p2, p3, p5 = (np.uint64(x) for x in (0x9E3779B185EBCA87, 0xC2B2AE3D27D4EB4F, 0x165667B19E3779F9, 0x27D4EB2F165667C5))
    first = np.uint64((epoch & 0xFFFFFFFF) * int(p1) & 0xFFFFFFFFFFFFFFFF)
    x = (h.view(np.uint64) + p5 + np.uint64(4)) ^ first
    x = ((x << np.uint64(23)) | (x >> np.uint64(41))) * p2 + p3
    x = (x ^ (x >> np.uint64(33))) * p2
    x = (x ^ (x >> np.uint64(29))) * p3
    return (x ^ (x >> np.uint64(32))).view(np.int64)


#: Of a triple in a task: which ends are the task's own, whether its head is replaced, whether it is at home there.
OWN_S, OWN_T, OWN_O, HEAD, HOME = 1, 2, 4, 8, 16
TRIPLE = np.dtype([("s", "<i4"), ("t", "<i4"), ("o", "<i4"), ("p", "<u2"), ("f", "u1")])
WIDE = np.dtype([("s", "<i4"), ("t", "<i4"), ("o", "<i4"), ("p", "<i4"), ("f", "u1")])
VECTORS_SCHEMA = "at binary, vec binary, sums binary"


def _dealt(blocks: int, n: int, epoch: int, hubs: np.ndarray):
    """Batches of (s, p, t, h) -> (block, data): triples with the entity that replaces an end, in the blocks of their entities and of their homes."""

    def out(rows):
        import pyarrow as pa

        s, p, t, h = (np.concatenate(x) for x in zip(*rows))
        h = _last_hash(h, epoch)
        x = np.zeros(len(s), WIDE if len(p) and p.max() > 65_535 else TRIPLE)
        x["s"], x["t"], x["o"], x["p"] = s, t, h % n, p
        head = np.where((h >> 40) % 2 == 0, HEAD, 0).astype(np.uint8)
        of = {}
        for c in "sto":
            of[c] = (x[c] % blocks).astype(np.int32)
            if len(hubs):
                of[c][np.isin(x[c], hubs)] = -1
        # the replacing entity is any, so triples between hubs are spread too
        home = np.where(of["s"] >= 0, of["s"], np.where(of["o"] >= 0, of["o"], np.arange(len(s)) % blocks))
        found, data = [], []
        for b in range(blocks):
            f = (of["s"] == b) * OWN_S + (of["t"] == b) * OWN_T + (of["o"] == b) * OWN_O + (home == b) * HOME
            mine = np.flatnonzero(f)
            if len(mine):
                part = x[mine]
                part["f"] = f[mine].astype(np.uint8) | head[mine]
                found.append(b)
                data.append(bytes([part.dtype == WIDE]) + part.tobytes())
        return pa.RecordBatch.from_arrays([pa.array(found, pa.int32()), pa.array(data, pa.binary())], names=["block", "data"])

    def run(batches):
        rows, held = [], 0
        for b in batches:
            if b.num_rows:
                rows.append([b.column(i).to_numpy() for i in range(4)])
                held += b.num_rows
            if held >= DEALT:
                yield out(rows)
                rows, held = [], 0
        if rows:
            yield out(rows)

    return run


def _unit_rows(v: np.ndarray) -> np.ndarray:
    return v / np.sqrt((v * v).sum(1, keepdims=True) + 1e-12)


def _vector_rows(at: np.ndarray, v: np.ndarray):
    """Batches of VECTORS_SCHEMA."""
    import pyarrow as pa

    for i in range(0, len(at), VECTORS):
        row = [at[i : i + VECTORS].astype("<i8").tobytes()], [np.ascontiguousarray(v[i : i + VECTORS]).tobytes()], [None]
        yield pa.RecordBatch.from_arrays([pa.array(x, pa.binary()) for x in row], names=["at", "vec", "sums"])


def _packed(batches):
    """(id, at, vec) -> VECTORS_SCHEMA."""
    for b in batches:
        if b.num_rows:
            yield from _vector_rows(b.column(1).to_numpy(), b.column(2).flatten().to_numpy().reshape(b.num_rows, -1))


def _unpacked(dim: int, hubs: np.ndarray, of_hubs: np.ndarray):
    """VECTORS_SCHEMA -> (at, vec), with the vectors of hubs."""

    def run(batches):
        import pyarrow as pa

        for b in batches:
            for a, x in zip(b.column(0), b.column(1)):
                at, v = np.frombuffer(a.as_buffer(), np.int64), np.frombuffer(x.as_buffer()).reshape(-1, dim)
                if len(hubs) and (known := np.isin(at, hubs)).any():
                    v = v.copy()
                    v[known] = of_hubs[np.searchsorted(hubs, at[known])]
                lists = pa.ListArray.from_arrays(pa.array(np.arange(len(at) + 1, dtype=np.int32) * dim, pa.int32()), pa.array(v.ravel()))
                yield pa.RecordBatch.from_arrays([pa.array(at), lists], names=["at", "vec"])

    return run


def _held_step(blocks: int, n: int, dim: int, r: np.ndarray, hubs: np.ndarray, of_hubs: np.ndarray, margin: float, norm: int, rate: float):
    """Batches of (block, at, data), all vectors and a block's triples -> the block's new vectors, and its sums of predicates and hubs."""
    size = (lambda x: np.abs(x).sum(1)) if norm == 1 else (lambda x: np.sqrt(np.einsum("ij,ij->i", x, x) + 1e-12))
    slope = (lambda x, _: np.sign(x)) if norm == 1 else (lambda x, s: x / s[:, None])

    def add(total, at, g, sign):
        if not len(at):
            return
        order = np.argsort(at, kind="stable")
        at = at[order]
        start = np.flatnonzero(np.concatenate(([True], at[1:] != at[:-1])))
        sums = np.add.reduceat(g[order], start, axis=0)
        if sign > 0:
            total[at[start]] += sums
        else:
            total[at[start]] -= sums

    def run(batches):
        import pyarrow as pa

        v, block, todo = np.zeros((n, dim)), None, []
        for b in batches:
            for i in range(b.num_rows):
                at, data = b.column(1)[i], b.column(2)[i].as_buffer()
                block = b.column(0)[i].as_py() if block is None else block
                if at.is_valid:
                    v[np.frombuffer(at.as_buffer(), np.int64)] = np.frombuffer(data).reshape(-1, dim)
                else:
                    todo.append(np.frombuffer(data[1:], WIDE if data[0] else TRIPLE).copy())
            b = at = data = None  # else a batch waits beside the next
        if block is None:
            return
        v[hubs] = of_hubs
        own = np.arange(block, n, blocks)
        total, by, of_hub = np.zeros((len(own), dim)), np.zeros((len(r), dim)), np.zeros((len(hubs), dim))
        loss, count = np.zeros(len(r)), np.zeros(len(r))
        while todo:
            x = todo.pop()
            for head in (True, False):
                own_head = x[(x["f"] & HEAD > 0) == head]
                for i in range(0, len(own_head), WEIGHED):
                    y = own_head[i : i + WEIGHED]
                    s, t, o, p, f = (np.ascontiguousarray(y[c]) for c in "stopf")
                    sv, tv, ov, rv = v[s], v[t], v[o], r[p]
                    d = sv + rv
                    d -= tv
                    e = (ov if head else sv) + rv
                    e -= tv if head else ov
                    nd, ne = size(d), size(e)
                    lost = np.maximum(0.0, margin + nd - ne)
                    home = f & HOME > 0
                    loss += np.bincount(p[home], lost[home], len(r))
                    count += np.bincount(p[home], minlength=len(r))
                    on = lost > 0
                    if not on.all():
                        s, t, o, p, f, home, d, e, nd, ne = (z[on] for z in (s, t, o, p, f, home, d, e, nd, ne))
                    gd, ge = slope(d, nd), slope(e, ne)
                    less = gd - ge
                    add(by, p[home], less[home], 1)
                    # a corrupted triple shares one end with its own: that end takes both gradients
                    parts = ((s, OWN_S, gd if head else less, 1), (t, OWN_T, less if head else gd, -1), (o, OWN_O, ge, -1 if head else 1))
                    for at, role, g, sign in parts:
                        mine = np.flatnonzero(f & role)
                        add(total, at[mine] // blocks, g[mine], sign)
                        if len(hubs) and len(mine := np.flatnonzero(home & np.isin(at, hubs))):
                            add(of_hub, np.searchsorted(hubs, at[mine]), g[mine], sign)
        sums = np.concatenate((loss, count, by.ravel(), of_hub.ravel()))
        yield pa.RecordBatch.from_arrays([pa.array([z], pa.binary()) for z in (None, None, sums.tobytes())], names=["at", "vec", "sums"])
        for i in range(0, len(own), 50 * VECTORS):
            mine = own[i : i + 50 * VECTORS]
            yield from _vector_rows(mine, _unit_rows(v[mine] - rate * total[i : i + 50 * VECTORS]))

    return run


def _let_go(spark) -> None:
    """Have Spark remove shuffles that nothing refers to any more."""
    import gc

    gc.collect()
    spark._jvm.System.gc()


def _unit(c):
    c = F.col(c) if isinstance(c, str) else c
    size = F.sqrt(F.aggregate(c, F.lit(1e-12), lambda s, v: s + v * v))
    # an array of one, so that the size is found once and not for each element
    return F.transform(F.array(size), lambda z: F.transform(c, lambda v: v / z))[0]
