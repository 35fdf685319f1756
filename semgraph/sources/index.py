"""The search index of a graph: what expansion needs of a neighbour stands on the adjacency row itself.

The search must know of each neighbour which stages it may end (its types) and the best weight at it (its predicates). Nodes
that agree in both form a profile, and a graph has few profiles, however many nodes: they belong to its schema. So a row
of the adjacency names the neighbour's profile, and a query joins the profiles it cares for as a broadcast vocabulary
instead of joining a table of nodes in each hop. Rows of a hub are dealt into slots, so that a shuffled join on (node, slot)
never puts a hub into one task.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import KG

#: Adjacency rows of a node in one slot; a node with more is a hub.
SLOT_ROWS = 100_000
#: SQL of the number of slots of a node with `degree` rows.
SLOTS = f"CAST(greatest(1, ceil(degree / {SLOT_ROWS})) AS INT)"
#: Adjacency rows of a file: at least (so that a small graph is spread over all tasks) and at most.
FILE_ROWS = (50_000, 4_000_000)
#: Files for each task that runs at once, where the graph has rows enough: states gather in few ranges of nodes, and small files of a
#: range are dealt to many tasks.
FILES_A_TASK = 8
#: Profiles that are held on the driver and broadcast; a graph with more joins them as a table.
MOST_PROFILES = 50_000
#: Hubs that are broadcast when the index is built.
MOST_HUBS = 1_000_000


@dataclass
class GraphIndex:
    """adj(node, slot, nbr, profile, degree, predicate): profile and degree are of `nbr`; entities(key, node_id, profile, degree): by
    normal name; profiles(profile, types, keys, preds, members). A node's rows lie in `slots(degree)` slots.
    """

    adj: DataFrame
    entities: DataFrame
    profiles: DataFrame
    n_profiles: int
    memo: dict = field(default_factory=dict, repr=False)

    def profile_rows(self) -> list | None:
        """(profile, keys, preds) rows on the driver, or None where they are too many."""
        if self.n_profiles > MOST_PROFILES:
            return None
        if "profiles" not in self.memo:
            self.memo["profiles"] = [(r.profile, frozenset(r["keys"]), tuple(r.preds)) for r in self.profiles.select("profile", "keys", "preds").collect()]
        return self.memo["profiles"]


def both_ways(edges: DataFrame) -> DataFrame:
    """(node, nbr, predicate, forward): direction plays no part in matches, so each edge counts both ways."""
    return edges.select(F.col("src").alias("node"), F.col("dst").alias("nbr"), "predicate", F.lit(True).alias("forward")).unionByName(
        edges.select(F.col("dst").alias("node"), F.col("src").alias("nbr"), "predicate", F.lit(False).alias("forward"))
    )


def write_index(kg: KG, path: str) -> None:
    """Store the index of a graph under `path`: adjacency by predicate, in files ordered by node; entities ordered by name."""
    from ..operators.library import norm

    both = both_ways(kg.edges).select("node", "nbr", "predicate")
    at = both.groupBy("node").agg(F.array_sort(F.collect_set("predicate")).alias("preds"), F.count("*").alias("degree"))
    none = F.array().cast("array<string>")
    known = kg.nodes.select("node_id", norm("name").alias("key"), F.array_sort(F.coalesce("types", none)).alias("types")).join(at, F.col("node_id") == F.col("node"), "full_outer")
    known = known.select(
        F.coalesce("node_id", "node").alias("node_id"), "key", F.coalesce("types", none).alias("types"), F.coalesce("preds", none).alias("preds"), F.coalesce("degree", F.lit(0)).alias("degree"),
    )
    known = known.select(
        "node_id", "key", "types", "preds", F.xxhash64(F.array_join("types", "\x01", "\x03"), F.lit("\x02"), F.array_join("preds", "\x01", "\x03")).alias("profile"), "degree",
    )
    known.repartitionByRange("key", "node_id").sortWithinPartitions("key", "node_id").write.parquet(f"{path}/entities")
    spark = kg.nodes.sparkSession
    known = spark.read.schema(known.schema).parquet(f"{path}/entities")
    profiles = known.groupBy("profile", "types", "preds").agg(F.count("*").alias("members"))
    profiles.select("profile", "types", F.transform("types", norm).alias("keys"), "preds", "members").coalesce(1).write.parquet(f"{path}/profiles")
    hubs = known.filter(F.col("degree") > SLOT_ROWS).selectExpr("node_id AS node", f"{SLOTS} AS slots")
    hubs = F.broadcast(hubs) if hubs.count() <= MOST_HUBS else hubs
    adj = both.join(known.select(F.col("node_id").alias("nbr"), "profile", "degree"), "nbr").join(hubs, "node", "left")
    adj = adj.select("node", F.when(F.col("slots").isNull(), 0).otherwise(F.pmod(F.xxhash64("nbr"), F.col("slots"))).cast("int").alias("slot"), "nbr", "profile", "degree", "predicate")
    rows = known.agg(F.sum("degree")).first()[0] or 0
    files = max(1, rows // FILE_ROWS[1], min(FILES_A_TASK * spark.sparkContext.defaultParallelism, rows // FILE_ROWS[0]))
    adj.repartitionByRange(files, "predicate", "node", "nbr").sortWithinPartitions("predicate", "node", "nbr").write.partitionBy("predicate").parquet(f"{path}/adj")


def read_index(spark: SparkSession, path: str) -> GraphIndex:
    profiles = spark.read.schema("profile long, types array<string>, keys array<string>, preds array<string>, members long").parquet(f"{path}/profiles")
    seen = profiles.agg(F.count("*").alias("n"), F.countDistinct("profile").alias("ids")).first()
    if seen.n != seen.ids:
        raise ValueError("two profiles share a number")
    adj = spark.read.schema("node long, slot int, nbr long, profile long, degree long, predicate string").parquet(f"{path}/adj")
    entities = spark.read.schema("key string, node_id long, profile long, degree long").parquet(f"{path}/entities")
    return GraphIndex(adj, entities, profiles, seen.n)


def index_of(kg: KG) -> GraphIndex:
    """The index of a graph, built and stored once."""
    if "index" not in kg.memo:
        from .tables import scratch

        path = scratch(kg.nodes.sparkSession, "index")
        write_index(kg, path)
        kg.memo["index"] = read_index(kg.nodes.sparkSession, path)
    return kg.memo["index"]
