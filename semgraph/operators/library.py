"""Node matching: the transformation library and the relation of query nodes to graph nodes."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model import KG, QueryNode
from ..sources.tables import keep, local

#: Authored rows (surface, canonical, target, relation).
AUTHORED = (
    ("Purchase", "Order", "type", "synonym"), ("Sale", "Order", "type", "synonym"), ("Client", "Customer", "type", "synonym"), ("Buyer", "Customer", "type", "synonym"),
    ("Cust", "Customer", "type", "abbreviation"), ("Vendor", "Supplier", "type", "synonym"), ("Provider", "Supplier", "type", "synonym"), ("Product", "Part", "type", "synonym"),
    ("Item", "Part", "type", "synonym"), ("Country", "Nation", "type", "synonym"), ("Continent", "Region", "type", "synonym"), ("Maker", "Brand", "type", "synonym"),
    ("Doc", "Document", "type", "abbreviation"), ("EU", "EUROPE", "name", "abbreviation"), ("AM", "AMERICA", "name", "abbreviation"), ("ME", "MIDDLE EAST", "name", "abbreviation"),
    ("AF", "AFRICA", "name", "abbreviation"), ("Français", "fr", "name", "synonym"), ("French", "fr", "name", "synonym"), ("German", "de", "name", "synonym"),
    ("Spanish", "es", "name", "synonym"), ("English", "en", "name", "synonym"),
)
STRENGTH = {"identical": 0, "synonym": 1, "abbreviation": 2}


def norm(c: Column | str) -> Column:
    """Case, underscores and runs of white space make no difference."""
    return F.lower(F.trim(F.regexp_replace(F.col(c) if isinstance(c, str) else c, r"[_\s]+", " ")))


def authored_library(spark: SparkSession) -> DataFrame:
    return local(spark, list(AUTHORED), "surface string, canonical string, target string, relation string")


def initials_rule(names: DataFrame) -> DataFrame:
    """name -> initials of its words with trailing number: NATION_7 gives N7, MIDDLE EAST gives ME."""
    words = F.split(F.trim(F.regexp_replace("name", r"[_\s]+", " ")), " ")
    short = F.concat_ws("", F.transform(words, lambda w: F.when(w.rlike("^[0-9]+$"), w).otherwise(F.substring(w, 1, 1))))
    return names.filter(F.size(words) > 1).select(short.alias("surface"), F.col("name").alias("canonical"), F.lit("name").alias("target"), F.lit("abbreviation").alias("relation"))


def prefix_rule(names: DataFrame, length: int = 4) -> DataFrame:
    """Names of one word longer than `length` + 2 letters -> their first letters."""
    single = names.filter(F.col("name").rlike(f"^[A-Za-z]{{{length + 3},}}$"))
    return single.select(F.substring("name", 1, length).alias("surface"), F.col("name").alias("canonical"), F.lit("name").alias("target"), F.lit("abbreviation").alias("relation"))


def casefold_rule(names: DataFrame) -> DataFrame:
    return names.select(F.lower("name").alias("surface"), F.col("name").alias("canonical"), F.lit("name").alias("target"), F.lit("synonym").alias("relation"))


def build_library(kg: KG, authored: DataFrame | None = None, rules: tuple[str, ...] = ("initials",), kinds: tuple[str, ...] = ("Nation", "Region")) -> DataFrame:
    """Authored rows and rows that rules derive from the names of some node types; stored once for a graph, as it is made before any query."""
    memo = ("library", rules, kinds) if authored is None else None
    if memo in kg.memo:
        return kg.memo[memo]
    names = kg.nodes.filter(F.arrays_overlap("types", F.array(*[F.lit(k) for k in kinds]))).select("name").distinct()
    out = authored if authored is not None else authored_library(kg.nodes.sparkSession)
    for rule in rules:
        out = out.unionByName({"initials": initials_rule, "prefix": prefix_rule, "casefold": casefold_rule}[rule](names))
    out = out.distinct()
    if memo:
        out = kg.memo[memo] = keep(out, "library")[0]
    return out


def resolve_labels(library: DataFrame, asked: list[tuple[str, str]], relations: tuple[str, ...], memo: dict) -> dict[tuple[str, str], dict[str, str]]:
    """(label, target) -> {normal form: relation} for the labels of a query: a few words each, whatever the size of the library."""
    held = memo.setdefault(("labels", id(library), relations), {"library": library})
    for target in ("type", "name"):
        new = sorted({label for label, t in asked if t == target and (label, t) not in held})
        if new:
            for label in new:
                held[label, target] = {}
            for r in candidate_labels(library, new, target, relations).collect():
                held[r.label, target][r.key] = r.relation
    return {a: held[a] for a in asked}


def candidate_labels(library: DataFrame, labels: list[str], target: str, relations: tuple[str, ...]) -> DataFrame:
    """(label, key, relation): normal forms that a query label may stand for, with the weakest relation used."""
    spark = library.sparkSession
    asked = local(spark, [(x,) for x in labels], "label string").withColumn("key", norm("label"))
    same = asked.select("label", "key", F.lit("identical").alias("relation"))
    rows = library.filter((F.col("target") == target) & F.col("relation").isin([r for r in relations if r != "identical"] or [""]))
    via = rows.select(norm("surface").alias("s"), norm("canonical").alias("key"), "relation")
    out = same.unionByName(F.broadcast(asked.select("label", F.col("key").alias("s"))).join(via, "s").select("label", "key", "relation"))
    if "identical" not in relations:
        out = out.filter("relation != 'identical'")
    strength = F.create_map(*[F.lit(x) for kv in STRENGTH.items() for x in kv])
    return out.groupBy("label", "key").agg(F.min_by("relation", strength[F.col("relation")]).alias("relation"))


def match_nodes(kg: KG, library: DataFrame | None, qnode: QueryNode, relations: tuple[str, ...] = ("identical", "synonym", "abbreviation")) -> DataFrame:
    """(node_id, relation): nodes of the graph that a query node may stand for; never collected.

    One of a node's types must match one of the query's types (all nodes if it has none), and its name the query's name if it
    has one. `relation` is the weakest that was used.
    """
    library = library if library is not None else authored_library(kg.nodes.sparkSession)
    found = kg.nodes.select("node_id", "name", "types").withColumn("strength", F.lit(0))
    strength = F.create_map(*[F.lit(x) for kv in STRENGTH.items() for x in kv])
    if qnode.name is not None:  # names first: the most selective
        names = candidate_labels(library, [qnode.name], "name", relations).select("key", strength[F.col("relation")].alias("by_name"))
        found = found.withColumn("key", norm("name")).join(F.broadcast(names), "key").withColumn("strength", F.greatest("strength", "by_name")).drop("key", "by_name")
    if qnode.types:
        types = candidate_labels(library, list(qnode.types), "type", relations).groupBy("key").agg(F.min(strength[F.col("relation")]).alias("by_type"))
        opened = found.withColumn("key", F.explode("types")).withColumn("key", norm("key"))
        best = opened.join(F.broadcast(types), "key")
        found = best.groupBy("node_id").agg(F.min(F.greatest("strength", "by_type")).alias("strength"))
    back = F.element_at(F.array(*[F.lit(r) for r in sorted(STRENGTH, key=STRENGTH.get)]), F.col("strength") + 1)
    return found.select("node_id", back.alias("relation"))


def infer_types(kg: KG, smoothing: float = 1.0, top: int = 1) -> DataFrame:
    """(node_id, type, log_score, rank) for nodes without a type: naive Bayes on the predicates at a node and their directions."""
    from pyspark.sql import Window

    from ..sources.builders import adjacency

    evidence = adjacency(kg.edges).select(F.col("node").alias("node_id"), F.concat("predicate", F.when(F.col("forward"), ">").otherwise("<")).alias("sign"))
    typed = kg.nodes.filter(F.size("types") > 0).select("node_id", F.explode("types").alias("type"))
    untyped = kg.nodes.filter(F.size("types") <= 0).select("node_id")
    seen = evidence.join(typed, "node_id").groupBy("type", "sign").agg(F.count("*").alias("n"))
    totals = seen.groupBy("type").agg(F.sum("n").alias("total"))
    signs = evidence.select("sign").distinct()
    prior = typed.groupBy("type").agg(F.count("*").alias("members"))
    everyone = prior.agg(F.sum("members").alias("all"))
    n_signs = signs.agg(F.count("*").alias("signs"))
    # vocabulary-sized tables: a row for each type and sign
    table = (
        prior.crossJoin(F.broadcast(signs)).join(seen, ["type", "sign"], "left").join(totals, "type", "left").crossJoin(F.broadcast(n_signs)).crossJoin(F.broadcast(everyone))
        .select("type", "sign", F.log(F.col("members") / F.col("all")).alias("prior"), F.log((F.coalesce("n", F.lit(0)) + smoothing) / (F.coalesce("total", F.lit(0)) + smoothing * F.col("signs"))).alias("ll"))
    )
    counts = evidence.join(untyped, "node_id").groupBy("node_id", "sign").agg(F.count("*").alias("times"))
    scored = counts.join(F.broadcast(table), "sign").groupBy("node_id", "type").agg((F.first("prior") + F.sum(F.col("times") * F.col("ll"))).alias("log_score"))
    order = Window.partitionBy("node_id").orderBy(F.desc("log_score"), "type")
    return scored.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= top)


def with_inferred_types(kg: KG, smoothing: float = 1.0) -> KG:
    found = infer_types(kg, smoothing).select("node_id", "type")
    nodes = kg.nodes.join(found, "node_id", "left").withColumn("types", F.when(F.size("types") > 0, F.col("types")).otherwise(F.array_compact(F.array("type"))))
    return KG(nodes.select("node_id", "name", "types", "attrs"), kg.edges)
