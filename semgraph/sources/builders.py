"""Knowledge graphs over the given tables. Ids are kind * 10^12 + key, computable in any SQL."""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model import KG, KG_EDGES, KG_NODES
from .index import both_ways, read_index, write_index
from .tables import cut, load, scratch

KINDS = {
    "region": 1, "nation": 2, "customer": 3, "supplier": 4, "part": 5, "order": 6, "brand": 7, "topic": 8, "document": 9, "source": 10, "language": 11, "page": 12,
    "host": 13, "path": 14, "item": 15, "conversation": 16, "turn": 17, "role": 18, "vector": 19,
}
BASE = 10**12
#: Vocabularies up to this size get their numbers from one window; larger ones from ranges and offsets.
SMALL_VOCABULARY = 100_000
#: Vectors of a block at most; a task holds two blocks.
MOST_BLOCK = 16_384


def node_id(kind: str, key: Column | str) -> Column:
    return (F.lit(KINDS[kind] * BASE) + (F.col(key) if isinstance(key, str) else key)).cast("long")


def _nodes(df: DataFrame, kind: str, key: Column | str, name: Column, types: list[Column], attrs: dict[str, str] | None = None) -> DataFrame:
    values = [x for k, c in (attrs or {}).items() for x in (F.lit(k), F.col(c).cast("string"))]
    return df.select(
        node_id(kind, key).alias("node_id"), name.cast("string").alias("name"), F.array(*types).alias("types"),
        (F.create_map(*values) if values else F.lit(None)).cast("map<string,string>").alias("attrs"),
    )


def _edges(df: DataFrame, src: Column, predicate: str | Column, dst: Column) -> DataFrame:
    p = F.lit(predicate) if isinstance(predicate, str) else predicate
    return df.select(src.alias("src"), p.alias("predicate"), dst.alias("dst"))


def _all(frames: list[DataFrame]) -> DataFrame:
    out = frames[0]
    for f in frames[1:]:
        out = out.unionByName(f)
    return out


def vocabulary(df: DataFrame, column: str) -> DataFrame:
    """(value, key): distinct values numbered from 1 in order."""
    values = df.select(F.col(column).alias("value")).filter("value is not null").distinct()
    n = values.count()
    if n <= SMALL_VOCABULARY:
        return values.withColumn("key", F.row_number().over(Window.orderBy("value")).cast("long"))
    parts = max(2, n // SMALL_VOCABULARY)
    dealt = cut(values.repartitionByRange(parts, "value").withColumn("pid", F.spark_partition_id()))
    own = dealt.withColumn("own", F.row_number().over(Window.partitionBy("pid").orderBy("value")))
    sizes = own.groupBy("pid").agg(F.count("*").alias("n"))
    offset = sizes.select("pid", (F.sum("n").over(Window.orderBy("pid")) - F.col("n")).alias("first"))
    return own.join(F.broadcast(offset), "pid").select("value", (F.col("first") + F.col("own")).cast("long").alias("key"))


def star_kg(spark: SparkSession, sf_dir: str, heterogeneous: bool = True) -> KG:
    """Orders, customers, suppliers, parts. Heterogeneous: a quarter of the orders have only a direct edge to a nation, the rest only their customer."""
    t = {n: load(spark, sf_dir, n) for n in ("region", "nation", "customer", "supplier", "part", "orders", "lineitem")}
    brand = vocabulary(t["part"], "p_brand")
    nodes = [
        _nodes(t["region"], "region", "r_regionkey", F.col("r_name"), [F.lit("Region")]),
        _nodes(t["nation"], "nation", "n_nationkey", F.col("n_name"), [F.lit("Nation")]),
        _nodes(t["customer"], "customer", "c_custkey", F.col("c_name"), [F.lit("Customer"), F.col("c_mktsegment")], {"acctbal": "c_acctbal"}),
        _nodes(t["supplier"], "supplier", "s_suppkey", F.col("s_name"), [F.lit("Supplier")], {"acctbal": "s_acctbal"}),
        _nodes(t["part"], "part", "p_partkey", F.concat(F.lit("Part#"), F.col("p_partkey").cast("string")), [F.lit("Part"), F.col("p_type")], {"retailprice": "p_retailprice"}),
        _nodes(t["orders"], "order", "o_orderkey", F.concat(F.lit("Order#"), F.col("o_orderkey").cast("string")), [F.lit("Order"), F.col("o_orderpriority")], {"totalprice": "o_totalprice"}),
        _nodes(brand, "brand", "key", F.col("value"), [F.lit("Brand")]),
    ]
    orders = t["orders"]
    placed = node_id("order", "o_orderkey")
    direct, via = (orders.filter("o_orderkey % 4 = 0"), orders.filter("o_orderkey % 4 != 0")) if heterogeneous else (orders, orders)
    nation_of = t["customer"].select(F.col("c_custkey").alias("o_custkey"), "c_nationkey")
    line = t["lineitem"]
    edges = [
        _edges(t["nation"], node_id("nation", "n_nationkey"), "inRegion", node_id("region", "n_regionkey")),
        _edges(t["customer"], node_id("customer", "c_custkey"), "customerNation", node_id("nation", "c_nationkey")),
        _edges(t["supplier"], node_id("supplier", "s_suppkey"), "supplierNation", node_id("nation", "s_nationkey")),
        _edges(via, placed, "placedBy", node_id("customer", "o_custkey")),
        _edges(direct.join(nation_of, "o_custkey"), placed, "originNation", node_id("nation", "c_nationkey")),
        _edges(line, node_id("order", "l_orderkey"), "containsPart", node_id("part", "l_partkey")),
        _edges(line, node_id("order", "l_orderkey"), "fulfilledBy", node_id("supplier", "l_suppkey")),
        _edges(line, node_id("part", "l_partkey"), "suppliedBy", node_id("supplier", "l_suppkey")),
        _edges(t["part"].join(brand, F.col("p_brand") == F.col("value")), node_id("part", "p_partkey"), "hasBrand", node_id("brand", "key")),
    ]
    return KG(_all(nodes), _all(edges).distinct())


def activity_kg(spark: SparkSession, sf_dir: str) -> KG:
    """Users (customers) and topics; predicates are the event types. Repeated events are one edge."""
    events = load(spark, sf_dir, "events").withColumn("topic", F.get_json_object("props", "$.k").cast("long"))
    customer = load(spark, sf_dir, "customer")
    users = events.select(F.col("user_id").alias("c_custkey")).distinct()
    nodes = [
        _nodes(customer.join(users, "c_custkey", "left_semi"), "customer", "c_custkey", F.col("c_name"), [F.lit("Customer"), F.col("c_mktsegment")]),
        _nodes(events.select("topic").filter("topic is not null").distinct(), "topic", "topic", F.concat(F.lit("Topic#"), F.col("topic").cast("string")), [F.lit("Topic")]),
    ]
    edges = _edges(events.filter("topic is not null"), node_id("customer", "user_id"), F.col("event_type"), node_id("topic", "topic"))
    return KG(_all(nodes), edges.distinct())


def quotes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(doc_id, item_id): documents whose text contains that of a benchmark item.

    Items meet documents by the item's first five words: a document's runs of five words join these keys, then the
    whole text is verified.
    """
    words = lambda c: F.split(c, r"\s+")
    docs = load(spark, sf_dir, "documents").select("doc_id", "text").filter("text is not null")
    items = load(spark, sf_dir, "benchmark").select("item_id", F.col("text").alias("passage")).filter("passage is not null")
    keyed = items.withColumn("w", words(F.trim("passage"))).filter(F.size("w") > 6).withColumn("key", F.xxhash64(F.array_join(F.slice("w", 2, 5), " ")))
    runs = docs.withColumn("w", words("text")).filter(F.size("w") >= 5)
    grams = runs.select("doc_id", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.size("w") - 4), lambda i: F.xxhash64(F.array_join(F.slice("w", i, 5), " "))))).alias("key"))
    found = grams.join(keyed.select("item_id", "key", "passage"), "key").select("doc_id", "item_id", "passage").distinct()
    return found.join(docs, "doc_id").filter(F.expr("instr(text, passage) > 0")).select("doc_id", "item_id")


def hrefs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(page_id, href): distinct link targets of each page."""
    pages = load(spark, sf_dir, "pages")
    return pages.select("page_id", F.explode(F.expr("regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)")).alias("href")).distinct()


def content_kg(spark: SparkSession, sf_dir: str) -> KG:
    docs, pages = load(spark, sf_dir, "documents"), load(spark, sf_dir, "pages")
    labels = load(spark, sf_dir, "labels")
    source, language = vocabulary(docs, "source"), vocabulary(docs, "lang")
    hosted = pages.select("page_id", F.expr("parse_url(url, 'HOST')").alias("host"))
    links = hrefs(spark, sf_dir)
    host, path = vocabulary(hosted, "host"), vocabulary(links, "href")
    labelled = docs.select("doc_id").join(labels.select("doc_id", "quality", "toxic"), "doc_id", "left")
    types = F.array_compact(F.array(F.lit("Document"), F.when(F.col("quality") == 1, "HighQuality"), F.when(F.col("toxic") == 1, "Toxic")))
    documents = labelled.select(node_id("document", "doc_id").alias("node_id"), F.concat(F.lit("Document#"), F.col("doc_id").cast("string")).alias("name"), types.alias("types"), F.lit(None).cast("map<string,string>").alias("attrs"))
    items = load(spark, sf_dir, "benchmark")
    nodes = [
        documents,
        _nodes(source, "source", "key", F.col("value"), [F.lit("Source")]),
        _nodes(language, "language", "key", F.col("value"), [F.lit("Language")]),
        _nodes(pages, "page", "page_id", F.col("url"), [F.lit("Page")]),
        _nodes(host, "host", "key", F.col("value"), [F.lit("Host")]),
        _nodes(path, "path", "key", F.col("value"), [F.lit("Path")]),
        _nodes(items, "item", "item_id", F.concat(F.lit("Item#"), F.col("item_id").cast("string")), [F.lit("Item")]),
    ]
    edges = [
        _edges(docs.join(source, docs.source == source.value), node_id("document", "doc_id"), "fromSource", node_id("source", "key")),
        _edges(docs.join(language, docs.lang == language.value), node_id("document", "doc_id"), "writtenIn", node_id("language", "key")),
        _edges(hosted.join(host, hosted.host == host.value), node_id("page", "page_id"), "onHost", node_id("host", "key")),
        _edges(links.join(path, links.href == path.value), node_id("page", "page_id"), "linksTo", node_id("path", "key")),
        _edges(quotes(spark, sf_dir), node_id("document", "doc_id"), "quotes", node_id("item", "item_id")),
    ]
    return KG(_all(nodes), _all(edges).distinct())


def dialog_kg(spark: SparkSession, sf_dir: str) -> KG:
    """Conversations, turns (conversation * 1000 + turn), roles; turns follow each other."""
    rows = load(spark, sf_dir, "conversations").withColumn("key", F.col("conv_id") * 1000 + F.col("turn"))
    role = vocabulary(rows, "role")
    named = lambda kind, c: F.concat(F.lit(f"{kind}#"), F.col(c).cast("string"))
    nodes = [
        _nodes(rows.select("conv_id").distinct(), "conversation", "conv_id", named("Conversation", "conv_id"), [F.lit("Conversation")]),
        _nodes(rows, "turn", "key", named("Turn", "key"), [F.lit("Turn")]),
        _nodes(role, "role", "key", F.col("value"), [F.lit("Role")]),
    ]
    edges = [
        _edges(rows, node_id("turn", "key"), "partOf", node_id("conversation", "conv_id")),
        _edges(rows.join(role.withColumnRenamed("key", "role_key"), F.col("role") == F.col("value")), node_id("turn", "key"), "spokenBy", node_id("role", "role_key")),
        _edges(rows.alias("a").join(rows.select(F.col("conv_id").alias("c"), (F.col("turn") - 1).alias("t"), F.col("key").alias("next")).alias("b"), F.expr("a.conv_id = b.c AND a.turn = b.t")), node_id("turn", "next"), "follows", node_id("turn", "key")),
    ]
    return KG(_all(nodes), _all(edges).distinct())


def vector_kg(spark: SparkSession, sf_dir: str, at_least: float = 0.35) -> KG:
    """Items whose embeddings have inner product `at_least`: a structural stress graph over a bounded table.

    Every two blocks of items meet in one group, as matrices. An item goes to as many groups as there are blocks, and a group holds two
    blocks, whatever the number of items. Null components count as zero, as in SQL sums.
    """
    e = load(spark, sf_dir, "embeddings").select("vec_id", "embedding", "label")
    nodes = _nodes(e, "vector", "vec_id", F.concat(F.lit("Vector#"), F.col("vec_id").cast("string")), [F.lit("Vector"), F.concat(F.lit("class_"), F.col("label").cast("string"))])
    v = e.select("vec_id", "embedding").filter("vec_id IS NOT NULL AND embedding IS NOT NULL")
    parts = max(math.ceil(math.sqrt(8 * spark.sparkContext.defaultParallelism)), math.ceil(v.count() / MOST_BLOCK))
    dealt = v.withColumn("own", F.expr(f"CAST(pmod(xxhash64(vec_id), {parts}) AS INT)")).withColumn("other", F.expr(f"explode(sequence(0, {parts} - 1))"))
    dealt = dealt.select(F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "vec_id", "embedding")
    pairs = dealt.groupBy("i", "j").applyInArrow(_near_pairs(at_least), "a long, b long")
    return KG(nodes, pairs.select(node_id("vector", "a").alias("src"), F.lit("near").alias("predicate"), node_id("vector", "b").alias("dst")))


def _near_pairs(at_least: float):
    """Table function (i, j, own, vec_id, embedding) -> (a, b): pairs of two blocks (or within one), a < b."""

    def run(group):
        import numpy as np
        import pyarrow as pa
        import pyarrow.compute as pc

        lists = group.column("embedding").combine_chunks()
        lists = lists.chunk(0) if isinstance(lists, pa.ChunkedArray) else lists
        sizes = pc.list_value_length(lists).to_numpy(zero_copy_only=False).astype(np.int64)
        flat = pc.fill_null(lists.flatten().cast(pa.float64()), 0.0).to_numpy(zero_copy_only=False)
        x = np.zeros((len(sizes), int(sizes.max(initial=0))))
        x[np.repeat(np.arange(len(sizes)), sizes), np.arange(len(flat)) - np.repeat(np.cumsum(sizes) - sizes, sizes)] = flat
        ids, own = group.column("vec_id").to_numpy(), group.column("own").to_numpy()
        i, j = group.column("i")[0].as_py(), group.column("j")[0].as_py()
        left, right = np.flatnonzero(own == i), np.flatnonzero(own == j)
        found = []
        with np.errstate(invalid="ignore", over="ignore"):
            for at in range(0, len(left), 512):
                rows = left[at : at + 512]
                dots = x[rows] @ x[right].T
                p, q = np.nonzero(~(dots < at_least - 1e-9))  # what is no number is greatest, as in SQL
                near = dots[p, q] < at_least + 1e-9
                p, q = rows[p], right[q]
                ok = np.ones(len(p), bool)
                ok[near] = ~(np.cumsum(x[p[near]] * x[q[near]], axis=1)[:, -1] < at_least)  # in the order of the components
                a, b = ids[p[ok]], ids[q[ok]]
                keep = a < b if i == j else a != b
                found.append((np.minimum(a, b)[keep], np.maximum(a, b)[keep]))
        a, b = (np.concatenate([f[n] for f in found]) if found else np.zeros(0, np.int64) for n in (0, 1))
        return pa.table({"a": pa.array(a, pa.int64()), "b": pa.array(b, pa.int64())})

    return run


BUILDERS = {"star": star_kg, "activity": activity_kg, "content": content_kg, "dialog": dialog_kg, "vector": vector_kg}


def build_kg(spark: SparkSession, sf_dir: str, kind: str, **options) -> KG:
    return BUILDERS[kind](spark, sf_dir, **options)


_stored: dict[tuple, str] = {}
_opened: dict[tuple, KG] = {}


def stored_kg(spark: SparkSession, sf_dir: str, kind: str, **options) -> KG:
    """The graph and its search index as tables in the session's shared folder: built once for an application, read by every query on it."""
    key = (spark.sparkContext.applicationId, sf_dir, kind, tuple(sorted(options.items())))
    kg = _opened.get(key)
    if kg is not None and kg.nodes.sparkSession is spark:
        return kg
    path = _stored.get(key)
    if path is None:
        built = build_kg(spark, sf_dir, kind, **options)
        path = scratch(spark, f"kg-{kind}")
        built.nodes.write.parquet(f"{path}/nodes")
        built.edges.write.parquet(f"{path}/edges")
    kg = KG(spark.read.schema(KG_NODES).parquet(f"{path}/nodes"), spark.read.schema(KG_EDGES).parquet(f"{path}/edges"))
    if key not in _stored:
        write_index(kg, path)
        _stored[key] = path
    kg.memo["index"] = read_index(spark, path)
    _opened[key] = kg
    return kg


def adjacency(edges: DataFrame) -> DataFrame:
    return both_ways(edges)


def restrict_entities(kg: KG, names: DataFrame) -> KG:
    """Only entities whose name is in `names(name)`, and edges between them."""
    nodes = kg.nodes.join(names.select("name"), "name", "left_semi").select(kg.nodes.columns)
    return KG(nodes, _between(kg.edges, nodes))


def core_portion(kg: KG, drop_kinds: list[str]) -> KG:
    """The graph without nodes of some kinds."""
    nodes = kg.nodes.filter(~F.expr(f"node_id div {BASE}").isin([KINDS[k] for k in drop_kinds]))
    return KG(nodes, _between(kg.edges, nodes))


def induced_subgraph(kg: KG, percent: int) -> KG:
    """Nodes whose id is below `percent` mod 100, and edges between them."""
    keep = lambda c: F.col(c) % 100 < percent
    return KG(kg.nodes.filter(keep("node_id")), kg.edges.filter(keep("src") & keep("dst")))


def _between(edges: DataFrame, nodes: DataFrame) -> DataFrame:
    ids = nodes.select("node_id")
    half = edges.join(ids, edges.src == ids.node_id, "left_semi")
    return half.join(ids, half.dst == ids.node_id, "left_semi")
