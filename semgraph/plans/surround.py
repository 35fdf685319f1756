"""Relational operators around the graph methods, batch and streaming, with their SQL."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..functions.scores import register_sql
from ..sources import builders as G
from ..sources.tables import load, read_query_graphs, read_triples, register_views, round_trip, scratch, write_triples
from ..streaming import edges as SE

QUERIES: dict = {}
ORACLE_SQL: dict = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql:
            ORACLE_SQL[name] = sql
        return f

    return add


def add_to(queries: dict, oracle: dict) -> None:
    queries.update(QUERIES)
    oracle.update(ORACLE_SQL)


def _r(df: DataFrame, *cols: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 4) for c in cols})


@query("scan_pruned", "SELECT c_custkey, c_acctbal FROM customer WHERE c_acctbal > 5000 AND c_mktsegment IN ('BUILDING', 'MACHINERY')")
def scan_pruned(spark, d):
    return load(spark, d, "customer").filter((F.col("c_acctbal") > 5000) & F.col("c_mktsegment").isin("BUILDING", "MACHINERY")).select("c_custkey", "c_acctbal")


@query("scan_json", "SELECT c_name AS label, CAST(2 AS INTEGER) AS n_nodes, CAST(1 AS INTEGER) AS n_edges, 'placedBy' AS predicate FROM customer")
def scan_json(spark, d):
    """A query graph for each customer, orders that the customer placed, written as JSON lines and read back."""
    path = f"{scratch(spark, 'queries')}/rows"
    node = lambda key, kind, name: F.struct(F.lit(key).alias("key"), F.array(F.lit(kind)).alias("types"), name.cast("string").alias("name"))
    edge = F.struct(F.lit("o").alias("a"), F.lit("c").alias("b"), F.lit("placedBy").alias("predicate"))
    graph = F.struct(F.col("c_name").alias("label"), F.array(node("o", "Order", F.lit(None)), node("c", "Customer", F.col("c_name"))).alias("nodes"), F.array(edge).alias("edges"))
    load(spark, d, "customer").select(F.to_json(graph).alias("value")).write.text(path)
    return read_query_graphs(spark, path).select("label", F.size("nodes").alias("n_nodes"), F.size("edges").alias("n_edges"), F.col("edges")[0]["predicate"].alias("predicate"))


@query("tsv_roundtrip", f"SELECT predicate, count(*) AS n FROM (SELECT 'inRegion' AS predicate FROM nation UNION ALL SELECT 'supplierNation' FROM supplier) GROUP BY 1")
def tsv_roundtrip(spark, d):
    path = scratch(spark, "triples")
    write_triples(G.stored_kg(spark, d, "star").edges.filter(F.col("predicate").isin("inRegion", "supplierNation")), path)
    return read_triples(spark, path).groupBy("predicate").agg(F.count("*").alias("n"))


def _format(kind: str) -> None:
    @query(f"{kind}_roundtrip", "SELECT s_suppkey, s_name, s_nationkey, round(s_acctbal, 2) AS s_acctbal FROM supplier")
    def run(spark, d):
        return round_trip(load(spark, d, "supplier"), kind).withColumn("s_acctbal", F.round("s_acctbal", 2))


for _kind in ("orc", "csv", "json"):
    _format(_kind)


@query("partitioned_adjacency", "SELECT count(*) AS n FROM (SELECT n_nationkey FROM nation UNION ALL SELECT n_nationkey FROM nation)")
def partitioned_adjacency(spark, d):
    from ..sources.tables import write_adjacency

    path = scratch(spark, "adjacency")
    write_adjacency(G.adjacency(G.stored_kg(spark, d, "star").edges.filter(F.col("predicate").isin("inRegion", "supplierNation"))), path)
    return spark.read.parquet(path).filter("predicate = 'inRegion'").agg(F.count("*").alias("n"))


@query("join_outer_lists", "SELECT coalesce(a.c_nationkey, b.s_nationkey) AS nation, coalesce(a.n, 0) AS customers, coalesce(b.n, 0) AS suppliers FROM (SELECT c_nationkey, count(*) AS n FROM customer WHERE c_acctbal > 0 GROUP BY 1) a FULL OUTER JOIN (SELECT s_nationkey, count(*) AS n FROM supplier WHERE s_acctbal > 0 GROUP BY 1) b ON a.c_nationkey = b.s_nationkey")
def join_outer_lists(spark, d):
    a = load(spark, d, "customer").filter("c_acctbal > 0").groupBy(F.col("c_nationkey").alias("nation")).agg(F.count("*").alias("customers"))
    b = load(spark, d, "supplier").filter("s_acctbal > 0").groupBy(F.col("s_nationkey").alias("nation")).agg(F.count("*").alias("suppliers"))
    return a.join(b, "nation", "full_outer").select("nation", F.coalesce("customers", F.lit(0)).alias("customers"), F.coalesce("suppliers", F.lit(0)).alias("suppliers"))


@query("join_semi_anti", "SELECT (SELECT count(*) FROM orders WHERE EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)) AS with_lines, (SELECT count(*) FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)) AS without")
def join_semi_anti(spark, d):
    o, li = load(spark, d, "orders"), load(spark, d, "lineitem")
    cond = o.o_orderkey == li.l_orderkey
    return o.join(li, cond, "left_semi").agg(F.count("*").alias("with_lines")).crossJoin(o.join(li, cond, "left_anti").agg(F.count("*").alias("without")))


@query("join_merge_hint", "SELECT o_orderpriority, count(*) AS n FROM orders JOIN customer ON o_custkey = c_custkey WHERE c_mktsegment = 'BUILDING' GROUP BY 1")
def join_merge_hint(spark, d):
    c = load(spark, d, "customer").filter("c_mktsegment = 'BUILDING'").select("c_custkey").hint("merge")
    return load(spark, d, "orders").join(c, F.col("o_custkey") == F.col("c_custkey")).groupBy("o_orderpriority").agg(F.count("*").alias("n"))


@query("range_price_band", "SELECT b.band, count(*) AS n FROM orders JOIN (VALUES (0, 0.0, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 1000000.0)) b(band, low, high) ON o_totalprice >= low AND o_totalprice < high GROUP BY 1")
def range_price_band(spark, d):
    bands = spark.createDataFrame([(0, 0.0, 50000.0), (1, 50000.0, 150000.0), (2, 150000.0, 1000000.0)], "band int, low double, high double")
    o = load(spark, d, "orders").select("o_totalprice")
    return o.join(F.broadcast(bands), (F.col("o_totalprice") >= F.col("low")) & (F.col("o_totalprice") < F.col("high"))).groupBy("band").agg(F.count("*").alias("n"))


@query("asof_activity", "SELECT p.event_id, c.ts AS last_click FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT user_id, ts FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND p.ts >= c.ts")
def asof_activity(spark, d):
    """Last click at or before each purchase of the user: one sort of the union, no range join."""
    e = load(spark, d, "events").filter(F.col("event_type").isin("purchase", "click"))
    order = Window.partitionBy("user_id").orderBy("ts").rangeBetween(Window.unboundedPreceding, Window.currentRow)
    clicks = F.when(F.col("event_type") == "click", F.col("ts"))
    return e.withColumn("last_click", F.max(clicks).over(order)).filter("event_type = 'purchase'").select("event_id", "last_click")


@query("interval_click_purchase", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY")
def interval_click_purchase(spark, d):
    return SE.two_hop_matches(SE.as_edges(load(spark, d, "events")), within="1 DAY").select("a_id", "b_id")


@query("window_rates_tumbling", "SELECT date_trunc('day', ts) AS day, event_type AS predicate, count(*) AS n, round(sum(value), 4) AS total FROM events GROUP BY 1, 2")
def window_rates_tumbling(spark, d):
    r = SE.window_rates(SE.as_edges(load(spark, d, "events")))
    return _r(r.select(F.col("w.start").cast("timestamp_ntz").alias("day"), "predicate", "n", "total"), "total")


@query("window_rates_sliding", "SELECT date_trunc('hour', ts) - INTERVAL (h) HOUR AS start, event_type AS predicate, count(*) AS n FROM events, (VALUES (0), (1)) t(h) GROUP BY 1, 2")
def window_rates_sliding(spark, d):
    r = SE.window_rates(SE.as_edges(load(spark, d, "events")), "2 hours", "1 hour")
    return r.select(F.col("w.start").cast("timestamp_ntz").alias("start"), "predicate", "n")


@query("session_users", """
WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 1 DAY THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts) AS session FROM g)
SELECT user_id AS src, session_start, n FROM (SELECT user_id, session, min(ts) AS session_start, count(*) AS n FROM s GROUP BY 1, 2)""")
def session_users(spark, d):
    r = SE.session_rates(SE.as_edges(load(spark, d, "events")))
    return r.select("src", F.col("w.start").cast("timestamp_ntz").alias("session_start"), "n")


@query("running_best_quality", "SELECT event_id, max(value) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS best, lag(value) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS before, CAST(sum(1) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS BIGINT) AS depth FROM events")
def running_best_quality(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    rows = w.rowsBetween(Window.unboundedPreceding, 0)
    return load(spark, d, "events").select("event_id", F.max("value").over(rows).alias("best"), F.lag("value").over(w).alias("before"), F.sum(F.lit(1)).over(rows).alias("depth"))


@query("window_ranks", "SELECT s_suppkey, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, CAST(ntile(4) OVER (ORDER BY s_acctbal, s_suppkey) AS INTEGER) AS quarter, round(percent_rank() OVER (ORDER BY s_acctbal), 4) AS pr FROM supplier WINDOW w AS (PARTITION BY s_nationkey ORDER BY floor(s_acctbal / 1000))")
def window_ranks(spark, d):
    w = Window.partitionBy("s_nationkey").orderBy(F.floor(F.col("s_acctbal") / 1000))
    return _r(load(spark, d, "supplier").select("s_suppkey", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.ntile(4).over(Window.orderBy("s_acctbal", "s_suppkey")).alias("quarter"), F.percent_rank().over(Window.orderBy("s_acctbal")).alias("pr")), "pr")


@query("setops_answers", "SELECT 'both' AS kind, count(*) AS n FROM (SELECT c_nationkey FROM customer INTERSECT SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000) UNION ALL SELECT 'either', count(*) FROM (SELECT c_nationkey FROM customer UNION SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000) UNION ALL SELECT 'less', count(*) FROM (SELECT c_nationkey FROM customer EXCEPT SELECT s_nationkey FROM supplier WHERE s_acctbal > 5000)")
def setops_answers(spark, d):
    a, b = load(spark, d, "customer").select(F.col("c_nationkey").alias("k")), load(spark, d, "supplier").filter("s_acctbal > 5000").select(F.col("s_nationkey").alias("k"))
    count = lambda df, kind: df.agg(F.lit(kind).alias("kind"), F.count("*").alias("n"))
    return count(a.intersect(b), "both").unionByName(count(a.union(b).distinct(), "either")).unionByName(count(a.subtract(b), "less"))


@query("props_json", "SELECT CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, count(*) AS n FROM events GROUP BY 1")
def props_json(spark, d):
    parsed = F.from_json("props", "k long")
    return load(spark, d, "events").groupBy(parsed["k"].alias("k")).agg(F.count("*").alias("n"))


@query("href_edges", """SELECT page_id, href FROM (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href="([^"]+)"', 1)) AS href FROM pages)""")
def href_edges(spark, d):
    return G.hrefs(spark, d)


@query("quotes_edges", "SELECT doc_id, item_id FROM documents d JOIN benchmark b ON contains(d.text, b.text)")
def quotes_edges(spark, d):
    return G.quotes(spark, d)


@query("agg_pivot", "SELECT o_orderpriority, count(*) FILTER (o_orderstatus = 'F') AS f, count(*) FILTER (o_orderstatus = 'O') AS o FROM orders GROUP BY 1")
def agg_pivot(spark, d):
    t = load(spark, d, "orders").groupBy("o_orderpriority").pivot("o_orderstatus", ["F", "O"]).count()
    return t.select("o_orderpriority", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))


@query("agg_unpivot", "SELECT r_regionkey, 'name' AS field, r_name AS value FROM region UNION ALL SELECT r_regionkey, 'key', CAST(r_regionkey AS VARCHAR) FROM region")
def agg_unpivot(spark, d):
    t = load(spark, d, "region").select("r_regionkey", F.col("r_name").alias("name"), F.col("r_regionkey").cast("string").alias("key"))
    return t.unpivot("r_regionkey", ["name", "key"], "field", "value")


@query("agg_moments", "SELECT l_returnflag, round(corr(l_quantity, l_extendedprice), 4) AS r, round(stddev_samp(l_discount), 4) AS sd, round(quantile_cont(l_quantity, 0.5), 4) AS median, count(DISTINCT l_suppkey) AS suppliers FROM lineitem GROUP BY 1")
def agg_moments(spark, d):
    t = load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.corr("l_quantity", "l_extendedprice").alias("r"), F.stddev_samp("l_discount").alias("sd"), F.percentile("l_quantity", 0.5).alias("median"), F.countDistinct("l_suppkey").alias("suppliers"))
    return _r(t, "r", "sd", "median")


@query("agg_max_by", "SELECT c_nationkey, max_by(c_name, c_acctbal) AS richest, min_by(c_name, c_acctbal) AS poorest FROM customer GROUP BY 1")
def agg_max_by(spark, d):
    """Of equal balances the first customer by key counts, and rows without a name or balance do not, as in SQL over a table in order of its key."""
    known = F.col("c_name").isNotNull() & F.col("c_acctbal").isNotNull()
    most, least = (F.when(known, F.struct("c_acctbal", key)) for key in (-F.col("c_custkey"), F.col("c_custkey")))
    return load(spark, d, "customer").groupBy("c_nationkey").agg(F.max_by("c_name", most).alias("richest"), F.min_by("c_name", least).alias("poorest"))


@query("agg_grouping_sets", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")
def agg_grouping_sets(spark, d):
    register_views(spark, d, ("customer",))
    return spark.sql("SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY GROUPING SETS ((c_mktsegment), (c_nationkey), ())")


@query("approx_types")
def approx_types(spark, d):
    return G.stored_kg(spark, d, "star").nodes.select(F.explode("types").alias("t")).agg(F.approx_count_distinct("t").alias("types"))


@query("subquery_correlated", "SELECT s_suppkey FROM supplier s WHERE s_acctbal > (SELECT avg(s_acctbal) FROM supplier t WHERE t.s_nationkey = s.s_nationkey)")
def subquery_correlated(spark, d):
    register_views(spark, d, ("supplier",))
    return spark.sql("SELECT s_suppkey FROM supplier s WHERE s_acctbal > (SELECT avg(s_acctbal) FROM supplier t WHERE t.s_nationkey = s.s_nationkey)")


@query("recursive_paths", "WITH RECURSIVE f AS (SELECT avg(1 - l_discount) AS w FROM lineitem), p(n, x) AS (SELECT 1, CAST(1 AS DOUBLE) UNION ALL SELECT n + 1, x * w FROM p, f WHERE n < 6) SELECT n, round(x, 4) AS x FROM p")
def recursive_paths(spark, d):
    """The score of paths of one to six edges that all weigh what is left of a price on average."""
    register_views(spark, d, ("lineitem",))
    return spark.sql("WITH RECURSIVE f AS (SELECT avg(1 - l_discount) AS w FROM lineitem), p(n, x) AS (SELECT 1, 1.0D UNION ALL SELECT n + 1, x * w FROM p, f WHERE n < 6) SELECT n, round(x, 4) AS x FROM p")


@query("string_functions", "SELECT n_nationkey, lower(n_name) AS low, CAST(levenshtein(n_name, 'NATION_7') AS INTEGER) AS d, split_part(n_name, '_', 2) AS number, regexp_extract(n_name, '([0-9]+)', 1) AS digits, substring(n_name, 1, 3) AS head FROM nation")
def string_functions(spark, d):
    return load(spark, d, "nation").select("n_nationkey", F.lower("n_name").alias("low"), F.levenshtein("n_name", F.lit("NATION_7")).alias("d"), F.split_part("n_name", F.lit("_"), F.lit(2)).alias("number"), F.regexp_extract("n_name", "([0-9]+)", 1).alias("digits"), F.substring("n_name", 1, 3).alias("head"))


@query("date_functions", "SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(month(o_orderdate) AS INTEGER) AS m, count(*) AS n, CAST(max(date_diff('day', DATE '1995-01-01', CAST(o_orderdate AS DATE))) AS INTEGER) AS last_day FROM orders GROUP BY 1, 2")
def date_functions(spark, d):
    o = load(spark, d, "orders")
    return o.groupBy(F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count("*").alias("n"), F.max(F.datediff("o_orderdate", F.lit("1995-01-01").cast("date"))).alias("last_day"))


@query("math_functions", "SELECT p_partkey, round(pow(p_size, 0.5), 4) AS root, round(ln(p_size), 4) AS l, round(exp(ln(p_size)), 4) AS e, greatest(p_size, 25) AS g, least(p_size, 25) AS s FROM part")
def math_functions(spark, d):
    p = F.col("p_size")
    return _r(load(spark, d, "part").select("p_partkey", F.pow(p, 0.5).alias("root"), F.log(p).alias("l"), F.exp(F.log(p)).alias("e"), F.greatest(p, F.lit(25)).alias("g"), F.least(p, F.lit(25)).alias("s")), "root", "l", "e")


@query("array_functions", "SELECT vec_id, round(CAST(list_max(embedding) AS DOUBLE), 4) AS top, len(list_filter(embedding, lambda x: x > 0)) AS positive, round(list_sum(list_transform(embedding[1:3], lambda x: CAST(x AS DOUBLE) * 2)), 4) AS head FROM embeddings")
def array_functions(spark, d):
    e = F.transform("embedding", lambda x: x.cast("double"))
    t = load(spark, d, "embeddings").select("vec_id", F.array_max(e).alias("top"), F.size(F.filter(e, lambda x: x > 0)).cast("long").alias("positive"), F.aggregate(F.slice(e, 1, 3), F.lit(0.0), lambda s, x: s + x * 2).alias("head"))
    return _r(t, "top", "head")


@query("map_functions", "SELECT 3 * 1000000000000 + c_custkey AS node_id, round(c_acctbal, 2) AS acctbal FROM customer WHERE c_acctbal > 9000")
def map_functions(spark, d):
    n = G.stored_kg(spark, d, "star").nodes.filter(F.array_contains("types", "Customer"))
    value = F.round(F.element_at("attrs", "acctbal").cast("double"), 2)
    return n.select("node_id", value.alias("acctbal"), F.size(F.map_keys("attrs")).alias("k")).filter("acctbal > 9000 AND k = 1").select("node_id", "acctbal")


@query("url_functions", "SELECT regexp_extract(url, '://([^/?#]+)', 1) AS host, count(*) AS n FROM pages GROUP BY 1")
def url_functions(spark, d):
    return load(spark, d, "pages").groupBy(F.expr("parse_url(url, 'HOST')").alias("host")).agg(F.count("*").alias("n"))


@query("hash_sample", "SELECT o_orderkey FROM orders WHERE (o_orderkey * 2654435761) % 1000 < 50")
def hash_sample(spark, d):
    """A repeatable sample by arithmetic on the key."""
    return load(spark, d, "orders").filter((F.col("o_orderkey") * 2654435761) % 1000 < 50).select("o_orderkey")


@query("stratified_sample")
def stratified_sample(spark, d):
    return load(spark, d, "orders").sampleBy("o_orderpriority", {"1-URGENT": 0.5, "5-LOW": 0.1}, seed=7).groupBy("o_orderpriority").count()


@query("sql_functions", """
WITH e AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(x AS DOUBLE)) AS v FROM embeddings), s AS (SELECT vec_id, abs(v[1]) AS w, abs(v[2]) AS m, v[1:32] AS a, v[33:64] AS b FROM e)
SELECT vec_id, round(power(w, 1.0 / 2), 6) AS psi, round(power(w * m, 1.0 / 4), 6) AS hat,
    round(list_sum(list_transform(list_zip(a, b), lambda p: p[1] * p[2])) / (sqrt(list_sum(list_transform(a, lambda x: x * x))) * sqrt(list_sum(list_transform(b, lambda x: x * x)))), 6) AS cosine FROM s""")
def sql_functions(spark, d):
    """The registered functions on every embedding: two components as weights, its halves as vectors."""
    register_sql(spark)
    register_views(spark, d, ("embeddings",))
    parts = "SELECT vec_id, abs(v[0]) AS w, abs(v[1]) AS m, slice(v, 1, 32) AS a, slice(v, 33, 32) AS b FROM (SELECT vec_id, CAST(embedding AS ARRAY<DOUBLE>) AS v FROM embeddings)"
    return spark.sql(f"SELECT vec_id, round(psi(w, 2), 6) AS psi, round(psi_hat(w, m, 4), 6) AS hat, round(cosine_sim(a, b), 6) AS cosine FROM ({parts})")


@query("udtf_split_path", """
WITH paths AS (SELECT c_custkey, 'Order-placedBy-' || c_mktsegment || '-customerNation-NATION_' || c_nationkey AS path FROM customer), parts AS (SELECT c_custkey, string_split(path, '-') AS p FROM paths)
SELECT c_custkey, CAST(i AS INTEGER) AS step, p[2 * i - 1] AS source_type, p[2 * i] AS predicate, p[2 * i + 1] AS target_type FROM parts, (VALUES (1), (2)) t(i)""")
def udtf_split_path(spark, d):
    """The steps of each customer's path from an order to the nation."""
    register_sql(spark)
    register_views(spark, d, ("customer",))
    return spark.sql("SELECT c_custkey, s.* FROM customer, LATERAL split_path(concat('Order-placedBy-', c_mktsegment, '-customerNation-NATION_', c_nationkey)) s")


@query("udaf_geo_mean", "SELECT l_returnflag, round(exp(avg(ln(l_quantity))), 4) AS g FROM lineitem GROUP BY 1")
def udaf_geo_mean(spark, d):
    return _r(load(spark, d, "lineitem").groupBy("l_returnflag").agg(F.exp(F.avg(F.log("l_quantity"))).alias("g")), "g")


# ---- streaming: results over all that is there equal those of the batch ----


def _stream(spark, d):
    """The events file of the folder of tables, as a stream."""
    return SE.stream_edges(spark, d, watermark="3650 days", name="events.parquet")


def _fresh(name: str) -> str:
    return f"{name}_{uuid.uuid4().hex[:12]}"


@query("stream_counts", "SELECT event_type AS predicate, count(*) AS n FROM events GROUP BY 1")
def stream_counts(spark, d):
    return SE.drain(_stream(spark, d).groupBy("predicate").agg(F.count("*").alias("n")), _fresh("counts"), "complete")


@query("stream_window_rates", "SELECT date_trunc('day', ts) AS day, event_type AS predicate, count(*) AS n FROM events GROUP BY 1, 2")
def stream_window_rates(spark, d):
    r = SE.drain(SE.window_rates(_stream(spark, d)), _fresh("rates"), "complete")
    return r.select(F.col("w.start").cast("timestamp_ntz").alias("day"), "predicate", "n")


@query("stream_distinct_edges", "SELECT count(*) AS n FROM (SELECT DISTINCT user_id, event_type, json_extract_string(props, '$.k') FROM events)")
def stream_distinct_edges(spark, d):
    return SE.drain(SE.distinct_edges(_stream(spark, d)), _fresh("edges")).agg(F.count("*").alias("n"))


@query("stream_interval_join", "SELECT a.event_id AS a_id, b.event_id AS b_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY")
def stream_interval_join(spark, d):
    return SE.drain(SE.two_hop_matches(_stream(spark, d), within="1 DAY").select("a_id", "b_id"), _fresh("pairs"))


@query("stream_topk")
def stream_topk(spark, d):
    from ..operators import predicate_space as P

    w = spark.createDataFrame(list(P.weights_for("purchase", {p: [float(x) for x in v] for p, v in P.AUTHORED.items()}).items()), "predicate string, w double")
    return SE.drain(SE.streaming_topk(SE.weighed(_stream(spark, d), w)), _fresh("top"), "update")

