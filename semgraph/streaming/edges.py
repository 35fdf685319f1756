"""Events as a stream of edges: windows, late data, duplicates, joins, and the best paths so far by user."""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..sources.tables import scratch

EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def stream_edges(spark: SparkSession, folder: str, watermark: str = "1 hour", files_a_trigger: int | None = None, name: str | None = None) -> DataFrame:
    """(event_id, ts, src, predicate, dst, value): events from a folder of Parquet files, with a watermark."""
    reader = spark.readStream.schema(EVENTS)
    if files_a_trigger:
        reader = reader.option("maxFilesPerTrigger", files_a_trigger)
    if name:
        reader = reader.option("pathGlobFilter", name)
    return as_edges(reader.parquet(folder)).withWatermark("ts", watermark)


def as_edges(events: DataFrame) -> DataFrame:
    return events.select(
        "event_id", F.col("ts").cast("timestamp").alias("ts"), F.col("user_id").alias("src"), F.col("event_type").alias("predicate"),
        F.get_json_object("props", "$.k").cast("long").alias("dst"), "value",
    )


def window_rates(edges: DataFrame, size: str = "1 day", slide: str | None = None) -> DataFrame:
    w = F.window("ts", size, slide) if slide else F.window("ts", size)
    return edges.groupBy(w.alias("w"), "predicate").agg(F.count("*").alias("n"), F.sum("value").alias("total"))


def session_rates(edges: DataFrame, gap: str = "1 day") -> DataFrame:
    return edges.groupBy(F.session_window("ts", gap).alias("w"), "src").agg(F.count("*").alias("n"))


def distinct_edges(edges: DataFrame) -> DataFrame:
    """Triples without repeats inside the watermark."""
    return edges.dropDuplicatesWithinWatermark(["src", "predicate", "dst"])


def weighed(edges: DataFrame, weights: DataFrame) -> DataFrame:
    """Stream-static join with (predicate, w)."""
    return edges.join(F.broadcast(weights), "predicate")  # a vocabulary


def two_hop_matches(edges: DataFrame, first: str = "click", second: str = "purchase", within: str = "1 hour") -> DataFrame:
    """Stream-stream interval join: a user's `second` on a topic within a time of the `first`."""
    a = edges.filter(F.col("predicate") == first).select(F.col("src").alias("a_src"), F.col("dst").alias("a_dst"), F.col("ts").alias("a_ts"), F.col("event_id").alias("a_id"))
    b = edges.filter(F.col("predicate") == second).select(F.col("src").alias("b_src"), F.col("dst").alias("b_dst"), F.col("ts").alias("b_ts"), F.col("event_id").alias("b_id"))
    return a.join(b, F.expr(f"a_src = b_src AND b_ts >= a_ts AND b_ts <= a_ts + INTERVAL {within}"))


def streaming_topk(edges: DataFrame, k: int = 3) -> DataFrame:
    """(src, rank, dst, w, state_rows): the best k weighed edges of each user so far; state holds k rows a user."""
    out = T.StructType([T.StructField("src", T.LongType()), T.StructField("rank", T.IntegerType()), T.StructField("dst", T.LongType()), T.StructField("w", T.DoubleType())])
    state = T.StructType([T.StructField("best", T.StringType())])

    def run(key, batches: Iterator, group_state) -> Iterator:
        import pandas as pd

        best = {int(d): w for d, w in json.loads(group_state.get[0])} if group_state.exists else {}
        for b in batches:
            for d, w in zip(b.dst, b.w):
                if not pd.isna(d):
                    best[int(d)] = max(best.get(int(d), 0.0), float(w))
        top = sorted(best.items(), key=lambda x: (-x[1], x[0]))[:k]
        group_state.update((json.dumps(top),))
        yield pd.DataFrame([(int(key[0]), i + 1, d, w) for i, (d, w) in enumerate(top)], columns=["src", "rank", "dst", "w"])

    return edges.groupBy("src").applyInPandasWithState(run, out, state, "update", "NoTimeout")


def drain(stream: DataFrame, name: str, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there, and give its rows as a table.

    Rows that are appended go to files in the shared folder: there may be as many as events. Other modes end in a table in memory.
    """
    spark = stream.sparkSession
    if mode == "append":
        path = scratch(spark, f"stream-{name}")
        q = stream.writeStream.format("parquet").option("path", f"{path}/rows").option("checkpointLocation", f"{path}/state").outputMode(mode).trigger(availableNow=True).start()
        q.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{path}/rows")
    q = stream.writeStream.format("memory").queryName(name).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.table(name)


def each_batch(stream: DataFrame, path: str, checkpoint: str) -> None:
    """foreachBatch: each batch replaces its own folder, so that a batch that runs again leaves no duplicates."""

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{path}/batch={number}")

    stream.writeStream.option("checkpointLocation", checkpoint).foreachBatch(put).trigger(availableNow=True).start().awaitTermination()
