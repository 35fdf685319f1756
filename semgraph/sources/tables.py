"""Readers and writers: Parquet tables, triple text, query graphs as JSON, round trips of other formats."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, Observation, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

from ..model import KG_EDGES

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def load(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def register_views(spark: SparkSession, sf_dir: str, tables: tuple[str, ...] = TABLES) -> None:
    for t in tables:
        load(spark, sf_dir, t).createOrReplaceTempView(t)


def shared_dir(spark: SparkSession) -> str:
    """The session's `spark.checkpoint.dir`. Unset, a temporary folder becomes it where all runs on one machine; a cluster must name one."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    current = spark.sparkContext._jsc.sc().getCheckpointDir()
    if current.isDefined():
        return current.get().rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    folder = f"file://{tempfile.mkdtemp(prefix='semgraph-checkpoint-')}"
    spark.sparkContext.setCheckpointDir(folder)
    return folder


def scratch(spark: SparkSession, name: str) -> str:
    """A new folder in the shared one; it goes when the application ends."""
    path = f"{shared_dir(spark)}/semgraph-{name}-{uuid.uuid4().hex}"
    hadoop = spark._jvm.org.apache.hadoop.fs.Path(path)
    files = hadoop.getFileSystem(spark._jsc.hadoopConfiguration())
    files.mkdirs(hadoop)
    files.deleteOnExit(hadoop)
    return path


def cut(df: DataFrame) -> DataFrame:
    """Checkpoint into the shared folder: an end to the lineage that survives lost executors."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


def local(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    """A small table of the driver's rows that needs no job to be read."""
    import pyarrow as pa
    from pyspark.sql.pandas.types import to_arrow_schema

    fields = to_arrow_schema(T._parse_datatype_string(schema))
    columns = list(zip(*rows)) if rows else [()] * len(fields)
    return spark.createDataFrame(pa.Table.from_arrays([pa.array(c, f.type) for c, f in zip(columns, fields)], schema=fields), T._parse_datatype_string(schema))


def keep(df: DataFrame, name: str, *measures: Column) -> tuple[DataFrame, dict]:
    """(the rows as a stored table, measures of them): one job writes and measures; the table ends the lineage."""
    seen = Observation()
    path = f"{scratch(df.sparkSession, name)}/rows"
    (df.observe(seen, *measures) if measures else df).write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path), seen.get if measures else {}


def drop(kept: DataFrame) -> None:
    """Delete the files of a table of `keep` that nothing reads any more."""
    spark = kept.sparkSession
    for folder in {f.rsplit("/", 1)[0] for f in kept.inputFiles()}:
        path = spark._jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def write_triples(edges: DataFrame, path: str) -> None:
    """subject<TAB>predicate<TAB>object lines."""
    edges.select("src", "predicate", "dst").write.mode("overwrite").option("sep", "\t").csv(path)


def read_triples(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.option("sep", "\t").schema(KG_EDGES).csv(path)


def write_adjacency(adj: DataFrame, path: str) -> None:
    """Parquet by predicate, so that the static cut prunes partitions; sorted by node within files."""
    adj.repartition("predicate").sortWithinPartitions("predicate", "node").write.mode("overwrite").partitionBy("predicate").parquet(path)


def save_bucketed(adj: DataFrame, table: str, buckets: int) -> None:
    """A table bucketed by node: expansion joins read it without a shuffle of the edges."""
    adj.write.mode("overwrite").bucketBy(buckets, "node").sortBy("node").saveAsTable(table)


QUERY_JSON = T.StructType([
    T.StructField("label", T.StringType()),
    T.StructField("nodes", T.ArrayType(T.StructType([T.StructField("key", T.StringType()), T.StructField("types", T.ArrayType(T.StringType())), T.StructField("name", T.StringType())]))),
    T.StructField("edges", T.ArrayType(T.StructType([T.StructField("a", T.StringType()), T.StructField("b", T.StringType()), T.StructField("predicate", T.StringType())]))),
])


def read_query_graphs(spark: SparkSession, path: str) -> DataFrame:
    return spark.read.schema(QUERY_JSON).json(path)


def round_trip(df: DataFrame, kind: str) -> DataFrame:
    """Write in a format and read back with the same schema."""
    path = f"{scratch(df.sparkSession, kind)}/rows"
    df.write.format(kind).save(path)
    return df.sparkSession.read.schema(df.schema).format(kind).load(path)


def triple_source(spark: SparkSession) -> str:
    """Register a Python data source `triples` for the text format; it splits a file list over tasks. Returns its name."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Reader(DataSourceReader):
        def __init__(self, paths: list[str]) -> None:
            self.paths = paths

        def partitions(self):
            return [InputPartition(p) for p in self.paths]

        def read(self, partition):
            with open(partition.value, encoding="utf-8") as lines:
                for line in lines:
                    s, p, o = line.rstrip("\n").split("\t")
                    yield int(s), p, int(o)

    class Triples(DataSource):
        @classmethod
        def name(cls):
            return "triples"

        def schema(self):
            return "src long, predicate string, dst long"

        def reader(self, schema):
            return Reader(self.options.get("paths", "").split(";"))

    spark.dataSource.register(Triples)
    return "triples"


def filtered_text(df: DataFrame) -> DataFrame:
    """Lines as a text file holds them."""
    return df.select(F.concat_ws("\t", *df.columns).alias("value"))
