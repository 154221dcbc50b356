"""Readers, the mixed corpus of graph sizes, generated sources and writers."""

from __future__ import annotations

import atexit
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Used only in local mode, where the session names no shared folder: there are no other machines then.
LOCAL_DEFAULT = "/tmp/checkpoints/evenbatch"


def shared_dir(spark: SparkSession) -> str:
    """The folder all executors share: that of the session's settings or else of its context; in local mode a default."""
    context = spark.sparkContext
    named = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if not named:
        if context.master != "local" and not context.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        named = LOCAL_DEFAULT
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(named)
    return named.rstrip("/")


def settled(df: DataFrame) -> DataFrame:
    """df written once to the shared folder, so that later jobs read the same rows in the same partitions."""
    shared_dir(df.sparkSession)
    return df.checkpoint()


_written: set[str] = set()


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh path under the shared folder, which goes when the application ends."""
    path = f"{shared_dir(spark)}/evenbatch-{label}-{uuid.uuid4().hex}"
    _written.add(path)
    return path


@atexit.register
def _sweep() -> None:
    spark = SparkSession.getActiveSession()
    for path in list(_written) if spark is not None else []:
        try:
            target = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            target.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(target, True)
        except Exception:  # noqa: BLE001  (the JVM is gone)
            return


def stored(df: DataFrame, label: str) -> DataFrame:
    """df as Parquet in the shared folder: for tables whose rows carry their order themselves."""
    path = scratch(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def read_table(spark: SparkSession, sf_dir: str, name: str, columns: list[str] | None = None, predicate: str | Column | None = None) -> DataFrame:
    """A table's columns and rows; both are left to the Parquet scan."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    if predicate is not None:
        df = df.where(predicate)
    if columns:
        missing = [c for c in columns if c not in df.columns]
        if missing:
            raise ValueError(f"{name} has no column {', '.join(missing)}")
        df = df.select(*columns)
    return df


def read_any(spark: SparkSession, path: str, fmt: str, schema: str | None = None, **options: str) -> DataFrame:
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path)


def literal_table(spark: SparkSession, rows: list[tuple], schema: str) -> DataFrame:
    return spark.createDataFrame(rows, schema).coalesce(1)


def words(text: str = "text") -> Column:
    return F.regexp_count(text, F.lit(r"\S+")).cast("long")


def tags(html: str = "html") -> Column:
    return (F.length(html) - F.length(F.replace(html, F.lit("<")))).cast("long")


def doc_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(id, size): words of each document; a null text has none."""
    return read_table(spark, sf_dir, "documents", ["doc_id", "text"]).select(F.col("doc_id").alias("id"), F.coalesce(words(), F.lit(0)).cast("long").alias("size"))


def _counted(df: DataFrame, key: str, source: str) -> DataFrame:
    return df.groupBy(F.col(key).cast("long").alias("graph_id")).agg(F.count("*").alias("n_vertices")).select(F.lit(source).alias("source"), "graph_id", "n_vertices")


def source_graphs(spark: SparkSession, sf_dir: str, source: str) -> DataFrame:
    """(source, graph_id, n_vertices) of one of the eight sources."""
    if source in ("orders", "parts", "suppliers"):
        key = {"orders": "l_orderkey", "parts": "l_partkey", "suppliers": "l_suppkey"}[source]
        return _counted(read_table(spark, sf_dir, "lineitem", [key]), key, source)
    if source == "customers":
        per_order = read_table(spark, sf_dir, "lineitem", ["l_orderkey"]).groupBy("l_orderkey").agg(F.count("*").alias("n"))
        owned = read_table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"]).join(per_order, F.col("o_orderkey") == F.col("l_orderkey"))
        return owned.groupBy(F.col("o_custkey").alias("graph_id")).agg(F.sum("n").alias("n_vertices")).select(F.lit(source).alias("source"), "graph_id", "n_vertices")
    if source == "documents":
        return doc_sizes(spark, sf_dir).select(F.lit(source).alias("source"), F.col("id").alias("graph_id"), F.col("size").alias("n_vertices"))
    if source == "pages":
        return read_table(spark, sf_dir, "pages", ["page_id", "html"]).select(F.lit(source).alias("source"), F.col("page_id").alias("graph_id"), tags().alias("n_vertices"))
    table, key = {"users": ("events", "user_id"), "conversations": ("conversations", "conv_id")}[source]
    return _counted(read_table(spark, sf_dir, table, [key]), key, source)


SOURCES = ("orders", "parts", "customers", "suppliers", "documents", "pages", "users", "conversations")


def mixed_graphs(spark: SparkSession, sf_dir: str, sources: tuple[str, ...] = SOURCES) -> DataFrame:
    out = source_graphs(spark, sf_dir, sources[0])
    for s in sources[1:]:
        out = out.unionByName(source_graphs(spark, sf_dir, s))
    return out


def synthetic_sizes(spark: SparkSession, n: int, lo: int, hi: int) -> DataFrame:
    """(id, size) with sizes spread over lo..hi by a hash."""
    return spark.range(n).select("id", (F.pmod(F.xxhash64("id"), F.lit(hi - lo + 1)) + lo).alias("size"))


def graph_size(vertices: str = "n_vertices", edges: str = "n_edges", alpha: float = 1.0, beta: float = 0.0) -> Column:
    """A graph's size as alpha * vertices + beta * edges, rounded up; a null count is 0."""
    part = lambda c, w: F.coalesce(F.col(c), F.lit(0)) * F.lit(w)
    total = part(vertices, alpha) if not beta else part(edges, beta) if not alpha else part(vertices, alpha) + part(edges, beta)
    return F.ceil(total).cast("long")


def write_batches(df: DataFrame, path: str, by: tuple[str, ...] = ("rank",), fmt: str = "parquet") -> None:
    df.repartition(*by).write.partitionBy(*by).format(fmt).save(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, column: str) -> None:
    df.write.bucketBy(buckets, column).sortBy(column).mode("overwrite").saveAsTable(table)


def sink_noop(df: DataFrame) -> None:
    """Run df and throw its rows away."""
    df.write.format("noop").mode("overwrite").save()


def sink_foreach(df: DataFrame, each) -> None:
    """Hand each partition's rows, an iterator, to a function that runs beside them."""
    df.foreachPartition(each)
