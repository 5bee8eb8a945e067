"""Tables, edge lists, generated graphs and result writers."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def read_table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given Parquet tables; timestamps without zone become UTC timestamps, which watermarks need."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.withColumns({f.name: F.col(f.name).cast("timestamp") for f in df.schema.fields if isinstance(f.dataType, T.TimestampNTZType)})


def read_edge_list(spark: SparkSession, path: str, format: str = "text", u: str = "u", v: str = "v") -> DataFrame:
    """``u, v`` as long from an edge list: ``text`` (white space between ids, ``#`` comments), csv, json, orc or parquet."""
    if format == "text":
        parts = F.split(F.trim("value"), r"\s+")
        lines = spark.read.text(path).where("value not like '#%' and trim(value) <> ''")
        return lines.select(parts[0].cast("long").alias("u"), parts[1].cast("long").alias("v"))
    reader = spark.read.format(format)
    if format == "csv":
        reader = reader.option("header", True)
    df = reader.load(path)
    return df.select(df[u].cast("long").alias("u"), df[v].cast("long").alias("v"))


def write_cores(cores: DataFrame, path: str, mode: str = "errorifexists") -> None:
    """Coreness as Parquet, one folder for each shell, so that a filter on coreness reads its shells only."""
    cores.withColumn("shell", F.col("coreness")).write.mode(mode).partitionBy("shell").parquet(path)


def write_arcs_bucketed(arcs: DataFrame, table: str, buckets: int) -> DataFrame:
    """Arcs as a table bucketed and sorted by source: later joins by source need no exchange."""
    arcs.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src", "dst").saveAsTable(table)
    return arcs.sparkSession.table(table)


def _pairs(spark: SparkSession, n: int, u, v) -> DataFrame:
    return spark.range(max(0, n)).select(u(F.col("id")).cast("long").alias("u"), v(F.col("id")).cast("long").alias("v"))


def path_graph(spark: SparkSession, n: int) -> DataFrame:
    return _pairs(spark, n - 1, lambda i: i, lambda i: i + 1)


def cycle_graph(spark: SparkSession, n: int) -> DataFrame:
    return _pairs(spark, n, lambda i: i, lambda i: (i + 1) % n)


def star_graph(spark: SparkSession, leaves: int) -> DataFrame:
    return _pairs(spark, leaves, lambda i: F.lit(0), lambda i: i + 1)


def clique_graph(spark: SparkSession, n: int) -> DataFrame:
    return _pairs(spark, n * n, lambda i: F.floor(i / n), lambda i: i % n).where("u < v")


def bipartite_graph(spark: SparkSession, a: int, b: int) -> DataFrame:
    return _pairs(spark, a * b, lambda i: F.floor(i / b), lambda i: a + i % b)


def grid_graph(spark: SparkSession, rows: int, columns: int) -> DataFrame:
    right = _pairs(spark, rows * columns, lambda i: i, lambda i: i + 1).where(f"u % {columns} <> {columns - 1}")
    return right.union(_pairs(spark, (rows - 1) * columns, lambda i: i, lambda i: i + columns))


def tree_graph(spark: SparkSession, n: int, arity: int = 2) -> DataFrame:
    return _pairs(spark, n - 1, lambda i: i + 1, lambda i: F.floor(i / arity))
