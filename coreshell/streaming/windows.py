"""One graph for each window, session or micro-batch of an event stream."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coreshell.operators.builders import graph_named
from coreshell.operators.graph import Graph
from coreshell.plans.choose import coreness


def union_graph(pairs: DataFrame) -> tuple[Graph, DataFrame]:
    """Many graphs (``g, u, v``: a graph's key and an edge) as one graph of disjoint parts, and ``id, g, vertex`` of its vertices.

    The vertices of all parts get dense ids; the parts never touch, so one run gives the coreness of all.
    """
    name = lambda v: F.struct(F.col("g"), F.col(v).alias("vertex"))
    g = graph_named(pairs.where("u <> v").select(name("u").alias("u"), name("v").alias("v")))
    return g, g.id_map.select("id", "raw.g", "raw.vertex")


def parted_cores(pairs: DataFrame) -> DataFrame:
    """``g, vertex, coreness`` of every part."""
    g, ids = union_graph(pairs)
    return coreness(g).cores.join(ids, "id").select("g", "vertex", F.col("coreness").cast("int").alias("coreness"))


def window_pairs(events: DataFrame, u: str, v: str, ts: str, width: str, slide: str | None = None) -> DataFrame:
    """Edges of each tumbling (or sliding) window, keyed by its start."""
    rows = events.select(F.window(F.col(ts).cast("timestamp"), width, slide or width).alias("w"), F.col(u).cast("long").alias("u"), F.col(v).cast("long").alias("v"))
    return rows.select(F.col("w.start").alias("g"), "u", "v").distinct()


def windowed_cores(events: DataFrame, u: str, v: str, ts: str, width: str, slide: str | None = None) -> DataFrame:
    """``g`` (start of the window), ``vertex, coreness`` of each window's graph."""
    return parted_cores(window_pairs(events, u, v, ts, width, slide))


def session_pairs(events: DataFrame, user: str, v: str, ts: str, gap: str) -> DataFrame:
    """Edges from a user to what a session touches, keyed by user and start of the session."""
    rows = events.select(F.col(user).cast("long").alias("user"), F.col(v).cast("long").alias("v"), F.col(ts).cast("timestamp").alias("ts"))
    sessions = rows.groupBy("user", F.session_window("ts", gap).alias("s")).agg(F.collect_set("v").alias("vs"))
    return sessions.select(F.struct("user", F.col("s.start").alias("start")).alias("g"), (2 * F.col("user")).alias("u"), F.explode("vs").alias("v")).withColumn("v", 2 * F.col("v") + 1)


def deduplicated(stream: DataFrame, key: str, ts: str, delay: str) -> DataFrame:
    """Late rows beyond ``delay`` and repeated keys within it are dropped."""
    return stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay).dropDuplicatesWithinWatermark([key])


def closed_window_edges(stream: DataFrame, u: str, v: str, ts: str, width: str, delay: str, slide: str | None = None) -> DataFrame:
    """A stream of the distinct edges of windows, sent once the watermark has passed their end (append mode)."""
    rows = stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, delay)
    grouped = rows.groupBy(F.window(ts, width, slide or width).alias("w"), F.col(u).cast("long").alias("u"), F.col(v).cast("long").alias("v")).agg(F.count("*").alias("n"))
    return grouped.select(F.col("w.start").alias("g"), "u", "v", "n")


def start_windowed_cores(edges: DataFrame, sink: Callable[[DataFrame, int], None], checkpoint: str):
    """Run closed windows through the batch engine as they arrive; the streaming query."""

    def batch(df: DataFrame, number: int) -> None:
        sink(parted_cores(df.select("g", "u", "v")), number)

    return edges.writeStream.outputMode("append").option("checkpointLocation", checkpoint).foreachBatch(batch).trigger(availableNow=True).start()


def streaming_degrees(edges: DataFrame) -> DataFrame:
    """Running degree of every vertex of a stream of distinct edges (update mode)."""
    ends = edges.select(F.explode(F.array("u", "v")).alias("id"))
    return ends.groupBy("id").agg(F.count("*").alias("degree"))




def latest(updates: DataFrame, key: list[str], out: str, checkpoint: str) -> DataFrame:
    """Run a stream in update mode to the end of its source; the last row of each ``key``, from a table of all updates by batch."""

    def batch(df: DataFrame, number: int) -> None:
        df.withColumn("batch", F.lit(number)).write.mode("append").parquet(out)

    updates.writeStream.outputMode("update").option("checkpointLocation", checkpoint).foreachBatch(batch).trigger(availableNow=True).start().awaitTermination()
    rows = updates.sparkSession.read.parquet(out)
    values = [c for c in rows.columns if c not in (*key, "batch")]
    return rows.groupBy(*key).agg(F.max(F.struct("batch", *values)).alias("last")).select(*key, *[f"last.{c}" for c in values])
