"""Undirected simple graphs as edge tables, and what is derived from them."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coreshell.plans.rounds import Store


def ordered_pairs(df: DataFrame, u: str = "u", v: str = "v", nulls: str = "drop", id_type: str = "long") -> DataFrame:
    """``u < v`` without loops, with repeats. ``nulls``: drop rows with a null endpoint, or ``error`` to fail on one."""
    a, b = df[u].cast(id_type), df[v].cast(id_type)
    if nulls == "error":
        a, b = (F.when(x.isNull(), F.raise_error(F.lit("null endpoint"))).otherwise(x) for x in (a, b))
    elif nulls != "drop":
        raise ValueError(nulls)
    rows = df.select(a.alias("a"), b.alias("b"))
    return rows.where("a <> b").select(F.least("a", "b").alias("u"), F.greatest("a", "b").alias("v"))


def canonical_edges(df: DataFrame, u: str = "u", v: str = "v", nulls: str = "drop", id_type: str = "long") -> DataFrame:
    """``u < v``, distinct, without loops. ``nulls``: drop rows with a null endpoint, or ``error`` to fail on one."""
    return ordered_pairs(df, u, v, nulls, id_type).distinct()


def symmetrize(edges: DataFrame) -> DataFrame:
    """``src, dst``: both directions of every edge, in one pass over the edges."""
    both = F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst")), F.struct(F.col("v").alias("src"), F.col("u").alias("dst")))
    return edges.select(F.inline(both))


def dense_ids(names: DataFrame, column: str = "raw") -> DataFrame:
    """``raw, id`` with ids 0, 1, ... for the distinct values of a column, without one global window.

    Values are dealt into ranges; each range is numbered by itself and moved by the sizes of those before it (one row a range).
    """
    spark = names.sparkSession
    store = Store(spark)
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    raw = names.select(F.col(column).alias("raw")).where("raw is not null").distinct()
    dealt = store.keep(raw.repartitionByRange(n, "raw").select("raw", F.spark_partition_id().alias("part")))
    sizes = sorted((r["part"], r["n"]) for r in dealt.groupBy("part").agg(F.count("*").alias("n")).collect())
    at, firsts = 0, []
    for part, count in sizes:
        firsts.append((part, at))
        at += count
    first = F.broadcast(spark.createDataFrame(firsts, "part int, first long"))  # one row a partition
    number = F.row_number().over(W.partitionBy("part").orderBy("raw")) - 1
    return store.keep(dealt.withColumn("number", number).join(first, "part").select("raw", (F.col("first") + F.col("number")).alias("id")))


@dataclass
class Graph:
    """Canonical ``edges`` and, for isolated vertices, a table of ``vertices`` (``id``)."""

    edges: DataFrame
    vertices: DataFrame | None = None
    id_map: DataFrame | None = None
    #: ``u, v`` before clean-up, where the graph was built from pairs
    raw: DataFrame | None = None
    #: The rows whose distinct ones are ``edges``, where known
    pairs: DataFrame | None = None
    #: About how many vertices, and at most how many pairs, where they were counted when the graph was built
    about: tuple[int, int] | None = None
    _kept: dict = field(default_factory=dict, repr=False)

    @property
    def spark(self):
        return self.edges.sparkSession

    @property
    def store(self) -> Store:
        if "store" not in self._kept:
            self._kept["store"] = Store(self.spark)
        return self._kept["store"]

    def arcs(self) -> DataFrame:
        """``src, dst`` in hash buckets of ``src``, written once: arcs stay where they are, whatever is joined to or counted by their sources."""
        if "arcs" not in self._kept:
            self._kept["arcs"] = self.store.keep(symmetrize(self.edges), bucketed="src")
        return self._kept["arcs"]

    def degrees(self) -> DataFrame:
        """``id, degree``; isolated vertices have 0."""
        if "degrees" not in self._kept:
            found = self.arcs().groupBy(F.col("src").alias("id")).agg(F.count("*").cast("int").alias("degree"))
            if self.vertices is not None:
                alone = self.vertices.select(F.col("id").cast("long").alias("id")).where("id is not null").distinct().join(found, "id", "left_anti")
                found = found.unionByName(alone.withColumn("degree", F.lit(0)))
            self._kept["degrees"] = self.store.keep(found)
        return self._kept["degrees"]

    def size(self) -> tuple[int, int]:
        """(vertices, arcs)."""
        if "size" not in self._kept:
            r = self.degrees().agg(F.count("*").alias("n"), F.sum("degree").alias("m")).first()
            self._kept["size"] = (r["n"], r["m"] or 0)
        return self._kept["size"]

    def adjacency(self) -> DataFrame:
        """``src, nbrs``: each vertex's neighbours as a sorted array (one row a vertex: not for hubs beyond a row's size)."""
        return self.arcs().groupBy("src").agg(F.array_sort(F.collect_list("dst")).alias("nbrs"))

    def named(self, df: DataFrame, column: str = "id") -> DataFrame:
        """``df`` with the raw names of its ids, where the graph was built from names."""
        if self.id_map is None:
            return df
        names = self.id_map.select(F.col("id").alias("__id"), F.col("raw").alias("__raw"))
        return df.join(names, df[column] == F.col("__id")).drop("__id").withColumn(column, F.col("__raw")).drop("__raw")


def profile(g: Graph, cores: DataFrame) -> DataFrame:
    """One row: pairs before clean-up and loops among them (null where unknown), vertices, edges, largest and mean coreness, mean degree."""
    core = cores.agg(F.count("*").alias("n"), F.max("coreness").cast("long").alias("k_max"), F.round(F.avg("coreness"), 6).alias("k_avg"))
    edges = g.edges.agg(F.count("*").alias("m"))
    if g.raw is None:
        raw = edges.select(F.lit(None).cast("long").alias("n_rows_raw"), F.lit(None).cast("long").alias("n_loops"))
    else:
        raw = g.raw.where("u is not null and v is not null").agg(F.count("*").alias("n_rows_raw"), F.count(F.when(F.col("u") == F.col("v"), 1)).alias("n_loops"))
    return raw.join(edges).join(core).select("n_rows_raw", "n_loops", "n", "m", "k_max", "k_avg", F.round(2 * F.col("m") / F.col("n"), 6).alias("d_avg"))
