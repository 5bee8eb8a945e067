"""Coreness kept up to date under inserted and deleted edges.

New upper bounds restart the frontier where something may have changed: coreness rises by at most one for each inserted
edge and never above the new degree; it never rises by deletions.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coreshell.operators.frontier import coreness_frontier
from coreshell.operators.graph import Graph, canonical_edges
from coreshell.plans.rounds import Store


class IncrementalCores:
    """``edges`` and ``cores`` as written tables; ``apply`` replaces them by those after a batch."""

    def __init__(self, edges: DataFrame):
        self.store = Store(edges.sparkSession)
        self.edges = self.store.keep(edges.sparkSession.createDataFrame([], "u long, v long"))
        self.cores = self.store.keep(edges.sparkSession.createDataFrame([], "id long, coreness int"))
        self.stats: dict = {}
        self.apply(edges)

    def _run(self, edges: DataFrame, bound: DataFrame, active: DataFrame) -> None:
        """``bound``: id, est for known vertices; others start at their degree and are active."""
        g = Graph(edges)
        known = bound.withColumnRenamed("id", "of")
        start = g.degrees().join(known, F.col("id") == F.col("of"), "left").select("id", F.least("degree", F.coalesce("est", "degree")).cast("int").alias("est"))
        awake = self.store.keep(active.join(g.degrees().select("id"), "id", "left_semi").distinct())
        result = coreness_frontier(g, start=self.store.keep(start), active=awake)
        self.edges, self.cores, self.stats = edges, self.store.keep(result.cores), result.stats

    def apply(self, inserts: DataFrame | None = None, deletes: DataFrame | None = None) -> DataFrame:
        """Deletes first, then inserts; edges that are there already, or aren't, are ignored. The new cores."""
        if deletes is not None:
            gone = self.store.keep(canonical_edges(deletes).join(self.edges, ["u", "v"], "left_semi"))
            if not gone.isEmpty():
                edges = self.store.keep(self.edges.join(gone, ["u", "v"], "left_anti"))
                ends = gone.select(F.explode(F.array("u", "v")).alias("id")).distinct()
                both = edges.select(F.inline(F.array(F.struct(F.col("u").alias("id"), F.col("v").alias("nbr")), F.struct(F.col("v").alias("id"), F.col("u").alias("nbr")))))
                near = both.join(ends.withColumnRenamed("id", "nbr"), "nbr", "left_semi").select("id")
                self._run(edges, self.cores.select("id", F.col("coreness").alias("est")), ends.union(near))
        if inserts is not None:
            new = self.store.keep(canonical_edges(inserts).join(self.edges, ["u", "v"], "left_anti"))
            n = new.count()
            if n:
                edges = self.store.keep(self.edges.union(new))
                degree = edges.select(F.explode(F.array("u", "v")).alias("id")).groupBy("id").agg(F.count("*").cast("int").alias("degree"))
                was = self.cores.withColumnRenamed("id", "of")
                bound = degree.join(was, F.col("id") == F.col("of"), "left").select("id", F.coalesce("coreness", F.lit(0)).alias("was"), F.least("degree", F.coalesce("coreness", F.lit(0)) + n).cast("int").alias("est"))
                bound = self.store.keep(bound)
                self._run(edges, bound.select("id", "est"), bound.where("est > was").select("id"))
        return self.cores

    def on_batch(self, batch: DataFrame, _: int) -> None:
        """For ``foreachBatch``: rows ``op`` (+ or -), ``u``, ``v``."""
        batch = self.store.keep(batch.select("op", "u", "v"))
        self.apply(batch.where("op = '+'"), batch.where("op = '-'"))
