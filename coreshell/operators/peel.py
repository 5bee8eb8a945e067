"""Baselines that remove vertices: in one task, on the driver, and level by level on the cluster."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coreshell.functions.settle import peel, sequential_cores
from coreshell.operators.frontier import BROADCAST_VERTICES, WHOLE_ARCS, coreness_frontier, small
from coreshell.operators.graph import Graph
from coreshell.operators.packed import PACKED_VERTICES, kept_pass, packed, packed_first
from coreshell.plans.rounds import CoreResult

#: Arcs that one task, or the driver, peels.
LOCAL_ARCS = 20_000_000
#: Arcs whose adjacency lists the driver holds as Python objects, some 100 bytes each.
DRIVER_ARCS = 4_000_000
LAYERS = "id long, coreness int, layer int"


def _with_isolated(g: Graph, found: DataFrame) -> DataFrame:
    if g.vertices is None:
        return found
    alone = g.degrees().where("degree = 0").select("id", F.lit(0).alias("coreness"), F.lit(0).alias("layer"))
    return found.unionByName(alone)


def peeled_arcs(g: Graph, local_arcs: int = LOCAL_ARCS, packed_vertices: tuple[int, int] = (BROADCAST_VERTICES, PACKED_VERTICES)) -> int:
    """Arcs that one task peels: ``local_arcs`` or, unless they are lowered, ``WHOLE_ARCS`` of a graph of more vertices than the first of ``packed_vertices`` and
    at most the second, which is packed here if it has more than ``local_arcs``."""
    if local_arcs < LOCAL_ARCS or g.vertices is not None:
        return local_arcs
    packed_first(g, packed_vertices)
    n, m = g.size()
    if local_arcs < m <= WHOLE_ARCS and packed_vertices[0] < n <= packed_vertices[1]:
        packed(g)
    return max(local_arcs, WHOLE_ARCS) if "packed" in g._kept else local_arcs


def peel_bucket(g: Graph, local_arcs: int = LOCAL_ARCS) -> CoreResult:
    """Linear-time peeling in one task; refuses graphs of more than ``local_arcs`` arcs. Packed lists are read where they are, some 4 bytes an arc and 90 a vertex at work."""
    began = time.perf_counter()
    if g.size()[1] > local_arcs:
        raise ValueError(f"{g.size()[1]} arcs are too many for one task; use the frontier or blocks")

    def run(batches):
        held = list(batches)
        if held:
            rows = pa.Table.from_batches(held)
            ids, core, layer = peel(rows["src"].to_numpy(), rows["dst"].to_numpy())
            yield from pa.table({"id": ids, "coreness": core.astype(np.int32), "layer": layer.astype(np.int32)}).to_batches()

    if "packed" in g._kept and g.vertices is None:
        found = kept_pass(g, g._kept["packed"].layers, None)
    else:
        found = g.store.keep(_with_isolated(g, g.arcs().coalesce(1).mapInArrow(run, LAYERS)))
    return CoreResult(found.select("id", "coreness"), [], {"plan": "peel in one task", "layers": found, "seconds": time.perf_counter() - began})


def local_neighbours(g: Graph, local_arcs: int = LOCAL_ARCS) -> dict[int, list[int]]:
    """The graph as an adjacency dictionary on the driver; small graphs only."""
    if g.size()[1] > local_arcs:
        raise ValueError(f"{g.size()[1]} arcs are too many for the driver")
    rows = g.arcs().toArrow()
    out: dict[int, list[int]] = {r["id"]: [] for r in g.degrees().select("id").collect()}
    for u, v in zip(rows["src"].to_pylist(), rows["dst"].to_pylist(), strict=True):
        out[u].append(v)
    return out


def core_number_local(g: Graph, local_arcs: int = LOCAL_ARCS) -> dict[int, int]:
    """Coreness on the driver, one vertex at a time in Python: what a sequential graph library does."""
    return sequential_cores(local_neighbours(g, local_arcs))


def cores_beyond(g: Graph, one_place: Callable[[Graph, int], CoreResult], local_arcs: int = LOCAL_ARCS) -> CoreResult:
    """Coreness by ``one_place`` (one task, or the driver) up to ``local_arcs`` arcs; a graph that no single place holds goes by the shared frontier."""
    return one_place(g, local_arcs) if g.size()[1] <= local_arcs else coreness_frontier(g)


def library_cores(g: Graph, local_arcs: int = LOCAL_ARCS) -> CoreResult:
    """The sequential routine's result as a table."""
    return CoreResult(g.spark.createDataFrame(list(core_number_local(g, local_arcs).items()), "id long, coreness int"), [], {"plan": "sequential on the driver"})


def peel_levels(g: Graph, broadcast_vertices: int = BROADCAST_VERTICES) -> CoreResult:
    """Level peeling on the cluster: all vertices of degree at most k go at once, then k rises. Also yields layers.

    Each step counts, for the vertices that remain, only the arcs that the last step removed, and appends its level to one table.
    """
    began = time.perf_counter()
    arcs, store, (n, _) = g.arcs(), g.store, g.size()
    as_broadcast = n if n <= broadcast_vertices else 1 << 62
    lowest = {"low": F.min("degree"), "n": F.count("*")}
    alive = store.keep(g.degrees(), **lowest)
    path = f"{store.root}/levels"
    k = step = 0
    while alive._counts["n"]:
        low = alive._counts["low"]
        k, step = max(k, low), step + (low > 0 or step > 0)
        gone = store.keep(alive.where(F.col("degree") <= k).select("id"), n=F.count("*"))
        few = min(as_broadcast, gone._counts["n"])
        gone.select("id", F.lit(k).alias("coreness"), F.lit(step).alias("layer")).write.mode("append").parquet(path)
        lost = arcs.join(small(gone.withColumnRenamed("id", "src"), few), "src", "left_semi").groupBy(F.col("dst").alias("__id")).agg(F.count("*").cast("int").alias("lost"))
        rest = alive.where(F.col("degree") > k).join(lost, F.col("id") == F.col("__id"), "left")
        after = store.keep(rest.select("id", (F.col("degree") - F.coalesce("lost", F.lit(0))).alias("degree")), **lowest)
        store.drop(alive, gone)
        alive = after
    found = g.spark.read.schema(LAYERS).parquet(path) if step or k or g.size()[0] else g.degrees().select("id", F.lit(0).alias("coreness"), F.lit(0).alias("layer"))
    return CoreResult(found.select("id", "coreness"), [], {"plan": "peel by levels", "rounds": step, "layers": found, "seconds": time.perf_counter() - began})
