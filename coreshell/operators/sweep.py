"""Synchronous full re-evaluation: every vertex, every round. The reference sequence of states."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from coreshell.functions import hindex
from coreshell.operators.frontier import BROADCAST_VERTICES, merged, pulled
from coreshell.operators.graph import Graph
from coreshell.plans.rounds import CoreResult, loop_until_stable

KERNELS = {"hist": hindex.h_index_hist, "rank": hindex.h_index_rank}


def _array(pairs):
    return pairs.groupBy("id").agg(F.collect_list("nbr_est").alias("all"), F.max("est").alias("est")).select("id", hindex.h_index_array(F.col("all"), F.col("est")).alias("new_est"))


def _udaf(pairs):
    return pairs.groupBy("id").agg(hindex.h_index_udaf("nbr_est", "est").alias("new_est"))


KERNELS |= {"array": _array, "udaf": _udaf}


def coreness_sweep(g: Graph, kernel: str = "hist", broadcast_vertices: int = BROADCAST_VERTICES, max_rounds: int | None = None) -> CoreResult:
    """Coreness with neither gate nor frontier; ``kernel`` is one of hist, rank, array, udaf."""
    began = time.perf_counter()
    arcs, store, (n, _) = g.arcs(), g.store, g.size()
    as_broadcast = n if n <= broadcast_vertices else 1 << 62
    now = {"state": store.keep(g.degrees().select("id", F.col("degree").alias("est")))}

    def step(_: int) -> dict:
        est = now["state"].select("id", "est")
        after = store.keep(merged(est, KERNELS[kernel](pulled(arcs, est, as_broadcast)).select("id", "new_est"), as_broadcast), changed=F.count(F.when(F.col("est") < F.col("old"), 1)))
        changed = after._counts["changed"]
        store.drop(now["state"])
        now["state"] = after
        return {"n_active": n, "n_changed": changed}

    rounds = loop_until_stable(step, max_rounds)
    stats = {"plan": f"sweep kernel={kernel}", "rounds": len(rounds), "evals": n * len(rounds), "seconds": time.perf_counter() - began}
    return CoreResult(now["state"].select("id", F.col("est").alias("coreness")), rounds, stats)
