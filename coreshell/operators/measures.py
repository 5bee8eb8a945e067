"""Cost and accuracy measures."""

from __future__ import annotations

import json
import statistics
import time
from collections.abc import Callable
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coreshell.operators.graph import Graph
from coreshell.operators.packed import kept_pass, of_all
from coreshell.plans.rounds import CoreResult, Store

MOVED = "round int, err int, n long"


def time_method(run: Callable[[], CoreResult], repeats: int = 5) -> dict:
    """Mean wall seconds of ``run`` (its cores are counted, so that they are computed); loading the edges isn't part of it."""
    took = []
    for _ in range(repeats):
        began = time.perf_counter()
        run().cores.count()
        took.append(time.perf_counter() - began)
    return {"mean": statistics.mean(took), "least": min(took), "runs": took}


def convergence_trace(result: CoreResult) -> DataFrame:
    """One row for each distinct state of a run with ``keep_states``: mean and largest distance to coreness, share of vertices within 1, and how many are off."""
    all_of, within = F.sum("n"), F.sum(F.when(F.col("err") <= 1, F.col("n")).otherwise(0))
    return distances(result).groupBy("round").agg(
        F.round(F.sum(F.col("err") * F.col("n")) / all_of, 6).alias("avg_err"), F.max("err").cast("int").alias("max_err"),
        F.round(within / all_of, 6).alias("within_1"), F.sum(F.when(F.col("err") > 0, F.col("n")).otherwise(0)).alias("n_off"),
    )


def distances(result: CoreResult) -> DataFrame:
    """``round, err, n``: how many vertices are at each distance to coreness in each distinct state of a run with ``keep_states``.

    The first state is counted, later ones by what dropped: rounds cost by their drops, not by all vertices.
    """
    if result.placed is not None:
        moved = _moved_places(result)
    else:
        first = result.states[0].join(result.cores, "id").groupBy((F.col("est") - F.col("coreness")).alias("err")).agg(F.count("*").alias("n"))
        moved = first.select(F.lit(0).alias("round"), "err", "n")
        moves = F.inline(F.array(*[F.struct((F.col(c) - F.col("coreness")).alias("err"), F.lit(by).alias("by")) for c, by in (("old", -1), ("est", 1))]))
        for drops in result.drops:
            moved = moved.union(drops.join(result.cores, "id").select("round", moves).groupBy("round", "err").agg(F.sum("by").alias("n")))
    moved = Store(result.cores.sparkSession).keep(moved)
    # distances are few, and at each the moves add up by round; a count stands until the round of the next move
    at = W.partitionBy("err").orderBy("round")
    counts = moved.withColumn("n", F.sum("n").over(at)).withColumn("until", F.lead("round").over(at))
    rounds = moved.select(F.col("round").alias("of")).distinct()
    stands = (F.col("of") >= F.col("round")) & (F.col("until").isNull() | (F.col("of") < F.col("until")))
    return counts.where("n > 0").join(F.broadcast(rounds), stands).select(F.col("of").alias("round"), "err", "n")


def _moved_places(result: CoreResult) -> DataFrame:
    """``round, err, n``: the first state's vertices by distance, and by how many each round changes those at each distance. Coreness is looked up by place."""
    spark, (first, last) = result.cores.sparkSession, result.placed
    n = np.bincount(first - last)
    moved = spark.createDataFrame([(0, int(err), int(n[err])) for err in np.flatnonzero(n)], MOVED)
    shared = spark.sparkContext.broadcast(last)

    def over(batches):
        for batch in batches:
            if batch.num_rows:
                number, node, old, est = (batch.column(c).to_numpy() for c in range(4))
                far = np.concatenate([old, est]) - np.tile(shared.value[node], 2)
                wide = int(far.max()) + 1
                keys, place = np.unique(np.tile(number.astype(np.int64), 2) * wide + far, return_inverse=True)
                by = np.bincount(place, np.repeat([-1, 1], len(number))).astype(np.int64)
                yield pa.record_batch([pa.array((keys // wide).astype(np.int32)), pa.array((keys % wide).astype(np.int32)), pa.array(by)], names=["round", "err", "n"])

    for drops in result.drops:
        moved = moved.union(drops.select("round", "node", "old", "est").mapInArrow(over, MOVED).groupBy("round", "err").agg(F.sum("n").alias("n")))
    return moved


def active_trace(result: CoreResult, n: int) -> DataFrame:
    """``round, n_active, percent``: how many vertices, and what share of all ``n``, each round evaluated."""
    return result.trace.select("round", "n_active", F.round(100.0 * F.col("n_active") / n, 6).alias("percent"))


def error_histogram(result: CoreResult) -> DataFrame:
    """``round, err, n``: vertices by distance to coreness in each distinct state of a run with ``keep_states``."""
    return distances(result)


def mismatches(a: DataFrame, b: DataFrame) -> DataFrame:
    """One row: how many vertices two results disagree on, absent ones included."""
    left, right = a.select("id", F.col("coreness").alias("x")), b.select("id", F.col("coreness").alias("y"))
    return left.join(right, "id", "full_outer").agg(F.count(F.when(~F.col("x").eqNullSafe(F.col("y")), 1)).alias("n_mismatch"))


def assert_same_cores(a: DataFrame, b: DataFrame) -> None:
    n = mismatches(a, b).first()[0]
    assert n == 0, f"{n} vertices differ"


def certify(g: Graph, cores: DataFrame, layers: DataFrame) -> DataFrame:
    """One row: violations of two linear conditions that together prove a result.

    Every vertex has as many neighbours of its coreness or more as its coreness (so none is too high), and at most as many
    neighbours at its own or a later place in the peeling order (so none is too low). On packed arcs they are counted where the lists lie.
    """
    if p := g._kept.get("packed"):
        core, layer = of_all(p, cores, "coreness"), of_all(p, layers, "layer")
        if core is not None and layer is not None:
            counts = kept_pass(g, p.violations, (core, layer))
            return counts.agg(*[F.coalesce(F.sum(c), F.lit(0)).alias(c) for c in ("too_high", "too_low")])
    at = cores.select("id", "coreness").join(layers.select("id", "layer"), "id")
    mine = at.select(F.col("id").alias("src"), F.col("coreness").alias("c"), F.col("layer").alias("p"))
    other = at.select(F.col("id").alias("dst"), F.col("coreness").alias("d"), F.col("layer").alias("q"))
    later = (F.col("d") > F.col("c")) | ((F.col("d") == F.col("c")) & (F.col("q") >= F.col("p")))
    rows = g.arcs().join(mine, "src").join(other, "dst").groupBy("src", "c").agg(F.count(F.when(F.col("d") >= F.col("c"), 1)).alias("support"), F.count(F.when(later, 1)).alias("rest"))
    return rows.agg(F.count(F.when(F.col("support") < F.col("c"), 1)).alias("too_high"), F.count(F.when(F.col("rest") > F.col("c"), 1)).alias("too_low"))


def state_footprint(g: Graph) -> dict:
    """Rows and bytes of state: a copy of each neighbour's estimate at every vertex, against one shared table."""
    n, m = g.size()
    return {"private_rows": m, "private_bytes": 20 * m, "shared_rows": n, "shared_bytes": 12 * n}


def speedup_curve(seconds: dict[int, float]) -> dict[int, float]:
    """T(1 thread) / T(t threads) from seconds by threads."""
    return {t: seconds[min(seconds)] / s for t, s in sorted(seconds.items())}


def ratio_table(seconds: dict[str, dict[str, float]], base: str) -> dict[str, dict[str, float]]:
    """For each graph, how many times as long as ``base`` each method takes."""
    return {graph: {method: s / of[base] for method, s in of.items()} for graph, of in seconds.items()}


def sweep(run: Callable[..., CoreResult], option: str, values: list, repeats: int = 1) -> dict:
    """Mean seconds by the values of one option, such as batch_size, neighbors or scheduler."""
    return {v: time_method(lambda v=v: run(**{option: v}), repeats)["mean"] for v in values}


def stage_metrics(event_log: str) -> list[dict]:
    """Tasks, shuffle and spill of each stage in a Spark event log."""
    out: dict[int, dict] = {}
    for path in sorted(Path(event_log).iterdir()) if Path(event_log).is_dir() else [Path(event_log)]:
        for line in path.open():
            e = json.loads(line)
            if e.get("Event") == "SparkListenerTaskEnd" and (m := e.get("Task Metrics")):
                s = out.setdefault(e["Stage ID"], {"stage": e["Stage ID"], "tasks": 0, "shuffle_written": 0, "shuffle_read": 0, "spilled": 0})
                read = m["Shuffle Read Metrics"]
                s["tasks"] += 1
                s["shuffle_written"] += m["Shuffle Write Metrics"]["Shuffle Bytes Written"]
                s["shuffle_read"] += read["Remote Bytes Read"] + read["Local Bytes Read"]
                s["spilled"] += m["Disk Bytes Spilled"]
    return [out[k] for k in sorted(out)]
