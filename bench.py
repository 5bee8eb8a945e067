"""Headline queries at ``$BENCH_SF_DIR`` on ``local[$BENCH_CPUS]``; prints one JSON line.

Each of ``queries`` is one decomposition: the edges are written before the clock starts, as loading isn't part of the
published times; the arcs, degrees and all rounds are. ``cores_*`` is the shared frontier with the published batch of 256,
``task_batch_*`` the same with the batch of one task's work, ``library_*`` the sequential routine in Python on the driver
(its adjacency lists are loaded before the clock starts), ``peel_*`` peeling in one task.

``bench.py --table``: frontier, library, batches and sequential mailbox on the graphs of ``TABLE`` (``BENCH_REPEATS`` runs
each, mean), with their ratios. ``bench.py --all``: the ablations (batch size, map or sorted, schedulers, phases, tails,
gates) as well. ``bench.py --speedup``: decompositions on 1, 2, 4, ... threads.
"""

from __future__ import annotations

import json
import os
import subprocess
import sys
import tempfile
import time

HERE = os.path.dirname(os.path.abspath(__file__))
os.environ["PYTHONPATH"] = os.pathsep.join(filter(None, [HERE, os.environ.get("PYTHONPATH")]))  # for the workers
SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = int(os.environ.get("BENCH_CPUS", os.cpu_count() or 4))
REPEATS = int(os.environ.get("BENCH_REPEATS", "1"))


def session(cpus: int):
    from pyspark.sql import SparkSession

    folder = tempfile.mkdtemp(prefix="coreshell-bench-")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", str(cpus))
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .config("spark.driver.memory", "8g")
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.checkpoint.dir", folder)
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    return spark


#: Graphs on which all four methods are timed: those whose mailboxes need a dozen rounds at most, of each kind.
TABLE = ("part_supplier", "customer_supplier", "user_handoff", "user_key", "page_link", "doc_line", "geo_tree", "vector_knn", "order_part")


def main() -> None:
    from coreshell.functions.settle import sequential_cores
    from coreshell.operators.blocked import coreness_blocked
    from coreshell.operators.frontier import TASK_VERTICES, coreness_frontier
    from coreshell.operators.graph import Graph
    from coreshell.operators.mailbox import coreness_mailbox
    from coreshell.operators.measures import ratio_table
    from coreshell.operators.peel import local_neighbours, peel_bucket
    from coreshell.workloads.graphs import GRAPHS, build

    spark = session(CPUS)
    edges = {}
    for name in GRAPHS:
        g = build(spark, SF_DIR, name)
        edges[name] = g.store.keep(g.edges)

    def mean(run) -> float:
        took = []
        for _ in range(REPEATS):
            began = time.perf_counter()
            run()
            took.append(time.perf_counter() - began)
        print(took, file=sys.stderr, flush=True)
        return round(sum(took) / len(took), 3)

    def timed(name: str, run) -> float:
        return mean(lambda: run(Graph(edges[name])).cores.count())

    def library(name: str) -> float:
        neighbours = local_neighbours(Graph(edges[name]))
        return mean(lambda: sequential_cores(neighbours))

    batches, one_by_one = lambda g: coreness_mailbox(g, "batch"), lambda g: coreness_mailbox(g, "sequential", gate="all")
    timed("geo_tree", coreness_frontier)  # workers start, code compiles
    out, extra = {}, {}
    if "--table" in sys.argv:
        methods = {"frontier": lambda n: timed(n, coreness_frontier), "library": library, "batches": lambda n: timed(n, batches), "sequential": lambda n: timed(n, one_by_one)}
        table = {n: {m: run(n) for m, run in methods.items()} for n in TABLE}
        out = {f"{m}_{n}": s for n, of in table.items() for m, s in of.items()}
        extra = {"ratios": {n: {m: round(x, 2) for m, x in of.items()} for n, of in ratio_table(table, "frontier").items()}}
    else:
        out |= {f"cores_{n}": timed(n, coreness_frontier) for n in GRAPHS}
        out |= {f"task_batch_{n}": timed(n, lambda g: coreness_frontier(g, batch_size=TASK_VERTICES)) for n in ("part_supplier", "order_part", "part_copurchase", "customer_part", "order_grid")}
        out |= {f"library_{n}": library(n) for n in ("part_copurchase", "order_part", "customer_part", "order_grid")}
        out |= {f"peel_{n}": timed(n, peel_bucket) for n in ("part_copurchase", "order_grid")}
        out |= {f"mailbox_batch_{n}": timed(n, batches) for n in ("user_key", "page_link")}
        out |= {f"mailbox_sequential_{n}": timed(n, one_by_one) for n in ("user_key", "page_link")}
        out["blocked_range_page_link"] = timed("page_link", lambda g: coreness_blocked(g, 4, "range"))
    if "--all" in sys.argv:
        out["blocked_range_order_grid"] = timed("order_grid", lambda g: coreness_blocked(g, 8, "range"))  # some 119 rounds
        out |= {f"batch_size_{b}_{n}": timed(n, lambda g, b=b: coreness_mailbox(g, "batch", batch_size=b)) for b in (16, 64, 256, 1024, 4096) for n in ("user_key", "customer_supplier")}
        out |= {f"neighbors_{k}_{n}": timed(n, lambda g, k=k: coreness_mailbox(g, neighbors=k)) for k in ("map", "sorted") for n in TABLE}
        out |= {f"scheduler_{k}_{n}": timed(n, lambda g, k=k: coreness_mailbox(g, k)) for k in ("sequential", "iterator", "pool", "batch") for n in ("customer_supplier", "order_part")}
        out |= {f"phases_{k}": timed("customer_part", lambda g, k=k: coreness_mailbox(g, "batch", phases=k)) for k in ("split", "fused")}
        out |= {f"tail_{k}": timed("order_grid", lambda g, k=k: coreness_frontier(g, tail=k)) for k in ("priority", "fifo", "heap")}
        out |= {f"gate_{k}": timed("customer_part", lambda g, k=k: coreness_frontier(g, tail="none", gate=k)) for k in ("all", "lower", "support", "counter")}
    spark.stop()
    print(json.dumps({"metric": "seconds of all headline decompositions", "value": round(sum(out.values()), 3), "unit": "sec", "queries": out, "sf": os.path.basename(SF_DIR.rstrip("/")), "cpus": CPUS} | extra))


def one(name: str) -> None:
    """Seconds of one decomposition on one graph, the second of two, for ``speedup``."""
    from coreshell.operators.frontier import coreness_frontier
    from coreshell.operators.graph import Graph
    from coreshell.workloads.graphs import build

    spark = session(CPUS)
    g = build(spark, SF_DIR, name)
    edges = g.store.keep(g.edges)
    took = []
    for _ in range(2):
        began = time.perf_counter()
        coreness_frontier(Graph(edges)).cores.count()
        took.append(time.perf_counter() - began)
    spark.stop()
    print(json.dumps({"seconds": min(took)}))


def speedup(names: tuple[str, ...] = ("part_supplier", "customer_part")) -> None:
    from coreshell.operators.measures import speedup_curve

    for name in names:
        seconds, t = {}, 1
        while t <= (os.cpu_count() or 4):
            run = subprocess.run([sys.executable, __file__, "--one", name], env=os.environ | {"BENCH_CPUS": str(t)}, capture_output=True, text=True, check=True)
            seconds[t], t = json.loads(run.stdout.strip().splitlines()[-1])["seconds"], 2 * t
        print(json.dumps({"graph": name, "seconds": seconds, "speedup": {k: round(v, 2) for k, v in speedup_curve(seconds).items()}}))


if __name__ == "__main__":
    if "--one" in sys.argv:
        one(sys.argv[-1])
    elif "--speedup" in sys.argv:
        speedup()
    else:
        main()
