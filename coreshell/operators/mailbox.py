"""Private mailboxes: every vertex keeps its own copies of its neighbours' estimates and learns of changes by messages only.

A vertex is a row: its estimate and its neighbours with the last values heard from them, as a map or as sorted arrays. A
round delivers the folded mail, re-estimates, and sends. The schedulers differ in how rows are dealt to tasks.
"""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from coreshell.functions.hindex import h_index_array, h_index_block
from coreshell.functions.settle import Block
from coreshell.operators.frontier import BROADCAST_VERTICES, small
from coreshell.operators.graph import Graph
from coreshell.plans.rounds import CoreResult, loop_until_stable

SCHEDULERS = ("sequential", "iterator", "pool", "batch")
SORTED = "id long, old int, est int, nbr array<long>, heard array<int>"


def init_state(g: Graph, neighbors: str) -> DataFrame:
    """Vertex rows whose copies are the neighbours' degrees: what everybody would send first (2m messages)."""
    degrees = g.degrees()
    heard = degrees.select(F.col("id").alias("dst"), F.col("degree").alias("of"))
    rows = g.arcs().join(heard, "dst").groupBy(F.col("src").alias("id")).agg(F.array_sort(F.collect_list(F.struct(F.col("dst").alias("id"), "of"))).alias("n"))
    rows = rows.join(degrees, "id").select("id", F.col("degree").alias("old"), F.col("degree").alias("est"), "n")
    if neighbors == "map":
        return rows.select("id", "old", "est", F.map_from_entries("n").alias("heard_of"))
    return rows.select("id", "old", "est", F.col("n.id").alias("nbr"), F.col("n.of").alias("heard"))


def send(state: DataFrame, gate: str, neighbors: str) -> DataFrame:
    """``dst, src, value`` from the vertices that dropped. lower: only if the value is below the last one heard from the receiver; all: to everybody."""
    dropped = state.where("est < old")
    if neighbors == "map":
        out = dropped.select(F.col("id").alias("src"), F.col("est").alias("value"), F.explode("heard_of").alias("dst", "of"))
    else:
        out = dropped.select(F.col("id").alias("src"), F.col("est").alias("value"), F.inline(F.arrays_zip(F.col("nbr").alias("dst"), F.col("heard").alias("of"))))
    if gate == "lower":
        out = out.where("value < of")
    elif gate != "all":
        raise ValueError(f"mailboxes know the gates all and lower, not {gate!r}")
    return out.select("dst", "src", "value")


def mailbox_fold(mail: DataFrame) -> DataFrame:
    """``to, mail``: of each sender the lowest value counts, as estimates never rise. The exchange by receiver stands for its lock."""
    folded = mail.groupBy("dst", "src").agg(F.min("value").alias("value"))
    return folded.groupBy(F.col("dst").alias("to")).agg(F.array_sort(F.collect_list(F.struct("src", "value"))).alias("mail"))


def _process_map(rows: DataFrame) -> DataFrame:
    """Deliver into maps and re-estimate, in built-in functions."""
    mail = F.coalesce(F.map_from_entries("mail"), F.create_map().cast("map<bigint,int>"))
    rows = rows.select("id", "est", F.map_zip_with("heard_of", mail, lambda _, a, b: F.coalesce(b, a)).alias("heard_of"))
    return rows.select("id", F.col("est").alias("old"), h_index_array(F.map_values("heard_of"), F.col("est")).alias("est"), "heard_of")


def _flat(column: pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    array = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    return array.flatten().to_numpy(zero_copy_only=False), np.asarray(array.value_lengths().fill_null(0)).astype(np.int64)


def _process_sorted(lookup: str, linear_below: int, fused: bool, batch: int):
    """Arrow kernel: deliver mail into sorted arrays by binary search (or a linear scan of short ones), then re-estimate.

    fused: vertices of a task in batches, each of which sees what the batches before it have changed.
    """

    def run(rows: pa.Table) -> pa.Table:
        ids, est = rows["id"].to_numpy(), rows["est"].to_numpy().astype(np.int64)
        nbr, size = _flat(rows["nbr"])
        heard = _flat(rows["heard"])[0].astype(np.int64).copy()
        src, mails = _flat(rows["src"])
        value = _flat(rows["value"])[0].astype(np.int64)
        first = np.cumsum(size) - size
        to = np.repeat(np.arange(len(ids)), mails)
        linear = np.zeros(len(src), bool) if lookup == "binary" else size[to] < linear_below
        for j in np.flatnonzero(linear).tolist():
            a = first[to[j]]
            heard[a + int(np.argmax(nbr[a : a + size[to[j]]] == src[j]))] = value[j]
        some = np.flatnonzero(~linear)
        if len(some):
            lo, hi = first[to[some]], first[to[some]] + size[to[some]]
            while (lo < hi).any():  # one binary search for each mail, all at once
                mid = (lo + hi) // 2
                right = (lo < hi) & (nbr[np.minimum(mid, len(nbr) - 1)] < src[some])
                lo, hi = np.where(right, mid + 1, lo), np.where((lo < hi) & ~right, mid, hi)
            heard[lo] = value[some]
        if fused:
            owner = np.repeat(np.arange(len(ids)), size)
            block = Block(ids[owner], nbr, est[owner], heard)
            block.sweep(np.arange(block.n), batch)
            new = est.copy()
            new[np.flatnonzero(size > 0)[np.argsort(ids[size > 0], kind="stable")]] = block.est[: block.n]
        else:
            new = h_index_block(size, est, heard)
        offsets = pa.array(np.r_[0, np.cumsum(size)].astype(np.int32))
        lists = [pa.ListArray.from_arrays(offsets, pa.array(x)) for x in (nbr, heard.astype(np.int32))]
        return pa.table([ids, est.astype(np.int32), new.astype(np.int32), *lists], names=["id", "old", "est", "nbr", "heard"])

    def over(batches):
        if fused:
            held = list(batches)
            if held:
                yield from run(pa.Table.from_batches(held)).to_batches()
            return
        for b in batches:
            for a in range(0, b.num_rows, batch):
                yield from run(pa.Table.from_batches([b.slice(a, batch)])).to_batches()

    return over


def coreness_mailbox(
    g: Graph,
    scheduler: str = "iterator",
    neighbors: str = "sorted",
    lookup: str = "binary",
    linear_below: int = 16,
    phases: str = "split",
    gate: str = "lower",
    batch_size: int = 256,
    n_tasks: int | None = None,
    broadcast_vertices: int = BROADCAST_VERTICES,
    max_rounds: int | None = None,
) -> CoreResult:
    """Coreness by messages.

    ``scheduler``: sequential (one task), iterator (rows wherever they are), pool (chunks of ``batch_size`` consecutive ids
    are dealt to ``n_tasks``), batch (so are they, and a task takes batch after batch). ``neighbors``: map or sorted.
    ``phases``: split, or fused (sorted only), where batches of a task see each other's changes at once.

    Vertices are dealt once and stay in their files; a round brings the mail to them. Beyond ``broadcast_vertices``
    vertices they lie in hash buckets of their ids instead, so that mail of any amount finds them there. A vertex is one
    row with all its neighbours, as the method has it: at most some 100 million of them fit; graphs with such hubs
    need the frontier.
    """
    if scheduler not in SCHEDULERS:
        raise ValueError(f"scheduler {scheduler!r}: one of {SCHEDULERS}")
    if phases == "fused" and neighbors != "sorted":
        raise ValueError("fused phases need sorted neighbours")
    began = time.perf_counter()
    store, spark, limit = g.store, g.spark, broadcast_vertices
    n_tasks = n_tasks or int(spark.conf.get("spark.sql.shuffle.partitions"))
    n, m = g.size()
    by = "id" if n > limit and scheduler != "sequential" else None
    first = init_state(g, neighbors)
    if scheduler == "sequential":
        first = first.repartition(1).sortWithinPartitions("id")
    elif scheduler != "iterator" and not by:
        first = first.repartitionByRange(n_tasks, F.floor(F.col("id") / batch_size)).sortWithinPartitions("id")
    now = {"state": store.keep(first, by), "mail": None, "sent": 0}
    per_call = batch_size if scheduler == "batch" or phases == "fused" else 1 << 30
    kernel = _process_sorted(lookup, linear_below, phases == "fused", per_call)
    parts = (("src", "array<bigint>"), ("value", "array<int>"))

    def step(_: int) -> dict:
        rows, mail = now["state"], now["mail"]
        if mail is None:
            rows = rows.withColumn("mail", F.lit(None).cast("array<struct<src:bigint,value:int>>"))
        else:  # mail comes to the vertices where they lie: by broadcast if that is small, else by bucket
            rows = rows.join(small(mail, mail._counts["sent"], limit), F.col("id") == F.col("to"), "left").drop("to")
        if neighbors == "map":
            state = _process_map(rows)
        else:
            mail_columns = [F.coalesce(F.col(f"mail.{c}"), F.array().cast(t)).alias(c) for c, t in parts]
            state = rows.select("id", "est", "nbr", "heard", *mail_columns).mapInArrow(kernel, SORTED)
        state = store.keep(state, by, changed=F.count(F.when(F.col("est") < F.col("old"), 1)))
        store.drop(now["state"], mail)
        now["state"], now["mail"], sent = state, None, 0
        if changed := state._counts["changed"]:
            now["mail"] = store.keep(mailbox_fold(send(state, gate, neighbors)), "to" if by else None, sent=F.sum(F.size("mail")))
            sent = now["mail"]._counts["sent"]
            now["sent"] += sent
        return {"n_active": n, "n_changed": changed, f"msgs_{gate}": sent}

    rounds = loop_until_stable(step, max_rounds)
    store.drop(now["mail"])
    cores = now["state"].select("id", F.col("est").alias("coreness"))
    if g.vertices is not None:
        cores = cores.unionByName(g.degrees().where("degree = 0").select("id", F.lit(0).alias("coreness")))
    stats = {"plan": f"mailbox {scheduler} {neighbors} {phases} gate={gate}", "rounds": len(rounds), "evals": n * len(rounds), "sent": now["sent"], "first_messages": m, "seconds": time.perf_counter() - began}
    return CoreResult(cores, rounds, stats)
