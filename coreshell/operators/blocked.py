"""One host, many vertices: blocks settle among themselves, and only what crosses their borders costs a round."""

from __future__ import annotations

import time
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coreshell.operators.frontier import BROADCAST_VERTICES, SETTLED, TASK_ARCS, TASK_VERTICES, merged, messages, pulled_by, settle_kernel, settled_whole, small, whole_arcs
from coreshell.operators.gates import gate
from coreshell.operators.graph import Graph
from coreshell.operators.packed import PACKED_VERTICES, Packed, estimates, kept_pass, packed, packed_first, settled_blocks, sliced, wakened_blocks
from coreshell.plans.rounds import CoreResult, loop_until_stable

#: Blocks that are named one by one in a filter, so that the files of others aren't read.
NAMED_BLOCKS = 1000


def assign_blocks(g: Graph, n_blocks: int, partitioner: str = "hash") -> DataFrame:
    """``id, block``. hash: spread evenly. range: neighbouring ids together, about as many arcs in each block. chunk: id ranges of equal width."""
    ids = g.degrees()
    if partitioner == "hash":
        block = F.pmod(F.xxhash64("id"), F.lit(n_blocks))
    elif partitioner == "range":
        return _by_degree(g, n_blocks)
    elif partitioner == "chunk":
        lo, hi = ids.agg(F.min("id"), F.max("id")).first()
        width = max(1, -(-((hi or 0) - (lo or 0) + 1) // n_blocks))
        block = F.floor((F.col("id") - F.lit(lo or 0)) / width)
    else:
        raise ValueError(partitioner)
    return ids.select("id", block.cast("int").alias("block"))


def _by_degree(g: Graph, n_blocks: int) -> DataFrame:
    """Blocks cut where the degrees of ascending ids have added up to another share of all arcs.

    Ids are dealt into ranges; each adds up its degrees by itself and is moved by the sums of those before it (one row a range).
    """
    spark, store = g.spark, g.store
    parts = int(spark.conf.get("spark.sql.shuffle.partitions"))
    dealt = store.keep(g.degrees().repartitionByRange(parts, "id").select("id", F.col("degree").cast("long").alias("degree"), F.spark_partition_id().alias("part")))
    firsts, at = [], 0
    for r in sorted(dealt.groupBy("part").agg(F.sum("degree").alias("n")).collect()):
        firsts.append((r["part"], at))
        at += r["n"]
    first = F.broadcast(spark.createDataFrame(firsts, "part int, first long"))  # one row a partition
    before = F.sum("degree").over(W.partitionBy("part").orderBy("id").rowsBetween(W.unboundedPreceding, 0)) - F.col("degree")
    share = F.floor((F.col("first") + F.col("before")) * n_blocks / max(1, at)).cast("int")
    return dealt.withColumn("before", before).join(first, "part").select("id", F.least(share, F.lit(n_blocks - 1)).alias("block"))


def _largest(blocks: DataFrame, g: Graph) -> int:
    """Arcs of the largest block."""
    return blocks.join(g.degrees(), "id").groupBy("block").agg(F.sum("degree").alias("n")).agg(F.max("n")).first()[0] or 0


def _blocks_for(n_blocks: int, assigned: Callable[[int], object], largest: Callable[[object], int], g: Graph, hub: Callable[[], int], most: int) -> tuple[int, object]:
    """(how many blocks, what ``assigned`` gives for them): ``n_blocks`` or, where the ``largest`` would have more than ``most`` arcs, as many more as are needed."""
    n, m = g.size()
    while (arcs := largest(blocks := assigned(n_blocks))) > most:
        if n_blocks >= n or hub() > most:
            raise ValueError(f"a block of {arcs} arcs is too large for one task; use the frontier")
        n_blocks = max(2 * n_blocks, -(-2 * m // most))
    return n_blocks, blocks


def packed_blocks(g: Graph, p: Packed, n_blocks: int, partitioner: str) -> np.ndarray:
    """The block of every vertex of ``p.ids``, as ``assign_blocks`` has it."""
    if partitioner == "range":
        degree = p.degree.astype(np.int64)
        return np.minimum((np.cumsum(degree) - degree) * n_blocks // max(1, int(degree.sum())), n_blocks - 1).astype(np.int32)
    return estimates(p, assign_blocks(g, n_blocks, partitioner).withColumnRenamed("block", "est"))


def coreness_blocked(
    g: Graph,
    n_blocks: int | None = None,
    partitioner: str = "hash",
    order: str = "priority",
    broadcast_vertices: int = BROADCAST_VERTICES,
    task_arcs: int = TASK_ARCS,
    start: DataFrame | None = None,
    active: DataFrame | None = None,
    merge_below: int = TASK_VERTICES,
    packed_vertices: tuple[int, int] = (BROADCAST_VERTICES, PACKED_VERTICES),
) -> CoreResult:
    """Coreness by local fixpoints: each round, every block with active vertices settles with its rim frozen at the values of the round's start.

    Estimates only fall and a local fixpoint never goes below coreness, so the rounds end at coreness. There are enough
    blocks for ``task_arcs`` arcs each unless ``n_blocks`` says otherwise, and more than that where a task couldn't take one of them; a
    hub that no block can hold is refused. Graphs of more vertices than the first of ``packed_vertices`` and at most the second are dealt from
    packed arcs, some 20 bytes an arc in a task, so that a block may have ``WHOLE_ARCS``. ``start``: ``id, est``, upper bounds to begin with, and ``active`` the vertices to begin with (all).
    Arcs lie in buckets by block and are read in place, those of blocks that are awake only. Once fewer than ``merge_below``
    vertices are awake after a round, the blocks become one if a task takes the whole graph: what is left is a long chain
    of drops that would cross a border in every round.
    """
    began = time.perf_counter()
    store, limit = g.store, broadcast_vertices
    if limit > 0:
        packed_first(g, packed_vertices)
    n, m = g.size()
    n_blocks = n_blocks or max(1, -(-2 * m // task_arcs))
    if limit > 0 and packed_vertices[0] < n <= packed_vertices[1] and g.vertices is None:
        return _blocked_packed(g, n_blocks, partitioner, order, task_arcs, start, active, merge_below, began)
    hub = lambda: g.degrees().agg(F.max("degree")).first()[0]
    n_blocks, blocks = _blocks_for(n_blocks, lambda k: store.keep(assign_blocks(g, k, partitioner)), lambda blocks: _largest(blocks, g), g, hub, task_arcs)
    mine = small(blocks.withColumnRenamed("id", "src"), n, limit)
    to = small(blocks.select(F.col("id").alias("dst"), F.col("block").alias("to_block")), n, limit)
    dealt = store.keep(g.arcs().join(mine, "src").join(to, "dst").select("src", "dst", "block", (F.col("block") != F.col("to_block")).alias("crosses")), bucketed="block")
    border = store.keep(dealt.where("crosses").select("src", "dst"), bucketed="src" if n > limit else None)
    first = g.degrees().select("id", F.col("degree").alias("est")) if start is None else start.select("id", "est")
    state = store.keep(first.select("id", F.col("est").alias("old"), "est"))
    woken = None if active is None else store.keep(active.select("id").join(small(blocks, n, limit), "id"), n=F.count("*"))
    now = {"state": state, "active": woken, "n_active": n if woken is None else woken._counts["n"], "evals": 0, "one": False}
    run = settle_kernel(order)

    def step(number: int) -> dict:
        n_active, state, some = now["n_active"], now["state"], now["active"]
        if not n_active:
            return {"n_active": 0, "n_changed": 0}
        est, rows = state.select("id", "est"), dealt
        now["one"] = number > 1 and n_active < merge_below and m <= whole_arcs(task_arcs)
        if some is not None and not now["one"]:
            awake = some.select("block").distinct()
            named = [r["block"] for r in awake.limit(NAMED_BLOCKS + 1).collect()]
            rows = rows.where(F.col("block").isin(named)) if len(named) <= NAMED_BLOCKS else rows.join(awake, "block", "left_semi")
        pulled = None if now["one"] else pulled_by(rows.select("src", "dst", "block"), est, n, est, n, limit, "block")
        if pulled is None:
            settled = settled_whole(g.arcs(), est, some, order)
        elif some is None:
            pulled = pulled.withColumn("active", F.lit(True))
        else:
            mark = small(some.select(F.col("id").alias("__id")), n_active, limit)
            pulled = pulled.join(mark, F.col("id") == F.col("__id"), "left").withColumn("active", F.col("__id").isNotNull()).drop("__id")
        if pulled is not None:
            settled = pulled.groupBy("block").applyInArrow(run, SETTLED)
        new = store.keep(settled, evals=F.sum("evals"), n=F.count("*"))
        now["evals"] += new._counts["evals"]
        after = store.keep(merged(est, new.select("id", "new_est"), new._counts["n"], limit), changed=F.count(F.when(F.col("est") < F.col("old"), 1)))
        changed = after._counts["changed"]
        # inside a block everything has settled; across borders the receivers are judged by merged values
        now["active"], now["n_active"] = None, 0
        if changed and n_blocks > 1 and not now["one"]:
            wake = messages(border, after, n, changed, limit).where(gate("support")).select(F.col("dst").alias("id")).distinct()
            now["active"] = store.keep(wake.join(small(blocks, n, limit), "id"), n=F.count("*"))
            now["n_active"] = now["active"]._counts["n"]
        store.drop(state, new, some)
        now["state"] = after
        return {"n_active": n_active, "n_changed": changed, "done": not now["n_active"]}

    rounds = loop_until_stable(step)
    store.drop(dealt, border)
    stats = {"plan": f"blocked n_blocks={n_blocks} partitioner={partitioner}", "rounds": len(rounds), "evals": now["evals"], "merged": now["one"], "seconds": time.perf_counter() - began}
    return CoreResult(now["state"].select("id", F.col("est").alias("coreness")), rounds, stats)


def _blocked_packed(g: Graph, n_blocks: int, partitioner: str, order: str, task_arcs: int, start: DataFrame | None, active: DataFrame | None, merge_below: int, began: float) -> CoreResult:
    """The same rounds on packed arcs: a block is one row, which a task reads in place; the driver sends all estimates to the tasks that settle and
    to those that judge which vertices the drops of other blocks concern."""
    p, (n, m) = packed(g), g.size()
    largest = lambda of: int(np.bincount(of, p.degree).max(initial=0))
    n_blocks, of = _blocks_for(n_blocks, lambda k: packed_blocks(g, p, k, partitioner), largest, g, lambda: int(p.degree.max()), whole_arcs(task_arcs))
    dealt = kept_pass(g, p.dealt, of, parted="block")
    est = p.degree if start is None else estimates(p, start)
    asked = np.ones(len(est), bool) if active is None else np.isin(p.ids, active.select("id").toArrow()["id"].to_numpy())
    now = {"est": est, "asked": asked, "evals": 0, "one": False}

    def step(number: int) -> dict:
        est, asked = now["est"], now["asked"]
        n_active = int(np.count_nonzero(asked))
        if not n_active:
            return {"n_active": 0, "n_changed": 0}
        now["one"] = number > 1 and n_active < merge_below and m <= whole_arcs(task_arcs)
        if now["one"]:
            new = kept_pass(g, lambda held: p.settled(held, order), (est, asked), evals=F.sum("evals"))
            after = sliced(new, len(est))
        else:
            named = np.unique(of[asked]).tolist()
            awake = dealt.where(F.col("block").isin(named)) if len(named) <= NAMED_BLOCKS else dealt
            new = kept_pass(g, lambda held: settled_blocks(awake, held, order), (est, asked), evals=F.sum("evals"))
            moves, after = new.where("node IS NOT NULL").select("node", "est").toArrow(), est.copy()
            after[moves["node"].to_numpy()] = moves["est"].to_numpy()
        now["evals"] += new._counts["evals"]
        g.store.drop(new)
        changed = int(np.count_nonzero(after < est))
        now["est"], now["asked"] = after, np.zeros(len(est), bool)
        # inside a block everything has settled; across borders the receivers are judged by merged values
        if changed and n_blocks > 1 and not now["one"]:
            wake = kept_pass(g, lambda held: wakened_blocks(dealt, held), (est, after))
            now["asked"][wake.toArrow()["node"].to_numpy()] = True
            g.store.drop(wake)
        return {"n_active": n_active, "n_changed": changed, "done": not now["asked"].any()}

    rounds = loop_until_stable(step)
    state = kept_pass(g, p.state, (now["est"], now["est"]))
    g.store.drop(dealt)
    stats = {"plan": f"blocked n_blocks={n_blocks} partitioner={partitioner}", "rounds": len(rounds), "evals": now["evals"], "merged": now["one"], "seconds": time.perf_counter() - began}
    return CoreResult(state.select("id", F.col("est").alias("coreness")), rounds, stats)
