"""Shared frontier: one table of estimates that all vertices see, and a frontier of those to re-estimate.

A round pulls the estimates that the frontier's arcs point to, re-estimates (process), merges what dropped into the
table (update) and activates the neighbours that a drop concerns, judged by the merged table. When few vertices are
active, the run leaves the parallel mode: the active ones and their surroundings go to one task, lowest estimates first.

A round writes two tables, the merged estimates and the next frontier, and counts both while it writes them. Arcs lie
in buckets by source and never move. Up to ``BROADCAST_VERTICES`` vertices the estimates are broadcast, and only the
names of activated vertices are exchanged. Beyond, up to ``PACKED_VERTICES``, rounds go over packed arcs (``packed.py``). Larger
graphs' estimates and frontier lie in buckets by vertex, and three exchanges are left of a round: two of counts of neighbours by estimate (summed by vertex and estimate, then by vertex, so that
a hub's are spread), and one to the neighbours that a drop may concern.
"""

from __future__ import annotations

import itertools
import time
from collections.abc import Callable, Iterable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coreshell.functions.hindex import h_index_hist, h_index_open
from coreshell.functions.settle import Block
from coreshell.operators.gates import gate as gate_predicate
from coreshell.operators.graph import Graph
from coreshell.operators.packed import COUNTS, PACKED_VERTICES, estimates, kept_pass, packed, packed_first, sliced
from coreshell.plans.rounds import CoreResult, loop_until_stable

#: A table of at most so many vertices (16 bytes each) is broadcast; larger ones are joined by shuffle or bucket.
BROADCAST_VERTICES = 500_000
#: Arcs (some 100 bytes each at work) that one task takes.
TASK_ARCS = 8_000_000
#: Arcs of a whole graph that one task takes, some 25 bytes each at work, as neither estimates nor both directions of an edge are sent to it.
WHOLE_ARCS = 40_000_000
#: Tails on surroundings after which one task takes all that is left, its lists on its disk.
SURROUNDINGS = 4
#: Active vertices below which the parallel mode is left: the batch that the published runs kept.
BATCH = 256
#: Vertices that make up one task's work on a cluster, where a round costs seconds: an option for ``batch_size``, and the drops below which packed rounds are one task's.
TASK_VERTICES = 1 << 17
#: Arcs of a round that one partition of its exchanges takes, for ``adaptive_partitions``.
ARCS_A_PARTITION = 1 << 18


def small(df: DataFrame, rows: int, limit: int = BROADCAST_VERTICES) -> DataFrame:
    """A hint to broadcast ``df`` if its counted rows allow it."""
    return F.broadcast(df) if rows <= limit else df


def active_arcs(arcs: DataFrame, active: DataFrame | None, n_active: int) -> DataFrame:
    if active is None:
        return arcs
    return arcs.join(small(active.select(F.col("id").alias("src")), n_active), "src", "left_semi")


def pulled(arcs: DataFrame, est: DataFrame, n: int) -> DataFrame:
    """``id, nbr, est, nbr_est`` of arcs."""
    return pulled_by(arcs, est, n, est, n)


def pulled_by(arcs: DataFrame, mine: DataFrame, n_mine: int, est: DataFrame, n: int, limit: int = BROADCAST_VERTICES, *more: str) -> DataFrame:
    """``id, nbr, est, nbr_est`` of the arcs that start in ``mine`` (``id, est``), and the arcs' columns named in ``more``."""
    own = small(mine.selectExpr("id AS src", "est"), n_mine, limit)
    other = small(est.selectExpr("id AS dst", "est AS nbr_est"), n, limit)
    return arcs.join(own, "src").join(other, "dst").selectExpr("src AS id", "dst AS nbr", "est", "nbr_est", *more)


def pushed(arcs: DataFrame, est: DataFrame, active: DataFrame | None) -> DataFrame:
    """``id, new_est`` of the vertices of ``active`` (all), without moving an arc: estimates join the arcs that start in their vertices, and what
    is exchanged are counts of neighbours by estimate."""
    theirs = arcs.join(est.selectExpr("id AS src", "est AS nbr_est"), "src").selectExpr("dst AS id", "nbr_est")
    if active is not None:
        theirs = theirs.join(F.broadcast(active.select("id")), "id", "left_semi")  # counted rows
    return h_index_open(theirs)


def merged(est: DataFrame, new: DataFrame, n_new: int = 1 << 62, limit: int = BROADCAST_VERTICES) -> DataFrame:
    """``id, old, est``: the table with the estimates that dropped (``id, new_est``)."""
    new = small(new.selectExpr("id", "new_est"), n_new, limit)
    return est.join(new, "id", "left").selectExpr("id", "est AS old", "CAST(least(est, new_est) AS INT) AS est")  # least ignores null


def messages(arcs: DataFrame, state: DataFrame, n: int, n_dropped: int | None = None, limit: int = BROADCAST_VERTICES) -> DataFrame:
    """``dst, src, old, new, est``: to each neighbour of a vertex that dropped, with the receiver's merged estimate."""
    dropped = small(state.where("est < old").selectExpr("id AS src", "old", "est AS new"), n if n_dropped is None else n_dropped, limit)
    mine = small(state.selectExpr("id AS dst", "est"), n, limit)
    return arcs.join(dropped, "src").join(mine, "dst")


def activated(arcs: DataFrame, state: DataFrame, n: int, kind: str) -> DataFrame:
    """``id`` of the vertices to re-estimate."""
    return messages(arcs, state, n).where(gate_predicate(kind)).select(F.col("dst").alias("id")).distinct()


def settle_kernel(order: str):
    """Arrow kernel: rows ``id, nbr, est, nbr_est, active`` of one block to ``id, new_est, evals`` of its vertices."""

    def run(rows: pa.Table) -> pa.Table:
        src, dst, est, nbr_est, active = (rows[c].to_numpy() for c in ("id", "nbr", "est", "nbr_est", "active"))
        block = Block(src, dst, est, nbr_est)
        wake = np.searchsorted(block.ids, np.unique(src[active.astype(bool)]))
        out = block.settle_by_heap(wake) if order == "heap" else block.settle(wake, order)
        return pa.table({"id": block.ids, "new_est": out.astype(np.int32), "evals": block.evals})

    return run


#: What a traced round counts besides its vertices.
TRACED = ("msgs_all", "msgs_lower", "msgs_support")
SETTLED = "id long, new_est int, evals long"
#: A round's drops, and one row for each round without ``id``, which counts it.
ROUNDS = "round int, id long, old int, est int, n_active long, n_changed long, msgs_all long, msgs_lower long, msgs_support long"
#: Drops that a task hands on at a time.
DROPS = 1 << 18


def whole_graph(arcs: DataFrame, est: DataFrame, active: DataFrame | None) -> DataFrame:
    """``a, b, kind`` of every edge (0), vertex and estimate (1) and active vertex (2; where ``active`` is None, all are), read by one task
    from where they lie."""
    rows = arcs.where("src < dst").selectExpr("src AS a", "dst AS b", "CAST(0 AS TINYINT) AS kind")
    rows = rows.union(est.selectExpr("id", "CAST(est AS LONG)", "CAST(1 AS TINYINT)"))
    if active is not None:
        rows = rows.union(active.selectExpr("id", "CAST(0 AS LONG)", "CAST(2 AS TINYINT)"))
    return rows.coalesce(1)


def held_graph(batches: Iterable[pa.RecordBatch], all_active: bool) -> tuple[Block, np.ndarray]:
    """(the block, active positions) from the rows of ``whole_graph``."""
    edges, ids, est, some = [], [np.zeros(0, np.int64)], [np.zeros(0, np.int32)], [np.zeros(0, np.int64)]
    for batch in batches:
        a, b, kind = (batch.column(i).to_numpy() for i in range(3))
        for k in np.unique(kind).tolist():
            x, y = a[kind == k], b[kind == k]
            if k == 0:
                edges.append((x, y))
            elif k == 1:
                ids.append(x)
                est.append(y.astype(np.int32))
            else:
                some.append(x)
    found, bounds = np.concatenate(ids), np.concatenate(est)
    order = np.argsort(found)
    block = Block.whole(edges, found[order], bounds[order])
    return block, np.arange(block.n) if all_active else np.searchsorted(block.ids, np.sort(np.concatenate(some)))


def settled_whole(arcs: DataFrame, est: DataFrame, active: DataFrame | None, order: str) -> DataFrame:
    """``id, new_est, evals`` of the vertices that one task has evaluated until nothing changed any more."""

    all_active = active is None
    def run(batches):
        block, wake = held_graph(batches, all_active)
        out = block.settle_by_heap(wake) if order == "heap" else block.settle(wake, order)
        seen = np.flatnonzero(block.evals)
        yield from pa.table({"id": block.ids[seen], "new_est": out[seen].astype(np.int32), "evals": block.evals[seen]}).to_batches()

    return whole_graph(arcs, est, active).mapInArrow(run, SETTLED)


def settled_listed(arcs: DataFrame, est: DataFrame, active: DataFrame, order: str) -> DataFrame:
    """``id, new_est, evals`` as ``settled_whole`` gives them, by a task that holds no arcs: they are sorted on its disk and looked up there."""
    rows = arcs.selectExpr("src AS a", "dst AS b", "CAST(2 AS TINYINT) AS kind").union(est.selectExpr("id", "CAST(est AS LONG)", "CAST(1 AS TINYINT)"))
    rows = rows.union(active.selectExpr("id", "CAST(0 AS LONG)", "CAST(0 AS TINYINT)")).coalesce(1).sortWithinPartitions("kind", "a")

    def run(batches):
        before = [[], []]  # active vertices, then all vertices: few and some bytes each

        def later():
            for batch in batches:
                a, b, kind = (batch.column(i).to_numpy() for i in range(3))
                for k in (0, 1):
                    before[k].append((a[kind == k], b[kind == k]))
                if len(a) and kind[-1] == 2:
                    yield a[kind == 2], b[kind == 2]

        arcs = later()
        first = [x for x in [next(arcs, None)] if x is not None]
        wake, (ids, bounds) = (tuple(np.concatenate(x) for x in zip(*rows, strict=True)) for rows in before)
        block = Block.listed(itertools.chain(first, arcs), ids, bounds)
        wake = np.searchsorted(ids, wake[0])
        out = block.settle_by_heap(wake) if order == "heap" else block.settle(wake, order)
        seen = np.flatnonzero(block.evals)
        yield from pa.table({"id": ids[seen], "new_est": out[seen].astype(np.int32), "evals": block.evals[seen]}).to_batches()

    return rows.mapInArrow(run, SETTLED)


def rounds_whole(arcs: DataFrame, est: DataFrame, active: DataFrame | None, gate: str) -> DataFrame:
    """The rows ``ROUNDS`` of all rounds that are left, which one task goes through."""
    columns = [c.split() for c in ROUNDS.split(", ")]
    types = {"int": pa.int32(), "long": pa.int64()}

    def table(drops: list[tuple], counts: list[tuple]) -> pa.RecordBatch:
        number = np.repeat([r for r, *_ in drops], [len(i) for _, i, *_ in drops]).astype(np.int64)
        cells = [np.concatenate([number, [r for r, *_ in counts]]), *(np.concatenate([x[i] for x in drops] + [np.zeros(len(counts), np.int64)]) for i in (1, 2, 3))]
        cells += [np.concatenate([np.zeros(len(number), np.int64), [x[i] for x in counts]]) for i in range(1, 6)]
        of_round = np.arange(len(cells[0])) >= len(number)
        masks = [np.zeros(len(of_round), bool)] + [of_round] * 3 + [~of_round] * 5
        return pa.record_batch([pa.array(x.astype(np.int64), mask=hide).cast(types[t]) for x, hide, (_, t) in zip(cells, masks, columns, strict=True)], names=[c for c, _ in columns])

    all_active = active is None
    def run(batches):
        block, wake = held_graph(batches, all_active)
        drops, counts, held = [], [], 0
        for r, (n_active, changed, old, new, sent) in enumerate(block.rounds(wake, gate), 1):
            drops.append((r, block.ids[changed], old, new))
            counts.append((r, n_active, len(changed), sent["all"], sent["lower"], sent["support"]))
            held += len(changed) + 1
            if held >= DROPS:
                yield table(drops, counts)
                drops, counts, held = [], [], 0
        if counts:
            yield table(drops, counts)

    return whole_graph(arcs, est, active).mapInArrow(run, ROUNDS)


def in_one_task(rows: DataFrame, order: str) -> DataFrame:
    """All of ``rows`` (their number is checked before) in one task."""
    run = settle_kernel(order)

    def over(batches):
        held = list(batches)
        if held:
            yield from run(pa.Table.from_batches(held)).to_batches()

    return rows.repartition(1).mapInArrow(over, SETTLED)


def surroundings(arcs: DataFrame, active: DataFrame, n: int, hops: int) -> DataFrame:
    """``id`` of the active vertices and those within ``hops``."""
    some = active
    for _ in range(hops):
        near = arcs.join(small(some.withColumnRenamed("id", "src"), n), "src", "left_semi").select(F.col("dst").alias("id"))
        some = some.union(near).distinct()
    return some


def whole_arcs(task_arcs: int) -> int:
    """Arcs of a whole graph that one task takes, where ``task_arcs`` of rows with estimates are allowed."""
    return max(WHOLE_ARCS, task_arcs) if task_arcs >= TASK_ARCS else task_arcs


def coreness_frontier(
    g: Graph,
    gate: str = "support",
    tail: str = "priority",
    batch_size: int = BATCH,
    switch_below: int | None = None,
    switch_fraction: float | None = None,
    task_arcs: int = TASK_ARCS,
    hops: int = 2,
    start: DataFrame | None = None,
    active: DataFrame | None = None,
    broadcast_vertices: int = BROADCAST_VERTICES,
    packed_vertices: tuple[int, int] = (BROADCAST_VERTICES, PACKED_VERTICES),
    adaptive_partitions: bool = False,
    trace: bool = False,
    keep_states: bool = False,
    max_rounds: int | None = None,
) -> CoreResult:
    """Coreness by the shared frontier.

    ``tail``: priority, fifo, heap, rounds or none; taken once fewer than ``switch_below`` vertices (``batch_size``, or
    ``switch_fraction`` of all) are active. A tail works on the whole graph if it has at most ``task_arcs`` arcs, otherwise
    on the active vertices' surroundings of ``hops`` with the estimates beyond frozen; if those are too many as well, the
    parallel mode goes on. After ``SURROUNDINGS`` of them one task goes on to the end on the whole graph with as few arcs in memory: it
    sorts them on its disk and looks up the lists that drops reach. A whole graph is sent without its estimates on arcs, so up to ``WHOLE_ARCS`` arcs are taken
    unless ``task_arcs`` is lowered. ``rounds`` takes whole graphs only: one task goes on with the same rounds, each counted
    as the parallel ones are. ``gate``: all, lower or support (counter: as support, with every vertex's supporters counted so
    that it wakes only when they have become too few). ``start``: ``id, est``, upper bounds to begin with, and ``active``
    the vertices to begin with (all). ``adaptive_partitions``: the exchanges of a round have as many partitions as its
    arcs fill, many early and few late (only while estimates are broadcast: buckets are fixed). ``packed_vertices``: rounds of
    graphs of more vertices than the first and at most the second go over packed arcs, each with the same counts, until a tail
    takes over (not with ``broadcast_vertices=0``, which asks for buckets). If one task takes the whole graph, it goes on with these rounds,
    each counted, as soon as a round has fewer than ``TASK_VERTICES`` drops, and then with the tail.
    """
    began = time.perf_counter()
    store, limit = g.store, broadcast_vertices
    if limit > 0 and task_arcs >= TASK_ARCS:
        packed_first(g, packed_vertices)
    n, m = g.size()
    fits = m <= whole_arcs(task_arcs)
    shuffled = n > limit
    packs = limit > 0 and packed_vertices[0] < n <= packed_vertices[1] and g.vertices is None
    by = "id" if shuffled and not packs else None
    below = int(switch_fraction * n) if switch_fraction is not None else batch_size if switch_below is None else switch_below
    held = packs and (n >= below or tail == "none") and start is None and active is None and not keep_states  # the first state is what is packed
    first = g.degrees().select("id", F.col("degree").alias("est")) if start is None else start.select("id", "est")
    state = None if held else store.keep(first.select("id", F.col("est").alias("old"), "est"), by)
    if active is not None:
        active = store.keep(state.select("id", "est").join(active.select("id"), "id", "left_semi"), by, n=F.count("*"))
    now = {"state": state, "active": active, "n_active": n if active is None else active._counts["n"], "arcs": m, "evals": 0, "tails": 0, "tries": 0, "states": [state] if keep_states else [], "drops": [], "placed": None}
    now["packs"] = packs and bool(n) and (now["n_active"] >= below or tail == "none")
    by = "id" if shuffled else None
    usual = g.spark.conf.get("spark.sql.shuffle.partitions")
    dropped = F.expr("count_if(est < old)")

    def tail_rows() -> DataFrame | None:
        est, some, arcs = now["state"].select("id", "est"), now["active"], g.arcs()
        if fits:
            return settled_whole(arcs, est, some, tail)
        if some is None:
            return None
        now["tries"] += 1
        if now["tries"] > SURROUNDINGS and n <= PACKED_VERTICES:
            now["whole"] = True
            return settled_listed(arcs, est, some.select("id"), tail)
        around = store.keep(surroundings(arcs, some.select("id"), n if not shuffled else 1 << 62, hops))
        part = store.keep(arcs.join(around.withColumnRenamed("id", "src"), "src", "left_semi"), n=F.count("*"))
        now["part"] = (around, part)
        if part._counts["n"] > task_arcs:
            return None
        rows = pulled_by(part, est, n, est, n, limit)
        mark = small(some.select(F.col("id").alias("__id")), now["n_active"], limit)
        return in_one_task(rows.join(mark, F.col("id") == F.col("__id"), "left").withColumn("active", F.col("__id").isNotNull()).drop("__id"), tail)

    def rounds_left(number: int, est: DataFrame) -> dict:
        """All rounds from ``number`` on, by one task."""
        out = store.keep(rounds_whole(g.arcs(), est, now["active"], gate))
        reports = [r.asDict() for r in out.where("id IS NULL").select("round", "n_active", "n_changed", *TRACED).sort("round").collect()]
        drops = out.where("id IS NOT NULL").select((F.col("round") + number - 1).alias("round"), "id", "old", "est")
        now["evals"] += sum(r["n_active"] for r in reports)
        now["tails"] += 1
        after = store.keep(merged(est, drops.groupBy("id").agg(F.min("est").alias("new_est")), n, limit), by, changed=dropped)
        store.drop(now["active"])
        if keep_states:
            now["states"].append(after)
            now["drops"].append(drops)
        else:
            store.drop(now["state"], out)
        now["state"], now["active"], now["n_active"] = after, None, 0
        return {"n_changed": after._counts["changed"], "done": True, "reports": [{k: v for k, v in r.items() if k != "round" and (trace or k not in TRACED)} for r in reports]}

    def packed_rounds() -> dict:
        """Rounds over packed arcs until nothing is active, a tail takes over or ``max_rounds`` are done."""
        p, now["packs"] = packed(g), False
        est = old = begin = p.degree if start is None else estimates(p, now["state"])
        asked = np.ones(len(est), bool)
        if now["active"] is not None:
            asked = np.isin(p.ids, now["active"].select("id").toArrow()["id"].to_numpy())
        leaves = tail != "none" and (tail != "rounds" or fits and max_rounds is None)
        goes_on = leaves and fits and max_rounds is None
        reports, drops, n_active = [], [], 0

        def kept(run: Callable[..., DataFrame], held: tuple, by: str | None = None, **counts: Column) -> DataFrame:
            return kept_pass(g, run, held, by, **counts)

        def rest() -> np.ndarray:
            """All that is left, by one task; the estimates at the end."""
            out = kept(lambda held: p.rest(held, len(reports), gate, tail, below, trace, keep_states), (old, est))
            rows = [r.asDict() for r in out.where("kind = 2").select("round", "n_active", "n_changed", "evals", *TRACED).sort("round").collect()]
            reports[-1] |= {c: rows[0][c] for c in TRACED if trace}
            for r in rows[1:]:
                now["evals"] += r["evals"]
                reports.append({c: r[c] for c in ("n_active", "n_changed", *(TRACED if trace else ()))})
            now["tails"] += any(r["n_active"] < below for r in rows[1:])
            end = sliced(out.where("kind = 1"), len(est))
            if keep_states:
                drops.append(out)
            else:
                store.drop(out)
            return end

        while True:
            last = max_rounds is not None and len(reports) >= max_rounds
            names = n + 1 if last else below if leaves else 0
            out = kept(lambda held: p.one_round(held, len(reports) + 1, gate, names, not last), (old, est, asked), **{c: F.sum(c) for c in COUNTS})
            seen, asked, applied = out._counts, None, False
            if reports and trace:
                reports[-1] |= {c: seen[c] for c in TRACED}
            n_active = seen["n_active"]
            if not n_active or last or leaves and n_active < below:
                if n_active and goes_on:
                    est, n_active = rest(), 0
                break
            moves, applied = out.where("kind = 0").select("node", "est").toArrow(), keep_states
            old, est = est, est.copy()
            est[moves["node"].to_numpy()] = moves["est"].to_numpy()
            now["evals"] += n_active
            reports.append({"n_active": n_active, "n_changed": seen["n_changed"]} | (dict.fromkeys(TRACED, 0) if trace else {}))
            if applied:
                drops.append(out)
            else:
                store.drop(out)
            n_active = seen["n_changed"]
            if not n_active:
                break
            if goes_on and n_active < TASK_VERTICES:
                est, n_active, applied = rest(), 0, True
                break
        after = kept(p.state, (est, est), by if n_active else None)
        store.drop(now["active"])
        now["active"], now["n_active"] = None, n_active
        if n_active:
            now["active"] = store.keep(out.where("kind = 1").select("id", "est"), by, n=F.count("*"))
        if not applied:
            store.drop(out)
        if keep_states:
            now["states"].append(after)
            if drops:
                found = g.spark.read.schema(out.schema).parquet(*[d._coreshell_path for d in drops])
                now["drops"].append(found.where("kind = 0").select("round", "id", "old", "est", "node"))
            if not n_active:
                now["placed"] = (begin, est)
        else:
            store.drop(now["state"])
        now["state"] = after
        return {"n_changed": 1 if n_active else 0, "done": not n_active, "reports": reports}

    def step(number: int) -> dict:
        if now["packs"]:
            return packed_rounds()
        n_active, state, some = now["n_active"], now["state"], now["active"]
        if not n_active:
            return {"n_active": 0, "n_changed": 0}
        arcs = g.arcs()
        if adaptive_partitions and not shuffled:
            tasks = max(1, min(int(usual), -(-now["arcs"] // ARCS_A_PARTITION)))
            g.spark.conf.set("spark.sql.shuffle.partitions", str(tasks))
        est = state.select("id", "est")
        now["part"], now["whole"] = (), fits
        if tail == "rounds" and n_active < below and fits and max_rounds is None:
            return rounds_left(number, est)
        rows = tail_rows() if tail not in ("none", "rounds") and n_active < below else None
        if rows is not None:
            new = store.keep(rows, evals=F.sum("evals"), n=F.count("*"))
            now["evals"] += new._counts["evals"]
            now["tails"] += 1
            after = store.keep(merged(est, new.select("id", "new_est"), new._counts["n"], limit), by, changed=dropped)
            store.drop(new, *now["part"])
        else:
            now["evals"] += n_active
            if shuffled:
                new = pushed(arcs, est, some if n_active <= limit else None)
            else:
                new = h_index_hist(pulled_by(arcs, est if some is None else some, n_active, est, n, limit)).where("new_est < est").select("id", "new_est")
            after = store.keep(merged(est, new, n_active, limit), by, changed=dropped)
            store.drop(*now["part"])
        changed = after._counts["changed"]
        whole = rows is not None and now["whole"]
        report = {"n_active": n_active, "n_changed": changed}
        now["active"], now["n_active"] = None, 0
        if changed and (trace or not whole):
            sent = messages(arcs, after, n, changed, limit)
            if trace:  # how many messages of the round each gate lets through
                report |= sent.agg(*[F.count(F.when(gate_predicate(k), 1)).alias(f"msgs_{k}") for k in ("all", "lower", "support")]).first().asDict()
            wake = sent.where(gate_predicate(gate)).selectExpr("dst AS id", "est").distinct()
            if gate == "counter":
                wake = woken(arcs, wake, after, n, limit)
            if not whole:
                degree = g.degrees().withColumnRenamed("id", "__id")
                wake = wake.join(small(degree, n, limit), F.col("id") == F.col("__id")).select("id", "est", "degree") if adaptive_partitions else wake
                now["active"] = store.keep(wake, by, n=F.count("*"), **({"arcs": F.sum("degree")} if adaptive_partitions else {}))
                now["n_active"], now["arcs"] = now["active"]._counts["n"], now["active"]._counts.get("arcs", m)
        elif trace:
            report |= dict.fromkeys(TRACED, 0)
        store.drop(some)
        if keep_states:
            now["states"].append(after)
            now["drops"].append(after.where("est < old").select(F.lit(number).alias("round"), "id", "old", "est"))
        else:
            store.drop(state)
        now["state"] = after
        return report | {"done": not now["n_active"], "tasks": int(g.spark.conf.get("spark.sql.shuffle.partitions"))}

    try:
        rounds = loop_until_stable(step, max_rounds)
    finally:
        g.spark.conf.set("spark.sql.shuffle.partitions", usual)
    cores = now["state"].select("id", F.col("est").alias("coreness"))
    stats = {"plan": f"frontier gate={gate} tail={tail}", "rounds": len(rounds), "evals": now["evals"], "tails": now["tails"], "active": now["active"], "seconds": time.perf_counter() - began}
    return CoreResult(cores, rounds, stats, now["states"], now["drops"], now["placed"])


def woken(arcs: DataFrame, concerned: DataFrame, state: DataFrame, n: int, limit: int = BROADCAST_VERTICES) -> DataFrame:
    """``id, est`` of those ``concerned`` (``id, est``) that have fewer supporters (neighbours of their estimate or more) than their estimate."""
    rows = pulled_by(arcs, concerned, n, state.select("id", "est"), n, limit)
    return rows.groupBy("id", "est").agg(F.count(F.when(F.col("nbr_est") >= F.col("est"), 1)).alias("k")).where("k < est").select("id", "est")
