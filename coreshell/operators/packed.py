"""Rounds of the shared frontier on packed arcs: neighbour lists as numbers in binary rows, estimates sent to all tasks once a round.

Beyond what Spark broadcasts as a table, a round by joins moves a row for every arc. Packed, an arc is 4 bytes that its task reads
in place; the driver holds 4 bytes a vertex for each of two states, and one pass a round judges which vertices the last round's
drops concern, re-estimates these and returns what drops. Lists are packed from the pairs as they come, in one exchange, where the graph
was counted when it was built. Once few vertices drop, one task that holds all lists goes on with the same rounds and the tail.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from coreshell.functions.hindex import h_index_block
from coreshell.functions.settle import Block, _distinct, _places, peeled
from coreshell.operators.graph import Graph, symmetrize

#: Vertices whose two states (8 bytes each) the driver holds and every task receives; larger graphs go by joins of buckets.
PACKED_VERTICES = 16_000_000
#: Arcs that a packed row holds about (more where a hub has more: never more than 4 bytes a vertex of the graph).
ARCS_A_BLOCK = 1 << 20
BLOCKS = "ids binary, nodes binary, size binary, nbrs binary"
#: The same before positions are known: vertices and neighbours by their ids.
LISTS = "ids binary, size binary, nbrs binary"
#: The whole lists of some vertices, and a block of vertices whose neighbours are places among its own vertices and then its rim's.
PART = "block int, nodes binary, size binary, nbrs binary"
DEALT = "nodes binary, size binary, nbrs binary, rim binary, block int"
#: Drops of blocks, and a row for each block that counts.
SETTLED = "node int, est int, evals long"
#: Estimates or drops that a task hands on at a time.
ROWS = 1 << 18
#: Of a round: drops (kind 0), vertices to evaluate where a block has few (1), and a row for each block that counts (2; messages are those of the last round's drops).
PASS = "kind int, round int, id long, node int, old int, est int, n_active long, n_changed long, msgs_all long, msgs_lower long, msgs_support long"
COUNTS = ("n_active", "n_changed", "msgs_all", "msgs_lower", "msgs_support")
_TYPES = {"int": pa.int32(), "long": pa.int64()}
_SCHEMA = pa.schema([(name, _TYPES[kind]) for name, kind in (c.split() for c in PASS.split(", "))])
#: Of what one task goes on with: drops (kind 0), slices of all estimates that begin at the vertex ``node`` (1), a row for each round (2; the tail is one, the first is that of
#: the drops it began with).
REST = f"{PASS}, evals long, slice binary"
_REST = pa.schema([*_SCHEMA, ("evals", pa.int64()), ("slice", pa.binary())])


def _rows(schema: pa.Schema = _SCHEMA, **cells) -> pa.RecordBatch:
    n = max(len(x) for x in cells.values() if isinstance(x, (np.ndarray, list)))
    columns = [
        pa.nulls(n, f.type) if f.name not in cells else pa.array(x) if isinstance(x := cells[f.name], list) else pa.array(np.broadcast_to(np.asarray(x), n)).cast(f.type)
        for f in schema
    ]
    return pa.record_batch(columns, schema=schema)


def concerned(nodes: np.ndarray, ends: np.ndarray, nbrs: np.ndarray, old: np.ndarray, est: np.ndarray, gate: str) -> tuple[np.ndarray, tuple[int, int, int]]:
    """(places in ``nodes`` that drops from ``old`` to ``est`` concern, messages that the gates all, lower and support let through)."""
    hit = np.flatnonzero((est < old)[nbrs])
    owner, to = np.searchsorted(ends, hit, side="right"), nbrs[hit]
    mine = est[nodes[owner]]
    lower = est[to] < mine
    support = lower & (old[to] >= mine)
    through = {"all": slice(None), "lower": lower, "support": support, "counter": support}[gate]
    wakes = np.zeros(len(nodes), bool)
    wakes[owner[through]] = True
    return np.flatnonzero(wakes), (len(hit), int(lower.sum()), int(support.sum()))


@dataclass
class Packed:
    """``blocks`` of whole neighbour lists as positions in the ascending ``ids``."""

    blocks: DataFrame
    ids: np.ndarray
    degree: np.ndarray

    def _each(self, run, schema: str, shared) -> DataFrame:
        """``run`` over the arrays of each block, one block at a time."""

        def over(batches):
            for cells in _cells(batches, np.int64, np.int32, np.int32, np.int32):
                yield from run(shared.value, *cells)

        return self.blocks.mapInArrow(over, schema)

    def one_round(self, shared, number: int, gate: str, names: int, evaluates: bool = True) -> DataFrame:
        """The rows ``PASS`` of a round. ``shared``: (old, est, the vertices to evaluate as a mask, or None for those that drops concern).
        Blocks of fewer than ``names`` vertices to evaluate name them."""

        def run(held, ids, nodes, size, nbrs):
            old, est, asked = held
            ends = np.cumsum(size)
            active, sent = concerned(nodes, ends, nbrs, old, est, gate) if asked is None else (np.flatnonzero(asked[nodes]), (0, 0, 0))
            begins = ends - size

            def lists(some):
                if len(some) == len(nodes):
                    return nbrs
                n = size[some]
                last = np.cumsum(n)
                return nbrs[np.arange(int(last[-1]) if len(last) else 0) + np.repeat(begins[some] - last + n, n)]

            if gate == "counter" and asked is None:
                owner = np.repeat(np.arange(len(active)), size[active])
                mine = est[nodes[active]]
                active = active[np.bincount(owner, est[lists(active)] >= mine[owner], len(active)) < mine]
            changed = 0
            if len(active) and evaluates:
                mine = est[nodes[active]]
                new = h_index_block(size[active], mine, est[lists(active)])
                down = new < mine
                if changed := int(down.sum()):
                    yield _rows(kind=0, round=number, id=ids[active[down]], node=nodes[active[down]], old=mine[down], est=new[down])
            if 0 < len(active) < names:
                yield _rows(kind=1, id=ids[active], est=est[nodes[active]])
            yield _rows(kind=np.array([2]), n_active=len(active), n_changed=changed, msgs_all=sent[0], msgs_lower=sent[1], msgs_support=sent[2])

        return self._each(run, PASS, shared)

    def rest(self, shared, number: int, gate: str, tail: str, below: int, traces: bool, drops: bool) -> DataFrame:
        """The rows ``REST`` of all that is left after round ``number``, by one task that holds every list: the same rounds, while at least ``below`` vertices
        are active, and then the ``tail`` (``rounds``: further rounds). ``shared``: (old, est) of round ``number``."""
        n_arcs = int(self.degree.sum())

        def rows(moves: list[tuple], reports: list[dict]):
            """Drops and reports of several rounds: most rounds have few."""
            if moves:
                number = np.repeat([r for r, *_ in moves], [len(nodes) for _, nodes, *_ in moves])
                names, nodes, old, est = (np.concatenate([x[i] for x in moves]) for i in range(1, 5))
                for a in range(0, len(nodes), ROWS):
                    some = slice(a, a + ROWS)
                    yield _rows(_REST, kind=0, round=number[some], id=names[some], node=nodes[some], old=old[some], est=est[some])
            if reports:
                yield _rows(_REST, kind=2, **{c: np.array([r[c] for r in reports]) for c in ("round", "evals", *COUNTS)})

        def over(batches):
            old, est = shared.value
            ids = np.zeros(len(est) if drops else 0, np.int64)

            def lists():
                for names, nodes, size, nbrs in _cells(batches, np.int64, np.int32, np.int32, np.int32):
                    if drops:
                        ids[nodes] = names
                    yield nodes, size, nbrs

            moves, reports, held = [], [], 0

            def report(n_active, changed, evals, sent):
                return {"round": r, "n_active": n_active, "n_changed": len(changed), "evals": evals} | {c: sent.get(c.removeprefix("msgs_"), 0) for c in COUNTS[2:]}

            block = Block.placed(lists(), n_arcs, est)
            changed, r = np.flatnonzero(est < old), number
            active, sent = block.concerned(changed, old[changed], block.est[changed], gate)
            reports.append(report(0, changed, 0, sent))
            while n_active := len(active):
                r += 1
                if n_active < below and tail != "rounds":
                    before, done = block.est.copy(), int(block.evals.sum())
                    block.settle_in(active, tail)
                    changed, active = np.flatnonzero(block.est < before), active[:0]
                    was, now = before[changed], block.est[changed]
                    sent, evals = block.concerned(changed, was, now, "all")[1] if traces else {}, int(block.evals.sum()) - done
                else:
                    changed, was, now = block.one_round(active)
                    active, sent = block.concerned(changed, was, now, gate)
                    evals = n_active
                reports.append(report(n_active, changed, evals, sent))
                if drops and len(changed):
                    moves.append((r, ids[changed], changed, was, now))
                held += len(changed) + 1
                if held >= ROWS:
                    yield from rows(moves, reports)
                    moves, reports, held = [], [], 0
            yield from rows(moves, reports)
            for a in range(0, block.n, ROWS):
                yield _rows(_REST, kind=1, node=np.array([a]), slice=[block.est[a : a + ROWS].astype(np.int32).tobytes()])

        return self.blocks.coalesce(1).mapInArrow(over, REST)

    def dealt(self, shared) -> DataFrame:
        """The rows ``DEALT``, one a block. ``shared``: the block of every vertex. A task holds one block, some 20 bytes an arc."""

        def split(of, ids, nodes, size, nbrs):
            order = np.argsort(of[nodes], kind="stable")
            begins = np.cumsum(size) - size
            cuts = np.flatnonzero(np.diff(of[nodes[order]])) + 1
            for some in np.split(order, cuts) if len(order) else ():
                n = size[some]
                last = np.cumsum(n)
                to = nbrs[np.arange(int(last[-1])) + np.repeat(begins[some] - last + n, n)]
                yield _binary(PART, pa.array([int(of[nodes[some[0]]])], pa.int32()), nodes[some], n, to)

        def joined(rows: pa.Table) -> pa.Table:
            columns = rows.select(["nodes", "size", "nbrs"]).to_batches()
            parts = sorted(_cells(columns, np.int32, np.int32, np.int32), key=lambda part: int(part[0][0]))
            nodes, size = (np.concatenate([part[i] for part in parts]) for i in (0, 1))
            top = max(int(x.max()) for part in parts for x in (part[0], part[2])) + 1
            place, seen = np.full(top, -1, np.int32), np.zeros(top, bool)
            for part in parts:
                seen[part[2]] = True
            seen[nodes] = False
            rim = np.flatnonzero(seen).astype(np.int32)
            place[nodes], place[rim] = np.arange(len(nodes)), len(nodes) + np.arange(len(rim))
            nbrs = np.concatenate([place[part[2]] for part in parts])
            return pa.Table.from_batches([_binary(DEALT, nodes, size, nbrs, rim, rows["block"][:1].combine_chunks())])

        return self._each(split, PART, shared).groupBy("block").applyInArrow(joined, DEALT)

    def settled(self, shared, order: str) -> DataFrame:
        """``node, slice, evals``: slices of all estimates that begin at the vertex ``node``, from one task that holds every list and evaluates until nothing changes
        any more. ``shared``: (est, the vertices to begin with as a mask)."""
        n_arcs = int(self.degree.sum())

        def over(batches):
            est, asked = shared.value
            block = Block.placed(((nodes, size, nbrs) for _, nodes, size, nbrs in _cells(batches, np.int64, np.int32, np.int32, np.int32)), n_arcs, est)
            out = block.settle_in(np.flatnonzero(asked), order)
            evals = int(block.evals.sum())
            for a in range(0, block.n, ROWS):
                cells = [pa.array([a], pa.int32()), pa.array([out[a : a + ROWS].astype(np.int32).tobytes()], pa.binary()), pa.array([0 if a else evals])]
                yield pa.record_batch(cells, names=["node", "slice", "evals"])

        return self.blocks.coalesce(1).mapInArrow(over, "node int, slice binary, evals long")

    def layers(self, _) -> DataFrame:
        """``id, coreness, layer`` of all vertices, peeled by one task that holds every list."""
        n, n_arcs = len(self.degree), int(self.degree.sum())

        def over(batches):
            ids = np.zeros(n, np.int64)

            def lists():
                for names, nodes, size, nbrs in _cells(batches, np.int64, np.int32, np.int32, np.int32):
                    ids[nodes] = names
                    yield nodes, size, nbrs

            core, layer = peeled(Block.placed(lists(), n_arcs, np.zeros(n, np.int32)))
            for a in range(0, n, ROWS):
                yield pa.record_batch([pa.array(x[a : a + ROWS]) for x in (ids, core, layer)], names=["id", "coreness", "layer"])

        return self.blocks.coalesce(1).mapInArrow(over, "id long, coreness int, layer int")

    def violations(self, shared) -> DataFrame:
        """``too_high, too_low`` of each block: vertices with fewer than their coreness of neighbours of that coreness or more, and with more than it at their own or a
        later place in the peeling order. ``shared``: (coreness, layer)."""

        def run(held, ids, nodes, size, nbrs):
            core, layer = held
            owner = np.repeat(np.arange(len(nodes)), size)
            most, mine, theirs = core[nodes], core[nodes][owner], core[nbrs]
            later = (theirs > mine) | ((theirs == mine) & (layer[nbrs] >= layer[nodes][owner]))
            high, low = (np.bincount(owner, x, len(nodes)) for x in (theirs >= mine, later))
            yield pa.record_batch([pa.array([int(np.count_nonzero(x))]) for x in (high < most, low > most)], names=["too_high", "too_low"])

        return self._each(run, "too_high long, too_low long", shared)

    def state(self, shared) -> DataFrame:
        """``id, old, est`` of all vertices. ``shared``: (old, est)."""

        def run(held, ids, nodes, size, nbrs):
            yield pa.record_batch([pa.array(ids), pa.array(held[0][nodes]), pa.array(held[1][nodes])], names=["id", "old", "est"])

        return self._each(run, "id long, old int, est int", shared)


def settled_blocks(dealt: DataFrame, shared, order: str) -> DataFrame:
    """The rows ``SETTLED`` of the blocks ``DEALT`` that are awake, each settled with its rim frozen. ``shared``: (est, the vertices to begin with as a mask)."""

    def over(batches):
        est, asked = shared.value
        for nodes, size, nbrs, rim in _cells(batches, np.int32, np.int32, np.int32, np.int32):
            wake = np.flatnonzero(asked[nodes])
            if len(wake):
                block = Block.rimmed(size, nbrs, est[nodes], est[rim])
                out = block.settle_in(wake, order)
                down = out < est[nodes]
                yield pa.record_batch([pa.array(nodes[down]), pa.array(out[down].astype(np.int32)), pa.nulls(int(down.sum()), pa.int64())], names=["node", "est", "evals"])
                yield pa.record_batch([pa.nulls(1, pa.int32()), pa.nulls(1, pa.int32()), pa.array([int(block.evals.sum())])], names=["node", "est", "evals"])

    return dealt.drop("block").mapInArrow(over, SETTLED)


def wakened_blocks(dealt: DataFrame, shared) -> DataFrame:
    """``node`` of the vertices that have lost the support of a vertex of another block. ``shared``: (old, est) of a round."""

    def over(batches):
        old, est = shared.value
        for nodes, size, nbrs, rim in _cells(batches, np.int32, np.int32, np.int32, np.int32):
            was, now = old[rim], est[rim]
            hit = np.flatnonzero(nbrs >= len(nodes))
            to = nbrs[hit] - len(nodes)
            moved = (now < was)[to]
            owner, to = np.searchsorted(np.cumsum(size), hit[moved], side="right"), to[moved]
            mine = est[nodes[owner]]
            yield pa.record_batch([pa.array(nodes[_distinct(owner[(now[to] < mine) & (was[to] >= mine)])])], names=["node"])

    return dealt.drop("block").mapInArrow(over, "node int")


def kept_pass(g: Graph, run: Callable[..., DataFrame], held: object, by: str | None = None, parted: str | None = None, **counts: Column) -> DataFrame:
    """What ``run`` makes of packed rows and ``held``, which every task receives; written."""
    shared = g.spark.sparkContext.broadcast(held)
    try:
        with a_row_at_a_time(g):
            return g.store.keep(run(shared), by, parted, **counts)
    finally:
        shared.unpersist()


def sliced(rows: DataFrame, n: int) -> np.ndarray:
    """All ``n`` estimates from slices (``node, slice``)."""
    out, slices = np.empty(n, np.int32), rows.select("node", "slice").toArrow()
    for a, cell in zip(slices["node"].to_pylist(), slices["slice"], strict=True):
        part = np.frombuffer(cell.as_buffer(), np.int32)
        out[a : a + len(part)] = part
    return out


def _binary(schema: str, *cells: np.ndarray | pa.Array) -> pa.RecordBatch:
    """A row of arrays."""
    return pa.record_batch([pa.array([x.tobytes()], pa.binary()) if isinstance(x, np.ndarray) else x for x in cells], names=[c.split()[0] for c in schema.split(", ")])


def _cells(batches, *types: type) -> Iterator[list[np.ndarray]]:
    """The arrays of each row."""
    for batch in batches:
        for i in range(batch.num_rows):
            yield [np.frombuffer(batch.column(c)[i].as_buffer(), t) for c, t in enumerate(types)]


def _sorted_pairs(src: np.ndarray, dst: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct pairs by source and neighbour."""
    a, b = int(src.min()), int(dst.min())
    wide = int(dst.max()) - b + 1
    if (int(src.max()) - a + 1) * wide < 1 << 62:  # a pair as one number sorts faster
        keys = (src - a) * wide + (dst - b)
        keys.sort()
        keys = keys[np.r_[True, keys[1:] != keys[:-1]]]
        src = keys // wide
        return src + a, keys - src * wide + b
    order = np.lexsort((dst, src))
    src, dst = src[order], dst[order]
    once = np.r_[True, (src[1:] != src[:-1]) | (dst[1:] != dst[:-1])]
    return src[once], dst[once]


def _listed(rows: DataFrame) -> DataFrame:
    """``LISTS`` of arcs (``src, dst``, repeats allowed) that lie together by source. A task holds its distinct arcs and about as many repeats."""
    usual = 4 * ARCS_A_BLOCK

    def run(batches):
        held, n, least = [], 0, usual
        for batch in batches:
            held.append(tuple(batch.column(c).to_numpy() for c in (0, 1)))
            n += batch.num_rows
            if n > least:
                held = [_sorted_pairs(*map(np.concatenate, zip(*held, strict=True)))]
                n = len(held[0][0])
                least = max(least, 2 * n)
        if n:
            src, nbrs = _sorted_pairs(*map(np.concatenate, zip(*held, strict=True)))
            begins = np.flatnonzero(np.r_[True, src[1:] != src[:-1]])
            cells = [src[begins], np.diff(np.r_[begins, len(src)]).astype(np.int32), nbrs]
            yield pa.record_batch([pa.array([x.tobytes()], pa.binary()) for x in cells], names=[c.split()[0] for c in LISTS.split(", ")])

    return rows.mapInArrow(run, LISTS)


def _degrees(blocks: DataFrame) -> DataFrame:
    """``id, degree`` of the vertices in blocks or lists."""

    def run(batches):
        for ids, size in _cells(batches, np.int64, np.int32):
            yield pa.record_batch([pa.array(ids), pa.array(size)], names=["id", "degree"])

    return blocks.select("ids", "size").mapInArrow(run, "id long, degree int")


def packed_first(g: Graph, vertices: tuple[int, int]) -> None:
    """Packs a graph that was counted when it was built, before its arcs are written, if it has more vertices than the first of ``vertices`` and at most the second:
    one exchange brings all pairs to their vertices, and degrees and sizes come from there."""
    if g.about is None or not vertices[0] < g.about[0] <= vertices[1] or g.vertices is not None or g._kept.keys() & {"arcs", "packed"}:
        return
    arcs = symmetrize(g.edges if g.pairs is None else g.pairs)
    lists = g.store.keep(_listed(arcs.repartition(max(1, -(-2 * g.about[1] // ARCS_A_BLOCK)), "src")))
    found = list(_cells(lists.select("ids", "size").toArrow().to_batches(), np.int64, np.int32))
    ids, degree = (np.concatenate([np.zeros(0, t), *[x[i] for x in found]]) for i, t in enumerate((np.int64, np.int32)))
    del found
    order = np.argsort(ids)
    ids, degree = ids[order], degree[order]
    shared = g.spark.sparkContext.broadcast(ids)

    def run(batches):
        place = _places(shared.value)
        for of, size, nbrs in _cells(batches, np.int64, np.int32, np.int64):
            cells = [of, place(of).astype(np.int32), size, place(nbrs).astype(np.int32)]
            yield pa.record_batch([pa.array([x.tobytes()], pa.binary()) for x in cells], names=[c.split()[0] for c in BLOCKS.split(", ")])

    with a_row_at_a_time(g):
        blocks = g.store.keep(lists.select("ids", "size", "nbrs").mapInArrow(run, BLOCKS))
    shared.unpersist()
    g.store.drop(lists)
    g._kept |= {"packed": Packed(blocks, ids, degree), "degrees": _degrees(blocks), "size": (len(ids), int(degree.sum()))}


@contextmanager
def a_row_at_a_time(g: Graph):
    """What is written meanwhile goes to Python row by row: a row is a block."""
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    usual = g.spark.conf.get(key)
    g.spark.conf.set(key, "1")
    try:
        yield
    finally:
        g.spark.conf.set(key, usual)


def packed(g: Graph) -> Packed:
    """The graph's arcs, packed once; vertices without neighbours have no list and aren't held."""
    if "packed" not in g._kept:
        spark, m = g.spark, g.size()[1]
        found = g.degrees().select("id", "degree").toArrow()
        ids = found["id"].to_numpy()
        order = np.argsort(ids)
        ids, degree = ids[order], found["degree"].to_numpy()[order].astype(np.int32)
        shared, n = spark.sparkContext.broadcast(ids), len(ids)

        def run(batches):
            place, held = _places(shared.value), []
            for batch in batches:
                src, dst = (place(batch.column(c).to_numpy()).astype(np.int64) for c in (0, 1))
                held.append(src * n + dst)
            if not held:
                return
            keys = np.concatenate(held)
            held.clear()
            keys.sort()
            src, nbrs = keys // n, (keys % n).astype(np.int32)
            begins = np.flatnonzero(np.r_[True, src[1:] != src[:-1]])
            nodes, size = src[begins].astype(np.int32), np.diff(np.r_[begins, len(src)]).astype(np.int32)
            cells = [shared.value[nodes], nodes, size, nbrs]
            yield pa.record_batch([pa.array([x.tobytes()], pa.binary()) for x in cells], names=[c.split()[0] for c in BLOCKS.split(", ")])

        rows = g.arcs().select("src", "dst").repartition(max(1, -(-m // ARCS_A_BLOCK)), "src")
        blocks = g.store.keep(rows.mapInArrow(run, BLOCKS))
        shared.unpersist()
        g._kept["packed"] = Packed(blocks, ids, degree)
    return g._kept["packed"]


def estimates(p: Packed, table: DataFrame) -> np.ndarray:
    """``id, est`` of all vertices in the order of ``p.ids``."""
    rows = table.select("id", F.col("est").cast("int").alias("est")).toArrow()
    return rows["est"].to_numpy()[np.argsort(rows["id"].to_numpy())].astype(np.int32)


def of_all(p: Packed, table: DataFrame, column: str) -> np.ndarray | None:
    """A column of ``table`` in the order of ``p.ids``; None where it hasn't one number for each vertex."""
    rows = table.select("id", F.col(column).cast("int").alias(column)).toArrow()
    if rows.num_rows != len(p.ids) or rows["id"].null_count or rows[column].null_count:
        return None
    ids = rows["id"].to_numpy()
    order = np.argsort(ids)
    return rows[column].to_numpy()[order] if np.array_equal(ids[order], p.ids) else None
