"""Which method fits a graph, by its size and by how a run goes."""

from __future__ import annotations

from pyspark.sql import functions as F

from coreshell.operators.blocked import coreness_blocked
from coreshell.operators.frontier import BROADCAST_VERTICES, coreness_frontier
from coreshell.operators.graph import Graph
from coreshell.operators.mailbox import coreness_mailbox
from coreshell.operators.packed import PACKED_VERTICES, packed_first
from coreshell.operators.peel import LOCAL_ARCS, peel_bucket, peel_levels
from coreshell.operators.sweep import coreness_sweep
from coreshell.plans.rounds import CoreResult

METHODS = {"frontier": coreness_frontier, "blocked": coreness_blocked, "mailbox": coreness_mailbox, "sweep": coreness_sweep, "peel_bucket": peel_bucket, "peel_levels": peel_levels}
#: Rounds of the frontier after which a long, low plateau of active vertices is looked for, and what share of all is low.
PLATEAU_ROUNDS, PLATEAU_SHARE = 10, 0.1


def coreness(g: Graph, method: str | None = None, local_arcs: int = LOCAL_ARCS, plateau_rounds: int = PLATEAU_ROUNDS, plateau_share: float = PLATEAU_SHARE, n_blocks: int | None = None, **options) -> CoreResult:
    """Coreness of all vertices. Without ``method``: peeling in one task up to ``local_arcs`` arcs; else the frontier
    (with ``options``). If it goes on after ``plateau_rounds`` rounds, its estimates and its active vertices are handed to
    blocks where fewer than ``plateau_share`` of all are active, else to further rounds. ``stats['plan']`` says which."""
    if method is not None:
        return METHODS[method](g, **options)
    packs = {"packed_vertices": options.get("packed_vertices", (BROADCAST_VERTICES, PACKED_VERTICES)), "broadcast_vertices": options.get("broadcast_vertices", BROADCAST_VERTICES)}
    if packs["broadcast_vertices"] > 0 and g.about is not None and 2 * g.about[1] > local_arcs:
        packed_first(g, packs["packed_vertices"])
    n, m = g.size()
    if m <= local_arcs:
        return peel_bucket(g, local_arcs)
    first = coreness_frontier(g, max_rounds=plateau_rounds, **options)
    active = first.stats["active"]
    if active is None:
        return first
    start = first.cores.select("id", F.col("coreness").alias("est"))
    low = active._counts["n"] < plateau_share * n
    rest = coreness_blocked(g, n_blocks, "range", start=start, active=active, **packs) if low else coreness_frontier(g, start=start, active=active, **options)
    rounds = first.rounds + [r | {"round": len(first.rounds) + r["round"]} for r in rest.rounds]
    stats = rest.stats | {"plan": f"{first.stats['plan']}, then {rest.stats['plan']}", "rounds": len(rounds), "evals": first.stats["evals"] + rest.stats["evals"]}
    return CoreResult(rest.cores, rounds, stats)
