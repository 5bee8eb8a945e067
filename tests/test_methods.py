import json
import os
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from coreshell.operators import analysis as A
from coreshell.operators import builders as B
from coreshell.operators import measures as M
from coreshell.operators.blocked import assign_blocks, coreness_blocked
from coreshell.operators.frontier import activated, coreness_frontier
from coreshell.operators.gates import gate
from coreshell.operators.graph import Graph, canonical_edges, dense_ids, profile
from coreshell.operators.mailbox import coreness_mailbox
from coreshell.operators.peel import core_number_local, cores_beyond, library_cores, peel_bucket, peel_levels
from coreshell.operators.sweep import coreness_sweep
from coreshell.plans.choose import coreness
from coreshell.plans.rounds import Store
from coreshell.sources import tables as S

from .test_kernels import brute_cores

CLIQUE_PATH = [(0, 1), (0, 2), (0, 3), (1, 2), (1, 3), (2, 3), (3, 4), (4, 5), (5, 6)]
STALE = [(0, 2), (1, 2), (1, 5), (2, 3), (3, 4)]
_r = random.Random(7)
RANDOM = [(_r.randint(0, 30), _r.randint(0, 30)) for _ in range(120)] + [(100 + i, 101 + i) for i in range(12)]

METHODS = {
    "frontier": lambda g: coreness_frontier(g),
    "rounds_all": lambda g: coreness_frontier(g, tail="none", gate="all"),
    "rounds_lower": lambda g: coreness_frontier(g, tail="none", gate="lower"),
    "rounds_support": lambda g: coreness_frontier(g, tail="none", gate="support", broadcast_vertices=0),
    "rounds_counter": lambda g: coreness_frontier(g, tail="none", gate="counter"),
    "tail_fifo": lambda g: coreness_frontier(g, tail="fifo", batch_size=8),
    "tail_heap": lambda g: coreness_frontier(g, tail="heap", batch_size=8),
    "tail_around": lambda g: coreness_frontier(g, batch_size=30, task_arcs=60),
    "bucketed": lambda g: coreness_frontier(g, tail="none", broadcast_vertices=0),
    "bucketed_tail": lambda g: coreness_frontier(g, batch_size=8, task_arcs=60, broadcast_vertices=0),
    "adaptive": lambda g: coreness_frontier(g, tail="none", adaptive_partitions=True),
    "fraction": lambda g: coreness_frontier(g, switch_fraction=0.2),
    "bucketed_mail": lambda g: coreness_mailbox(g, "batch", broadcast_vertices=0),
    "bucketed_blocks": lambda g: coreness_blocked(g, 3, "range", broadcast_vertices=0),
    "auto_frontier": lambda g: coreness(g, local_arcs=0),
    "auto_rounds": lambda g: coreness(g, local_arcs=0, plateau_rounds=1, plateau_share=0.0, tail="none"),
    "auto_blocks": lambda g: coreness(g, local_arcs=0, plateau_rounds=1, plateau_share=1.0, n_blocks=3, tail="none"),
    "blocked_hash": lambda g: coreness_blocked(g, 3, "hash"),
    "blocked_range": lambda g: coreness_blocked(g, 3, "range"),
    "blocked_chunk": lambda g: coreness_blocked(g, 3, "chunk"),
    "mail_sequential": lambda g: coreness_mailbox(g, "sequential", gate="all"),
    "mail_map": lambda g: coreness_mailbox(g, "pool", "map", batch_size=4),
    "mail_batch": lambda g: coreness_mailbox(g, "batch", batch_size=4, lookup="linear"),
    "mail_fused": lambda g: coreness_mailbox(g, "batch", phases="fused", batch_size=4, n_tasks=2),
    "sweep_rank": lambda g: coreness_sweep(g, "rank"),
    "sweep_array": lambda g: coreness_sweep(g, "array"),
    "sweep_udaf": lambda g: coreness_sweep(g, "udaf"),
    "peel_bucket": peel_bucket,
    "peel_levels": peel_levels,
    "auto": coreness,
}


def graph(spark, edges, vertices=None):
    df = spark.createDataFrame(edges, "u long, v long")
    return Graph(canonical_edges(df), None if vertices is None else spark.createDataFrame([(v,) for v in vertices], "id long"))


def found(result):
    return {r.id: r.coreness for r in result.cores.collect()}


@pytest.mark.parametrize("method", METHODS)
def test_every_method(spark, method):
    edges = RANDOM + [(200 + u, 200 + v) for u, v in STALE] + [(300 + u, 300 + v) for u, v in CLIQUE_PATH]
    assert found(METHODS[method](graph(spark, edges))) == brute_cores(edges)


def test_the_default_runs_in_parallel_until_a_batch_is_left(spark):
    """A grid with a random graph on it: thousands are active at first, fewer than 256 at the end."""
    edges = S.grid_graph(spark, 40, 40).union(spark.createDataFrame([(_r.randint(0, 1599), _r.randint(0, 1599)) for _ in range(3000)], "u long, v long"))
    g = Graph(canonical_edges(edges))
    result = coreness_frontier(g, trace=True)
    parallel = [r for r in result.rounds if r["n_active"] >= 256]
    assert len(parallel) >= 2 and result.stats["tails"] == 1 and result.rounds[-1]["n_active"] < 256
    M.assert_same_cores(result.cores, peel_bucket(g).cores)
    none = coreness_frontier(g, tail="none", trace=True)
    assert none.stats["tails"] == 0 and [r["n_active"] for r in none.rounds][: len(result.rounds)] == [r["n_active"] for r in result.rounds]
    assert coreness_frontier(g, switch_fraction=1.1).stats["rounds"] == 1


def plans_of(spark, monkeypatch, run):
    """The plans of all tables that a run writes."""
    plans, keep, n = [], Store.keep, int(spark.conf.get("spark.sql.shuffle.partitions"))

    def noted(self, df, bucketed=None, parted=None, **counts):
        rows = df.repartition(n, bucketed) if bucketed else df
        plans.append(rows._jdf.queryExecution().executedPlan().toString())
        return keep(self, df, bucketed, parted, **counts)

    monkeypatch.setattr(Store, "keep", noted)
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        result = run()
    finally:
        spark.conf.unset("spark.sql.autoBroadcastJoinThreshold")
    return plans, result


def test_three_exchanges_a_round(spark, monkeypatch):
    g = graph(spark, RANDOM)
    g.size()
    plans, result = plans_of(spark, monkeypatch, lambda: coreness_frontier(g, tail="none", broadcast_vertices=0))
    assert result.stats["rounds"] > 2
    rounds = plans[1:]  # the first is the table of degrees
    for process, activate in zip(rounds[2::2], rounds[3::2], strict=False):
        assert process.count("Exchange hashpartitioning") == 2 and activate.count("Exchange hashpartitioning") == 1, process + activate
        assert "BroadcastExchange" not in process + activate


def test_vertices_of_mailboxes_are_dealt_once(spark, monkeypatch):
    g = graph(spark, RANDOM)
    g.size()
    plans, _ = plans_of(spark, monkeypatch, lambda: coreness_mailbox(g, "batch", batch_size=4))
    assert sum("rangepartitioning" in p for p in plans) == 1
    assert all("Exchange hash" not in p for p in plans if "MapInArrow" in p)


def test_past_tables_are_removed(spark):
    for run in (lambda g: coreness_frontier(g, tail="none"), lambda g: coreness_mailbox(g, "batch"), lambda g: coreness_blocked(g, 3, "range"), lambda g: coreness_frontier(g, batch_size=30, task_arcs=60)):
        g = graph(spark, RANDOM)
        run(g)
        assert len(os.listdir(g.store.root.removeprefix("file:"))) <= 6  # arcs, degrees, blocks and the last state


def test_blocks_by_degree(spark):
    edges = S.star_graph(spark, 300).union(S.path_graph(spark, 300).select((F.col("u") + 1000).alias("u"), (F.col("v") + 1000).alias("v")))
    g = Graph(canonical_edges(edges))
    blocks = assign_blocks(g, 4, "range").join(g.degrees(), "id").groupBy("block").agg(F.sum("degree").alias("arcs"), F.min("id").alias("a"), F.max("id").alias("b")).orderBy("block").collect()
    assert all(x.b < y.a for x, y in zip(blocks, blocks[1:])) and max(r.arcs for r in blocks) <= 300 + g.size()[1] // 4
    with pytest.raises(ValueError, match="too large"):
        coreness_blocked(g, 4, "range", task_arcs=250)


def test_trace_of_a_clique_with_a_path(spark):
    g = graph(spark, CLIQUE_PATH)
    result = coreness_frontier(g, tail="none", trace=True, keep_states=True)
    rows = [(r.n_active, r.n_changed, r.msgs_all, r.msgs_lower, r.msgs_support) for r in result.trace.orderBy("round").collect()]
    assert rows == [(7, 2, 6, 1, 1), (1, 1, 2, 1, 0)]
    assert [r.avg_err for r in M.convergence_trace(result).orderBy("round").collect()] == [round(3 / 7, 6), round(1 / 7, 6), 0.0]
    wider = coreness_frontier(g, tail="none", gate="lower")
    assert wider.stats["rounds"] == 3 and wider.stats["evals"] > result.stats["evals"]


def test_the_support_gate_needs_merged_estimates(spark):
    """Judged by estimates from before the round, vertex 2 would sleep on and keep coreness 2."""
    g = graph(spark, STALE)
    before = g.degrees().select("id", F.col("degree").alias("est"))
    after = coreness_frontier(g, tail="none", max_rounds=1, keep_states=True).states[-1]
    assert {r.id for r in activated(g.arcs(), after, 10, "support").collect()} == {2}
    drops = after.where("est < old").select(F.col("id").alias("src"), "old", F.col("est").alias("new"))
    stale = g.arcs().join(drops, "src").join(before.withColumnRenamed("id", "dst"), "dst").where(gate("support"))
    assert 2 not in {r.dst for r in stale.collect()}
    assert set(found(coreness_frontier(g, tail="none")).values()) == {1}


@pytest.mark.parametrize(
    "edges, want",
    [
        (lambda s: S.path_graph(s, 6), {1}),
        (lambda s: S.cycle_graph(s, 5), {2}),
        (lambda s: S.clique_graph(s, 6), {5}),
        (lambda s: S.star_graph(s, 7), {1}),
        (lambda s: S.bipartite_graph(s, 3, 5), {3}),
        (lambda s: S.grid_graph(s, 4, 5), {2}),
        (lambda s: S.tree_graph(s, 12, 3), {1}),
    ],
)
def test_closed_forms(spark, edges, want):
    assert set(found(coreness_frontier(Graph(canonical_edges(edges(spark))))).values()) == want


def test_clean_up_and_isolated_vertices(spark):
    df = spark.createDataFrame([(1, 2), (2, 1), (1, 2), (3, 3), (None, 4), (5, None)], "u long, v long")
    assert [tuple(r) for r in canonical_edges(df).collect()] == [(1, 2)]
    with pytest.raises(Exception, match="null endpoint"):
        canonical_edges(df, nulls="error").collect()
    for method in ("frontier", "rounds_support", "blocked_hash", "mail_batch", "sweep_rank", "peel_bucket", "peel_levels"):
        assert found(METHODS[method](graph(spark, [(1, 2), (3, 3)], [1, 2, 3, 9]))) == {1: 1, 2: 1, 3: 0, 9: 0}, method
        assert found(METHODS[method](graph(spark, [], []))) == {}, method


def test_a_hub(spark):
    edges = S.star_graph(spark, 20_000).union(S.clique_graph(spark, 6))
    cores = coreness_frontier(Graph(canonical_edges(edges)), tail="none").cores
    assert {r.coreness: r.n for r in cores.groupBy("coreness").agg(F.count("*").alias("n")).collect()} == {1: 19_995, 5: 6}


def test_sizes_are_checked(spark):
    with pytest.raises(ValueError, match="too many"):
        peel_bucket(graph(spark, CLIQUE_PATH), local_arcs=5)
    with pytest.raises(ValueError, match="too many"):
        core_number_local(graph(spark, CLIQUE_PATH), local_arcs=5)


def test_measures(spark):
    g = graph(spark, CLIQUE_PATH)
    cores, layers = coreness(g).cores, A.core_layers(g)
    assert tuple(M.certify(g, cores, layers).first()) == (0, 0)
    assert tuple(M.certify(g, cores.withColumn("coreness", F.col("coreness") + 1), layers).first())[0] > 0
    assert M.certify(g, cores.withColumn("coreness", F.lit(0)), layers.withColumn("layer", F.lit(1))).first().too_low > 0
    M.assert_same_cores(cores, peel_levels(g).cores)
    with pytest.raises(AssertionError):
        M.assert_same_cores(cores, cores.where("id > 0"))
    p = profile(g, cores).first()
    assert (p.n, p.m, p.k_max, p.k_avg, p.d_avg) == (7, 9, 3, round(15 / 7, 6), round(18 / 7, 6)) and p.n_loops is None
    assert core_number_local(g) == found(coreness(g))
    assert M.speedup_curve({1: 4.0, 2: 2.0}) == {1: 1.0, 2: 2.0} and M.state_footprint(g)["private_rows"] == 18
    assert M.ratio_table({"g": {"a": 1.0, "b": 3.0}}, "a") == {"g": {"a": 1.0, "b": 3.0}}
    assert M.time_method(lambda: coreness(g), 2)["mean"] > 0


def test_stage_metrics(tmp_path):
    task = {"Shuffle Read Metrics": {"Remote Bytes Read": 5, "Local Bytes Read": 7}, "Shuffle Write Metrics": {"Shuffle Bytes Written": 11}, "Disk Bytes Spilled": 2}
    lines = [{"Event": "SparkListenerTaskEnd", "Stage ID": 3, "Task Metrics": task}] * 2 + [{"Event": "SparkListenerTaskEnd", "Stage ID": 4}, {"Event": "other"}]
    (tmp_path / "log").write_text("\n".join(map(json.dumps, lines)))
    assert M.stage_metrics(str(tmp_path / "log")) == [{"stage": 3, "tasks": 2, "shuffle_written": 22, "shuffle_read": 24, "spilled": 4}]


def test_errors_and_shares(spark):
    g = graph(spark, CLIQUE_PATH)
    result = coreness_frontier(g, tail="none", keep_states=True)
    assert sorted(map(tuple, M.error_histogram(result).collect())) == [(0, 0, 4), (0, 1, 3), (1, 0, 6), (1, 1, 1), (2, 0, 7)]
    assert [r.percent for r in M.active_trace(result, 7).orderBy("round").collect()] == [100.0, round(100 / 7, 6)]


def test_graphs_from_events(spark):
    rows = [("a", 1, 10), ("a", 2, 11), ("b", 2, 12), ("a", 1, 30), ("b", 3, 12), (None, 7, 1), (None, 8, 2)]
    events = spark.createDataFrame([(k, v, t) for k, v, t in rows], "k string, v long, t long")
    found = B.graph_sequence(events, "v", (["k"], ["t", "v"]))
    assert sorted(map(tuple, found.edges.collect())) == [(1, 2), (2, 3), (7, 8)]
    assert found.raw.where("v is not null").count() == 4  # (2, 1) and (1, 2) are both there
    near = B.graph_cooccurrence_window(events.select("v", F.timestamp_seconds("t").alias("t")), "v", "t", 1)
    assert sorted(map(tuple, near.edges.collect())) == [(1, 2), (2, 3), (7, 8)]


def test_knn_in_blocks(spark):
    vectors = [(i, [float(_r.gauss(0, 1)) for _ in range(5)]) for i in range(60)]
    df = spark.createDataFrame([*vectors, (99, None), (None, [1.0] * 5)], "vec_id long, embedding array<double>")
    norm = lambda x: sum(a * a for a in x) ** 0.5
    want = set()
    for i, x in vectors:
        like = sorted(((-sum(a * b for a, b in zip(x, y)) / norm(x) / norm(y), j) for j, y in vectors if i != j))
        want |= {(min(i, j), max(i, j)) for _, j in like[:3]}
    assert {tuple(r) for r in B.graph_knn(df, k=3, block_bytes=700).edges.collect()} == want


def test_knn_holds_some_likenesses_at_a_time(spark, monkeypatch):
    """Two blocks' likenesses were one matrix: of 32 MB blocks of 64 numbers, 34 GB. Ties, a zero vector and blocks of several slices."""
    vectors = [(i, [float(i % 7), float(i % 3) + 1, 1.0]) for i in range(40)] + [(50, [0.0, 0.0, 0.0])]
    df = spark.createDataFrame(vectors, "vec_id long, embedding array<float>")
    whole = {tuple(r) for r in B.graph_knn(df, k=3).edges.collect()}
    monkeypatch.setattr(B, "LIKENESS_BYTES", 100)
    assert {tuple(r) for r in B.graph_knn(df, k=3, block_bytes=400).edges.collect()} == whole
    like, ids = np.array([[0.5, 0.9, 0.5, 0.5]]), np.array([9, 8, 7, 6])
    assert [x.tolist() for x in B.nearest_of(like, ids, 2)] == [[0, 0], [1, 3]]
    many, ids = np.tile([0.5, 0.7, 0.5, 0.5], (3, 500)), np.arange(2000)[::-1].copy()
    many[1, 7] = 0.9
    assert [ids[x].tolist() for x in np.split(B.nearest_of(many, ids, 3)[1], 3)] == [[2, 6, 10], [1992, 2, 6], [2, 6, 10]]


def test_one_place_up_to_a_size_the_frontier_beyond(spark):
    g = graph(spark, RANDOM)
    want = peel_bucket(g).cores
    for one_place in (peel_bucket, library_cores):
        for arcs, plan in ((g.size()[1], "peel in one task" if one_place is peel_bucket else "sequential"), (g.size()[1] - 1, "frontier")):
            result = cores_beyond(g, one_place, arcs)
            assert result.stats["plan"].startswith(plan)
            M.assert_same_cores(result.cores, want)


def test_samples_and_sketches(spark):
    g = graph(spark, RANDOM)
    half = A.sampled(g, 0.5)
    assert 0 < half.edges.count() < g.edges.count() and half.edges.exceptAll(g.edges).isEmpty()
    row = A.degree_sketch(g).first()
    assert abs(row.n_degrees - g.degrees().select("degree").distinct().count()) <= 1 and len(row.percentiles) == 3
    cores = coreness(g).cores
    assert A.same_cores(cores, cores).count() == cores.count()


def test_layers_beyond_one_task(spark):
    g = graph(spark, CLIQUE_PATH)
    few = A.core_layers(g, local_arcs=3)  # fewer than the graph has
    assert sorted(map(tuple, few.collect())) == sorted(map(tuple, A.core_layers(g).collect()))


def test_analysis(spark):
    g = graph(spark, CLIQUE_PATH)
    cores = coreness(g).cores
    assert A.k_core(g, cores, 3).count() == 6 and A.k_core(A.pruned(g, 3), cores, 3).count() == 6
    assert {r.id for r in A.k_shell(cores, 1).collect()} == {4, 5, 6} == {r.id for r in A.k_crust(cores, 2).collect()}
    assert {r.id for r in A.k_corona(g, cores, 3).collect()} == {0, 1, 2, 3}
    assert A.degeneracy(cores).first()[0] == 3 and A.main_core(cores).count() == 4
    assert sorted(map(tuple, A.shell_histogram(cores).collect())) == [(1, 3, 7), (3, 4, 4)]
    assert sorted(map(tuple, A.core_density(g, cores).collect())) == [(1, 9, round(9 / 7, 6)), (3, 6, 1.5)]
    assert {r.component for r in A.core_components(g, cores, 1).collect()} == {0}
    assert [r.id for r in A.top_core_vertices(g, cores, 2).collect()] == [3, 0]
    assert [r.id for r in A.peel_order(A.core_layers(g)).collect()] == [r.id for r in A.peel_order(A.core_layers(g, local=False)).collect()]
    assert {r.id for r in A.core_changes(cores, cores.where("id < 6")).collect()} == {6}
    rows = {r.id: r for r in A.centrality_table(g, cores).collect()}
    assert (rows[3].degree, rows[3].h_index, rows[3].coreness) == (4, 3, 3)


def test_as_of(spark):
    snaps = spark.createDataFrame([(1, 10, 2), (1, 20, 5)], "id long, ts long, coreness int")
    events = spark.createDataFrame([(1, 5, 100), (1, 10, 101), (1, 19, 102), (1, 25, 103), (2, 25, 104)], "id long, ts long, event_id long")
    assert {r.event_id: r.coreness for r in A.snapshots_at(events, snaps).collect()} == {100: None, 101: 2, 102: 2, 103: 5, 104: None}


def test_dense_ids(spark):
    names = spark.createDataFrame([(x,) for x in ["b", "a", None, "c", "a", ""]], "raw string")
    rows = dense_ids(names).collect()
    assert sorted(r.id for r in rows) == [0, 1, 2, 3] and len({r.raw for r in rows}) == 4


@pytest.mark.parametrize("limit", [0, 500_000])
def test_rounds_that_one_task_goes_through_are_those_of_the_frontier(spark, limit):
    g = graph(spark, RANDOM + [(200 + i, 201 + i) for i in range(40)])
    want = coreness_frontier(g, tail="none", trace=True, keep_states=True, broadcast_vertices=limit)
    short = coreness_frontier(g, tail="rounds", trace=True, keep_states=True, batch_size=30, broadcast_vertices=limit)
    assert short.stats["tails"] == 1 and 2 < len(short.states) < len(want.states) and found(short) == found(want)
    rows = lambda r: [tuple(x)[:6] for x in r.trace.orderBy("round").collect()]
    assert rows(short) == rows(want) and short.stats["evals"] == want.stats["evals"]
    for measure in (M.convergence_trace, M.error_histogram):
        assert sorted(map(tuple, measure(short).collect())) == sorted(map(tuple, measure(want).collect()))


def test_blocks_become_one_when_few_vertices_are_awake(spark):
    edges = [(i, i + 1) for i in range(24)]
    g = graph(spark, edges)
    apart, one = coreness_blocked(g, 3, "hash", merge_below=0), coreness_blocked(g, 3, "hash")
    assert one.stats["merged"] and not apart.stats["merged"] and len(one.rounds) == 2 < len(apart.rounds) and found(one) == found(apart) == brute_cores(edges)
