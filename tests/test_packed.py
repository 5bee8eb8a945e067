from dataclasses import replace

import numpy as np
import pytest
from pyspark.sql import functions as F

from coreshell.operators import analysis as A
from coreshell.operators import builders as B
from coreshell.operators import measures as M
from coreshell.operators.blocked import assign_blocks, coreness_blocked, packed_blocks
from coreshell.operators.frontier import coreness_frontier
from coreshell.operators.graph import Graph
from coreshell.operators.packed import packed
from coreshell.plans.choose import coreness

from .test_kernels import brute_cores
from .test_methods import RANDOM, found, graph

EDGES = RANDOM
PACKED = (0, 1000)


@pytest.mark.parametrize(("gate", "tail"), [("counter", "none"), ("lower", "rounds"), ("support", "priority")])
def test_packed_rounds_are_those_of_the_frontier(spark, monkeypatch, gate, tail):
    monkeypatch.setattr("coreshell.operators.packed.ARCS_A_BLOCK", 50)
    options = {"gate": gate, "tail": tail, "trace": True, "keep_states": True, "batch_size": 15}
    g = graph(spark, EDGES)
    want, packed = coreness_frontier(g, **options), coreness_frontier(g, packed_vertices=PACKED, **options)
    assert found(packed) == found(want) == brute_cores([(u, v) for u, v in EDGES if u != v])
    rows = lambda r: [tuple(x)[:6] for x in r.trace.orderBy("round").collect()]
    assert rows(packed) == rows(want) and packed.stats["evals"] == want.stats["evals"] and packed.stats["tails"] == want.stats["tails"]
    assert g._kept["packed"].blocks.count() > 1
    for measure in (M.convergence_trace, M.error_histogram):
        assert sorted(map(tuple, measure(packed).collect())) == sorted(map(tuple, measure(want).collect()))


def test_packed_rounds_stop_and_go_on(spark):
    g = graph(spark, EDGES)
    some = coreness_frontier(g, max_rounds=2, tail="none", packed_vertices=PACKED)
    want = coreness_frontier(g, max_rounds=2, tail="none")
    assert found(some) == found(want) and sorted(some.stats["active"].collect()) == sorted(want.stats["active"].collect())
    for share in (0.0, 1.0):
        rest = coreness(g, local_arcs=0, plateau_rounds=2, plateau_share=share, n_blocks=3, tail="none", packed_vertices=PACKED)
        assert found(rest) == brute_cores([(u, v) for u, v in EDGES if u != v])


@pytest.mark.parametrize(("gate", "tail", "few"), [("counter", "rounds", 20), ("support", "heap", 0), ("support", "fifo", 20)])
def test_one_task_goes_on_with_the_same_rounds(spark, monkeypatch, gate, tail, few):
    """Passes until fewer than ``few`` vertices drop, then one task, whose rounds, messages and drops are those of the frontier."""
    monkeypatch.setattr("coreshell.operators.frontier.TASK_VERTICES", few)
    options = {"gate": gate, "tail": tail, "trace": True, "keep_states": True, "batch_size": 4}
    g = graph(spark, EDGES + [(200 + i, 201 + i) for i in range(30)])
    want, packed = coreness_frontier(g, **options), coreness_frontier(g, packed_vertices=PACKED, **options)
    rows = lambda r: [tuple(x)[:6] for x in r.trace.orderBy("round").collect()]
    assert found(packed) == found(want) and rows(packed) == rows(want) and len(rows(want)) > 4
    assert packed.stats["tails"] == want.stats["tails"] == 1 and (tail != "rounds" or packed.stats["evals"] == want.stats["evals"])
    assert sorted(map(tuple, M.convergence_trace(packed).collect())) == sorted(map(tuple, M.convergence_trace(want).collect()))


@pytest.mark.parametrize("shift", [0, -(1 << 62)])
def test_a_counted_graph_is_packed_from_its_pairs(spark, monkeypatch, shift):
    """No table of arcs is written for it; repeated rows, loops and nulls as ever."""
    monkeypatch.setattr("coreshell.operators.packed.ARCS_A_BLOCK", 20)
    rows = [(i % 7, i, (i * i) % 31 * (1 << 57 if shift else 1) + shift) for i in range(120)] + [(8, i, v) for i, v in enumerate([1, 2] * 150 + [2, None, 1, 2])]
    events = spark.createDataFrame(rows, "k long, t long, v long")
    g = B.graph_sequence(events, "v", (["k"], ["t"]))
    edges = [(r.u, r.v) for r in g.edges.collect()]
    assert g.about[1] == len(rows) and abs(g.about[0] - len({v for *_, v in rows} - {None})) <= 2
    result = coreness_frontier(g, packed_vertices=PACKED, batch_size=2)
    assert "arcs" not in g._kept and found(result) == brute_cores(edges)
    assert g.size() == (len({x for e in edges for x in e}), 2 * len(edges)) and g._kept["packed"].blocks.count() > 1
    want = Graph(g.edges)
    assert sorted(map(tuple, g.degrees().collect())) == sorted(map(tuple, want.degrees().collect()))
    assert found(coreness_frontier(g, max_rounds=1, tail="none", packed_vertices=PACKED)) == found(coreness_frontier(want, max_rounds=1, tail="none"))
    assert g.arcs().count() == 2 * len(edges)


@pytest.mark.parametrize(("partitioner", "order", "merge"), [("range", "priority", 0), ("hash", "heap", 0), ("chunk", "fifo", 0), ("range", "priority", 1000)])
def test_packed_blocks_go_the_rounds_of_blocks(spark, monkeypatch, partitioner, order, merge):
    monkeypatch.setattr("coreshell.operators.packed.ARCS_A_BLOCK", 50)
    edges = EDGES + [(200 + i, 201 + i) for i in range(30)]
    options = {"n_blocks": 9, "partitioner": partitioner, "order": order, "merge_below": merge}
    g = graph(spark, edges)
    want, got = coreness_blocked(g, **options), coreness_blocked(g, **options, packed_vertices=PACKED)
    assert "packed" in g._kept and found(got) == found(want) == brute_cores([(u, v) for u, v in edges if u != v])
    counts = lambda r: [(x["n_active"], x["n_changed"]) for x in r.rounds]
    assert counts(got) == counts(want) and len(counts(got)) > 1 and got.stats["merged"] == want.stats["merged"] == bool(merge)
    place = assign_blocks(g, 9, partitioner).orderBy("id").toArrow()["block"].to_pylist()
    assert packed_blocks(g, packed(g), 9, partitioner).tolist() == place


@pytest.mark.parametrize("vertices", [(1000, 2000), PACKED])
def test_blocks_too_large_for_a_task_become_more(spark, vertices):
    """The plan asks for one block; a task takes 60 arcs of some 250."""
    g = graph(spark, EDGES)
    first = coreness_frontier(g, max_rounds=1, tail="none")
    rest = coreness_blocked(g, 1, "range", start=first.cores.withColumnRenamed("coreness", "est"), active=first.stats["active"], task_arcs=60, packed_vertices=vertices)
    assert found(rest) == brute_cores([(u, v) for u, v in EDGES if u != v])
    n_blocks = int(rest.stats["plan"].split("n_blocks=")[1].split()[0])
    sizes = assign_blocks(g, n_blocks, "range").join(g.degrees(), "id").groupBy("block").agg(F.sum("degree")).toArrow()[1].to_numpy()
    assert n_blocks > 1 and np.sum(sizes) == g.size()[1] and np.max(sizes) <= 60


def test_layers_and_certificate_on_packed_arcs(spark, monkeypatch):
    """More arcs than one task takes unpacked: peeled in one task all the same, and certified where the lists lie."""
    monkeypatch.setattr("coreshell.operators.packed.ARCS_A_BLOCK", 50)
    g, table = graph(spark, EDGES), graph(spark, EDGES)
    want = A.core_layers(table, local=False)
    monkeypatch.setattr("coreshell.operators.peel.LOCAL_ARCS", 3)
    monkeypatch.setattr("coreshell.operators.analysis.peel_levels", None)
    layers = A.core_layers(g, local_arcs=3, packed_vertices=PACKED)
    assert "packed" in g._kept and sorted(map(tuple, layers.collect())) == sorted(map(tuple, want.collect()))
    cores, mixed = layers.select("id", "coreness"), F.pmod("id", F.lit(4)) - 1
    for c, p in ((cores, layers), (cores.withColumn("coreness", F.col("coreness") + mixed), layers), (cores, layers.withColumn("layer", F.lit(1))), (cores.where("id > 5"), layers)):
        assert tuple(M.certify(g, c, p).first()) == tuple(M.certify(table, c, p).first())
    assert tuple(M.certify(g, cores, layers).first()) == (0, 0) and min(M.certify(g, cores.withColumn("coreness", F.col("coreness") + mixed), layers).first()) > 0


@pytest.mark.parametrize("few", [0, 20])
def test_distances_of_packed_rounds_need_no_join(spark, monkeypatch, few):
    """Counted by place, wherever the rounds were gone through; as many rows of drops and reports as ever, in few batches from one task."""
    monkeypatch.setattr("coreshell.operators.frontier.TASK_VERTICES", few)
    g = graph(spark, EDGES + [(200 + i, 201 + i) for i in range(30)])
    result = coreness_frontier(g, tail="rounds", keep_states=True, batch_size=4, packed_vertices=PACKED)
    rows = lambda r: sorted(map(tuple, M.distances(r).collect()))
    want = rows(replace(result, placed=None))
    assert rows(replace(result, cores=spark.range(0))) == want == rows(coreness_frontier(g, tail="rounds", keep_states=True, batch_size=4))
    assert sum(d.count() for d in result.drops) == sum(r["n_changed"] for r in result.rounds) and len({r for r, *_ in want}) > 10
