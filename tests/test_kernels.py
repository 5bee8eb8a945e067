import random

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from coreshell.functions.hindex import h_index_block
from coreshell.functions.settle import Block, peel, sequential_cores


def brute_cores(edges):
    """Coreness by removing vertices of too low a degree for each k."""
    edges = {(min(e), max(e)) for e in edges if e[0] != e[1]}
    out = {v: 0 for e in edges for v in e}
    k, left = 0, set(edges)
    while left:
        k += 1
        while True:
            degree = {}
            for u, v in left:
                degree[u], degree[v] = degree.get(u, 0) + 1, degree.get(v, 0) + 1
            low = {v for v, d in degree.items() if d < k}
            if not low:
                break
            left = {(u, v) for u, v in left if u not in low and v not in low}
        out |= {v: k for e in left for v in e}
    return out


def arcs(edges):
    edges = {(min(e), max(e)) for e in edges if e[0] != e[1]}
    src = np.array([u for u, v in edges] + [v for u, v in edges], np.int64)
    dst = np.array([v for u, v in edges] + [u for u, v in edges], np.int64)
    return src, dst


graphs = st.lists(st.tuples(st.integers(0, 9), st.integers(0, 9)), max_size=40)


@given(graphs)
@settings(max_examples=200, deadline=None)
def test_peel_equals_brute_force(edges):
    ids, core, layer = peel(*arcs(edges))
    assert dict(zip(ids.tolist(), core.tolist(), strict=True)) == brute_cores(edges)
    assert (layer > 0).all()


@given(graphs)
@settings(max_examples=200, deadline=None)
def test_one_vertex_at_a_time_equals_brute_force(edges):
    neighbours = {}
    for u, v in {(min(e), max(e)) for e in edges if e[0] != e[1]}:
        neighbours.setdefault(u, []).append(v)
        neighbours.setdefault(v, []).append(u)
    assert sequential_cores(neighbours) == brute_cores(edges)


def test_long_paths_take_linear_work():
    n = 200_000
    u = np.arange(n - 1)
    src, dst = np.r_[u, u + 1], np.r_[u + 1, u]
    _, core, layer = peel(src, dst)
    assert core.max() == 1 and layer.max() == n // 2
    degree = np.bincount(src)
    b = Block(src, dst, degree[src], degree[dst])
    assert b.settle(np.arange(b.n)).max() == 1 and b.evals.sum() < 2.1 * n


@given(graphs, st.sampled_from(["priority", "fifo", "heap"]), st.randoms())
@settings(max_examples=200, deadline=None)
def test_settling_from_any_upper_bound(edges, order, rnd):
    src, dst = arcs(edges)
    want = brute_cores(edges)
    bound = {v: c + rnd.randint(0, 4) for v, c in want.items()}
    at = lambda x: np.array([bound[v] for v in x.tolist()], np.int64)
    b = Block(src, dst, at(src), at(dst))
    out = b.settle_by_heap(np.arange(b.n)) if order == "heap" else b.settle(np.arange(b.n), order)
    assert dict(zip(b.ids.tolist(), out.tolist(), strict=True)) == want


@given(graphs, st.integers(0, 9))
@settings(max_examples=150, deadline=None)
def test_a_frozen_rim_keeps_upper_bounds(edges, cut):
    src, dst = arcs(edges)
    want = brute_cores(edges)
    degree = {v: int((src == v).sum()) for v in want}
    keep = src <= cut
    at = lambda x: np.array([degree[v] for v in x.tolist()], np.int64)
    b = Block(src[keep], dst[keep], at(src[keep]), at(dst[keep]))
    out = b.settle(np.arange(b.n))
    assert all(o >= want[v] for v, o in zip(b.ids.tolist(), out.tolist(), strict=True))


@given(st.lists(st.lists(st.integers(0, 12), max_size=12), max_size=6), st.integers(0, 12))
@settings(max_examples=200, deadline=None)
def test_h_index(lists, cap):
    size = np.array([len(x) for x in lists], np.int64)
    flat = np.array([v for x in lists for v in x], np.int64)
    want = [max([h for h in range(0, min(cap, len(x)) + 1) if sum(v >= h for v in x) >= h]) for x in lists]
    assert h_index_block(size, np.full(len(lists), cap), flat).tolist() == want


def test_lowest_first_evaluates_less():
    r = random.Random(2)
    edges = [(r.randint(0, 300), r.randint(0, 300)) for _ in range(3000)] + [(1000 + i, 1001 + i) for i in range(300)]
    src, dst = arcs(edges)
    degree = np.bincount(src, minlength=2000)
    evals = {}
    for order in ("priority", "fifo"):
        b = Block(src, dst, degree[src], degree[dst])
        b.settle(np.arange(b.n), order)
        evals[order] = int(b.evals.sum())
    assert evals["priority"] < evals["fifo"]


@pytest.mark.parametrize("values", [[], [(1, 1)]])
def test_empty(values):
    ids, core, _ = peel(*arcs(values))
    assert len(ids) == len(core) == 0


@given(graphs, st.sampled_from(["all", "lower", "support", "counter"]))
@settings(max_examples=200, deadline=None)
def test_synchronous_rounds_of_a_whole_graph(edges, gate):
    src, dst = arcs(edges)
    once = src < dst
    ids = np.unique(src)
    b = Block.whole([(src[once], dst[once])], ids, np.array([(src == v).sum() for v in ids], np.int64))
    est = {v: int((src == v).sum()) for v in ids.tolist()}
    for _, changed, old, new, sent in b.rounds(np.arange(b.n), gate):
        # every vertex is re-estimated: those that were not active would not have dropped
        now = {v: max(h for h in range(est[v] + 1) if sum(est[u] >= h for u in dst[src == v].tolist()) >= h) for v in est}
        assert {b.ids[i]: (o, n) for i, o, n in zip(changed.tolist(), old.tolist(), new.tolist(), strict=True)} == {v: (est[v], now[v]) for v in est if now[v] < est[v]}
        assert sent["all"] == sum((src == v).sum() for v in est if now[v] < est[v])
        est = now
    assert est == brute_cores(edges)


def test_one_task_takes_long_rounds_by_a_heap_without_a_call_a_vertex():
    n = 100_000
    ids, u = np.arange(n), np.arange(n - 1)
    b = Block.whole([(u[:500], u[:500] + 1), (u[500:], u[500:] + 1)], ids, np.minimum(2, 1 + ((ids > 0) & (ids < n - 1))))
    assert b.settle_by_heap(ids).max() == 1 and b.evals.sum() < 2.1 * n and b.nbrs.dtype == np.int32
