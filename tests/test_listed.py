import numpy as np

from coreshell.functions.settle import Block
from coreshell.operators.frontier import SURROUNDINGS, coreness_frontier

from .test_kernels import brute_cores
from .test_methods import found, graph


def test_lists_on_disk():
    ids = np.array([1, 4, 5, 900])
    arcs = [([1, 1], [4, 5]), ([1, 4], [900, 1]), ([5, 5, 900, 900], [1, 900, 1, 5])]
    b = Block.listed([tuple(np.array(x) for x in part) for part in arcs], ids, np.array([3, 1, 2, 2]))
    assert b.settle(np.arange(4)).tolist() == [2, 1, 2, 2] and isinstance(b.nbrs, np.memmap) and b.size.tolist() == [3, 1, 2, 2]


def test_surroundings_that_get_nowhere_are_left_to_one_task(spark):
    """A path falls by one step from each end a round, 100 rounds of two hops."""
    edges = [(i, i + 1) for i in range(200)]
    result = coreness_frontier(graph(spark, edges), batch_size=30, task_arcs=60)
    assert found(result) == brute_cores(edges) and result.stats["tails"] == SURROUNDINGS + 1
