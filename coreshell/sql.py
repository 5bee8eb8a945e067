"""Names for SQL users: a function and views."""

from __future__ import annotations

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf

from coreshell.functions.settle import peel
from coreshell.operators.graph import Graph
from coreshell.plans.choose import coreness


def register_sql(spark: SparkSession, graphs: dict[str, Graph] | None = None) -> None:
    """``h_index(array<int>)``, the table functions ``peel_steps(us, vs)`` and ``neighbors_within(us, vs, start, hops)`` for small graphs in arrays, and a view ``cores_<name>`` for each graph."""

    spark.sql(
        "CREATE OR REPLACE TEMPORARY FUNCTION h_index(estimates ARRAY<INT>) RETURNS INT RETURN "
        "IF(estimates IS NULL, NULL, coalesce(array_max(transform(reverse(array_sort(estimates)), (x, i) -> least(x, i + 1))), 0))"
    )

    @udtf(returnType="id bigint, coreness int, layer int")
    class PeelSteps:
        def eval(self, us, vs):
            pairs = {(min(u, v), max(u, v)) for u, v in zip(us, vs) if u != v}
            src = np.array([p[0] for p in pairs] + [p[1] for p in pairs], np.int64)
            dst = np.array([p[1] for p in pairs] + [p[0] for p in pairs], np.int64)
            for i, c, s in zip(*(x.tolist() for x in peel(src, dst)), strict=True):
                yield i, c, s

    @udtf(returnType="id bigint, hops int")
    class NeighborsWithin:
        def eval(self, us, vs, start, hops):
            near = {}
            for u, v in zip(us, vs):
                near.setdefault(u, set()).add(v)
                near.setdefault(v, set()).add(u)
            seen, edge = {start: 0}, [start]
            for h in range(1, hops + 1):
                edge = [w for u in edge for w in near.get(u, ()) if seen.setdefault(w, h) == h and w not in edge]
                edge = list(dict.fromkeys(edge))
            yield from seen.items()

    spark.udtf.register("peel_steps", PeelSteps)
    spark.udtf.register("neighbors_within", NeighborsWithin)
    for name, g in (graphs or {}).items():
        g.named(coreness(g).cores).createOrReplaceTempView(f"cores_{name}")
