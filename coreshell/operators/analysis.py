"""What users ask of coreness: cores, shells, layers, components, centralities, breakdowns and snapshots."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coreshell.functions.hindex import h_index_hist
from coreshell.operators.frontier import BROADCAST_VERTICES
from coreshell.operators.graph import Graph
from coreshell.operators.packed import PACKED_VERTICES
from coreshell.operators.peel import LOCAL_ARCS, peel_bucket, peel_levels, peeled_arcs
from coreshell.plans.rounds import Store


def k_core(g: Graph, cores: DataFrame, k: int) -> DataFrame:
    """``u, v``: the edges among vertices of coreness ``k`` or more."""
    inside = cores.where(F.col("coreness") >= k).select("id")
    return g.edges.join(inside.withColumnRenamed("id", "u"), "u", "left_semi").join(inside.withColumnRenamed("id", "v"), "v", "left_semi").select("u", "v")


def pruned(g: Graph, k: int, passes: int = 3) -> Graph:
    """The graph without vertices of degree below ``k``, again and again while any are found, ``passes`` times at most: the same k-core, fewer edges."""
    for _ in range(passes):
        enough = g.degrees().where(F.col("degree") >= k).select("id")
        if enough.count() == g.size()[0]:
            break
        edges = g.edges.join(enough.withColumnRenamed("id", "u"), "u", "left_semi").join(enough.withColumnRenamed("id", "v"), "v", "left_semi")
        g = Graph(g.store.keep(edges.select("u", "v")), id_map=g.id_map)
    return g


def sampled(g: Graph, share: float, seed: int = 17) -> Graph:
    """The graph among a hash sample of its vertices: the same vertices at every run and in every graph."""
    keep = lambda c: F.pmod(F.xxhash64(F.lit(seed), F.col(c)), F.lit(1 << 20)) < int(share * (1 << 20))
    return Graph(g.store.keep(g.edges.where(keep("u") & keep("v"))), id_map=g.id_map)


def degree_sketch(g: Graph) -> DataFrame:
    """One row: distinct degrees and some of their percentiles by Spark's sketches, which never hold all degrees."""
    return g.degrees().agg(F.approx_count_distinct("degree").alias("n_degrees"), F.percentile_approx("degree", F.array(*[F.lit(x) for x in (0.5, 0.9, 0.99)]), 10_000).alias("percentiles"))


def k_shell(cores: DataFrame, k: int) -> DataFrame:
    return cores.where(F.col("coreness") == k).select("id")


def k_crust(cores: DataFrame, k: int) -> DataFrame:
    """Vertices outside the (k + 1)-core."""
    return cores.where(F.col("coreness") <= k).select("id")


def k_corona(g: Graph, cores: DataFrame, k: int) -> DataFrame:
    """Vertices of coreness ``k`` with exactly ``k`` neighbours in the k-core."""
    inside = cores.where(F.col("coreness") >= k)
    shell = inside.where(F.col("coreness") == k).select(F.col("id").alias("src"))
    arcs = g.arcs().join(shell, "src", "left_semi").join(inside.select(F.col("id").alias("dst")), "dst", "left_semi")
    return arcs.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("n")).where(F.col("n") == k).select("id")


def degeneracy(cores: DataFrame) -> DataFrame:
    return cores.agg(F.coalesce(F.max("coreness"), F.lit(0)).cast("int").alias("degeneracy"))


def main_core(cores: DataFrame) -> DataFrame:
    """The vertices of the highest coreness."""
    top = F.broadcast(cores.agg(F.max("coreness").alias("top")))  # one row
    return cores.join(top, F.col("coreness") == F.col("top")).select("id", "coreness")


def shell_histogram(cores: DataFrame) -> DataFrame:
    """``coreness, n_shell, n_core``: vertices of each coreness, and of it or more (one row for each value of coreness)."""
    shells = cores.groupBy("coreness").agg(F.count("*").alias("n_shell"))
    above = F.sum("n_shell").over(W.orderBy(F.desc("coreness")).rowsBetween(W.unboundedPreceding, 0))
    return shells.withColumn("n_core", above)


def core_layers(g: Graph, local: bool | None = None, local_arcs: int = LOCAL_ARCS, packed_vertices: tuple[int, int] = (BROADCAST_VERTICES, PACKED_VERTICES)) -> DataFrame:
    """``id, coreness, layer``: the order in which peeling removes vertices. In one task (``local``) up to ``local_arcs`` arcs, or up to ``WHOLE_ARCS`` where they
    are packed, as graphs of more vertices than the first of ``packed_vertices`` and at most the second are; else level by level."""
    if local is None:
        local_arcs = peeled_arcs(g, local_arcs, packed_vertices)
        local = g.size()[1] <= local_arcs
    return (peel_bucket(g, local_arcs) if local else peel_levels(g)).stats["layers"]


def peel_order(layers: DataFrame) -> DataFrame:
    return layers.orderBy("coreness", "layer", "id")


def core_density(g: Graph, cores: DataFrame) -> DataFrame:
    """``coreness, n_edges, density``: edges whose lower end has each coreness or more, by the vertices of that core."""
    cu, cv = cores.select(F.col("id").alias("u"), F.col("coreness").alias("cu")), cores.select(F.col("id").alias("v"), F.col("coreness").alias("cv"))
    edges = g.edges.join(cu, "u").join(cv, "v").groupBy(F.least("cu", "cv").alias("coreness")).agg(F.count("*").alias("m"))
    line = W.orderBy(F.desc("coreness")).rowsBetween(W.unboundedPreceding, 0)
    sizes = shell_histogram(cores).join(edges, "coreness", "left").withColumn("n_edges", F.sum(F.coalesce("m", F.lit(0))).over(line))
    return sizes.select("coreness", "n_edges", F.round(F.col("n_edges") / F.col("n_core"), 6).alias("density"))


def core_components(g: Graph, cores: DataFrame, k: int) -> DataFrame:
    """``id, component``: connected components of the k-core, by their smallest id. Smallest labels travel along arcs, then jump."""
    store = Store(g.spark)
    arcs = store.keep(k_core(g, cores, k).select(F.inline(F.array(F.struct(F.col("u").alias("src"), F.col("v").alias("dst")), F.struct(F.col("v").alias("src"), F.col("u").alias("dst"))))))
    state = store.keep(cores.where(F.col("coreness") >= k).select("id", F.col("id").alias("component")))
    while True:
        near = arcs.join(state.withColumnRenamed("id", "dst"), "dst").groupBy(F.col("src").alias("of")).agg(F.min("component").alias("near"))
        step = state.join(near, F.col("id") == F.col("of"), "left").select("id", F.col("component").alias("was"), F.least("component", F.coalesce("near", "component")).alias("mid"))
        jump = state.select(F.col("id").alias("at"), F.col("component").alias("far"))
        after = store.keep(step.join(jump, F.col("mid") == F.col("at"), "left").select("id", "was", F.least("mid", F.coalesce("far", "mid")).alias("component")))
        if after.where("component < was").isEmpty():
            return after.select("id", "component")
        store.drop(state)
        state = after.select("id", "component")


def _share_below(df: DataFrame, column: str) -> DataFrame:
    """``column, share``: the share of rows with smaller values, from one row for each distinct value."""
    counts = df.groupBy(column).agg(F.count("*").alias("n"))
    before = F.sum("n").over(W.orderBy(column).rowsBetween(W.unboundedPreceding, -1))
    total = F.sum("n").over(W.partitionBy())
    return counts.select(column, F.when(total > 1, F.coalesce(before, F.lit(0)) / (total - 1)).otherwise(0.0).alias("share"))


def centrality_table(g: Graph, cores: DataFrame) -> DataFrame:
    """``id, degree, h_index, coreness, degree_rank, core_rank``: three centralities, and percent ranks of two."""
    degrees = g.degrees()
    mine, other = degrees.select(F.col("id").alias("src"), F.col("degree").alias("est")), degrees.select(F.col("id").alias("dst"), F.col("degree").alias("nbr_est"))
    h = h_index_hist(g.arcs().join(mine, "src").join(other, "dst").select(F.col("src").alias("id"), "est", "nbr_est")).select("id", F.col("new_est").alias("h_index"))
    rows = degrees.join(cores, "id").join(h, "id", "left").withColumn("h_index", F.coalesce("h_index", F.lit(0)))
    d, c = _share_below(rows, "degree").withColumnRenamed("share", "degree_rank"), _share_below(rows, "coreness").withColumnRenamed("share", "core_rank")
    return rows.join(d, "degree").join(c, "coreness").select("id", "degree", "h_index", "coreness", F.round("degree_rank", 6).alias("degree_rank"), F.round("core_rank", 6).alias("core_rank"))


def coreness_outliers(g: Graph, cores: DataFrame, least: float = 0.5) -> DataFrame:
    """``id, degree, coreness, gap``: vertices whose degree ranks far above their coreness, by ``least`` or more."""
    gap = F.round(F.col("degree_rank") - F.col("core_rank"), 6)
    return centrality_table(g, cores).withColumn("gap", gap).where(F.col("gap") >= least).select("id", "degree", "coreness", "gap")


def top_core_vertices(g: Graph, cores: DataFrame, n: int) -> DataFrame:
    """The ``n`` vertices of highest coreness, ties by degree, then id."""
    return cores.join(g.degrees(), "id").orderBy(F.desc("coreness"), F.desc("degree"), "id").limit(n).select("id", "coreness", "degree")


def coreness_by(cores: DataFrame, attributes: DataFrame, dims: list[str], how: str = "rollup") -> DataFrame:
    """Vertices, mean and largest coreness by attributes of vertices (``id`` and ``dims``); how: rollup, cube or groupBy."""
    grouped = getattr(cores.join(attributes, "id"), how)(*dims)
    return grouped.agg(F.count("*").alias("n"), F.round(F.avg("coreness"), 6).alias("mean_core"), F.max("coreness").cast("int").alias("max_core"))


def snapshots_at(events: DataFrame, snapshots: DataFrame) -> DataFrame:
    """As-of join: to each event (``id, ts, event_id``) the coreness of the vertex in the latest snapshot (``id, ts, coreness``) at or before it.

    Both sides in one sorted window for each vertex, snapshots before events of the same time; null before the first.
    """
    both = snapshots.select("id", "ts", F.lit(0).alias("kind"), "coreness", F.lit(None).cast("long").alias("event_id"))
    both = both.unionByName(events.select("id", "ts", F.lit(1).alias("kind"), F.lit(None).cast("int").alias("coreness"), "event_id"))
    past = W.partitionBy("id").orderBy("ts", "kind", "event_id").rowsBetween(W.unboundedPreceding, 0)
    return both.withColumn("coreness", F.last("coreness", ignorenulls=True).over(past)).where("kind = 1").select("event_id", "id", "coreness")


def same_cores(before: DataFrame, after: DataFrame) -> DataFrame:
    """``id, coreness`` of the vertices that two results agree on."""
    return before.select("id", "coreness").intersect(after.select("id", "coreness"))


def core_changes(before: DataFrame, after: DataFrame) -> DataFrame:
    """``id, was, now``: vertices whose coreness differs between two results; null where a vertex is absent."""
    a, b = before.select("id", F.col("coreness").alias("was")), after.select("id", F.col("coreness").alias("now"))
    return a.join(b, "id", "full_outer").where(~F.col("was").eqNullSafe(F.col("now")))
