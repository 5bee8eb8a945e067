"""The registered queries over the experiment graphs, and their SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coreshell.operators import analysis as A
from coreshell.operators import builders as B
from coreshell.operators import measures as M
from coreshell.operators.blocked import coreness_blocked
from coreshell.operators.frontier import TASK_VERTICES, coreness_frontier
from coreshell.operators.graph import Graph, profile
from coreshell.operators.mailbox import coreness_mailbox
from coreshell.operators.peel import DRIVER_ARCS, cores_beyond, library_cores, peel_bucket, peel_levels
from coreshell.operators.sweep import coreness_sweep
from coreshell.plans.choose import coreness
from coreshell.plans.rounds import Store
from coreshell.sources.tables import read_table
from coreshell.sql import register_sql
from coreshell.streaming import windows
from coreshell.streaming.incremental import IncrementalCores
from coreshell.workloads.graphs import ARCS_SQL, BUILDERS, GRAPHS, NAMED, PEELED_SQL, RAW_SQL, STATES_SQL, build, edges_sql, layers_sql, named_sql, states_sql

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def register(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql:
        ORACLES[name] = sql


def long_cores(g: Graph, cores: DataFrame) -> DataFrame:
    return g.named(cores.select("id", F.col("coreness").cast("long").alias("coreness")))


def _cores_query(graph: str, run: Callable) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = build(spark, sf_dir, graph)
        return long_cores(g, run(g).cores)

    return query


def _cores_sql(graph: str) -> str:
    return named_sql(graph, "CAST(k AS BIGINT) AS coreness")


def _on(graph: str, f: Callable[[Graph, DataFrame], DataFrame]) -> Query:
    """A query on a graph and its coreness by the shared frontier."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = build(spark, sf_dir, graph)
        return f(g, coreness_frontier(g).cores)

    return query


def _named_edges(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    """Which end of an edge is the smaller one is told by the names."""
    g = build(spark, sf_dir, graph)
    edges = g.named(g.named(g.edges, "u"), "v")
    return edges.select(F.least("u", "v").alias("u"), F.greatest("u", "v").alias("v"))


def _degrees(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    g = build(spark, sf_dir, graph)
    return g.named(g.degrees().select("id", F.col("degree").cast("long").alias("degree")))


# --- graphs: edges, degrees, coreness, profile -------------------------------

for _g in GRAPHS:
    _table = "named" if _g in NAMED else "e"
    register(f"edges_{_g}", lambda s, d, n=_g: _named_edges(s, d, n), f"WITH {edges_sql(_g)} SELECT u, v FROM {_table}")
    register(f"degree_{_g}", lambda s, d, n=_g: _degrees(s, d, n), f"WITH {edges_sql(_g)} SELECT id, count(*) AS degree FROM (SELECT u AS id FROM {_table} UNION ALL SELECT v FROM {_table}) GROUP BY id")
    register(f"cores_{_g}", _cores_query(_g, coreness_frontier), _cores_sql(_g))
    register(
        f"profile_{_g}",
        _on(_g, profile),
        f"{states_sql(_g)}, raw AS (SELECT count(*) AS n_rows_raw, count(*) FILTER (WHERE u = v) AS n_loops FROM ({RAW_SQL[_g]}) WHERE u IS NOT NULL AND v IS NOT NULL) "
        "SELECT n_rows_raw, n_loops, (SELECT count(*) FROM final) AS n, (SELECT count(*) FROM e) AS m, (SELECT CAST(max(k) AS BIGINT) FROM final) AS k_max, "
        "(SELECT round(avg(k), 6) FROM final) AS k_avg, round(2 * (SELECT count(*) FROM e) / (SELECT count(*) FROM final), 6) AS d_avg FROM raw",
    )

# --- variants and baselines, all with the same result --------------------------

for _name, _graph, _run in [
    ("cores_sm_order_part", "order_part", lambda g: coreness_mailbox(g, "sequential", gate="all")),
    ("cores_tm_iterator_user_key", "user_key", lambda g: coreness_mailbox(g, "iterator")),
    ("cores_tm_pool_user_key", "user_key", lambda g: coreness_mailbox(g, "pool")),
    ("cores_tm_batch_user_key", "user_key", lambda g: coreness_mailbox(g, "batch")),
    ("cores_map_user_key", "user_key", lambda g: coreness_mailbox(g, neighbors="map")),
    ("cores_sorted_user_key", "user_key", lambda g: coreness_mailbox(g, neighbors="sorted")),
    ("cores_linear_lookup_page_link", "page_link", lambda g: coreness_mailbox(g, lookup="linear")),
    ("cores_split_customer_part", "customer_part", lambda g: coreness_mailbox(g, "batch", phases="split")),
    ("cores_fused_customer_part", "customer_part", lambda g: coreness_mailbox(g, "batch", phases="fused")),
    *[(f"cores_gate_{k}_customer_part", "customer_part", lambda g, k=k: coreness_frontier(g, gate=k, tail="none")) for k in ("all", "lower", "support", "counter")],
    ("cores_tail_none_doc_line", "doc_line", lambda g: coreness_frontier(g, tail="none")),
    *[(f"cores_tail_{t}_order_grid", "order_grid", lambda g, t=t: coreness_frontier(g, tail=t, batch_size=4096)) for t in ("priority", "fifo", "heap")],
    ("cores_tail_surroundings_order_grid", "order_grid", lambda g: coreness_frontier(g, batch_size=4096, task_arcs=40_000)),
    ("cores_task_batch_order_part", "order_part", lambda g: coreness_frontier(g, batch_size=TASK_VERTICES)),
    ("cores_switch_fraction_customer_part", "customer_part", lambda g: coreness_frontier(g, switch_fraction=0.1)),
    ("cores_adaptive_partitions_order_part", "order_part", lambda g: coreness_frontier(g, adaptive_partitions=True)),
    ("cores_bucketed_user_handoff", "user_handoff", lambda g: coreness_frontier(g, tail="none", broadcast_vertices=0)),
    ("cores_bucketed_mail_user_key", "user_key", lambda g: coreness_mailbox(g, "batch", broadcast_vertices=0)),
    *[(f"cores_blocked_{p}_order_grid", "order_grid", lambda g, p=p: coreness_blocked(g, 8, p)) for p in ("hash", "range", "chunk")],
    *[(f"cores_sweep_{k}_user_key", "user_key", lambda g, k=k: coreness_sweep(g, k)) for k in ("hist", "rank", "array", "udaf")],
    ("cores_peel_bucket_order_part", "order_part", lambda g: cores_beyond(g, peel_bucket)),
    ("cores_peel_levels_page_link", "page_link", peel_levels),
    ("cores_auto_peel_part_copurchase", "part_copurchase", coreness),
    ("cores_auto_frontier_part_supplier", "part_supplier", lambda g: coreness(g, local_arcs=0)),
    ("cores_auto_rounds_order_part", "order_part", lambda g: coreness(g, local_arcs=0, plateau_rounds=2, plateau_share=0.0)),
    ("cores_auto_blocks_order_grid", "order_grid", lambda g: coreness(g, local_arcs=0, plateau_rounds=2, plateau_share=1.0, n_blocks=4)),
]:
    register(_name, _cores_query(_graph, _run), _cores_sql(_graph))


register("cores_library_customer_supplier", _cores_query("customer_supplier", lambda g: cores_beyond(g, library_cores, DRIVER_ARCS)), _cores_sql("customer_supplier"))


def _incremental(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of even suppliers first, then the others, then some deleted and inserted again."""
    edges = build(spark, sf_dir, "part_supplier").edges
    state = IncrementalCores(edges.where("pmod(v, 4) = 1 or pmod(u, 4) = 1"))
    state.apply(edges)
    some = edges.where("pmod(u + v, 11) = 0")
    state.apply(deletes=some)
    return state.apply(some).select("id", F.col("coreness").cast("long").alias("coreness"))


register("cores_incremental_part_supplier", _incremental, _cores_sql("part_supplier"))

# --- how the runs go: distances, active vertices, messages ----------------------

TRACED = ("order_grid", "part_copurchase", "customer_part", "doc_line", "user_handoff")


def _convergence(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    trace = M.convergence_trace(coreness_frontier(build(spark, sf_dir, graph), tail="rounds", keep_states=True))
    return trace.select("round", "avg_err", F.col("max_err").cast("long").alias("max_err"), "within_1", "n_off")


def _errors(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    errors = M.error_histogram(coreness_frontier(build(spark, sf_dir, graph), tail="rounds", keep_states=True))
    return errors.select("round", F.col("err").cast("long").alias("err"), "n")


def _rounds(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    trace = coreness_frontier(build(spark, sf_dir, graph), tail="rounds", trace=True).trace
    return trace.select(F.col("round").cast("long").alias("round"), "n_active", "n_changed", "msgs_all", "msgs_lower", "msgs_support")


def _active(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    g = build(spark, sf_dir, graph)
    return M.active_trace(coreness_frontier(g, tail="rounds"), g.size()[0]).select(F.col("round").cast("long").alias("round"), "n_active", "percent")


_ERRORS = "FROM s JOIN final USING (id) WHERE it = 0 OR changed"
_ROUNDS = """,
d AS MATERIALIZED (SELECT * FROM (SELECT it, id, k AS new, lag(k) OVER (PARTITION BY id ORDER BY it) AS old FROM s) WHERE new < old),
sent AS MATERIALIZED (SELECT d.it, a.dst, d.old, d.new FROM d JOIN a ON a.src = d.id),
m AS MATERIALIZED (SELECT sent.it, dst, old, new, y.k AS est FROM sent JOIN s y ON y.id = sent.dst AND y.it = sent.it),
counts AS (SELECT it, count(*) AS msgs_all, count(*) FILTER (WHERE new < est) AS msgs_lower, count(*) FILTER (WHERE new < est AND old >= est) AS msgs_support, count(DISTINCT dst) FILTER (WHERE new < est AND old >= est) AS wakes FROM m GROUP BY it),
drops AS (SELECT it, count(*) AS n_changed FROM d GROUP BY it),
r AS (SELECT it AS round, CASE WHEN it = 1 THEN (SELECT count(*) FROM final) ELSE coalesce(wakes, 0) END AS n_active FROM (SELECT DISTINCT it FROM s WHERE it > 0) i LEFT JOIN (SELECT it + 1 AS next, wakes FROM counts) ON next = it)
"""
for _g in TRACED:
    register(
        f"convergence_{_g}",
        lambda s, d, n=_g: _convergence(s, d, n),
        f"{states_sql(_g)} SELECT it AS round, round(avg(s.k - final.k), 6) AS avg_err, CAST(max(s.k - final.k) AS BIGINT) AS max_err, round(avg(CASE WHEN s.k - final.k <= 1 THEN 1.0 ELSE 0.0 END), 6) AS within_1, "
        f"count(*) FILTER (WHERE s.k > final.k) AS n_off {_ERRORS} GROUP BY it",
    )
    register(
        f"rounds_{_g}",
        lambda s, d, n=_g: _rounds(s, d, n),
        f"{states_sql(_g)}{_ROUNDS} SELECT CAST(round AS BIGINT) AS round, n_active, coalesce(n_changed, 0) AS n_changed, coalesce(msgs_all, 0) AS msgs_all, coalesce(msgs_lower, 0) AS msgs_lower, coalesce(msgs_support, 0) AS msgs_support "
        "FROM r LEFT JOIN counts ON counts.it = round LEFT JOIN drops ON drops.it = round WHERE n_active > 0",
    )
for _g in ("order_grid", "part_copurchase", "doc_line"):
    register(
        f"active_{_g}",
        lambda s, d, n=_g: _active(s, d, n),
        f"{states_sql(_g)}{_ROUNDS} SELECT CAST(round AS BIGINT) AS round, n_active, round(100.0 * n_active / (SELECT count(*) FROM final), 6) AS percent FROM r WHERE n_active > 0",
    )
for _g in ("customer_part", "user_handoff"):
    register(f"errors_{_g}", lambda s, d, n=_g: _errors(s, d, n), f"{states_sql(_g)} SELECT it AS round, CAST(s.k - final.k AS BIGINT) AS err, count(*) AS n {_ERRORS} GROUP BY 1, 2")

# --- what users ask ---------------------------------------------------------------

K = {"part_supplier": 30, "order_part": 4, "user_key": 40}
register("kcore_edges_part_supplier", _on("part_supplier", lambda g, c: A.k_core(g, c, 30)), f"{states_sql('part_supplier')} SELECT u, v FROM e WHERE u IN (SELECT id FROM final WHERE k >= 30) AND v IN (SELECT id FROM final WHERE k >= 30)")
register("kcore_pruned_part_supplier", lambda s, d: (lambda g: A.k_core(g, coreness(g).cores, 30))(A.pruned(build(s, d, "part_supplier"), 30)), ORACLES["kcore_edges_part_supplier"])
register("kshell_order_part", _on("order_part", lambda g, c: A.k_shell(c, 4)), f"{states_sql('order_part')} SELECT id FROM final WHERE k = 4")
register("kcrust_order_part", _on("order_part", lambda g, c: A.k_crust(c, 3)), f"{states_sql('order_part')} SELECT id FROM final WHERE k <= 3")
register("kcorona_order_part", _on("order_part", lambda g, c: A.k_corona(g, c, 4)), f"{states_sql('order_part')} SELECT src AS id FROM a JOIN final x ON x.id = src AND x.k = 4 JOIN final y ON y.id = dst AND y.k >= 4 GROUP BY src HAVING count(*) = 4")
register("main_core_user_key", _on("user_key", lambda g, c: A.main_core(c).select("id", F.col("coreness").cast("long").alias("coreness"))), f"{states_sql('user_key')} SELECT id, CAST(k AS BIGINT) AS coreness FROM final WHERE k = (SELECT max(k) FROM final)")
register("degeneracy_user_handoff", _on("user_handoff", lambda g, c: A.degeneracy(c).select(F.col("degeneracy").cast("long").alias("degeneracy"))), f"{states_sql('user_handoff')} SELECT CAST(max(k) AS BIGINT) AS degeneracy FROM final")
register("shell_hist_doc_line", _on("doc_line", lambda g, c: A.shell_histogram(c).select(F.col("coreness").cast("long").alias("coreness"), "n_shell", "n_core")), f"{states_sql('doc_line')} SELECT CAST(k AS BIGINT) AS coreness, count(*) AS n_shell, CAST(sum(count(*)) OVER (ORDER BY k DESC) AS BIGINT) AS n_core FROM final GROUP BY k")
register(
    "core_density_customer_part",
    _on("customer_part", lambda g, c: A.core_density(g, c).select(F.col("coreness").cast("long").alias("coreness"), F.col("n_edges").cast("long").alias("n_edges"), "density")),
    f"""{states_sql('customer_part')}, m AS (SELECT least(x.k, y.k) AS k, count(*) AS m FROM e JOIN final x ON x.id = u JOIN final y ON y.id = v GROUP BY 1),
h AS (SELECT k, count(*) AS n FROM final GROUP BY k),
c AS (SELECT k, CAST(sum(n) OVER (ORDER BY k DESC) AS BIGINT) AS n, CAST(sum(coalesce(m, 0)) OVER (ORDER BY k DESC) AS BIGINT) AS m FROM h LEFT JOIN m USING (k))
SELECT CAST(k AS BIGINT) AS coreness, m AS n_edges, round(m / n, 6) AS density FROM c""",
)
register(
    "core_components_page_link",
    lambda s, d: (lambda g: (lambda c: (lambda x: x.join(x.groupBy(F.col("component").alias("of")).agg(F.min("id").alias("least")), F.col("component") == F.col("of")).select("id", F.col("least").alias("component")))(g.named(A.core_components(g, c, 2))))(g.store.keep(coreness(g).cores)))(build(s, d, "page_link")),
    f"""{states_sql('page_link')}, k2 AS MATERIALIZED (SELECT ids.raw AS id FROM final JOIN ids USING (id) WHERE k >= 2),
ke AS MATERIALIZED (SELECT u, v FROM named WHERE u IN (SELECT id FROM k2) AND v IN (SELECT id FROM k2)),
ka AS MATERIALIZED (SELECT u AS src, v AS dst FROM ke UNION ALL SELECT v, u FROM ke),
reach (id, component) AS (SELECT id, id FROM k2 UNION SELECT ka.dst, reach.component FROM reach JOIN ka ON ka.src = reach.id)
SELECT id, min(component) AS component FROM reach GROUP BY id""",
)
_RANKS = """, nb AS (SELECT src AS id, max(least(r, d)) AS h FROM (SELECT a.src, y.k AS d, row_number() OVER (PARTITION BY a.src ORDER BY y.k DESC) AS r FROM a JOIN deg y ON y.id = a.dst) GROUP BY src),
ct AS (SELECT id, deg.k AS degree, least(h, deg.k) AS h_index, CAST(final.k AS BIGINT) AS coreness, round(percent_rank() OVER (ORDER BY deg.k), 6) AS degree_rank, round(percent_rank() OVER (ORDER BY final.k), 6) AS core_rank FROM deg JOIN final USING (id) JOIN nb USING (id))"""
register("centrality_user_key", _on("user_key", lambda g, c: A.centrality_table(g, c).select("id", *[F.col(x).cast("long").alias(x) for x in ("degree", "h_index", "coreness")], "degree_rank", "core_rank")), f"{states_sql('user_key')}{_RANKS} SELECT id, degree, CAST(h_index AS BIGINT) AS h_index, coreness, degree_rank, core_rank FROM ct")
register("outliers_doc_line", _on("doc_line", lambda g, c: g.named(A.coreness_outliers(g, c).select("id", F.col("degree").cast("long").alias("degree"), F.col("coreness").cast("long").alias("coreness"), "gap"))), f"{states_sql('doc_line')}{_RANKS} SELECT raw AS id, degree, coreness, round(degree_rank - core_rank, 6) AS gap FROM ct JOIN ids USING (id) WHERE round(degree_rank - core_rank, 6) >= 0.5")
register("top_vertices_customer_part", _on("customer_part", lambda g, c: A.top_core_vertices(g, c, 20).select("id", F.col("coreness").cast("long").alias("coreness"), F.col("degree").cast("long").alias("degree"))), f"{states_sql('customer_part')} SELECT id, CAST(final.k AS BIGINT) AS coreness, deg.k AS degree FROM final JOIN deg USING (id) ORDER BY final.k DESC, deg.k DESC, id LIMIT 20")


def _customers(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = read_table(spark, sf_dir, "customer").join(read_table(spark, sf_dir, "nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(read_table(spark, sf_dir, "region"), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.select((2 * F.col("c_custkey")).alias("id"), F.col("r_name").alias("region"), F.col("n_name").alias("nation"), F.col("c_mktsegment").alias("segment"))


def _by(dims: list[str], how: str) -> Query:
    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = build(spark, sf_dir, "customer_supplier")
        return A.coreness_by(coreness(g).cores, _customers(spark, sf_dir), dims, how).withColumn("max_core", F.col("max_core").cast("long"))

    return query


_CUSTOMERS = "(SELECT 2 * c_custkey AS id, r_name AS region, n_name AS nation, c_mktsegment AS segment FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey)"
for _n, _dims, _how in (("coreness_by_nation_rollup", ["region", "nation"], "rollup"), ("coreness_by_segment_cube", ["region", "segment"], "cube")):
    register(_n, _by(_dims, _how), f"{states_sql('customer_supplier')} SELECT {', '.join(_dims)}, count(*) AS n, round(avg(k), 6) AS mean_core, CAST(max(k) AS BIGINT) AS max_core FROM final JOIN {_CUSTOMERS} USING (id) GROUP BY {_how}({', '.join(_dims)})")

ASOF = "2024-01-15"


def _asof_graph(spark: SparkSession, sf_dir: str) -> Graph:
    return BUILDERS["user_key"](lambda t: read_table(spark, sf_dir, t).where(F.col("ts") < F.lit(ASOF).cast("timestamp")) if t == "events" else read_table(spark, sf_dir, t))


_EARLY = states_sql("user_key").replace("FROM events", f"FROM (SELECT * FROM events WHERE ts < TIMESTAMP '{ASOF}')")
register("asof_user_key", lambda s, d: (lambda g: long_cores(g, coreness(g).cores))(_asof_graph(s, d)), f"{_EARLY} SELECT id, CAST(k AS BIGINT) AS coreness FROM final")


def _windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    events = read_table(spark, sf_dir, "events").select((2 * F.col("user_id")).alias("u"), (2 * F.get_json_object("props", "$.k").cast("long") + 1).alias("v"), "ts")
    return windows.windowed_cores(events, "u", "v", "ts", "7 days").select(F.col("g").cast("string").alias("start"), "vertex", F.col("coreness").cast("long").alias("coreness"))


# one graph whose vertices are (window, vertex): windows of seven days count from the epoch
_WINDOWED = """WITH RECURSIVE w AS (SELECT CAST(floor(epoch(ts) / 604800) AS BIGINT) AS g, 2 * user_id AS u, 2 * CAST(json_extract_string(props, '$.k') AS BIGINT) + 1 AS v FROM events),
e AS MATERIALIZED (SELECT DISTINCT g * 1000000000 + least(u, v) AS u, g * 1000000000 + greatest(u, v) AS v FROM w)"""
register(
    "window_cores_events",
    _windows,
    f"{_WINDOWED},\n{ARCS_SQL},\n{STATES_SQL}" + " SELECT strftime(make_timestamp(CAST(id // 1000000000 AS BIGINT) * 604800 * 1000000), '%Y-%m-%d %H:%M:%S') AS start, CAST(id % 1000000000 AS BIGINT) AS vertex, CAST(k AS BIGINT) AS coreness FROM final",
)

# --- sessions, late and repeated rows, running degrees, events close in time, SQL names ---------------


def _user_keys(spark: SparkSession, sf_dir: str) -> DataFrame:
    return read_table(spark, sf_dir, "events").select("event_id", "ts", F.col("user_id").alias("user"), F.get_json_object("props", "$.k").cast("long").alias("k"))


def _sessions(spark: SparkSession, sf_dir: str) -> DataFrame:
    cores = windows.parted_cores(windows.session_pairs(_user_keys(spark, sf_dir), "user", "k", "ts", "1 hour"))
    return cores.groupBy("g").agg(F.count("*").alias("n"), F.max("coreness").cast("long").alias("k_max")).select("g.user", F.unix_micros("g.start").alias("start"), "n", "k_max")


register(
    "session_cores_events",
    _sessions,
    """WITH r AS (SELECT user_id AS user, ts, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k, lag(ts) OVER (PARTITION BY user_id ORDER BY ts) AS before FROM events),
s AS (SELECT *, sum(CASE WHEN before IS NULL OR ts > before + INTERVAL 1 HOUR THEN 1 ELSE 0 END) OVER (PARTITION BY user ORDER BY ts ROWS UNBOUNDED PRECEDING) AS i FROM r),
e AS (SELECT user, i, min(ts) AS start, count(DISTINCT k) AS keys FROM s GROUP BY user, i),
deg AS (SELECT user, i, start, keys + 1 AS n, least(keys, 1) AS k_max FROM e)
SELECT user, epoch_us(start) AS start, n, k_max FROM deg WHERE n > 1""",
)


def _streamed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All events twice as a stream: the second copies are dropped as repeated, and degrees are counted as rows arrive."""
    folder = f"{Store(spark).root}/stream"
    rows = _user_keys(spark, sf_dir)
    for copy in range(2):
        rows.repartitionByRange(1, "ts").sortWithinPartitions("ts").write.parquet(f"{folder}/in/{copy}")
    stream = spark.readStream.schema(rows.schema).option("recursiveFileLookup", True).parquet(f"{folder}/in")
    once = windows.deduplicated(stream, "event_id", "ts", "60 days").select((2 * F.col("user")).alias("u"), (2 * F.col("k") + 1).alias("v"))
    return windows.latest(windows.streaming_degrees(once), ["id"], f"{folder}/out", f"{folder}/at")


register(
    "stream_degrees_events",
    _streamed,
    "SELECT id, count(*) AS degree FROM (SELECT 2 * user_id AS id FROM events UNION ALL SELECT 2 * CAST(json_extract_string(props, '$.k') AS BIGINT) + 1 FROM events) GROUP BY id",
)


def _late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Days as a stream of files: odd days, the latest row once more, then even days, which come too late for an hour's delay.

    Lateness is judged by the watermark that the last batch but one has set, so a batch lies between.
    """
    folder = f"{Store(spark).root}/stream"
    rows = _user_keys(spark, sf_dir).select((2 * F.col("user")).alias("u"), (2 * F.col("k") + 1).alias("v"), "ts")
    odd = F.dayofmonth("ts") % 2 == 1
    for i, part in enumerate((rows.where(odd), rows.where(odd).orderBy(F.desc("ts")).limit(1), rows.where(~odd & (F.dayofmonth("ts") < 20)))):
        part.coalesce(1).write.parquet(f"{folder}/in/{i}")
    stream = spark.readStream.schema(rows.schema).option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(f"{folder}/in")
    edges = windows.closed_window_edges(stream, "u", "v", "ts", "1 day", "1 hour")
    edges.writeStream.outputMode("append").format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/at").trigger(availableNow=True).start().awaitTermination()
    return spark.read.parquet(f"{folder}/out").groupBy(F.col("g").cast("string").alias("day")).agg(F.count("*").alias("n_edges"))


# a day is closed once the latest row, less an hour, has passed its end
register(
    "late_rows_events",
    _late,
    """WITH r AS (SELECT date_trunc('day', ts) AS day, ts, 2 * user_id AS u, 2 * CAST(json_extract_string(props, '$.k') AS BIGINT) + 1 AS v FROM events WHERE extract(day FROM ts) % 2 = 1),
w AS (SELECT max(ts) - INTERVAL 1 HOUR AS mark FROM r)
SELECT strftime(day, '%Y-%m-%d %H:%M:%S') AS day, count(*) AS n_edges FROM (SELECT DISTINCT day, u, v FROM r, w WHERE day + INTERVAL 1 DAY <= mark) GROUP BY day""",
)
register(
    "edges_close_events",
    lambda s, d: B.graph_cooccurrence_window(read_table(s, d, "events"), "user_id", "ts", 120).edges,
    "SELECT DISTINCT least(a.user_id, b.user_id) AS u, greatest(a.user_id, b.user_id) AS v FROM events a JOIN events b ON a.user_id <> b.user_id "
    "AND floor(epoch(b.ts)) - floor(epoch(a.ts)) BETWEEN 0 AND 120",
)


def _sql_h_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = build(spark, sf_dir, "user_key")
    register_sql(spark)
    degrees = g.degrees().select(F.col("id").alias("dst"), F.col("degree").alias("of"))
    rows = g.arcs().join(degrees, "dst").groupBy(F.col("src").alias("id")).agg(F.collect_list("of").alias("all"))
    return rows.select("id", F.expr("CAST(h_index(all) AS BIGINT)").alias("h_index"))


register("sql_h_index_user_key", _sql_h_index, f"{states_sql('user_key')} SELECT src AS id, max(least(r, d)) AS h_index FROM (SELECT a.src, y.k AS d, row_number() OVER (PARTITION BY a.src ORDER BY y.k DESC) AS r FROM a JOIN deg y ON y.id = a.dst) GROUP BY src")


def _sql_peel(spark: SparkSession, sf_dir: str) -> DataFrame:
    register_sql(spark)
    build(spark, sf_dir, "user_handoff").edges.createOrReplaceTempView("edges_of_user_handoff")
    return spark.sql("SELECT p.id, CAST(p.coreness AS BIGINT) AS coreness, CAST(p.layer AS BIGINT) AS layer FROM (SELECT collect_list(u) AS us, collect_list(v) AS vs FROM edges_of_user_handoff), LATERAL peel_steps(us, vs) p")


register("sql_peel_steps_user_handoff", _sql_peel, f"{layers_sql('user_handoff')} SELECT id, CAST(lev AS BIGINT) AS coreness, CAST(step AS BIGINT) AS layer FROM peeled WHERE gone")


def _sketch(spark: SparkSession, sf_dir: str) -> DataFrame:
    g = A.sampled(build(spark, sf_dir, "part_supplier"), 1.0)
    exact = g.degrees().agg(F.countDistinct("degree").alias("exact"))
    return A.degree_sketch(g).join(exact).select((F.abs(F.col("n_degrees") - F.col("exact")) <= 0.2 * F.col("exact")).alias("close"), F.size("percentiles").cast("long").alias("n"), F.col("percentiles")[0].cast("long").alias("median"))


register("degree_sketch_part_supplier", _sketch, f"WITH {edges_sql('part_supplier')}, d AS (SELECT id, count(*) AS k FROM (SELECT u AS id FROM e UNION ALL SELECT v FROM e) GROUP BY id) SELECT count(DISTINCT k) > 0 AS close, CAST(3 AS BIGINT) AS n, CAST(quantile_disc(k, 0.5) AS BIGINT) AS median FROM d")

# --- equality and certificates ---------------------------------------------------------


def _mismatch(graph: str, one: Callable, two: Callable) -> Query:
    """Vertices, the sum of their coreness by the first method, and how many differ by the second."""

    def query(spark: SparkSession, sf_dir: str) -> DataFrame:
        g = build(spark, sf_dir, graph)
        a, b = one(g).cores, two(g).cores
        return a.agg(F.count("*").alias("n"), F.sum("coreness").alias("total")).join(M.mismatches(a, b))

    return query


def _mismatch_sql(graph: str) -> str:
    """The fixpoint of the recursion against the levels of a peeling recursion."""
    return f"{states_sql(graph)},\n{PEELED_SQL} SELECT count(*) AS n, CAST(sum(f.k) AS BIGINT) AS total, count(*) FILTER (WHERE f.k IS DISTINCT FROM p.lev) AS n_mismatch FROM final f FULL JOIN (SELECT id, lev FROM peeled WHERE gone) p USING (id)"


register("mismatch_frontier_peel_user_handoff", _mismatch("user_handoff", coreness_frontier, peel_bucket), _mismatch_sql("user_handoff"))
register("mismatch_mailbox_frontier_page_link", _mismatch("page_link", lambda g: coreness_mailbox(g), coreness_frontier), _mismatch_sql("page_link"))


def _certificate(spark: SparkSession, sf_dir: str, graph: str) -> DataFrame:
    g = build(spark, sf_dir, graph)
    return M.certify(g, coreness_frontier(g).cores, A.core_layers(g))


_CERTIFICATE = """,
c AS (SELECT id, lev, step FROM peeled WHERE gone),
n AS (SELECT a.src, x.lev, count(*) FILTER (WHERE y.lev >= x.lev) AS support, count(*) FILTER (WHERE y.lev > x.lev OR y.lev = x.lev AND y.step >= x.step) AS rest
      FROM a JOIN c x ON x.id = a.src JOIN c y ON y.id = a.dst GROUP BY a.src, x.lev)
SELECT count(*) FILTER (WHERE support < lev) AS too_high, count(*) FILTER (WHERE rest > lev) AS too_low FROM n"""
for _g in ("order_grid", "user_key"):
    register(f"certificate_{_g}", lambda s, d, n=_g: _certificate(s, d, n), layers_sql(_g) + _CERTIFICATE)
register(
    "layers_page_link",
    lambda s, d: (lambda g: g.named(A.core_layers(g).select("id", F.col("coreness").cast("long").alias("coreness"), F.col("layer").cast("long").alias("layer"))))(build(s, d, "page_link")),
    f"{layers_sql('page_link')} SELECT raw AS id, CAST(lev AS BIGINT) AS coreness, CAST(step AS BIGINT) AS layer FROM peeled JOIN ids USING (id) WHERE gone",
)


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLES)
