"""The experiment graphs: how each is built from the given tables, in Spark and in SQL."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coreshell.operators import builders as B
from coreshell.operators.graph import Graph
from coreshell.sources.tables import read_table

Reader = Callable[[str], DataFrame]


def _orders_of_lines(read: Reader) -> DataFrame:
    return read("lineitem").join(read("orders"), F.col("l_orderkey") == F.col("o_orderkey"))


def _geo_tree(read: Reader) -> Graph:
    """Regions 4r, nations 4n + 1, customers 4c + 2, suppliers 4s + 3."""
    code = lambda c, k: (4 * F.col(c).cast("long") + k)
    rows = read("nation").select(code("n_regionkey", 0).alias("u"), code("n_nationkey", 1).alias("v"))
    rows = rows.union(read("customer").select(code("c_nationkey", 1), code("c_custkey", 2))).union(read("supplier").select(code("s_nationkey", 1), code("s_suppkey", 3)))
    return B.graph_from_pairs(rows)


def _page_link(read: Reader) -> Graph:
    links = read("pages").select(F.concat(F.lit("p:"), F.col("page_id").cast("string")).alias("u"), F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("t"))
    return B.graph_named(links.select("u", F.concat(F.lit("t:"), "t").alias("v")))


def _order_grid(read: Reader) -> Graph:
    orders = read("orders").select("o_orderkey", "o_custkey", "o_orderdate")
    return B.graph_sequence(orders, "o_orderkey", (["o_custkey"], ["o_orderdate", "o_orderkey"]), (["o_orderdate"], ["o_orderkey"]))


BUILDERS: dict[str, Callable[[Reader], Graph]] = {
    "part_supplier": lambda read: B.graph_bipartite(read("lineitem"), "l_partkey", "l_suppkey"),
    "order_part": lambda read: B.graph_bipartite(read("lineitem"), "l_orderkey", "l_partkey"),
    "part_copurchase": lambda read: B.graph_projection(read("lineitem"), "l_orderkey", "l_partkey"),
    "customer_supplier": lambda read: B.graph_bipartite(_orders_of_lines(read), "o_custkey", "l_suppkey"),
    "customer_part": lambda read: B.graph_bipartite(_orders_of_lines(read), "o_custkey", "l_partkey"),
    "order_grid": _order_grid,
    "user_handoff": lambda read: B.graph_sequence(read("events"), "user_id", (["event_type"], ["ts", "event_id"])),
    "user_key": lambda read: B.graph_bipartite(read("events").withColumn("k", F.get_json_object("props", "$.k").cast("long")), "user_id", "k"),
    "page_link": _page_link,
    "doc_line": lambda read: B.graph_shared_token(read("documents"), "doc_id", F.transform(F.split("text", "\n", -1), lambda x: F.md5(F.trim(x))), ("d:", "l:")),
    "geo_tree": _geo_tree,
    "vector_knn": lambda read: B.graph_knn(read("embeddings")),
}

GRAPHS = tuple(BUILDERS)
NAMED = ("page_link", "doc_line")


def build(spark: SparkSession, sf_dir: str, name: str) -> Graph:
    return BUILDERS[name](lambda table: read_table(spark, sf_dir, table))


#: ``u, v`` of each graph before clean-up, in SQL.
RAW_SQL = {
    "part_supplier": "SELECT 2 * l_partkey AS u, 2 * l_suppkey + 1 AS v FROM lineitem",
    "order_part": "SELECT 2 * l_orderkey AS u, 2 * l_partkey + 1 AS v FROM lineitem",
    "part_copurchase": "SELECT a.l_partkey AS u, b.l_partkey AS v FROM (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) a JOIN (SELECT DISTINCT l_orderkey, l_partkey FROM lineitem) b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey",
    "customer_supplier": "SELECT 2 * o_custkey AS u, 2 * l_suppkey + 1 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "customer_part": "SELECT 2 * o_custkey AS u, 2 * l_partkey + 1 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "order_grid": "SELECT o_orderkey AS u, lead(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderdate, o_orderkey) AS v FROM orders UNION ALL SELECT o_orderkey, lead(o_orderkey) OVER (PARTITION BY o_orderdate ORDER BY o_orderkey) FROM orders",
    "user_handoff": "SELECT user_id AS u, lead(user_id) OVER (PARTITION BY event_type ORDER BY ts, event_id) AS v FROM events",
    "user_key": "SELECT 2 * user_id AS u, 2 * CAST(json_extract_string(props, '$.k') AS BIGINT) + 1 AS v FROM events",
    "page_link": """SELECT 'p:' || page_id AS u, 't:' || unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS v FROM pages""",
    "doc_line": "SELECT u, 'l:' || md5(trim(line, ' ')) AS v FROM (SELECT 'd:' || doc_id AS u, unnest(string_split(text, chr(10))) AS line FROM documents)",
    "geo_tree": "SELECT 4 * n_regionkey AS u, 4 * n_nationkey + 1 AS v FROM nation UNION ALL SELECT 4 * c_nationkey + 1, 4 * c_custkey + 2 FROM customer UNION ALL SELECT 4 * s_nationkey + 1, 4 * s_suppkey + 3 FROM supplier",
    "vector_knn": """SELECT u, v FROM (SELECT a.vec_id AS u, b.vec_id AS v, row_number() OVER (PARTITION BY a.vec_id ORDER BY list_cosine_similarity(CAST(a.embedding AS DOUBLE[]), CAST(b.embedding AS DOUBLE[])) DESC, b.vec_id) AS r
        FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id) WHERE r <= 10""",
}


def edges_sql(name: str) -> str:
    """Common table expressions ending in ``e`` (u, v): canonical edges, by name; and ``ids`` (raw, id) for graphs of names."""
    raw = RAW_SQL[name]
    kind = "VARCHAR" if name in NAMED else "BIGINT"
    clean = f"SELECT DISTINCT least(CAST(u AS {kind}), CAST(v AS {kind})) AS u, greatest(CAST(u AS {kind}), CAST(v AS {kind})) AS v FROM ({raw}) WHERE u <> v AND u IS NOT NULL AND v IS NOT NULL"
    if name not in NAMED:
        return f"e AS MATERIALIZED ({clean})"
    return f"""named AS MATERIALIZED ({clean}),
ids AS MATERIALIZED (SELECT raw, row_number() OVER (ORDER BY raw) AS id FROM (SELECT u AS raw FROM named UNION SELECT v FROM named)),
e AS MATERIALIZED (SELECT a.id AS u, b.id AS v FROM named JOIN ids a ON a.raw = named.u JOIN ids b ON b.raw = named.v)"""


#: Both directions of the edges ``e``.
ARCS_SQL = "a AS MATERIALIZED (SELECT u AS src, v AS dst FROM e UNION ALL SELECT v, u FROM e)"
#: The sequence of synchronous states: ``s`` (it, id, k, changed) and ``final`` (id, k). Every round re-ranks all
#: neighbours; the recursion stops once a round has changed nothing.
STATES_SQL = """deg AS MATERIALIZED (SELECT src AS id, count(*) AS k FROM a GROUP BY src),
loop (it, id, k, changed) AS (
  SELECT 0, id, k, true FROM deg
  UNION ALL
  SELECT it + 1, id, new, bool_or(new < k) OVER () FROM (
    SELECT it, id, k, max(least(r, other, k)) AS new FROM (
      SELECT x.it, x.id, x.k, y.k AS other, row_number() OVER (PARTITION BY x.id ORDER BY y.k DESC) AS r
      FROM loop x JOIN a ON a.src = x.id JOIN loop y ON y.id = a.dst WHERE x.changed) GROUP BY it, id, k)
),
s AS MATERIALIZED (SELECT * FROM loop),
final AS MATERIALIZED (SELECT id, CAST(k AS INTEGER) AS k FROM s WHERE it = (SELECT max(it) FROM s))"""
#: Peeling wave by wave: ``peeled`` (step, id, d, lev, gone), the vertices alive at each step. A step removes those of
#: degree at most the level, which rises to the lowest degree when none are left below.
PEELED_SQL = """peeled (step, id, d, lev, gone) AS (
  SELECT 1, id, d, min(d) OVER (), d <= min(d) OVER () FROM (SELECT src AS id, count(*) AS d FROM a GROUP BY src)
  UNION ALL
  SELECT step + 1, id, d, greatest(lev, min(d) OVER ()), d <= greatest(lev, min(d) OVER ()) FROM (
    SELECT x.step, x.id, x.lev, count(y.id) AS d
    FROM peeled x LEFT JOIN a ON a.src = x.id LEFT JOIN peeled y ON y.id = a.dst AND NOT y.gone WHERE NOT x.gone GROUP BY x.step, x.id, x.lev)
)"""


def states_sql(name: str) -> str:
    """The states of a graph, and its edges."""
    return f"WITH RECURSIVE {edges_sql(name)},\n{ARCS_SQL},\n{STATES_SQL}"


def layers_sql(name: str) -> str:
    """The peeling of a graph, and its edges."""
    return f"WITH RECURSIVE {edges_sql(name)},\n{ARCS_SQL},\n{PEELED_SQL}"


def named_sql(name: str, columns: str, rest: str = "") -> str:
    """``SELECT id, columns FROM final``, with names instead of ids where the graph has them."""
    if name in NAMED:
        return f"{states_sql(name)} SELECT ids.raw AS id, {columns} FROM final JOIN ids USING (id) {rest}"
    return f"{states_sql(name)} SELECT id, {columns} FROM final {rest}"
