import datetime as dt
import random

from pyspark.sql import functions as F

from coreshell.sources import tables as S
from coreshell.sql import register_sql
from coreshell.streaming import windows
from coreshell.streaming.incremental import IncrementalCores

from .test_kernels import brute_cores
from .test_methods import CLIQUE_PATH, graph

T0 = dt.datetime(2024, 1, 1)


def events(spark, rows):
    return spark.createDataFrame([(i, T0 + dt.timedelta(hours=h), u, v) for i, (h, u, v) in enumerate(rows)], "event_id long, ts timestamp, u long, v long")


ROWS = [(h, u, v) for h in (1, 30, 60) for u, v in CLIQUE_PATH[: 9 - h // 20]]


def test_windows_batch(spark):
    found = {(r.g, r.vertex): r.coreness for r in windows.windowed_cores(events(spark, ROWS), "u", "v", "ts", "1 day").collect()}
    want = {}
    for day in range(4):
        part = [(u, v) for h, u, v in ROWS if h // 24 == day]
        want |= {(T0 + dt.timedelta(days=day), x): c for x, c in brute_cores(part).items()}
    assert found == want


def test_windows_stream_equal_batch(spark, tmp_path):
    late = (0, 0, 9)  # arrives after its window has closed
    batches = [ROWS[:9], ROWS[9:], [(200, 0, 1)], [late, (300, 0, 1)]]
    for i, rows in enumerate(batches):
        events(spark, rows).coalesce(1).write.parquet(str(tmp_path / "in" / str(i)))
    stream = spark.readStream.schema("event_id long, ts timestamp, u long, v long").option("maxFilesPerTrigger", 1).option("recursiveFileLookup", True).parquet(str(tmp_path / "in"))
    seen = {}

    def sink(df, _):
        seen.update({(r.g, r.vertex): r.coreness for r in df.collect()})

    edges = windows.closed_window_edges(stream, "u", "v", "ts", "1 day", "1 hour")
    windows.start_windowed_cores(edges, sink, str(tmp_path / "at")).awaitTermination()
    batch = {(r.g, r.vertex): r.coreness for r in windows.windowed_cores(events(spark, ROWS), "u", "v", "ts", "1 day").collect()}
    assert {k: v for k, v in seen.items() if k[0] < T0 + dt.timedelta(days=4)} == batch


def test_duplicates_and_degrees(spark, tmp_path):
    rows = events(spark, [(1, 0, 1), (2, 0, 2)])
    for i in range(2):
        rows.coalesce(1).write.parquet(str(tmp_path / "in" / str(i)))
    stream = spark.readStream.schema(rows.schema).option("recursiveFileLookup", True).parquet(str(tmp_path / "in"))
    once = windows.deduplicated(stream, "event_id", "ts", "1 hour").select("u", "v")
    windows.streaming_degrees(once).writeStream.outputMode("update").format("memory").queryName("degrees").trigger(availableNow=True).start().awaitTermination()
    assert {r.id: r.degree for r in spark.table("degrees").collect()} == {0: 2, 1: 1, 2: 1}


def test_sessions(spark):
    rows = [(0, 1, 7), (0.2, 1, 8), (5, 1, 7), (5.1, 2, 7)]
    found = windows.parted_cores(windows.session_pairs(events(spark, rows), "u", "v", "ts", "1 hour"))
    assert sorted((r.g.user, r.vertex, r.coreness) for r in found.collect()) == [(1, 2, 1), (1, 2, 1), (1, 15, 1), (1, 15, 1), (1, 17, 1), (2, 4, 1), (2, 15, 1)]


def test_incremental(spark):
    r = random.Random(4)
    edges = {(min(a, b), max(a, b)) for a, b in ((r.randint(0, 14), r.randint(0, 14)) for _ in range(45)) if a != b}
    state = IncrementalCores(spark.createDataFrame(sorted(edges), "u long, v long"))
    for step in range(3):
        out = set(r.sample(sorted(edges), 6))
        new = {(min(a, b), max(a, b)) for a, b in ((r.randint(0, 16), r.randint(0, 16)) for _ in range(9)) if a != b}
        if step == 2:
            rows = [("-", *e) for e in out] + [("+", *e) for e in new]
            state.on_batch(spark.createDataFrame(rows, "op string, u long, v long"), 0)
        else:
            state.apply(spark.createDataFrame(sorted(new), "u long, v long"), spark.createDataFrame(sorted(out), "u long, v long"))
        edges = (edges - out) | new
        assert {r.id: r.coreness for r in state.cores.collect()} == brute_cores(edges)


def test_sql_names(spark):
    register_sql(spark, {"toy": graph(spark, CLIQUE_PATH)})
    assert spark.sql("select h_index(array(3, 3, 1, 5))").first()[0] == 3
    assert spark.sql("select count(*) from cores_toy where coreness = 3").first()[0] == 4
    us, vs = ",".join(str(u) for u, _ in CLIQUE_PATH), ",".join(str(v) for _, v in CLIQUE_PATH)
    assert dict(spark.sql(f"select id, coreness from peel_steps(array({us}), array({vs}))").collect()) == brute_cores(CLIQUE_PATH)
    assert dict(spark.sql(f"select id, hops from neighbors_within(array({us}), array({vs}), 6, 2)").collect()) == {6: 0, 5: 1, 4: 2}


def test_edge_lists(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# comment\n1\t2\n2 3\n\n")
    assert sorted(map(tuple, S.read_edge_list(spark, str(tmp_path / "e.txt")).collect())) == [(1, 2), (2, 3)]
    df = spark.createDataFrame([(1, 2), (2, 3)], "u long, v long")
    for kind in ("csv", "json", "orc", "parquet"):
        df.write.format(kind).option("header", True).save(str(tmp_path / kind))
        assert sorted(map(tuple, S.read_edge_list(spark, str(tmp_path / kind), kind).collect())) == [(1, 2), (2, 3)]
    cores = spark.createDataFrame([(1, 2), (2, 1)], "id long, coreness int")
    S.write_cores(cores, str(tmp_path / "cores"))
    assert spark.read.parquet(str(tmp_path / "cores")).where("shell = 2").count() == 1
    arcs = S.write_arcs_bucketed(df.select(F.col("u").alias("src"), F.col("v").alias("dst")), "arcs_of_test", 4)
    assert arcs.count() == 2
    spark.sql("drop table arcs_of_test")
