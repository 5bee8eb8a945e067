"""Graphs from ordinary tables."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coreshell.operators.graph import Graph, dense_ids, ordered_pairs
from coreshell.plans.rounds import Store

#: Bytes of vectors that a block of the nearest-neighbour search holds, and of likenesses that are worked on at once.
VECTOR_BYTES, LIKENESS_BYTES = 8 << 20, 16 << 20


def graph_from_pairs(df: DataFrame, u: str = "u", v: str = "v") -> Graph:
    pairs = ordered_pairs(df, u, v)
    return Graph(pairs.distinct(), raw=df.select(F.col(u).alias("u"), F.col(v).alias("v")), pairs=pairs)


def graph_bipartite(df: DataFrame, left: str, right: str) -> Graph:
    """Two kinds of vertices that share an id space: 2 * left and 2 * right + 1."""
    return graph_from_pairs(df.select((2 * F.col(left).cast("long")).alias("u"), (2 * F.col(right).cast("long") + 1).alias("v")))


def graph_projection(df: DataFrame, group: str, member: str) -> Graph:
    """Members of the same group are linked. Pairs grow with the square of a group: meant for small groups such as orders."""
    rows = df.select(F.col(group).alias("g"), F.col(member).cast("long").alias("m")).where("g is not null and m is not null").distinct()
    pairs = rows.select("g", F.col("m").alias("u")).join(rows.select("g", F.col("m").alias("v")), "g").where("u < v")
    return graph_from_pairs(pairs)


def followed(df: DataFrame, value: str, group: list[str], order: list[str], store: Store) -> DataFrame:
    """``value, next``: each row's value and that of the next row of its group, however few groups there are.

    Rows are dealt into ranges of (group, order); a range finds its own followers, and the last row of a group in it takes
    the first row of the next range (one row a range). Rows, and about how many values, stand in ``_counts`` of the result.
    """
    spark = df.sparkSession
    n = int(spark.conf.get("spark.sql.shuffle.partitions"))
    names = [f"g{i}" for i in range(len(group))], [f"o{i}" for i in range(len(order))]
    rows = df.select(*[F.col(c).alias(x) for c, x in zip([*group, *order], [*names[0], *names[1]], strict=True)], F.col(value).alias("value"))
    dealt = store.keep(rows.repartitionByRange(n, *names[0], *names[1], "value").withColumn("part", F.spark_partition_id()), rows=F.count("*"), values=F.approx_count_distinct("value"))
    heads = dealt.groupBy("part").agg(F.min(F.struct(*names[0], *names[1], "value")).alias("head"))
    heads = heads.select("part", F.lead("head").over(W.orderBy("part")).alias("head"))
    ahead = W.partitionBy("part", *names[0]).orderBy(*names[1], "value")
    rows = dealt.withColumns({"own": F.lead("value").over(ahead), "last": F.lead(F.lit(True)).over(ahead).isNull()}).join(F.broadcast(heads), "part")  # one row a partition
    same = F.lit(True)
    for c in names[0]:
        same = same & F.col(c).eqNullSafe(F.col(f"head.{c}"))
    out = rows.select("value", F.when(~F.col("last"), F.col("own")).when(same, F.col("head.value")).alias("next"))
    out._counts = dealt._counts
    return out


def graph_sequence(df: DataFrame, vertex: str, *orders: tuple[list[str], list[str]]) -> Graph:
    """Each row's vertex is linked to that of the next row, for each (group columns, sort columns) of ``orders``."""
    out, store, n, m = None, Store(df.sparkSession), 0, 0
    rows = df.withColumn("__vertex", F.col(vertex).cast("long"))
    for group, order in orders:
        found = followed(rows, "__vertex", group, order, store)
        n, m = max(n, found._counts["values"]), m + found._counts["rows"]
        step = found.select(F.col("value").alias("u"), F.col("next").alias("v"))
        out = step if out is None else out.union(step)
    g = graph_from_pairs(out)
    g.about = (n, m)
    return g


def graph_named(df: DataFrame, u: str = "u", v: str = "v") -> Graph:
    """Vertices given by names: they get dense ids, and the graph keeps the map."""
    raw = df.select(F.col(u).alias("u"), F.col(v).alias("v"))
    pairs = raw.select(F.col("u").alias("a"), F.col("v").alias("b")).where("a is not null and b is not null").distinct()
    ids = dense_ids(pairs.select(F.explode(F.array("a", "b")).alias("raw")))
    left, right = ids.select(F.col("raw").alias("a"), F.col("id").alias("u")), ids.select(F.col("raw").alias("b"), F.col("id").alias("v"))
    g = graph_from_pairs(pairs.join(left, "a").join(right, "b"))
    g.id_map, g.raw = ids, raw
    return g


def graph_shared_token(df: DataFrame, key: str, tokens: Column, prefix: tuple[str, str] = ("d:", "t:")) -> Graph:
    """Rows linked to the tokens (an array column) they hold."""
    rows = df.select(F.concat(F.lit(prefix[0]), F.col(key).cast("string")).alias("u"), F.explode(tokens).alias("t"))
    return graph_named(rows.select("u", F.concat(F.lit(prefix[1]), "t").alias("v")))


def graph_cooccurrence_window(events: DataFrame, vertex: str, ts: str, seconds: int) -> Graph:
    """Vertices with events at most ``seconds`` apart: an equi-join on time buckets and their successors, then the range predicate."""
    rows = events.select(F.col(vertex).cast("long").alias("x"), F.unix_timestamp(F.col(ts).cast("timestamp")).alias("t")).where("x is not null and t is not null").distinct()
    rows = rows.withColumn("bucket", F.floor(F.col("t") / max(1, seconds)))
    ahead = rows.select(F.col("x").alias("u"), F.col("t").alias("t1"), F.explode(F.array(F.col("bucket"), F.col("bucket") + 1)).alias("bucket"))
    pairs = ahead.join(rows.select(F.col("x").alias("v"), F.col("t").alias("t2"), "bucket"), "bucket").where(f"u <> v and t2 - t1 between 0 and {seconds}")
    return graph_from_pairs(pairs)


def nearest_of(like: np.ndarray, ids: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) of the ``k`` highest of each row of ``like``, ties by ``ids``; only those as high as the k-th are sorted."""
    row, column = np.divmod(np.arange(like.size), like.shape[1])
    if like.shape[1] > k:
        least = np.partition(like, like.shape[1] - k, axis=1)[:, -k, None]
        keep = like >= least
        if np.count_nonzero(keep) > 2 * k * len(like):  # many copies: of those as high as the k-th, k by ids are enough
            by_id = np.argsort(ids)
            equal = (like == least)[:, by_id]
            equal &= np.cumsum(equal, axis=1, dtype=np.int32) <= k
            keep = like > least
            keep[:, by_id] |= equal
        row, column = np.nonzero(keep)
    order = np.lexsort((ids[column], -like[row, column], row))
    row, column = row[order], column[order]
    best = np.arange(len(row)) - np.searchsorted(row, row) < k
    return row[best], column[best]


def graph_knn(vectors: DataFrame, key: str = "vec_id", column: str = "embedding", k: int = 10, block_bytes: int = VECTOR_BYTES) -> Graph:
    """Each vector linked to its ``k`` nearest by cosine (ties by id), exactly.

    Vectors are packed into blocks of about ``block_bytes`` (a row each), every block is compared with every other, some
    ``LIKENESS_BYTES`` of likenesses at a time, and of all blocks' nearest the nearest are kept. Pairs of blocks are read
    where each block lies, once for each task, and not exchanged. Work grows with the square of the vectors: that
    is what exact search costs.
    """
    store, spark = Store(vectors.sparkSession), vectors.sparkSession
    rows = store.keep(vectors.select(F.col(key).cast("long").alias("id"), F.col(column).cast("array<double>").alias("x")).where("id is not null and x is not null"), n=F.count("*"), wide=F.max(F.size("x")))
    n_blocks = max(1, -(-8 * rows._counts["n"] * rows._counts["wide"] // block_bytes), min(rows._counts["n"], int(spark.sparkContext.defaultParallelism) // 2))

    def pack(t: pa.Table) -> pa.Table:
        x = t["x"].combine_chunks().flatten().to_numpy(zero_copy_only=False).reshape(t.num_rows, -1)
        x = x / np.linalg.norm(x, axis=1, keepdims=True)
        return pa.table({"ids": [t["id"].to_numpy().tobytes()], "x": [x.tobytes()]}, pa.schema({"ids": pa.binary(), "x": pa.binary()}))

    blocks = rows.withColumn("block", F.pmod(F.xxhash64("id"), F.lit(n_blocks))).groupBy("block").applyInArrow(pack, "ids binary, x binary")
    blocks = store.keep(blocks).repartition(n_blocks, F.xxhash64("ids"))
    pairs = blocks.crossJoin(blocks.withColumnsRenamed({"ids": "other_ids", "x": "other_x"}).hint("shuffle_replicate_nl"))

    def nearest(batches):
        for batch in batches:
            for i in range(batch.num_rows):
                own, ids, x, y = (np.frombuffer(batch.column(c)[i].as_buffer(), t) for c, t in (("ids", np.int64), ("other_ids", np.int64), ("x", float), ("other_x", float)))
                x, y, step = x.reshape(len(own), -1), y.reshape(len(ids), -1), max(1, LIKENESS_BYTES // (8 * len(ids)))
                for a in range(0, len(own), step):
                    some = own[a : a + step]
                    like = x[a : a + step] @ y.T
                    like[(some[:, None] == ids[None, :]) | np.isnan(like)] = -np.inf
                    row, column = nearest_of(like, ids, k)
                    near = like[row, column]
                    keep = np.isfinite(near)
                    yield pa.record_batch([pa.array(some[row[keep]]), pa.array(ids[column[keep]]), pa.array(near[keep])], names=["u", "v", "like"])

    found = pairs.mapInArrow(nearest, "u long, v long, like double")
    rank = F.row_number().over(W.partitionBy("u").orderBy(F.desc("like"), "v"))
    return graph_from_pairs(found.withColumn("rank", rank).where(F.col("rank") <= k))
