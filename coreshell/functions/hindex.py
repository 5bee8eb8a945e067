"""Re-estimation of a vertex: the largest h, at most its own estimate, such that h neighbours have estimates of h or more."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F
from pyspark.sql.functions import pandas_udf


#: Of neighbours counted by estimate: the estimate or, if fewer have it or more, how many do.
BEST = "least(bucket, sum(n) OVER (PARTITION BY id ORDER BY bucket DESC ROWS UNBOUNDED PRECEDING)) AS best"


def h_index_hist(pairs: DataFrame) -> DataFrame:
    """``id, est, new_est`` from ``id, est, nbr_est``, by a histogram.

    Neighbours are counted by estimate, capped at the vertex's own, before anything is exchanged: a hub sends at most as
    many rows as its estimate is high, however many neighbours it has.
    """
    counts = pairs.groupBy("id", "est", F.expr("least(est, nbr_est) AS bucket")).agg(F.expr("count(1) AS n"))
    return counts.selectExpr("id", "est", BEST).groupBy("id", "est").agg(F.expr("CAST(max(best) AS INT) AS new_est"))


def h_index_open(pairs: DataFrame) -> DataFrame:
    """``id, new_est`` from ``id, nbr_est``: the same without the cap at the vertex's own estimate, which the caller applies."""
    counts = pairs.selectExpr("id", "nbr_est AS bucket").groupBy("id", "bucket").agg(F.expr("count(1) AS n"))
    return counts.selectExpr("id", BEST).groupBy("id").agg(F.expr("CAST(max(best) AS INT) AS new_est"))


def h_index_rank(pairs: DataFrame) -> DataFrame:
    """The same by ranking all neighbours; a hub's neighbours meet in one window."""
    rank = F.row_number().over(W.partitionBy("id").orderBy(F.desc("nbr_est")))
    return pairs.withColumn("rank", rank).groupBy("id").agg(F.max(F.least("rank", "nbr_est", "est")).cast("int").alias("new_est"))


def h_index_array(estimates: Column, cap: Column | None = None) -> Column:
    """The same for an array of neighbour estimates in a column."""
    ordered = F.reverse(F.array_sort(estimates))
    best = F.coalesce(F.array_max(F.transform(ordered, lambda x, i: F.least(x, (i + 1).cast("int")))), F.lit(0))
    return F.least(best, cap) if cap is not None else best


def _best(estimates: pd.Series, cap: pd.Series) -> int:
    values = np.sort(estimates.to_numpy())[::-1]
    return int(min(np.minimum(values, np.arange(1, len(values) + 1)).max(initial=0), cap.max())) if len(values) else 0


def h_index_udaf(estimates: Column | str, cap: Column | str) -> Column:
    """The same as a pandas aggregate function over the neighbours of a group."""

    def best(estimates: pd.Series, cap: pd.Series) -> int:
        return _best(estimates, cap)

    return pandas_udf(best, "int")(estimates, cap)


def h_index_block(size: np.ndarray, est: np.ndarray, nbr_est: np.ndarray) -> np.ndarray:
    """The same for many vertices at once: neighbours lie in a row, ``size`` of them for each vertex.

    A counting sort in a histogram whose stretch for a vertex is as long as its estimate, so the work is linear.
    """
    cap = np.minimum(est, size).astype(np.int64)
    first = np.cumsum(cap + 1) - (cap + 1)
    owner = np.repeat(np.arange(len(size)), size)
    hist = np.bincount(first[owner] + np.minimum(nbr_est, cap[owner]), minlength=int((cap + 1).sum()) if len(cap) else 0)
    total = np.cumsum(hist)
    ends = first + cap
    level = np.arange(len(hist)) - np.repeat(first, cap + 1)
    # neighbours at this level or above: all of the vertex less those below
    at_least = np.repeat(total[ends], cap + 1) - total + hist
    good = (at_least >= level).astype(np.int64)
    return np.add.reduceat(good, first) - 1 if len(first) else np.zeros(0, np.int64)
