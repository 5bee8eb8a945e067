"""Rounds on Spark: state between rounds lives in files of the folder that all executors share.

A round's plan is run once, its result written and read back, so lineage never grows and a lost executor costs only
the tasks that are running. Files of past rounds are removed as soon as the next round no longer reads them.
"""

from __future__ import annotations

import atexit
import tempfile
import time
import uuid
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
from py4j.protocol import Py4JJavaError
from pyspark.sql import Column, DataFrame, Observation, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The session's ``spark.checkpoint.dir``; where it is unset, a folder of our own (local sessions) or the warehouse."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if not found:
        local = spark.sparkContext.master.split("[")[0] == "local"
        found = tempfile.mkdtemp(prefix="coreshell-") if local else spark.conf.get("spark.sql.warehouse.dir")
        spark.conf.set("spark.checkpoint.dir", found)
    if spark.sparkContext.getCheckpointDir() is None:
        spark.sparkContext.setCheckpointDir(found)
    return found


def _remove(spark: SparkSession, path: str) -> None:
    try:
        p = spark._jvm.org.apache.hadoop.fs.Path(path)
        p.getFileSystem(spark._jsc.hadoopConfiguration()).delete(p, True)
    except Exception:  # noqa: BLE001  the session may be gone when the interpreter ends
        return


def _seen(seen: Observation) -> dict[str, int]:
    """The observed counts; none where a plan turned out to have no rows and nothing was left of it to observe."""
    try:
        return {k: v or 0 for k, v in seen.get.items()}
    except Py4JJavaError as e:
        if "AssertionError" not in str(e):
            raise
        return {}


class Store:
    """Written tables of one run."""

    def __init__(self, spark: SparkSession):
        self.spark, self.root = spark, f"{shared_dir(spark)}/coreshell-{uuid.uuid4().hex}"
        self.made = 0
        atexit.register(_remove, spark, self.root)

    def keep(self, df: DataFrame, bucketed: str | None = None, parted: str | None = None, **counts: Column) -> DataFrame:
        """Run ``df`` now; the same rows, read from where they were written.

        ``bucketed``: one file for each of as many hash buckets of that column as there are shuffle partitions, sorted by
        it, so that joins and aggregations on it move nothing. ``parted``: a folder for each value of that column.
        ``counts``: aggregates of the rows, taken while they are written; they stand in ``_counts`` of the result.
        """
        path, name = f"{self.root}/{self.made}", f"coreshell_{self.root.rpartition('-')[2]}_{self.made}"
        self.made += 1
        seen = Observation() if counts else None
        rows = df.observe(seen, *[c.alias(k) for k, c in counts.items()]) if counts else df
        if bucketed:
            n = int(self.spark.conf.get("spark.sql.shuffle.partitions"))
            rows.repartition(n, bucketed).write.bucketBy(n, bucketed).sortBy(bucketed).format("parquet").option("path", path).saveAsTable(name)
            out = self.spark.table(name)
            out._coreshell_table = name
        else:
            writer = rows.write.partitionBy(parted) if parted else rows.write
            writer.parquet(path)
            out = self.spark.read.schema(df.schema).parquet(path)
        out._coreshell_path = path
        out._counts = dict.fromkeys(counts, 0) | _seen(seen) if counts else {}
        return out

    def drop(self, *tables: DataFrame | None) -> None:
        """Remove the files behind kept tables that nothing reads any more."""
        for df in tables:
            if name := getattr(df, "_coreshell_table", None):
                self.spark.sql(f"DROP TABLE IF EXISTS {name}")
            if path := getattr(df, "_coreshell_path", None):
                _remove(self.spark, path)


@dataclass
class CoreResult:
    """``cores`` (id, coreness), one row of ``trace`` for each round, and ``stats`` (plan, rounds, evals, seconds)."""

    cores: DataFrame
    rounds: list[dict] = field(default_factory=list)
    stats: dict = field(default_factory=dict)
    states: list[DataFrame] = field(default_factory=list)
    #: With ``states``: ``round, id, old, est`` of what dropped in each round.
    drops: list[DataFrame] = field(default_factory=list)
    #: Estimates of the first state and of the last by place, where all rounds were packed; ``drops`` then name each vertex's place, ``node``, too.
    placed: tuple[np.ndarray, np.ndarray] | None = None

    @property
    def trace(self) -> DataFrame:
        spark = self.cores.sparkSession
        return spark.createDataFrame([tuple(r.get(c) for c in TRACE) for r in self.rounds], "round int, n_active long, n_changed long, msgs_all long, msgs_lower long, msgs_support long, wall_ms long")


TRACE = ("round", "n_active", "n_changed", "msgs_all", "msgs_lower", "msgs_support", "wall_ms")


def loop_until_stable(step: Callable[[int], dict], max_rounds: int | None = None) -> list[dict]:
    """Call ``step(round)`` from 1 until it reports that nothing changed (``n_changed`` 0) or nothing was active; its reports.

    A step that went through several rounds hands them on as ``reports``; each is given an equal share of the time."""
    out: list[dict] = []
    while max_rounds is None or len(out) < max_rounds:
        began = time.perf_counter()
        report = step(len(out) + 1)
        if not report.get("n_active", 1):
            break
        several = report.get("reports", [report])
        for one in several:
            out.append(one | {"round": len(out) + 1, "wall_ms": int(1000 * (time.perf_counter() - began) / len(several))})
        if not report["n_changed"] or report.get("done"):
            break
    return out
