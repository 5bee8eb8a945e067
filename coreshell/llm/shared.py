"""Input columns, shared working tables and Arrow slices used by the operators."""

from __future__ import annotations

import atexit
import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: UTF-8 bytes of text that an Arrow kernel holds at once (one document may be longer).
SLICE_BYTES = 8 << 20


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def id_and_text(docs: DataFrame, *more: str) -> DataFrame:
    """``doc_id`` as long, ``text`` with null as empty, and the columns named in ``more``; nothing else."""
    return docs.select(
        docs["doc_id"].cast("long").alias("doc_id"),
        F.coalesce(docs["text"].cast("string"), F.lit("")).alias("text"),
        *[docs[c] for c in more],
    )


def shared_dir(spark: SparkSession) -> str:
    """The folder that driver and executors share: ``spark.checkpoint.dir``; where it is unset, one of our own."""
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
    except Exception:  # noqa: BLE001  the session may have ended before the interpreter does
        return


def stored(df: DataFrame, name: str) -> DataFrame:
    """Write ``df`` once as Parquet in the shared folder and read it back: lineage ends there, and a lost executor costs only the tasks that read it."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/coreshell-{uuid.uuid4().hex}/{name}"
    df.write.parquet(path)
    atexit.register(_remove, spark, path.rpartition("/")[0])
    return spark.read.schema(df.schema).parquet(path)


def slices(batches: Iterator[pa.RecordBatch], column: int = 1, most: int = SLICE_BYTES) -> Iterator[pa.RecordBatch]:
    """Cut record batches so that ``column`` has about ``most`` bytes in each."""
    for batch in batches:
        if not batch.num_rows:
            continue
        block = np.cumsum(pc.fill_null(pc.binary_length(batch.column(column)), 0).to_numpy(zero_copy_only=False).astype(np.int64)) // most
        cuts = [0, *(np.flatnonzero(np.diff(block)) + 1).tolist(), batch.num_rows]
        for a, b in zip(cuts, cuts[1:], strict=False):
            yield batch.slice(a, b - a)


#: What a Python worker remembers between tasks, by the operator that uses it.
MEMORIES: dict[str, dict] = {}


def memory(name: str) -> dict:
    """The memory of one operator; those of others are given up, as workers outlive the stage that filled them."""
    for other, held in MEMORIES.items():
        if other != name:
            held.clear()
    return MEMORIES.setdefault(name, {})


def returned() -> None:
    """Give memory that a task has freed back to the system: workers outlive their tasks."""
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except AttributeError:  # another C library
        return


def over_slices(df: DataFrame, kernel: Callable[[pa.RecordBatch], pa.RecordBatch], schema: str, most: int = SLICE_BYTES, uses: str = "") -> DataFrame:
    """``kernel`` over slices of bounded size of ``df`` (the text is the second column); it uses the memory named ``uses``."""

    def run(batches):
        memory(uses)
        for part in slices(batches, most=most):
            out = kernel(part)
            if out.num_rows:
                yield out

    return df.mapInArrow(run, schema)


def plain(array: pa.Array) -> pa.Array:
    """A string array without offset."""
    return pa.concat_arrays([array]) if array.offset else array


def word_codes(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, pa.Array]:
    """(document position, word code) of each white-space separated word, in order, and the dictionary of codes."""
    lists = pc.utf8_split_whitespace(texts)
    offsets = lists.offsets.to_numpy().astype(np.int64)
    coded = lists.flatten().dictionary_encode()
    codes = coded.indices.to_numpy(zero_copy_only=False).astype(np.int64)
    where = np.repeat(np.arange(len(texts)), np.diff(offsets))
    blank = pc.index(coded.dictionary, "").as_py() if len(coded.dictionary) else -1
    if blank >= 0:
        keep = codes != blank
        where, codes = where[keep], codes[keep]
    return where, codes, coded.dictionary


def strings(array: pa.Array) -> list[str]:
    """Python strings of an array without nulls, made in one go."""
    return array.to_numpy(zero_copy_only=False).tolist()
