"""Helpers that the operators of this subpackage share."""

from __future__ import annotations

import atexit
import ctypes
import shutil

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.storagelevel import StorageLevel

__all__ = ["Local", "NON_SPACE", "StorageLevel", "cut_lineage", "free_name", "give_back", "shared_folder", "partitions_for", "remove_folder", "small_batches", "text_bytes", "text_parts"]

#: One word: anything but the six ASCII white-space characters.
NON_SPACE = r"[^\x20\x09-\x0D]+"


class Local(dict):
    """A cache of this process; it travels to executors empty."""

    def __reduce__(self):
        return Local, ()


def give_back() -> None:
    """Returns what a worker has freed to the system, where the allocators would keep it for themselves."""
    import pyarrow as pa

    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL(None).malloc_trim(0)
    except (AttributeError, OSError):  # another allocator
        pass


def small_batches(spark: SparkSession, rows: int = 2000) -> None:
    """Arrow batches of ``rows`` rows unless the session has a number of its own: of whole texts, Spark's 10 000 fill tens of MB on both sides."""
    name = "spark.sql.execution.arrow.maxRecordsPerBatch"
    if spark.conf.get(name) == "10000":
        spark.conf.set(name, str(rows))


def text_parts(column, most: int):
    """(first row, texts) of slices of an Arrow text column with about ``most`` bytes each."""
    import numpy as np
    import pyarrow.compute as pc

    size = np.cumsum(pc.fill_null(pc.binary_length(column), 0).to_numpy(zero_copy_only=False).astype(np.int64)) if len(column) else []
    lo = 0
    while lo < len(column):
        start = int(size[lo - 1]) if lo else 0
        hi = max(lo + 1, int(np.searchsorted(size, start + most, "right")))
        yield lo, column.slice(lo, hi - lo).to_pylist()
        lo = hi
    give_back()


def ensure_checkpoint_dir(spark: SparkSession) -> None:
    """Uses the folder that the cluster names; where none is set, one of our own in the warehouse, which executors share too.

    On a single machine our own folder is removed at exit.
    """
    sc = spark.sparkContext
    if sc._jsc.sc().getCheckpointDir().isDefined():
        return
    named = spark.conf.get("spark.checkpoint.dir", None)
    sc.setCheckpointDir(named or f"{spark.conf.get('spark.sql.warehouse.dir').rstrip('/')}/ctxpress-checkpoints")
    if not named and sc.master.startswith("local["):
        atexit.register(shutil.rmtree, sc._jsc.sc().getCheckpointDir().get().removeprefix("file:"), ignore_errors=True)


def remove_folder(spark: SparkSession, folder: str) -> None:
    """Deletes a folder of ours that is read no more, in whatever file system it is."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark.sparkContext._jsc.sc().hadoopConfiguration()).delete(path, True)


def shared_folder(spark: SparkSession) -> str:
    """The folder that the driver and all executors share."""
    ensure_checkpoint_dir(spark)
    return spark.sparkContext._jsc.sc().getCheckpointDir().get()


def cut_lineage(df: DataFrame) -> DataFrame:
    """Writes the rows to the shared checkpoint folder and goes on from there, whatever executor is lost later."""
    ensure_checkpoint_dir(df.sparkSession)
    return df.checkpoint(eager=True)


def partitions_for(total: float, each: float, least: int = 8, most: int = 200_000) -> int:
    """How many parts of about ``each`` a ``total`` needs."""
    return int(min(most, max(least, -(-total // each))))


def text_bytes(docs: DataFrame, text_col: str = "text") -> int:
    """UTF-8 bytes of all texts."""
    return docs.agg(F.coalesce(F.sum(F.octet_length(F.col(text_col))), F.lit(0))).first()[0]


def free_name(df: DataFrame, stem: str) -> str:
    """A column name that ``df`` does not have, in any spelling."""
    taken, name = {c.lower() for c in df.columns}, stem
    while name.lower() in taken:
        name = "_" + name
    return name
