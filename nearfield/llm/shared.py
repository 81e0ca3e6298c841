"""What the operators share: the folder all executors see, and lineage cuts."""

from __future__ import annotations

import ctypes
import tempfile
import uuid
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

#: ASCII white space, as every operator here means it.
ASCII_SPACE = " \t\n\x0b\x0c\r"
#: A word: a run of anything else.
WORD = r"[^\x20\x09-\x0D]+"
LEAST_LONG = -(2**63)


def shared_root(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; a temporary one only where it is unset and the master is local."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    context = spark.sparkContext
    if root is None:
        root = context.getCheckpointDir()
        if root is None:
            if not context.master.startswith("local"):
                raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
            root = "file://" + tempfile.mkdtemp(prefix="nearfield-")
            context.setCheckpointDir(root)
    elif context.getCheckpointDir() is None:
        context.setCheckpointDir(root)
    return root.rstrip("/")


def shared_folder(spark: SparkSession, label: str) -> str:
    """A new folder for one run's files."""
    return f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"


def remove_folder(spark: SparkSession, folder: str) -> None:
    """Delete a run's files, wherever Spark's file systems reach."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def cut(df: DataFrame) -> DataFrame:
    """Compute ``df`` once into the shared folder: later uses read it, also after the loss of executors.

    A reliable checkpoint; Spark's cleaner removes the files when nothing refers to them.
    """
    shared_root(df.sparkSession)
    return df.checkpoint(eager=True)


def settle(df: DataFrame) -> DataFrame:
    """``cut`` for the rows that a loop carries on, without Spark's estimate of their size.

    A checkpoint keeps the estimate, and that of a join is the product of its sides': over the rounds of a loop it
    becomes a number so long that planning takes longer than the work.
    """
    done, spark = cut(df)._jdf, df.sparkSession
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(done.queryExecution().toRdd(), done.schema(), False), spark)


def tidy(run: Callable[[Iterable[pa.RecordBatch]], Iterator[pa.RecordBatch]]):
    """``run`` for mapInArrow, giving memory that it has freed back to the system when a partition ends.

    Workers wait for their next task beside the executor's JVM, and would hold on to what their largest one took.
    """

    def own(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            pa.default_memory_pool().release_unused()
            if trim := getattr(ctypes.CDLL(None), "malloc_trim", None):  # of glibc
                trim(0)

    return own


def plain(column: str):
    """The column's text, null as empty."""
    return F.coalesce(F.col(column), F.lit(""))


def word_count(column: str):
    """Number of words in a text column, 0 for null; long."""
    return F.coalesce(F.regexp_count(F.col(column), F.lit(WORD)), F.lit(0)).cast("long")
