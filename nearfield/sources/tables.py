"""Reading tables and files, lineage cuts, and sinks."""

from __future__ import annotations

import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """One of the given tables."""
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read(spark: SparkSession, path: str, kind: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """Parquet, ORC, CSV, JSON or text; a schema spares a pass over CSV and JSON."""
    r = spark.read.format(kind).options(**options)
    return (r.schema(schema) if schema else r).load(path)


def shared_root(spark: SparkSession) -> str:
    """The folder of spark.checkpoint.dir; a temporary one only where it is unset and the master is local."""
    context = spark.sparkContext
    root = spark.conf.get("spark.checkpoint.dir", None) or context.getCheckpointDir()
    if root is None and not context.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that the driver and all executors share")
    root = root or "file://" + tempfile.mkdtemp(prefix="nearfield-")
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(root)
    return root.rstrip("/")


def passing_folder(spark: SparkSession, label: str) -> str:
    """A new folder that driver and executors share, for files that are removed when read back."""
    return f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"


def remove_folder(spark: SparkSession, folder: str) -> None:
    """Delete a folder, wherever Spark's file systems reach."""
    path = spark._jvm.org.apache.hadoop.fs.Path(folder)
    path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def cut(df: DataFrame) -> DataFrame:
    """A reliable checkpoint: computed once, read by later uses, kept in the folder that all executors share."""
    shared_root(df.sparkSession)
    return df.checkpoint(eager=True)


def settle(df: DataFrame) -> DataFrame:
    """``cut`` for the rows that a loop carries on, without Spark's estimate of their size.

    A checkpoint keeps the estimate, and that of a join is the product of its sides': over the rounds of a loop it
    becomes a number so long that planning takes longer than the work.
    """
    done, spark = cut(df)._jdf, df.sparkSession
    return DataFrame(spark._jsparkSession.internalCreateDataFrame(done.queryExecution().toRdd(), done.schema(), False), spark)


def squeeze(table: pa.RecordBatch | pa.Table) -> bytes:
    """A table as compressed bytes; ``unsqueeze`` gives it back."""
    sink = pa.BufferOutputStream()
    with pa.ipc.new_stream(sink, table.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
        out.write(table)
    return sink.getvalue().to_pybytes()


def unsqueeze(data: bytes) -> pa.Table:
    return pa.ipc.open_stream(data).read_all()


def settle_packed(df: DataFrame) -> DataFrame:
    """``settle`` for many narrow rows: whole batches are kept as compressed bytes, a few bytes a row instead of about fifty."""

    def pack(batches):
        for b in batches:
            yield pa.RecordBatch.from_arrays([pa.array([squeeze(b)], pa.binary())], ["batch"])

    def unpack(batches):
        for b in batches:
            for x in b.column("batch").to_pylist():
                yield from unsqueeze(x).to_batches()

    return settle(df.mapInArrow(pack, "batch binary")).mapInArrow(unpack, df.schema)


def repeated(df: DataFrame, times: int, id_column: str, stride: int) -> DataFrame:
    """``times`` copies with ids moved by ``stride`` each, and the copy's number."""
    copies = F.explode(F.sequence(F.lit(0), F.lit(times - 1))).alias("copy")
    return df.select("*", copies).withColumn(id_column, F.col(id_column) + F.col("copy") * stride)


def utc(column: str):
    """A timestamp without zone as one that streams accept; the session's zone is UTC."""
    return F.col(column).cast("timestamp")


def write_matrix(m: DataFrame, path: str, buckets: int = 16, step: int | None = None) -> None:
    """Parquet by bucket of columns (and step): readers of a column range or a step skip the rest."""
    out = m.withColumn("bucket", F.pmod(F.hash("col"), F.lit(buckets)))
    keys = ["bucket"]
    if step is not None:
        out, keys = out.withColumn("step", F.lit(step)), ["step", "bucket"]
    out.repartition("bucket").sortWithinPartitions("col", "row").write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy(*keys).parquet(path)


def write_bucketed(df: DataFrame, name: str, key: str, buckets: int = 16) -> None:
    """A table bucketed and sorted by a key, so that later joins on it need no shuffle."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(name)


def run(df: DataFrame) -> None:
    """Compute everything and keep nothing, for timing."""
    df.write.format("noop").mode("overwrite").save()
