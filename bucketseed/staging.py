"""Stage files in the shared checkpoint folder: they cut lineage and outlive lost executors."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder named by ``spark.checkpoint.dir``; a temporary one only in local mode."""
    found = spark.conf.get("spark.checkpoint.dir", None)
    if found:
        return found.rstrip("/")
    sc = spark.sparkContext
    found = sc.getCheckpointDir()
    if not found:
        if not sc.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that all executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="bucketseed-"))
        found = sc.getCheckpointDir()
    return found.rstrip("/")


def stage_folder(df: DataFrame, name: str = "stage") -> str:
    """Write ``df`` as Parquet in the shared folder; returns the path."""
    path = f"{shared_dir(df.sparkSession)}/bucketseed/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").parquet(path)
    return path


def unstage(spark: SparkSession, path: str) -> None:
    """Removes a stage that nothing reads any more: of an iteration's states only the last is needed."""
    at = spark._jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(spark._jsc.hadoopConfiguration()).delete(at, True)


def staged(df: DataFrame, name: str = "stage") -> DataFrame:
    """``stage_folder``, read back."""
    return df.sparkSession.read.schema(df.schema).parquet(stage_folder(df, name))


def staged_by(df: DataFrame, column: str, name: str = "stage") -> DataFrame:
    """``staged`` with a folder for each value of ``column``: a filter on it reads that folder alone."""
    path = f"{shared_dir(df.sparkSession)}/bucketseed/{name}-{uuid.uuid4().hex}"
    df.write.option("compression", "zstd").partitionBy(column).parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def spread(df: DataFrame) -> DataFrame:
    """``df`` over as many tasks as there are cores, where its scan gives fewer: few bytes may hold much work.

    For plans of scans and projections alone; large tables have more partitions than that and stay as they are.
    """
    cores = df.sparkSession.sparkContext.defaultParallelism
    return df.repartition(cores) if df.rdd.getNumPartitions() < cores else df


#: Stage files of up to this many rows are worked on in one task, where a shuffle would cost more.
SMALL_ROWS = 200_000


def counted(df: DataFrame, name: str = "stage") -> tuple[DataFrame, int]:
    """``staged``, and its rows' number; a small result is one partition, so it needs no shuffle."""
    out = staged(df, name)
    n = out.count()
    return (out.coalesce(1) if n <= SMALL_ROWS else out), n
