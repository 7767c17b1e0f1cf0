"""Tables in the folder that the driver and all executors share."""

from __future__ import annotations

import atexit
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """spark.checkpoint.dir; where it is unset, a temporary folder, which only a local master can share."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if not found:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        found = tempfile.mkdtemp(prefix="shared-")
        spark.sparkContext.setCheckpointDir(found)
    return found.rstrip("/")


_written: list[tuple[SparkSession, str]] = []


def _path(spark: SparkSession, path: str):
    at = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return at, at.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())


def exists(spark: SparkSession, path: str) -> bool:
    at, files = _path(spark, path)
    return files.exists(at)


def stored(df: DataFrame, path: str | None = None) -> DataFrame:
    """df written as Parquet and read again: its lineage ends there. Without a path, in the shared folder until the
    program ends."""
    spark = df.sparkSession
    if path is None:
        path = f"{shared_dir(spark)}/tables/{uuid.uuid4().hex}"
        _written.append((spark, path))
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path)


def spread(df: DataFrame, most_bytes: int = 64 << 20) -> DataFrame:
    """df over all cores if, by the planner's estimate, it is so small that it stands in few files; else as it is."""
    cores = df.sparkSession.sparkContext.defaultParallelism
    if int(str(df._jdf.queryExecution().optimizedPlan().stats().sizeInBytes())) > most_bytes or df.rdd.getNumPartitions() >= cores:
        return df
    return df.repartition(cores)


def dealt(df: DataFrame, *by: str) -> DataFrame:
    """df over as many tasks as a shuffle has, and no fewer than there are cores: for work that is heavy where the rows
    are few, which Spark would put in one task for their bytes."""
    spark = df.sparkSession
    return df.repartition(max(int(spark.conf.get("spark.sql.shuffle.partitions")), spark.sparkContext.defaultParallelism), *by)


@atexit.register
def _clean() -> None:
    for spark, path in _written:
        try:
            at, files = _path(spark, path)
            files.delete(at, True)
        except Exception:  # noqa: BLE001  the session may be gone at exit
            return
