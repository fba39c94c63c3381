"""Where intermediate relations are written: the folder that the driver and all executors share."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession

_own_dir: str | None = None
_written: list[str] = []


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; where it is unset, the warehouse of a cluster or, on one machine, a folder of our own."""
    global _own_dir
    if path := spark.conf.get("spark.checkpoint.dir", None):
        return path.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        return spark.conf.get("spark.sql.warehouse.dir").rstrip("/") + "/_scratch"
    if _own_dir is None:
        _own_dir = tempfile.mkdtemp(prefix="volume-engine-")
    return _own_dir


def new_path(spark: SparkSession, label: str) -> str:
    _written.append(f"{shared_dir(spark)}/{label}-{uuid.uuid4().hex}")
    return _written[-1]


def keep(df: DataFrame, label: str = "kept") -> DataFrame:
    """Cut the lineage: write ``df`` into the shared folder and read it back, so that it outlives any executor."""
    path = new_path(df.sparkSession, label)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def clean(spark: SparkSession) -> None:
    """Delete every folder this process has asked for; nothing lazy may read them any more."""
    while _written:
        drop(spark, _written.pop())


def hadoop_path(spark: SparkSession, path: str):
    """The Hadoop path and its file system."""
    where = spark._jvm.org.apache.hadoop.fs.Path(path)
    return where, where.getFileSystem(spark._jsc.hadoopConfiguration())


def exists(spark: SparkSession, path: str) -> bool:
    where, system = hadoop_path(spark, path)
    return system.exists(where)


def drop(spark: SparkSession, path: str) -> None:
    where, system = hadoop_path(spark, path)
    system.delete(where, True)


def rename(spark: SparkSession, path: str, to: str) -> None:
    where, system = hadoop_path(spark, path)
    if not system.rename(where, hadoop_path(spark, to)[0]):
        raise OSError(f"{path} cannot be renamed to {to}")


def touch(spark: SparkSession, path: str) -> None:
    where, system = hadoop_path(spark, path)
    system.create(where).close()


def bytes_of(spark: SparkSession, path: str) -> int:
    where, system = hadoop_path(spark, path)
    return int(system.getContentSummary(where).getLength())


def state_of(spark: SparkSession, path: str) -> tuple[int, int]:
    """Length and time of change of a file or folder, to tell whether it is still the one that was read."""
    where, system = hadoop_path(spark, path)
    return int(system.getContentSummary(where).getLength()), int(system.getFileStatus(where).getModificationTime())
