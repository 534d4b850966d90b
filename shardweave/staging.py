"""Cutting lineage by writing a table to storage that every executor shares.

``checkpoint()`` computes a frame twice unless it is cached, so the loops of this package write Parquet instead and read
it back: one computation, columnar, and it outlives lost executors.
"""

from __future__ import annotations

import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

from pyspark import StorageLevel
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import types as T


def shared_root(spark: SparkSession) -> str:
    """The folder of ``spark.checkpoint.dir``; where it is unset (tests, one machine) a temporary one is set."""
    root = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if root:
        return root.rstrip("/")
    known = spark.sparkContext._jsc.sc().getCheckpointDir()
    if known.isDefined():
        return known.get().rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("spark.checkpoint.dir must name a shared folder on a cluster")
    spark.sparkContext.setCheckpointDir(tempfile.mkdtemp(prefix="shardweave-"))
    return shared_root(spark)


def fresh_path(spark: SparkSession, label: str) -> str:
    return f"{shared_root(spark)}/{label}-{uuid.uuid4().hex}"


#: How frames are kept now; a list, as worker code that travels by value can carry one.
_STORAGE = ["parquet"]


@contextmanager
def storing(storage: str) -> Iterator[None]:
    """How :func:`stage` keeps frames inside: ``parquet`` in the shared folder, or ``cache``, where what is read back from there
    stays in the executors' memory as well; what a lost executor held is read again."""
    if storage not in ("parquet", "cache"):
        raise ValueError(f"storage must be parquet or cache, not {storage!r}")
    _STORAGE.append(storage)
    try:
        yield
    finally:
        _STORAGE.pop()


def stage(df: DataFrame, label: str = "stage", partition_by: list[str] | None = None) -> DataFrame:
    """Write ``df`` to the shared folder and return the table as read back; see :func:`storing`."""
    spark = df.sparkSession
    path = fresh_path(spark, label)
    writer = df.write.mode("errorifexists")
    if partition_by:
        writer = writer.partitionBy(*partition_by)
    writer.parquet(path)
    out = spark.read.schema(_nullable(df.schema)).parquet(path)
    if _STORAGE[-1] == "cache":
        out = out.persist(StorageLevel.MEMORY_AND_DISK)
    out._staged_at = path
    return out


def _nullable(schema: T.StructType) -> T.StructType:
    return T.StructType([T.StructField(f.name, f.dataType, True) for f in schema.fields])


def drop(df: DataFrame) -> None:
    """Delete the files behind a frame that :func:`stage` returned."""
    spark = df.sparkSession
    if df.is_cached:
        df.unpersist()
    jvm = spark.sparkContext._jvm
    known = getattr(df, "_staged_at", None)
    for folder in {known} if known else {name.rsplit("/", 1)[0] for name in df.inputFiles()}:
        path = jvm.org.apache.hadoop.fs.Path(folder)
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)
