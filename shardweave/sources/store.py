"""Index storage: Parquet by index and layer, with the metadata that a reader checks; and vectors in fvecs and ivecs files."""

from __future__ import annotations

import json
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T

EDGE = T.StructType([
    T.StructField("index_id", T.IntegerType()), T.StructField("layer", T.IntegerType()), T.StructField("src", T.LongType()), T.StructField("dst", T.LongType()), T.StructField("dist", T.DoubleType()),
])


def save(edges: DataFrame, path: str, meta: dict, entries: DataFrame | None = None) -> None:
    """Edges under ``path/edges``, partitioned by index and layer and sorted by source; metadata as one JSON row."""
    shaped = edges.withColumns({c: F.lit(0) for c in ("index_id", "layer") if c not in edges.columns}).select(*EDGE.names)
    shaped.repartition("index_id", "layer", "src").sortWithinPartitions("src", "dist").write.partitionBy("index_id", "layer").mode("overwrite").parquet(f"{path}/edges")
    spark = edges.sparkSession
    spark.createDataFrame([(json.dumps(meta, sort_keys=True),)], "value string").coalesce(1).write.mode("overwrite").text(f"{path}/meta")
    if entries is not None:
        entries.select("index_id", "ep").write.mode("overwrite").parquet(f"{path}/entries")


def load(spark: SparkSession, path: str, metric: str | None = None) -> tuple[DataFrame, dict]:
    """Edges and metadata of an index; a metric other than the stored one is an error."""
    meta = json.loads(spark.read.text(f"{path}/meta").first()[0])
    if metric and meta.get("metric") != metric:
        raise ValueError(f"the index is for {meta.get('metric')!r}, not {metric!r}")
    return spark.read.schema(EDGE).parquet(f"{path}/edges"), meta


def save_bucketed(edges: DataFrame, name: str, buckets: int) -> None:
    """A table bucketed by source, so that joins by source need no shuffle."""
    edges.write.bucketBy(buckets, "src").sortBy("src", "dist").mode("overwrite").saveAsTable(name)


def pack(edges: DataFrame) -> DataFrame:
    """Edge rows to one row a source, neighbours in order."""
    lists = edges.groupBy("src").agg(F.array_sort(F.collect_list(F.struct("dist", "dst"))).alias("n"))
    return lists.select("src", F.transform("n", lambda s: F.struct(s.dst.alias("dst"), s.dist.alias("dist"))).alias("nbrs"))


def unpack(adjacency: DataFrame) -> DataFrame:
    flat = adjacency.select("src", F.posexplode("nbrs").alias("pos", "n"))
    return flat.select("src", F.col("n.dst").alias("dst"), F.col("n.dist").alias("dist"), (F.col("pos") + 1).alias("rank"))


def vecs_bytes(rows: np.ndarray) -> bytes:
    """The fvecs (float32) or ivecs (int32) form of a matrix: each row after its dimension."""
    head = np.full((len(rows), 1), rows.shape[1], "<i4")
    kind = "<i4" if rows.dtype.kind in "iu" else "<f4"
    return np.hstack((head.view("<i4"), rows.astype(kind).view("<i4"))).astype("<i4").tobytes()


def read_vecs(spark: SparkSession, path: str, integers: bool = False) -> DataFrame:
    """``(file, row, x)`` of fvecs or ivecs files, a file a task through Spark's own readers."""
    kind = "int" if integers else "float"

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for name, content in zip(b.column("path").to_pylist(), b.column("content"), strict=True):
                raw = np.frombuffer(content.as_buffer(), "<i4")
                if not len(raw):
                    continue
                dim = int(raw[0])
                if dim <= 0 or len(raw) % (dim + 1):
                    raise ValueError(f"{name} isn't a vecs file of dimension {dim}")
                rows = raw.reshape(-1, dim + 1)
                if (rows[:, 0] != dim).any():
                    raise ValueError(f"{name} mixes dimensions")
                values = np.ascontiguousarray(rows[:, 1:])
                flat = pa.array(values.ravel() if integers else values.view("<f4").ravel())
                ends = pa.array(np.arange(len(rows) + 1, dtype=np.int32) * dim)
                yield pa.RecordBatch.from_arrays([pa.array([name] * len(rows)), pa.array(np.arange(len(rows))), pa.ListArray.from_arrays(ends, flat)], names=["file", "row", "x"])

    files = spark.read.format("binaryFile").load(path).select("path", "content")
    return files.mapInArrow(run, f"file string, row long, x array<{kind}>")
