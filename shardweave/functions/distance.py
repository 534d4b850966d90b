"""Distances: column expressions, NumPy blocks, and the transform of inner products to distances."""

from __future__ import annotations

from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

METRICS = ("l2", "l2sq", "cosine", "ip")


def known(metric: str) -> str:
    if metric not in METRICS:
        raise ValueError(f"metric must be one of {METRICS}, not {metric!r}")
    return metric


def _fold(a: Column, b: Column, f) -> Column:
    parts = F.zip_with(a, b, lambda x, y: f(x.cast("double"), y.cast("double")))
    return F.aggregate(parts, F.lit(0.0), lambda s, x: s + x)


def expr(metric: str, a: Column, b: Column) -> Column:
    """The distance of two array columns in native expressions; ``ip`` is the inner product itself."""
    known(metric)
    if metric == "ip":
        return _fold(a, b, lambda x, y: x * y)
    if metric == "cosine":
        return 1 - _fold(a, b, lambda x, y: x * y) / F.sqrt(_fold(a, a, lambda x, y: x * y) * _fold(b, b, lambda x, y: x * y))
    squared = _fold(a, b, lambda x, y: (x - y) * (x - y))
    return squared if metric == "l2sq" else F.sqrt(squared)


def rows(metric: str, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Distances of matching rows by direct difference, in double."""
    if metric in ("l2", "l2sq"):
        d = ((a - b) ** 2).sum(axis=-1)
        return np.sqrt(d) if metric == "l2" else d
    dot = (a * b).sum(axis=-1)
    if metric == "ip":
        return -dot
    return 1 - dot / np.sqrt((a * a).sum(axis=-1) * (b * b).sum(axis=-1))


def to_row(metric: str, q: np.ndarray) -> Callable[[np.ndarray], np.ndarray]:
    """:func:`rows` from one vector to those of a matrix that may be overwritten, with the same results."""
    if metric not in ("l2", "l2sq"):
        return lambda x: rows(metric, q[None, :], x)

    def far(x: np.ndarray) -> np.ndarray:
        x -= q
        x *= x
        d = np.add.reduce(x, 1)
        return np.sqrt(d, d) if metric == "l2" else d

    return far


def block(metric: str, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """All distances of two blocks by one matrix product: good for choosing candidates, not for reporting."""
    dot = a @ b.T
    if metric == "ip":
        return -dot
    na, nb = (a * a).sum(axis=1), (b * b).sum(axis=1)
    if metric == "cosine":
        return 1 - dot / np.sqrt(np.maximum(na[:, None] * nb[None, :], 1e-300))
    d = np.maximum(na[:, None] + nb[None, :] - 2 * dot, 0)
    return np.sqrt(d) if metric == "l2" else d


def rough(metric: str, a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """All distances of two blocks by one matrix product, of l2 the squares; and by row how far they may be off."""
    off = 8 * (a.shape[1] + 8) * np.finfo(float).eps
    na, nb = (a * a).sum(axis=1), (b * b).sum(axis=1)
    if metric in ("l2", "l2sq"):
        return block("l2sq", a, b), off * (na + nb.max(initial=0))
    if metric == "ip":
        return block("ip", a, b), off * np.sqrt(na * nb.max(initial=0))
    return block("cosine", a, b), np.full(len(a), 4 * off)


def matrix(column: pa.ChunkedArray | pa.Array) -> np.ndarray:
    """A column of equally long lists as a matrix of doubles."""
    flat = column.combine_chunks() if isinstance(column, pa.ChunkedArray) else column
    n = len(flat)
    values = flat.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return values.reshape(n, -1) if n else np.zeros((0, 0))


def measured(df: DataFrame, a: str, b: str, out: str = "dist", metric: str = "l2") -> DataFrame:
    """``df`` with the distance of two array columns instead of them: an Arrow kernel over whole batches."""
    known(metric)
    kept = [f for f in df.schema.fields if f.name not in (a, b)]
    names = [f.name for f in kept]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            d = rows(metric, matrix(batch.column(a)), matrix(batch.column(b))) if batch.num_rows else np.zeros(0)
            yield pa.RecordBatch.from_arrays([*(batch.column(n) for n in names), pa.array(d)], names=[*names, out])

    shape = ", ".join([f"`{f.name}` {f.dataType.simpleString()}" for f in kept] + [f"{out} double"])
    return df.mapInArrow(run, shape)


def mips_to_l2(vectors: DataFrame, x: str = "x") -> DataFrame:
    """Vectors with one more component, so that nearest by l2 is greatest by inner product; queries get a zero."""
    norm = _fold(F.col(x), F.col(x), lambda a, b: a * b)
    top = vectors.agg(F.max(norm)).first()[0] or 0.0
    return vectors.withColumn(x, F.concat(F.transform(x, lambda c: c.cast("double")), F.array(F.sqrt(F.greatest(F.lit(0.0), F.lit(top) - norm)))))


def mips_query(queries: DataFrame, x: str = "x") -> DataFrame:
    return queries.withColumn(x, F.concat(F.transform(x, lambda c: c.cast("double")), F.array(F.lit(0.0))))


#: Bodies of the SQL functions by name; vectors are ``a`` and ``b``.
_DOT = "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)"
_SQ = "aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x)"
_NORM = "sqrt(aggregate(a, 0D, (s, x) -> s + x * x))"
SQL_FUNCTIONS = {
    "inner_product": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", _DOT),
    "l2sq": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", _SQ),
    "l2": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", f"sqrt({_SQ})"),
    "norm2": ("a ARRAY<DOUBLE>", "DOUBLE", _NORM),
    "cosine_dist": ("a ARRAY<DOUBLE>, b ARRAY<DOUBLE>", "DOUBLE", f"1 - {_DOT} / ({_NORM} * {_NORM.replace('(a,', '(b,')})"),
    "normalize_vec": ("a ARRAY<DOUBLE>", "ARRAY<DOUBLE>", f"transform(a, x -> x / {_NORM})"),
}


def register(spark: SparkSession) -> None:
    """Temporary SQL functions over vectors, made of native expressions."""
    for name, (takes, gives, body) in SQL_FUNCTIONS.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}({takes}) RETURNS {gives} RETURN {body}")
