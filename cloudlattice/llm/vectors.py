"""Vectors of an embeddings table as double precision, and those that can take part."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def usable(embedding: Column) -> Column:
    """Not null, no null or non-finite component, not zero (as doubles)."""
    v = embedding.cast("array<double>")
    finite = F.forall(v, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < F.lit(float("inf"))))
    return F.coalesce(v.isNotNull() & finite & F.exists(v, lambda x: x != 0), F.lit(False))


def matrix(column: pa.Array) -> np.ndarray:
    """Equal-length list column as a matrix of doubles, without a Python object per row."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    flat = column.flatten().to_numpy(zero_copy_only=False).astype(np.float64)
    return flat.reshape(len(column), -1) if len(column) else flat.reshape(0, 0)


def widths(vectors: DataFrame) -> list[int]:
    """The lengths of the vectors ``v``, by a count over all rows."""
    return sorted(r[0] for r in vectors.groupBy(F.size("v").alias("width")).count().collect())


def by_width(batch: pa.RecordBatch) -> Iterator[tuple[int, pa.RecordBatch]]:
    """The parts of a batch whose vectors ``v`` have one length, rows in order."""
    sizes = pc.list_value_length(batch.column("v"))
    for width in sorted(pc.unique(sizes).to_pylist()):
        yield width, batch.filter(pc.equal(sizes, width))


def norms(x: np.ndarray) -> np.ndarray:
    return np.sqrt(np.einsum("ij,ij->i", x, x))


def cosine(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Row by row, in double precision; components are summed in order, whatever the batch."""
    dot, aa, bb = (np.zeros(len(a)) for _ in range(3))
    for k in range(a.shape[1]):
        dot += a[:, k] * b[:, k]
        aa += a[:, k] * a[:, k]
        bb += b[:, k] * b[:, k]
    return dot / (np.sqrt(aa) * np.sqrt(bb))


def participants(vectors: DataFrame, *columns: str) -> DataFrame:
    return vectors.where(F.col("vec_id").isNotNull() & usable(F.col("embedding"))).select(*columns, F.col("embedding").cast("array<double>").alias("v"))
