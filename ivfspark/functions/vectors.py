"""Distances twice: as Catalyst expressions (JVM only, summed from left to right in doubles) and as numpy
kernels (``pairwise`` sums in the same order and agrees to the bit; ``pairwise_fast`` uses one matrix
product)."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, SparkSession
from pyspark.sql import functions as F

METRICS = ("l2", "cosine", "ip")


def _fold(a: Column, b: Column, step) -> Column:
    return F.aggregate(F.zip_with(a, b, step), F.lit(0.0), lambda s, x: s + x)


def doubles(a: Column | str) -> Column:
    return (F.col(a) if isinstance(a, str) else a).cast("array<double>")


def dot(a: Column, b: Column) -> Column:
    return _fold(doubles(a), doubles(b), lambda x, y: x * y)


def norm(a: Column) -> Column:
    return F.sqrt(dot(a, a))


def l2(a: Column, b: Column) -> Column:
    return F.sqrt(_fold(doubles(a), doubles(b), lambda x, y: (x - y) * (x - y)))


def cosine(a: Column, b: Column) -> Column:
    """1 less the cosine; 1 where either side is the zero vector."""
    size = F.sqrt(dot(a, a)) * F.sqrt(dot(b, b))
    return F.when(size == 0, F.lit(1.0)).otherwise(F.lit(1.0) - dot(a, b) / size)


def distance(a: Column, b: Column, metric: str = "l2") -> Column:
    """Smaller is nearer under every metric."""
    if metric == "l2":
        return l2(a, b)
    if metric == "cosine":
        return cosine(a, b)
    if metric == "ip":
        return -dot(a, b)
    raise ValueError(f"unknown metric {metric}")


def literal(vector) -> Column:
    """A vector as a constant."""
    return F.array(*[F.lit(float(x)) for x in vector])


def normalise(a: Column) -> Column:
    size = norm(a)
    return F.when(size == 0, doubles(a)).otherwise(F.transform(doubles(a), lambda x: x / size))


def add(a: Column, b: Column) -> Column:
    return F.zip_with(doubles(a), doubles(b), lambda x, y: x + y)


def scale(a: Column, by) -> Column:
    return F.transform(doubles(a), lambda x: x * by)


def pairwise(a: np.ndarray, b: np.ndarray, metric: str = "l2") -> np.ndarray:
    """(m, k) distances summed component by component, as the expressions do."""
    a, b = np.asarray(a, np.float64), np.asarray(b, np.float64)
    out = np.zeros((len(a), len(b)))
    if metric == "l2":
        for j in range(a.shape[1]):
            diff = a[:, j, None] - b[None, :, j]
            out += diff * diff
        return np.sqrt(out)
    aa, bb = np.zeros(len(a)), np.zeros(len(b))
    for j in range(a.shape[1]):
        out += a[:, j, None] * b[None, :, j]
        aa += a[:, j] * a[:, j]
        bb += b[:, j] * b[:, j]
    if metric == "ip":
        return -out
    size = np.sqrt(aa)[:, None] * np.sqrt(bb)[None, :]
    with np.errstate(invalid="ignore", divide="ignore"):
        return np.where(size == 0, 1.0, 1.0 - out / size)


def pairwise_fast(a: np.ndarray, b: np.ndarray, metric: str = "l2") -> np.ndarray:
    """The same by one matrix product; last digits differ."""
    a, b = np.asarray(a, np.float64), np.asarray(b, np.float64)
    product = a @ b.T
    if metric == "ip":
        return -product
    aa, bb = np.einsum("ij,ij->i", a, a), np.einsum("ij,ij->i", b, b)
    if metric == "l2":
        return np.sqrt(np.maximum(aa[:, None] + bb[None, :] - 2 * product, 0))
    size = np.sqrt(aa)[:, None] * np.sqrt(bb)[None, :]
    with np.errstate(invalid="ignore", divide="ignore"):
        return np.where(size == 0, 1.0, 1.0 - product / size)


def paired(a: np.ndarray, b: np.ndarray, metric: str = "l2") -> np.ndarray:
    """Distances of row i of ``a`` and row i of ``b``, summed from left to right."""
    a, b = np.asarray(a, np.float64), np.asarray(b, np.float64)
    out, aa, bb = np.zeros(len(a)), np.zeros(len(a)), np.zeros(len(a))
    for j in range(a.shape[1]):
        if metric == "l2":
            diff = a[:, j] - b[:, j]
            out += diff * diff
        else:
            out += a[:, j] * b[:, j]
            aa += a[:, j] * a[:, j]
            bb += b[:, j] * b[:, j]
    if metric == "l2":
        return np.sqrt(out)
    if metric == "ip":
        return -out
    size = np.sqrt(aa) * np.sqrt(bb)
    with np.errstate(invalid="ignore", divide="ignore"):
        return np.where(size == 0, 1.0, 1.0 - out / size)


def matrix(column: pa.Array | pa.ChunkedArray) -> np.ndarray:
    """An Arrow list column as an (m, d) float64 matrix; all rows must have one length."""
    if isinstance(column, pa.ChunkedArray):
        column = column.combine_chunks()
    if column.null_count:
        raise ValueError("null vector")
    flat = column.flatten().to_numpy(zero_copy_only=False)
    if len(column) == 0:
        return np.zeros((0, 0))
    if len(flat) % len(column) or len(set(np.diff(column.offsets.to_numpy()).tolist())) > 1:
        raise ValueError("vectors of different dimensions")
    return flat.reshape(len(column), -1).astype(np.float64)


def pack(vector) -> bytes:
    """Little-endian 32-bit floats, the matrix kernels' own format."""
    return np.asarray(vector, "<f4").tobytes()


def unpack(blobs, dim: int) -> np.ndarray:
    """Packed vectors to an (m, dim) matrix without copying each."""
    return np.frombuffer(b"".join(blobs), "<f4").reshape(-1, dim)


def register_sql_functions(spark: SparkSession) -> None:
    """vec_dot, vec_l2, vec_cosine and vec_norm as SQL functions that Catalyst inlines."""
    vector = "ARRAY<DOUBLE>"
    body = {
        "vec_dot": "aggregate(zip_with(a, b, (x, y) -> x * y), 0D, (s, x) -> s + x)",
        "vec_l2": "sqrt(aggregate(zip_with(a, b, (x, y) -> (x - y) * (x - y)), 0D, (s, x) -> s + x))",
    }
    for name, text in body.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {name}(a {vector}, b {vector}) RETURNS DOUBLE RETURN {text}")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION vec_norm(a {vector}) RETURNS DOUBLE RETURN sqrt(aggregate(zip_with(a, a, (x, y) -> x * y), 0D, (s, x) -> s + x))")
    spark.sql(
        f"CREATE OR REPLACE TEMPORARY FUNCTION vec_cosine(a {vector}, b {vector}) RETURNS DOUBLE RETURN "
        "CASE WHEN vec_norm(a) * vec_norm(b) = 0 THEN 1D ELSE 1D - vec_dot(a, b) / (vec_norm(a) * vec_norm(b)) END"
    )
