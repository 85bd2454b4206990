"""Broadcast of driver-side arrays, behind a check of their size."""

from __future__ import annotations

import numpy as np
from pyspark import Broadcast
from pyspark.sql import SparkSession

#: Bytes of arrays that are broadcast; every executor holds them once, and every Python worker reads them.
MOST_BYTES = 1 << 30


def array_bytes(value) -> int:
    """Bytes of all arrays in nested tuples, lists and dicts."""
    if isinstance(value, np.ndarray):
        return value.nbytes
    if isinstance(value, dict):
        return sum(array_bytes(x) for x in value.values())
    return sum(array_bytes(x) for x in value) if isinstance(value, (tuple, list)) else 8


def share(spark: SparkSession, value, what: str, most: int = MOST_BYTES) -> Broadcast:
    """Broadcast ``value``, or an error that says what grew too large."""
    size = array_bytes(value)
    if size > most:
        raise ValueError(f"{what}: {size} bytes are too many to broadcast (at most {most}); use larger partitions or smaller blocks")
    return spark.sparkContext.broadcast(value)
