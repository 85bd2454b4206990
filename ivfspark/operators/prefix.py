"""Distributed prefix sums: rank or running totals without one task seeing all rows."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F


def running_total(
    df: DataFrame,
    bucket: Column,
    order: list[Column],
    value: Column,
    name: str,
    keys: list[str] | None = None,
) -> DataFrame:
    """Add ``name``: the sum of ``value`` over all earlier rows of the same ``keys``.

    ``bucket`` must be a non-decreasing function of ``order``. Rows are windowed within a bucket only;
    bucket totals, one row a bucket, give each bucket its offset. ``df`` is read twice; keys and
    buckets must not be null.
    """
    keys = keys or []
    placed = df.withColumn("_bucket", bucket).withColumn("_value", value)
    totals = placed.groupBy(*keys, "_bucket").agg(F.sum("_value").alias("_total"))
    before = W.partitionBy(*[F.col(k) for k in keys]).orderBy("_bucket").rowsBetween(W.unboundedPreceding, -1)
    offsets = totals.withColumn("_offset", F.coalesce(F.sum("_total").over(before), F.lit(0))).drop("_total")
    inside = W.partitionBy(*[F.col(k) for k in keys], F.col("_bucket")).orderBy(*order).rowsBetween(W.unboundedPreceding, -1)
    local = placed.withColumn("_local", F.coalesce(F.sum("_value").over(inside), F.lit(0)))
    return (
        local.join(offsets, [*keys, "_bucket"])
        .withColumn(name, F.col("_local") + F.col("_offset"))
        .select(*df.columns, name)
    )
