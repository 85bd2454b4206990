"""Search as SQL table functions and Arrow user functions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql.functions import pandas_udf, udtf

from ivfspark.functions.vectors import paired, pairwise
from ivfspark.sources.index import Index


def distance_udf(metric: str = "l2"):
    """Arrow-batched distance of two vector columns; the expression form stays in the JVM and is faster."""

    @pandas_udf("double")
    def fn(a: pd.Series, b: pd.Series) -> pd.Series:
        if not len(a):
            return pd.Series([], dtype="float64")
        return pd.Series(paired(np.stack(a.to_numpy()), np.stack(b.to_numpy()), metric))

    return fn


def centroid_udaf():
    """Grouped mean of a vector column, by fixed-point sums."""

    @pandas_udf("array<double>")
    def fn(e: pd.Series) -> list[float]:
        sums = np.floor(np.stack(e.to_numpy()).astype(np.float64) * (1 << 30) + 0.5).astype(np.int64).sum(axis=0)
        return (sums / (1 << 30) / len(e)).tolist()

    return fn


def register_probe(spark: SparkSession, index: Index, name: str = "ivf_probe") -> None:
    """SQL table function ``ivf_probe(query, n)``: partitions nearest to a vector, with their rank."""
    centers, metric = index.centroids().centers, index.metric

    @udtf(returnType="rank int, part_id long, dist double")
    class Probe:
        def eval(self, query: list, n: int):
            dist = pairwise(np.array([query], np.float64), centers, metric)[0]
            for rank, part in enumerate(np.lexsort((np.arange(len(dist)), dist))[:n].tolist(), 1):
                yield rank, part, float(dist[part])

    spark.udtf.register(name, Probe)


def register_ann(spark: SparkSession, index: Index, name: str = "ivf") -> None:
    """Temporary views ``<name>_vectors`` and ``<name>_centroids`` and the probe function, so that
    ``SELECT ... FROM ivf_probe(q, n) JOIN ivf_vectors USING (part_id)`` is a search."""
    index.live().createOrReplaceTempView(f"{name}_vectors")
    index.centroid_rows().createOrReplaceTempView(f"{name}_centroids")
    register_probe(spark, index, f"{name}_probe")
