"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ivfspark.config import IndexConfig
from ivfspark.sources.index import Index


def recall_at_k(approximate: DataFrame, truth: DataFrame, k: int) -> DataFrame:
    """``(qid, recall)``: shared ids over min(k, size of the truth); queries without truth are left out."""
    size = truth.groupBy("qid").agg(F.least(F.count("*"), F.lit(k)).alias("size"))
    shared = truth.join(approximate.select("qid", "vec_id"), ["qid", "vec_id"]).groupBy("qid").agg(F.count("*").alias("hits"))
    return size.join(shared, "qid", "left").select("qid", (F.coalesce("hits", F.lit(0)) / F.col("size")).alias("recall"))


def partition_sizes(index: Index) -> DataFrame:
    return index.live(include_delta=False).groupBy("part_id").agg(F.count("*").alias("size"))


def balance(sizes: DataFrame) -> DataFrame:
    """Least, greatest and mean size, deviation, and greatest over mean."""
    s = sizes.agg(F.min("size").alias("min_size"), F.max("size").alias("max_size"), F.avg("size").alias("avg_size"), F.stddev_pop("size").alias("std_size"))
    return s.withColumn("imbalance", F.col("max_size") / F.col("avg_size"))


def scan_cost(index: Index, probes: DataFrame) -> DataFrame:
    """``(qid, rows_scanned)``: rows of the probed partitions and of the delta."""
    sizes = partition_sizes(index)
    delta = index.manifest["n_delta"]
    joined = probes.join(sizes, "part_id", "left").groupBy("qid").agg(F.sum(F.coalesce("size", F.lit(0))).alias("n"))
    return joined.select("qid", (F.col("n") + delta).alias("rows_scanned"))


def sharing_factor(probes: DataFrame) -> DataFrame:
    """Partition reads asked for over partitions read, of a batch."""
    return probes.agg((F.count("*") / F.count_distinct("part_id")).alias("factor"))


def memory_model(n: int, dim: int, cfg: IndexConfig, k: int, top: int = 100, workers: int = 8) -> dict[str, int]:
    """Bytes held while training and searching, beside the same without an index on disk."""
    return {
        "train_bytes": min(cfg.batch, n) * dim * 4 + k * dim * 8,
        "full_kmeans_bytes": n * dim * 4 + k * dim * 8,
        "query_bytes": k * dim * 8 + workers * top * 16,
        "in_memory_bytes": n * dim * 4 + k * dim * 8,
    }
