"""The given tables and the vector collections derived from them, all ``(vec_id, embedding)``.

V1 the given embeddings; V2 the same, scaled so that norms differ; V3 hashed tokens of documents; V4 orders
and V5 lineitem as feature vectors; V6 hashed character trigrams of pages; V7 hashed tokens of conversations.
"""

from __future__ import annotations

import hashlib
import re
from collections import Counter
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

TOKEN_SPLIT = "[^A-Za-z0-9À-ÿ]+"
WORD = re.compile("[A-Za-z0-9À-ÿ]+")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def tokens(text: Column) -> Column:
    return F.filter(F.transform(F.split(F.coalesce(text, F.lit("")), TOKEN_SPLIT), F.lower), lambda t: t != "")


#: Buckets of terms that a worker keeps; rows of dense vectors that it makes at once.
KEPT_TERMS, DENSE_ROWS = 1 << 18, 512


class _Buckets(dict):
    """Terms to the first eight hex digits of their md5, as a number below ``dim``; bounded."""

    def __init__(self, dim: int):
        super().__init__()
        self.dim = dim

    def __missing__(self, term: str) -> int:
        if len(self) >= KEPT_TERMS:
            self.clear()
        self[term] = found = int(hashlib.md5(term.encode()).hexdigest()[:8], 16) % self.dim
        return found


def count_tokens(text: str, buckets: _Buckets) -> tuple[list, list]:
    """Bucket and count of every distinct token, those of ``tokens``."""
    counts = Counter(WORD.findall(text))
    return [buckets[t.lower()] for t in counts], list(counts.values())


def count_trigrams(text: str, buckets: _Buckets) -> tuple[list, list]:
    """Bucket and count of every distinct run of three code points."""
    points = np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.int64)
    grams, counts = np.unique(points[:-2] << 42 | points[1:-1] << 21 | points[2:], return_counts=True)
    low = (1 << 21) - 1
    return [buckets[chr(g >> 42) + chr(g >> 21 & low) + chr(g & low)] for g in grams.tolist()], counts.tolist()


def hashed(rows: DataFrame, key: str, text: str, count: Callable, dim: int) -> DataFrame:
    """Term counts by hash bucket as dense unit vectors; rows without terms are dropped. One pass, nothing is shuffled."""

    def dense(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        buckets = _Buckets(dim)
        for batch in batches:
            for at in range(0, batch.num_rows, DENSE_ROWS):
                piece = batch.slice(at, DENSE_ROWS)
                out = np.zeros((piece.num_rows, dim))
                for i, value in enumerate(piece.column(1)):
                    where, n = count(value.as_py() or "", buckets)
                    if where:
                        np.add.at(out[i], where, n)
                some = out.any(axis=1)
                out = out[some]
                out /= np.sqrt((out * out).sum(axis=1, keepdims=True))
                offsets = pa.array(np.arange(len(out) + 1, dtype=np.int32) * dim)
                lists = pa.ListArray.from_arrays(offsets, pa.array(out.astype(np.float32).ravel()))
                yield pa.RecordBatch.from_arrays([piece.column(0).filter(pa.array(some)), lists], ["vec_id", "embedding"])

    return rows.select(F.col(key).cast("long").alias(key), text).mapInArrow(dense, "vec_id long, embedding array<float>")


def v1(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "embeddings").select("vec_id", "embedding")


def v2(spark: SparkSession, sf_dir: str) -> DataFrame:
    by = (1 + F.col("vec_id") % 7).cast("float")
    return v1(spark, sf_dir).select("vec_id", F.transform("embedding", lambda x: x * by).alias("embedding"))


def v3(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hashed(table(spark, sf_dir, "documents"), "doc_id", "text", count_tokens, 256)


def _hot(column: str, values: list[str]) -> list[Column]:
    return [F.when(F.col(column) == v, 1.0).otherwise(0.0) for v in values]


def _days(column: str) -> Column:
    return F.datediff(F.col(column).cast("date"), F.lit("1995-01-01").cast("date")).cast("double")


def v4(spark: SparkSession, sf_dir: str) -> DataFrame:
    features = [
        F.col("o_totalprice") / 500000,
        _days("o_orderdate") / 2404,
        *_hot("o_orderstatus", ["F", "O", "P"]),
        *_hot("o_orderpriority", ["1-URGENT", "2-HIGH", "3-MEDIUM", "4-NOT SPECIFIED", "5-LOW"]),
    ]
    return table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("vec_id"), F.array(*features).cast("array<float>").alias("embedding"))


def v5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ids come from the order of all columns, as no shorter key is unique; numbered within ranges of
    the order key, not in one task."""
    rows = table(spark, sf_dir, "lineitem")
    features = [
        F.col("l_quantity") / 50,
        F.col("l_extendedprice") / 105000,
        F.col("l_discount") / 0.1,
        F.col("l_tax") / 0.08,
        _days("l_shipdate") / 2500,
        *_hot("l_returnflag", ["A", "N", "R"]),
        *_hot("l_linestatus", ["F", "O"]),
    ]
    within = W.partitionBy("l_orderkey").orderBy(*[c for c in rows.columns if c != "l_orderkey"])
    number = F.col("l_orderkey") * 1024 + F.row_number().over(within)
    return rows.select(number.cast("long").alias("vec_id"), F.array(*features).cast("array<float>").alias("embedding"))


def v6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return hashed(table(spark, sf_dir, "pages"), "page_id", "html", count_trigrams, 960)


def v7(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = table(spark, sf_dir, "conversations").withColumn("row", F.col("conv_id") * 4096 + F.col("turn"))
    return hashed(rows, "row", "text", count_tokens, 200)


COLLECTIONS = {"v1": v1, "v2": v2, "v3": v3, "v4": v4, "v5": v5, "v6": v6, "v7": v7}
DIMENSIONS = {"v1": 64, "v2": 64, "v3": 256, "v4": 10, "v5": 10, "v6": 960, "v7": 200}
METRIC = {"v1": "cosine", "v2": "l2", "v3": "cosine", "v4": "l2", "v5": "l2", "v6": "l2", "v7": "l2"}
