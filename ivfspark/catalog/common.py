"""What the queries share: the standard index, query vectors, attributes."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ivfspark.config import IndexConfig
from ivfspark.operators import search
from ivfspark.plans import statistics
from ivfspark.plans.scratch import scratch_path
from ivfspark.sources import collections
from ivfspark.sources.collections import table
from ivfspark.sources.index import Index, build, open_index

#: Neighbours, probes where a query fixes them (others use ``calibrated``), the seed, and query ids: those divisible by EVERY.
K, PROBES, SEED, EVERY = 10, 3, 42, 50
CONFIG = IndexConfig(target_size=50, batch=64, iters=6, seed=SEED, lam=0.5)
SUPER_SIZE = 4

_built: dict[tuple, str] = {}
_probes: dict[tuple, int] = {}


def standard_index(spark: SparkSession, sf_dir: str, metric: str = "l2", source: str = "v1", cfg: IndexConfig | None = None) -> Index:
    """The index that queries search; built once an application, then opened."""
    cfg = cfg or IndexConfig(**{**CONFIG.as_dict(), "metric": metric})
    key = (spark.sparkContext.applicationId, sf_dir, source, cfg)
    if key not in _built:
        path = scratch_path(spark, f"index-{source}")
        build(spark, path, collections.COLLECTIONS[source](spark, sf_dir), cfg, two_level=SUPER_SIZE)
        _built[key] = path
    return open_index(spark, _built[key])


def private_index(spark: SparkSession, sf_dir: str, cfg: IndexConfig | None = None, rows: DataFrame | None = None) -> Index:
    """A new index of one's own, to change."""
    path = scratch_path(spark, "private")
    return build(spark, path, collections.v1(spark, sf_dir) if rows is None else rows, cfg or CONFIG)


def calibrated(spark: SparkSession, sf_dir: str, metric: str = "l2", source: str = "v1", k: int = K) -> int:
    """Least number of probes whose recall of the query batch is 0.9; found once an application."""
    key = (spark.sparkContext.applicationId, sf_dir, metric, source, k)
    if key not in _probes:
        _probes[key] = search.calibrate_probes(standard_index(spark, sf_dir, metric, source), query_batch(spark, sf_dir, source), k, 0.9)
    return _probes[key]


def attributed_index(spark: SparkSession, sf_dir: str) -> Index:
    """The standard index with attributes beside its partitions, and their statistics."""
    index = standard_index(spark, sf_dir)
    if not index.manifest.get("attributes"):
        index = statistics.attach(index, attributes(spark, sf_dir), ["lang", "source", "n_chars", "quality"], ["tokens"])
    return index


def query_vector(spark: SparkSession, sf_dir: str, vec_id: int = 0, source: str = "v1") -> list[float]:
    return collections.COLLECTIONS[source](spark, sf_dir).where(F.col("vec_id") == vec_id).first().embedding


def query_batch(spark: SparkSession, sf_dir: str, source: str = "v1") -> DataFrame:
    """The stated queries: every row whose id is divisible by 50, to be asked of all rows."""
    rows = collections.COLLECTIONS[source](spark, sf_dir).where(F.col("vec_id") % EVERY == 0)
    return rows.select(F.col("vec_id").alias("qid"), F.col("embedding").alias("qvec"))


def attributes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Attributes of vectors: their documents' columns and tokens, and labels where there are any."""
    docs = table(spark, sf_dir, "documents").select(F.col("doc_id").alias("asset_id"), "lang", "source", "n_chars", "text")
    own = docs.join(collections.v1(spark, sf_dir).select(F.col("vec_id").alias("asset_id")), "asset_id", "left_semi")
    own = own.select("asset_id", "lang", "source", "n_chars", F.array_distinct(collections.tokens(F.col("text"))).alias("tokens"))
    labels = table(spark, sf_dir, "labels").select(F.col("doc_id").alias("asset_id"), "quality", "toxic")
    return own.join(labels, "asset_id", "left")


def rounded(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.round(c, 6) for c in columns})


#: SQL of the attributes relation.
ATTRIBUTES = (
    "att AS MATERIALIZED (SELECT d.doc_id AS asset_id, lang, source, n_chars, "
    "list_distinct(list_filter(list_transform(regexp_split_to_array(coalesce(text, ''), '[^A-Za-z0-9À-ÿ]+'), lambda t: lower(t)), lambda t: t <> '')) AS tokens, "
    "quality, toxic FROM documents d JOIN embeddings e ON e.vec_id = d.doc_id LEFT JOIN labels l ON l.doc_id = d.doc_id)"
)
Q0 = "(SELECT e FROM x WHERE vec_id = 0)"
