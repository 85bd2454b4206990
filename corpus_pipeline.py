"""Corpus pipeline: quality rules, near-duplicates, decontamination, mixing, token output.

Each stage takes ``(spark, docs, sf_dir)``; its result is written as parquet and read again as the next
stage's ``docs``. All stages but the last return the columns of documents. Decisions are made and applied
row by row: a stage numbers its rows by file and place and passes the numbers through the operator, so rows without
id, and different texts under one id, are each judged by themselves.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.errors import AnalysisException
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ivfspark.llm.decontaminate import contamination
from ivfspark.llm.mixing import mix
from ivfspark.llm.near_copies import near_copies
from ivfspark.llm.quality_rules import judge
from ivfspark.llm.token_output import token_output
from ivfspark.plans.scratch import materialize

Stage = Callable[[SparkSession, DataFrame, str], DataFrame]


#: A row's number within a stage.
ROW = "_row"
#: Bits of a row's place in its file; the file's number stands above them.
PLACE_BITS = 40


def _numbered(docs: DataFrame) -> DataFrame:
    """Rows with numbers that are the same in every reading: file and place in it. Rows that are not read from files
    are written once."""
    try:
        placed = docs.select("*", F.col("_metadata.file_path").alias("_file"), F.col("_metadata.row_index").alias("_place"))
        files = placed.select("_file").distinct().orderBy("_file").collect()  # one row a file
    except AnalysisException:
        return materialize(docs.withColumn(ROW, F.monotonically_increasing_id()), "rows")
    numbers = docs.sparkSession.createDataFrame([(r._file, i << PLACE_BITS) for i, r in enumerate(files)], "_file string, _base long")
    return placed.join(F.broadcast(numbers), "_file").withColumn(ROW, F.col("_base") + F.col("_place")).select(*docs.columns, ROW)


def _keep(rows: DataFrame, numbers: DataFrame) -> DataFrame:
    """The numbered rows whose number is among the ``doc_id`` of ``numbers``, without it."""
    return rows.join(numbers.select(F.col("doc_id").alias(ROW)), ROW, "left_semi").drop(ROW)


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the host-level rules keep."""
    rows = _numbered(docs)
    return _keep(rows, judge(rows, id_col=ROW).where("kept"))


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One row of every group of texts alike in at least 0.8 of their five-word shingles, found by SimHash and by bands
    for what lies beyond its radius: that of least id, null ids last, ties by text."""
    rows = _numbered(docs)
    found = near_copies(rows, id_col=ROW).select(F.col("doc_id").alias(ROW), "component_id")
    order = F.struct(F.col("doc_id").isNull(), "doc_id", F.xxhash64("text"), ROW)
    ranked = found.join(rows.select(ROW, order.alias("place")), ROW)
    return _keep(rows, ranked.groupBy("component_id").agg(F.min("place").alias("place")).select(F.col(f"place.{ROW}").alias("doc_id")))


def decontaminate(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without any benchmark window."""
    benchmark = spark.read.parquet(f"{sf_dir}/benchmark.parquet")
    rows = _numbered(docs)
    return _keep(rows, contamination(rows.select(F.col(ROW).alias("doc_id"), "text"), benchmark).where("n_hit = 0"))


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Each document as often as the mix reads it, to whole readings; at a source's last block only
    one document is read in part, and counts if at least half of it is."""
    rows = _numbered(docs)
    readings = mix(rows, row_col=ROW).where("size > 0").select(ROW, F.round(F.col("taken") / F.col("size")).cast("int").alias("_readings"))
    joined = rows.join(readings.where("_readings > 0"), ROW)
    return joined.withColumn("_k", F.explode(F.sequence(F.lit(1), F.col("_readings")))).select(*docs.columns)


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token files, and every document's place in them."""
    return token_output(docs)


STAGES: list[tuple[str, Stage]] = [
    ("quality_rules", quality),
    ("simhash_near_dedup", near_dedup),
    ("benchmark_decontamination", decontaminate),
    ("source_mixing", mixture),
    ("token_output", tokens),
]

#: SQL has no tokenizer, so the run is tested against a brute-force version.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over the documents table."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        docs = materialize(stage(spark, docs, sf_dir), name)
    return STAGES[-1][1](spark, docs, sf_dir)
