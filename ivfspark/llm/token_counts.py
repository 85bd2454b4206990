"""Exact token counts from a length histogram.

Documents are encoded and only their lengths kept; one row a length then answers, by suffix sums, the
totals, quantiles and truncated totals for every context limit. Null and empty texts have length zero.
The histogram has as many rows as there are different lengths; an empty table gives none.
"""

from __future__ import annotations

from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ivfspark.llm.tokens import encoder, tokenizer_path
from ivfspark.operators.prefix import running_total
from ivfspark.plans.scratch import materialize


def token_lengths(docs: DataFrame, path: str | None = None, split_spaces: bool = True, text_col: str = "text") -> DataFrame:
    """``n_tokens`` of every row."""
    path = path or tokenizer_path()

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = encoder(path, split_spaces)
        for batch in batches:
            sizes = [len(coder.encode(x.as_py())) // 4 for x in batch.column(0)]
            yield pa.RecordBatch.from_arrays([pa.array(sizes, pa.int64())], ["n_tokens"])

    return docs.select(F.col(text_col).alias("text")).mapInArrow(kernel, "n_tokens long")


def length_histogram(docs: DataFrame, **options) -> DataFrame:
    """Per length, as a context limit: ``n_docs`` of it, ``docs_longer``, ``tokens_longer`` (of longer
    documents), ``total_tokens``, ``truncated_tokens`` (documents cut at it) and ``quantile`` (share of
    documents not longer)."""
    counts = materialize(token_lengths(docs, **options).groupBy("n_tokens").agg(F.count("*").alias("n_docs")), "lengths")
    reverse, bucket = [F.col("n_tokens").desc()], -F.shiftright("n_tokens", 8)
    docs_longer = running_total(counts, bucket, reverse, F.col("n_docs"), "docs_longer")
    longer = running_total(docs_longer, bucket, reverse, F.col("n_docs") * F.col("n_tokens"), "tokens_longer")
    totals = counts.agg(F.sum("n_docs").alias("all_docs"), F.sum(F.col("n_docs") * F.col("n_tokens")).alias("total_tokens"))
    limit = F.col("n_tokens")
    return longer.crossJoin(F.broadcast(totals)).select(  # totals is one row
        "n_tokens",
        "n_docs",
        "docs_longer",
        "tokens_longer",
        "total_tokens",
        (F.col("total_tokens") - F.col("tokens_longer") + limit * F.col("docs_longer")).alias("truncated_tokens"),
        ((F.col("all_docs") - F.col("docs_longer")) / F.col("all_docs")).alias("quantile"),
    )


def at_limits(histogram: DataFrame, limits: DataFrame) -> DataFrame:
    """``limits(context)`` with the truncated total at any context limit, met or not in the histogram."""
    at = histogram.groupBy("n_tokens").agg(F.first("n_docs").alias("n_docs")).alias("h")
    joined = limits.alias("l").join(at, F.lit(True), "left")  # limits are a stated list
    return joined.groupBy("l.context").agg(
        F.sum(F.col("n_docs") * F.least("n_tokens", "context")).alias("truncated_tokens"),
        F.sum(F.when(F.col("n_tokens") > F.col("context"), F.col("n_docs")).otherwise(0)).alias("docs_longer"),
    )


def quantile_length(histogram: DataFrame, q: float) -> int | None:
    """Least length that a share ``q`` of the documents does not exceed."""
    return histogram.where(F.col("quantile") >= q).agg(F.min("n_tokens")).first()[0]
