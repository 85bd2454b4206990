"""Queries of the corpus operators: ``queries()`` by name, ``oracle_sql()`` where SQL can say the same."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op8_host_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ivfspark.llm.quality_rules import judge

    return judge(table(spark, sf_dir, "documents")).select(
        "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"
    )


def op1_html_wrappers(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ivfspark.llm.html_wrapper import extract

    return extract(table(spark, sf_dir, "pages")).withColumn("n_chars", F.length("text").cast("long"))


def op2_wavelet_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ivfspark.llm.token_output import token_output

    return token_output(table(spark, sf_dir, "documents"))


def op3_source_mix(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ivfspark.llm.mixing import mix

    return mix(table(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op4_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ivfspark.llm.token_counts import length_histogram

    return length_histogram(table(spark, sf_dir, "documents"))


def op5_suffix_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ivfspark.llm.suffix_dedup import dedup_substrings

    found = dedup_substrings(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"), "n_shared_words")


def op6_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ivfspark.llm.chat_format import format_rows, read_back

    said = "\\### Assistant: </turn> ok"
    extra = spark.createDataFrame([(-7, 0, "user", said), (-7, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    rows = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    return read_back(format_rows(rows.unionByName(extra)))


def op7_simhash(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ivfspark.llm.simhash import near_duplicates

    return near_duplicates(table(spark, sf_dir, "documents"))


def op9_line_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ivfspark.llm.line_bloom import dedup_lines

    found = dedup_lines(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_lines", "n_dropped", F.sha2("kept", 256).alias("kept_sha256"))


def op10_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    from ivfspark.llm.decontaminate import contamination

    found = contamination(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))
    digest = F.sha2(F.array_join("items", ",").cast("binary"), 256)
    return found.select("doc_id", "n_words", "n_hit", "n_items", digest.alias("items_sha256"), (F.col("n_hit") > 0).alias("contaminated"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    return {
        "op1_html_wrappers": op1_html_wrappers,
        "op2_wavelet_tokens": op2_wavelet_tokens,
        "op3_source_mix": op3_source_mix,
        "op4_token_counts": op4_token_counts,
        "op5_suffix_dedup": op5_suffix_dedup,
        "op6_chat_format": op6_chat_format,
        "op7_simhash": op7_simhash,
        "op8_host_quality": op8_host_quality,
        "op9_line_dedup": op9_line_dedup,
        "op10_decontamination": op10_decontamination,
    }


def oracle_sql() -> dict[str, str]:
    from ivfspark.llm.oracles import ORACLES

    return dict(ORACLES)
