"""Host-level quality rules, in DataFrame expressions only.

Each document is measured, each host's rate of rule failures is shrunk towards the corpus by an
empirical beta prior (method of moments over hosts), and the host's verdict comes back to its
documents: a host above ``host_limit`` is distrusted, and there one soft failure rejects a document;
elsewhere it takes two (symbols beyond three in ten words count twice). A document without failures stays, wherever it comes from.

Null text counts as empty (no words: base failure). A null host is a host of its own. Repeated rows
are judged alike. An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ivfspark.plans.scratch import materialize

#: The white space between words, and the symbols counted.
SPACES = "\x20\x09\x0a\x0b\x0c\x0d"
SYMBOLS = "#*$%&|<>"
#: Bits that hold a window's place beside its hash.
PLACE_BITS = 30


def measure(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", host_col: str = "source") -> DataFrame:
    """Per document: id, host and counts of words, characters, symbols, repeated lines and words.

    A window of three words becomes one number, 34 bits of hash above its place; in the sorted
    numbers, windows that may repeat stand side by side. Only those are compared as whole strings,
    so the count is exact and the work is that of one sort a document.
    """
    text = F.coalesce(F.col(text_col), F.lit(""))
    w, keys, n = F.col("words"), F.col("keys"), F.col("named")
    base = docs.select(F.col(id_col).alias("doc_id"), F.col(host_col).alias("host"), text.alias("body"))
    trimmed = F.btrim("body", F.lit(SPACES))
    split = base.select(
        "doc_id",
        "host",
        F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, "[\\x20\\x09-\\x0D]+")).alias("words"),
        (F.size(F.split("body", f"[{SYMBOLS}]")) - 1).cast("long").alias("n_symbols"),
        F.filter(F.split("body", "\n"), lambda x: F.btrim(x, F.lit(SPACES)) != "").alias("lines"),
    )
    keyed = split.select(
        "doc_id",
        "host",
        F.length(F.array_join("words", "")).cast("long").alias("word_chars"),
        "n_symbols",
        F.size("lines").cast("long").alias("n_lines"),
        (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        "words",
        F.size("words").cast("long").alias("n_words"),
        F.when(
            F.size("words") >= 3,
            F.sort_array(
                F.transform(
                    F.sequence(F.lit(0), F.size("words") - 3),
                    lambda i: F.shiftleft(F.xxhash64(F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)), PLACE_BITS).bitwiseOR(i.cast("long")),
                )
            ),
        ).alias("keys"),
    )
    alike_keys = lambda k: F.shiftrightunsigned(F.get(keys, k).bitwiseXOR(F.get(keys, k - 1)), PLACE_BITS) == 0
    place = lambda k: F.get(keys, k).bitwiseAND(F.lit((1 << PLACE_BITS) - 1)).cast("int")
    seconds = keyed.withColumn("seconds", F.when(F.size("keys") >= 2, F.filter(F.sequence(F.lit(1), F.size("keys") - 1), alike_keys)))
    places = F.array_distinct(F.flatten(F.transform("seconds", lambda k: F.array(place(k - 1), place(k)))))
    found = seconds.withColumn("places", places).drop("keys", "seconds")
    named = found.withColumn(
        "named",
        F.array_sort(F.transform("places", lambda i: F.struct(F.concat_ws("\n", F.get(w, i), F.get(w, i + 1), F.get(w, i + 2)).alias("s"), i.alias("i")))),
    ).drop("words", "places")
    alike = lambda x, i: F.coalesce(F.get(n, i)["s"] == x["s"], F.lit(False))
    confirmed = F.filter(n, lambda x, i: alike(x, i - 1) | alike(x, i + 1))
    covered = F.array_distinct(F.flatten(F.transform(confirmed, lambda x: F.array(x["i"], x["i"] + 1, x["i"] + 2))))
    return named.withColumn("n_repeat_words", F.when(n.isNotNull(), F.size(covered)).otherwise(0).cast("long")).drop("named")


def _flags(measured: DataFrame) -> DataFrame:
    n = F.col("n_words")
    soft = [
        F.col("n_symbols") * 10 > n,
        F.col("n_symbols") * 10 > n * 3,
        F.col("n_dup_lines") * 10 > F.col("n_lines") * 3,
        (F.col("word_chars") < n * 3) | (F.col("word_chars") > n * 12),
        F.col("n_repeat_words") * 10 > n * 3,
    ]
    total = sum((f.cast("int") for f in soft[1:]), soft[0].cast("int"))
    return measured.withColumn("base_failed", (n < 50) | (F.col("n_repeat_words") * 100 > n * 50)).withColumn("n_soft", total)


def host_rates(flagged: DataFrame) -> DataFrame:
    """Per host: documents, failures and the failure rate shrunk by the beta prior.

    The prior's mean and strength come from the mean and variance of the hosts' own rates; with one
    host, or no spread, the prior is the mean with a strength of one document. Hosts are
    pre-aggregated in each task, so a host with a third of all rows costs no more than another.
    """
    hosts = flagged.groupBy("host").agg(
        F.count("*").alias("n_docs"),
        F.sum((F.col("base_failed") | (F.col("n_soft") > 0)).cast("long")).alias("n_failed"),
    )
    rate = F.col("n_failed") / F.col("n_docs")
    prior = hosts.agg(F.avg(rate).alias("m"), F.var_pop(rate).alias("v"))
    strength = F.when((F.col("v") > 0) & (F.col("m") * (1 - F.col("m")) > F.col("v")), F.col("m") * (1 - F.col("m")) / F.col("v") - 1).otherwise(F.lit(1.0))
    return hosts.crossJoin(F.broadcast(prior)).select(
        "host",
        "n_docs",
        "n_failed",
        ((F.col("n_failed") + strength * F.col("m")) / (F.col("n_docs") + strength)).alias("host_rate"),
    )


def judge(docs: DataFrame, host_limit: float = 0.5, **columns: str) -> DataFrame:
    """``measure`` plus ``base_failed``, ``host_rate`` and ``kept``."""
    flagged = materialize(_flags(measure(docs, **columns)), "quality")
    rates = materialize(host_rates(flagged), "hosts")
    joined = flagged.alias("d").join(rates.select(F.col("host").alias("h"), "host_rate"), F.col("d.host").eqNullSafe(F.col("h")), "left")
    tolerated = F.when(F.col("host_rate") > host_limit, 0).otherwise(1)
    return joined.drop("h").withColumn("kept", ~F.col("base_failed") & (F.col("n_soft") <= tolerated))
