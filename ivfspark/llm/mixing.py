"""Mixing sources to target weights by a low-discrepancy schedule.

The mix is a row of slots of ``block`` words. Slot i draws the i-th point of the golden-ratio sequence
(in 32-bit integers, so every engine agrees) and the cumulative target weights turn the point into a
source; the slots of a source are ranked, and rank r takes the r-th block of that source's words, read
in shuffled document order and over again while the source's cap allows. Any prefix of the schedule
already has the target proportions up to a few slots.

Sources are ordered by code point, null last, and weigh 1, 2, 3, repeating. A target never exceeds
``max_repeat`` times its source's words; the excess is reshared by weight. A document's words are the
runs outside ASCII white space; null text has none. Empty documents take nothing. Rows that repeat an
id are placed side by side, told apart by size. An empty table gives an empty result. Only ids, sources
and sizes are moved; sources are few (the weights are a driver-side list, one entry a source).
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from ivfspark.operators.prefix import running_total
from ivfspark.plans.scratch import materialize

#: Fixed value: 2^32 less 2^32 over the golden ratio, rounded to odd; below 2^31, so products fit a long.
GOLDEN = 1640531527
POINTS = 1 << 32
WEIGHTS = (1, 2, 3)
MAX_REPEAT = 3
#: Slots of at least this number, so that prefixes of the schedule are fine-grained.
LEAST_SLOTS = 1 << 16
MOST_BLOCK = 4096
SEED = "mix"


def word_count(text_col: str = "text"):
    """Number of runs of characters other than ASCII white space."""
    trimmed = F.btrim(F.coalesce(F.col(text_col), F.lit("")), F.lit("\x20\x09\x0a\x0b\x0c\x0d"))
    return F.when(trimmed == "", 0).otherwise(F.size(F.split(trimmed, "[\\x20\\x09-\\x0D]+"))).cast("long")


def targets(sizes: list[int], weights: tuple[int, ...] = WEIGHTS, cap: int = MAX_REPEAT) -> list[float]:
    """Capped proportional shares of all words; ``sizes`` in source order."""
    weight = [weights[i % len(weights)] for i in range(len(sizes))]
    out, free, left = [0.0] * len(sizes), set(range(len(sizes))), float(sum(sizes))
    while free:
        total = sum(weight[i] for i in free)
        over = {i for i in free if left * weight[i] / total > cap * sizes[i]}
        if not over:
            for i in free:
                out[i] = left * weight[i] / total
            break
        for i in over:
            out[i] = float(cap * sizes[i])
        left -= sum(out[i] for i in over)
        free -= over
    return out


def block_words(total: int) -> int:
    return max(1, min(MOST_BLOCK, total // LEAST_SLOTS))


def schedule(spark, bounds: list[int], n_slots: int, parts: int):
    """``(slot, src, rank)``: the source of every slot and its rank among the source's slots."""
    point = F.pmod(F.col("id").bitwiseAND(F.lit(POINTS - 1)) * F.lit(GOLDEN), F.lit(POINTS))
    # a source's interval of points is [bounds[i - 1], bounds[i]); the list has an entry a source
    src = F.size(F.filter(F.array(*[F.lit(b).cast("long") for b in bounds]), lambda b: b <= point)).cast("int")
    slots = spark.range(0, n_slots, 1, parts).select(F.col("id").alias("slot"), src.alias("src")).where(F.col("src") < len(bounds))
    chunk = F.shiftright(F.col("slot"), 12)
    return running_total(slots, chunk, [F.col("slot")], F.lit(1).cast("long"), "rank", ["src"])


def mix(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", source_col: str = "source", row_col: str | None = None) -> DataFrame:
    """Per document ``doc_id, source, size, source_size, target, taken``, and ``row_col`` if given, a column
    that tells rows of equal ids apart."""
    spark = docs.sparkSession
    own = [row_col] if row_col else []
    sized = materialize(
        docs.select(F.col(id_col).alias("doc_id"), F.col(source_col).alias("source"), word_count(text_col).alias("size"), *own), "sizes"
    )
    per_source = sized.groupBy("source").agg(F.sum("size").alias("words"), F.count("*").alias("n"))
    rows = sorted(per_source.collect(), key=lambda r: (r.source is None, (r.source or "").encode()))
    aim = targets([r.words for r in rows])
    total = sum(r.words for r in rows)
    info_schema = "src int, src_name string, source_size long, target double, aim long"
    info = spark.createDataFrame([(i, r.source, r.words, aim[i], min(round(aim[i]), MAX_REPEAT * r.words)) for i, r in enumerate(rows)], info_schema)
    named = sized.join(F.broadcast(info), F.col("source").eqNullSafe(F.col("src_name"))).drop("src_name", "aim")
    if total == 0:
        return named.select("doc_id", "source", "size", "source_size", "target", F.lit(0).cast("long").alias("taken"), *own)
    block = block_words(total)
    n_slots = round(sum(aim) / block)
    bounds, run = [], 0.0
    for a in aim:
        run += a
        bounds.append(round(POINTS * run / sum(aim)))
    # every source's blocks that the schedule asks for: one row a source and block, with its readings
    slots = schedule(spark, bounds, n_slots, max(8, n_slots >> 18))
    needed = F.ceil(F.col("aim") / block)
    given = F.broadcast(slots.groupBy("src").agg(F.count("*").alias("given")))
    short = info.join(given, "src", "left").withColumn("given", F.coalesce("given", F.lit(0))).where(F.col("given") < needed)
    late = short.select("src", F.explode(F.sequence(F.col("given"), needed - 1)).alias("rank"))  # a few a source
    blocks = F.col("rank") * block  # first word, counted over all readings
    ranks = slots.select("src", "rank").unionByName(late)
    asked = ranks.join(F.broadcast(info.select("src", "source_size", "aim")), "src").where(blocks < F.col("aim"))
    # a block that crosses the end of a reading goes on at the beginning; its last word stays within the target
    last = F.least(blocks + block, F.col("aim"))
    pieces = asked.select(
        "src",
        F.explode(
            F.transform(
                F.sequence(F.floor(blocks / F.col("source_size")), F.floor((last - 1) / F.col("source_size"))),
                lambda k: F.struct(
                    F.greatest(blocks - k * F.col("source_size"), F.lit(0)).alias("lo"),
                    F.least(last - k * F.col("source_size"), F.col("source_size")).alias("hi"),
                ),
            )
        ).alias("p"),
    ).select("src", "p.lo", "p.hi")
    # documents in shuffled order, at their places in the source's words
    shuffle_key = F.xxhash64(F.lit(SEED), "doc_id", "size")
    n_buckets = max(8, sum(r.n for r in rows) >> 12)
    order = [F.col("_key"), F.col("doc_id"), F.col("size"), *map(F.col, own)]
    keyed = named.where("size > 0").withColumn("_key", F.shiftrightunsigned(shuffle_key, 1))
    bucket = F.floor(F.col("_key").cast("double") / 2.0**63 * n_buckets).cast("long")
    placed = materialize(running_total(keyed, bucket, order, F.col("size"), "at", ["src"]), "placed")
    # overlap of documents with asked blocks, met in cells of words; counts of a cell come first
    cell = max(block, 1 << 12)
    met = pieces.select(
        "src", "lo", "hi", F.explode(F.sequence(F.floor(F.col("lo") / cell), F.floor((F.col("hi") - 1) / cell))).alias("cell")
    ).select("src", "cell", F.greatest("lo", F.col("cell") * cell).alias("lo"), F.least("hi", (F.col("cell") + 1) * cell).alias("hi"))
    spans = met.groupBy("src", "cell", "lo", "hi").agg(F.count("*").alias("readings"))
    parts = placed.select(
        "src", "doc_id", "size", "at", F.explode(F.sequence(F.floor(F.col("at") / cell), F.floor((F.col("at") + F.col("size") - 1) / cell))).alias("cell")
    )
    overlap = F.least(F.col("at") + F.col("size"), "hi") - F.greatest("at", "lo")
    took = (
        parts.join(spans, ["src", "cell"])
        .where(overlap > 0)
        .groupBy("src", "doc_id", "size", "at")
        .agg(F.sum(overlap * F.col("readings")).alias("taken"))
    )
    full = placed.join(took.select("src", "at", "taken"), ["src", "at"], "left")
    columns = ["doc_id", "source", "size", "source_size", "target", *own]
    return full.select(*columns, F.coalesce("taken", F.lit(0)).cast("long").alias("taken")).unionByName(
        named.where("size = 0").select(*columns, F.lit(0).cast("long").alias("taken"))
    )
