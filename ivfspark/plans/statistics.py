"""Column statistics and the cardinality estimates made from them.

A scalar column has its most frequent values with exact counts and an equi-depth histogram of its numbers; a
token column has document frequencies. Everything is aggregated on executors; what reaches the driver is
``mcv`` values and ``bins`` bounds a column, and the tokens asked for.
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ivfspark.operators.prefix import running_total
from ivfspark.plans.predicates import And, Leaf, Or, Predicate
from ivfspark.plans.scratch import materialize
from ivfspark.sources import snapshots
from ivfspark.sources.index import Index, attach_attributes, table_name

#: Slices of a column's value range whose values are ranked together.
RANK_SLICES = 256


@dataclass
class ColumnStats:
    n: int
    nulls: int
    ndv: int
    mcv: dict = field(default_factory=dict)
    bins: list[tuple[float, float, int]] = field(default_factory=list)

    @property
    def filled(self) -> int:
        return self.n - self.nulls


@dataclass
class Statistics:
    n: int
    columns: dict[str, ColumnStats]
    tokens: dict[str, DataFrame] = field(default_factory=dict)
    known: dict[str, dict[str, int]] = field(default_factory=dict)

    def frequencies(self, column: str, words: set[str]) -> dict[str, int]:
        """Document frequencies of words; those not asked before are looked up together."""
        known = self.known.setdefault(column, {})
        new = sorted(words - known.keys())
        if new:
            known.update(dict.fromkeys(new, 0))
            known.update({r.token: r.df for r in self.tokens[column].where(F.col("token").isin(new)).collect()})
        return known


def histogram(attributes: DataFrame, column: str, bins: int = 32) -> DataFrame:
    """``(bin, lo, hi, cnt)``: equi-depth bins of a numeric column, exact.

    Distinct values with counts are ranked by running totals over slices of the value range.
    """
    filled = attributes.where(F.col(column).isNotNull()).select(F.col(column).cast("double").alias("v"))
    values = filled.groupBy("v").agg(F.count("*").alias("c"))
    span = filled.agg(F.min("v").alias("lo"), F.max("v").alias("hi"), F.count("*").alias("n")).first()
    width = (span.hi - span.lo) / RANK_SLICES if span.n and span.hi > span.lo else 1.0
    piece = F.floor((F.col("v") - F.lit(span.lo or 0.0)) / F.lit(width))
    placed = running_total(values, piece, [F.col("v")], F.col("c"), "before")
    numbered = placed.withColumn("bin", F.floor(F.col("before") * bins / F.lit(max(1, span.n))).cast("int"))
    return numbered.groupBy("bin").agg(F.min("v").alias("lo"), F.max("v").alias("hi"), F.sum("c").alias("cnt"))


def histogram_sketch(attributes: DataFrame, column: str, bins: int = 32, accuracy: int = 10000) -> list[float]:
    """Approximate bin bounds from one mergeable sketch, for columns of too many values to rank."""
    shares = [i / bins for i in range(bins + 1)]
    return attributes.agg(F.percentile_approx(F.col(column).cast("double"), shares, accuracy)).first()[0]


def common_values(attributes: DataFrame, column: str, top: int = 64) -> DataFrame:
    """``(value, cnt)`` of the most frequent values; ties by value."""
    counts = attributes.where(F.col(column).isNotNull()).groupBy(F.col(column).cast("string").alias("value")).agg(F.count("*").alias("cnt"))
    return counts.orderBy(F.desc("cnt"), "value").limit(top)


def token_frequencies(attributes: DataFrame, column: str = "tokens") -> DataFrame:
    """``(token, df)``: documents that hold each token."""
    return attributes.select(F.explode(F.array_distinct(column)).alias("token")).groupBy("token").agg(F.count("*").alias("df"))


def analyze(attributes: DataFrame, columns: list[str], tokens: list[str] | None = None, bins: int = 32, mcv: int = 64) -> Statistics:
    n = attributes.count()
    types = dict(attributes.dtypes)
    found = {}
    counts = attributes.agg(*[f(c).alias(f"{name}_{c}") for c in columns for name, f in (("filled", F.count), ("ndv", F.count_distinct))]).first() if columns else {}
    for c in columns:
        values = {r.value: r.cnt for r in common_values(attributes, c, mcv).collect()}
        numeric = types[c] in ("int", "bigint", "double", "float", "smallint")
        bounds = [(r.lo, r.hi, r.cnt) for r in histogram(attributes, c, bins).orderBy("bin").collect()] if numeric else []
        found[c] = ColumnStats(n, n - counts[f"filled_{c}"], counts[f"ndv_{c}"], values, bounds)
    return Statistics(n, found, {t: token_frequencies(attributes, t) for t in tokens or []})


#: Bytes of a row group of stored token counts: what a look-up of one token reads.
TOKEN_GROUP_BYTES = 1 << 18


def attach(index: Index, attributes: DataFrame, columns: list[str], tokens: list[str] | None = None, bins: int = 32, mcv: int = 64) -> Index:
    """A version of the index that has ``attributes(asset_id, ...)`` clustered as its vectors are, and their statistics.

    Token counts are written in the order of tokens, so that a look-up reads one row group.
    """
    kept = materialize(attributes, "attributes")
    stats = analyze(kept, columns, tokens, bins, mcv)
    stored: dict = {"n": stats.n, "columns": {c: asdict(s) for c, s in stats.columns.items()}, "tokens": {}}
    for column, rows in stats.tokens.items():
        stored["tokens"][column] = table_name("tokens")
        placed = rows.repartitionByRange("token").sortWithinPartitions("token")
        placed.write.option("parquet.block.size", TOKEN_GROUP_BYTES).parquet(f"{index.store.path}/{stored['tokens'][column]}")
    manifest = {**index.manifest, "parent": index.version, "attributes": [attach_attributes(index, kept)], "attribute_schema": kept.schema.simpleString(), "statistics": json.dumps(stored)}
    manifest.pop("version")
    return Index(index.store, snapshots.commit(index.store, manifest))


def stored_statistics(index: Index) -> Statistics:
    """The statistics of this version of the index."""
    stored = json.loads(index.manifest["statistics"])
    columns = {c: ColumnStats(**{**s, "bins": [tuple(b) for b in s["bins"]]}) for c, s in stored["columns"].items()}
    tokens = {c: index.store.table(name, "token string, df long") for c, name in stored["tokens"].items()}
    return Statistics(stored["n"], columns, tokens)


def _below(stats: ColumnStats, a: float, inclusive: bool) -> float:
    """Rows below ``a``: whole bins, and a linear share of the bin that holds it."""
    total = 0.0
    for lo, hi, cnt in stats.bins:
        if hi < a or inclusive and hi <= a:
            total += cnt
        elif lo < a:
            total += cnt * (a - lo) / (hi - lo) if hi > lo else 0.0
    return min(total, float(stats.filled))


def _text(value) -> str:
    return str(value)


def leaf_estimate(leaf: Leaf, stats: Statistics) -> float:
    if leaf.op.endswith("match"):
        df = float(stats.frequencies(leaf.column, {leaf.value})[leaf.value])
        return df if leaf.op == "match" else stats.n - df
    s = stats.columns[leaf.column]
    if leaf.op == "=":
        if _text(leaf.value) in s.mcv:
            return float(s.mcv[_text(leaf.value)])
        rest = s.ndv - len(s.mcv)
        return (s.filled - sum(s.mcv.values())) / rest if rest > 0 else 0.0
    if leaf.op == "!=":
        return s.filled - leaf_estimate(Leaf(leaf.column, "=", leaf.value), stats)
    if leaf.op == "is null":
        return float(s.nulls)
    if leaf.op == "is not null":
        return float(s.filled)
    if leaf.op == "in":
        return sum(leaf_estimate(Leaf(leaf.column, "=", v), stats) for v in leaf.value)
    if leaf.op == "between":
        return max(0.0, _below(s, leaf.value[1], True) - _below(s, leaf.value[0], False))
    if leaf.op in ("<", "<="):
        return _below(s, leaf.value, leaf.op == "<=")
    if leaf.op in (">", ">="):
        return s.filled - _below(s, leaf.value, leaf.op == ">")
    if leaf.op.startswith("not "):
        return s.filled - leaf_estimate(Leaf(leaf.column, leaf.op[4:], leaf.value), stats)
    raise ValueError(leaf.op)


def leaves(predicate: Predicate) -> list[Leaf]:
    return [predicate] if isinstance(predicate, Leaf) else [x for p in predicate.parts for x in leaves(p)]


def estimate(predicate: Predicate, stats: Statistics, rule: str = "min_sum") -> float:
    """Rows that qualify. min_sum: least part of a conjunction, sum of a disjunction, at most all rows;
    independence: products of shares."""
    for column in stats.tokens:
        words = {x.value for x in leaves(predicate) if x.column == column and x.op.endswith("match")}
        if words:
            stats.frequencies(column, words)
    if isinstance(predicate, Leaf):
        return leaf_estimate(predicate, stats)
    parts = [estimate(p, stats, rule) for p in predicate.parts]
    n = max(1, stats.n)
    if rule == "independence":
        share = 1.0
        for p in parts:
            share *= p / n if isinstance(predicate, And) else 1 - p / n
        return n * (share if isinstance(predicate, And) else 1 - share)
    return min(parts) if isinstance(predicate, And) else min(sum(parts), float(stats.n)) if isinstance(predicate, Or) else sum(parts)


def selectivity(predicate: Predicate, stats: Statistics, rule: str = "min_sum") -> float:
    return min(estimate(predicate, stats, rule), stats.n) / max(1, stats.n)


def true_selectivity(attributes: DataFrame, predicate: Predicate) -> float:
    return attributes.agg(F.avg(predicate.to_column().cast("int"))).first()[0] or 0.0


def q_error(estimated: float, true: float) -> float:
    """How many times the larger of the two exceeds the smaller, each at least one row."""
    e, t = max(estimated, 1.0), max(true, 1.0)
    return max(e / t, t / e)
