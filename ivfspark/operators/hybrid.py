"""Searches with attribute predicates: filter first, filter inside the scan, filter last, or chosen.

Attributes are a table keyed by asset_id, or those stored with the index (``Index.attributes``), which have a part_id
and are read for the probed partitions only. Predicates are evaluated on attributes alone, so they reach the
attribute scan; vectors without an attribute row do not qualify.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ivfspark.config import DELTA_ID
from ivfspark.functions.vectors import distance, literal, matrix
from ivfspark.operators.search import RESULT, _parts_for, _ranked, _united, ann, asked_by, nearest_in, probes_for, query_blocks, top_k_per_query, within_reach
from ivfspark.plans.sharing import share
from ivfspark.plans.planner import Plan, choose
from ivfspark.plans.predicates import Predicate
from ivfspark.plans.statistics import Statistics
from ivfspark.sources.index import Index

#: Qualifying assets that a pre-filter may broadcast; beyond it the join is by shuffle.
BROADCAST_ASSETS = 1_000_000


def qualifying(attributes: DataFrame, predicate: Predicate) -> DataFrame:
    """``(asset_id)`` of the rows that satisfy the predicate."""
    return attributes.where(predicate.to_column()).select("asset_id")


def _with_filter(rows: DataFrame, attributes: DataFrame, predicate: Predicate, estimated: float | None) -> DataFrame:
    ids = qualifying(attributes, predicate)
    if estimated is not None and estimated <= BROADCAST_ASSETS / 4 and ids.limit(BROADCAST_ASSETS + 1).count() <= BROADCAST_ASSETS:
        ids = F.broadcast(ids)  # counted: at most BROADCAST_ASSETS ids
    return rows.join(ids, "asset_id", "left_semi")


def prefilter(index: Index, attributes: DataFrame, query, k: int, predicate: Predicate, estimated: float | None = None) -> DataFrame:
    """Exact search over the qualifying rows; recall is 1."""
    rows = _with_filter(index.live(), attributes, predicate, estimated)
    return _ranked(rows.select("vec_id", distance(F.col("embedding"), literal(query), index.metric).alias("dist")), k)


def postfilter(
    index: Index, attributes: DataFrame, query, k: int, n: int, predicate: Predicate, fused: bool = True, overfetch: int = 1, widen: bool = False
) -> DataFrame:
    """Search through the index under a predicate.

    fused joins qualifying assets inside the partition scan, before the top k; otherwise the top
    k * overfetch are filtered afterwards and fewer than k may remain. ``widen`` doubles the probes until k rows
    are found, and then reads all partitions in which a nearer one may lie: the result is that of ``prefilter``.
    """
    own = index.centroids()
    if not fused:
        parts = _parts_for(index, query, n)
        first = ann(index, query, k * overfetch, n, parts=parts)
        named = first.join(index.live(parts).select("vec_id", "asset_id"), "vec_id")
        return _ranked(named.join(qualifying(attributes, predicate), "asset_id", "left_semi").select("vec_id", "dist"), k)

    def found(parts: list[int]) -> DataFrame:
        rows = _joined(index, attributes, parts, predicate.to_column(), None)
        return _ranked(rows.select("vec_id", distance(F.col("embedding"), literal(query), index.metric).alias("dist")), k)

    if not widen:
        return found(_parts_for(index, query, n))
    while n < own.k:
        parts = _parts_for(index, query, n)
        dists = [r.dist for r in found(parts).collect()]  # k rows
        if len(dists) == k:
            return found(sorted({*parts, *within_reach(index, query, max(dists))}))
        n *= 2
    return found(list(range(own.k)))


def _joined(index: Index, attributes: DataFrame, parts: list[int], qualifies: Column, flags: Column | None) -> DataFrame:
    """Visible rows of the partitions and the delta whose attributes qualify, with the flags ``ok`` if asked.

    Attributes that know their partition are read for these partitions; the delta's assets may be anywhere.
    """
    columns = ["asset_id"] if flags is None else ["asset_id", flags.alias("ok")]
    clustered = "part_id" in attributes.columns
    near = attributes.where(F.col("part_id").isin(parts)) if clustered else attributes

    def join(rows: DataFrame, own: DataFrame) -> DataFrame:
        chosen = own.where(qualifies).select(*columns)
        if flags is None:
            return rows.join(chosen, "asset_id", "left_semi")
        return rows.join(chosen.dropDuplicates(["asset_id"]) if clustered else chosen, "asset_id")

    found = join(index.live_main(parts), near)
    return found.unionByName(join(index.live_delta(), attributes)) if index.manifest.get("delta") else found


def hybrid(
    index: Index, attributes: DataFrame, stats: Statistics, query, k: int, n: int, predicate: Predicate, threshold: float | None = None
) -> tuple[DataFrame, Plan]:
    """The chosen plan's result, and the plan; partitions count with their present size, the delta is always read."""
    plan = choose(predicate, stats, n, index.average, threshold, index.manifest["n_delta"])
    if plan.kind == "pre":
        return prefilter(index, attributes, query, k, predicate, plan.f_filters * stats.n), plan
    return postfilter(index, attributes, query, k, n, predicate), plan


def hybrid_batch(index: Index, attributes: DataFrame, queries: DataFrame, k: int, n: int, predicates: dict[int, Predicate]) -> DataFrame:
    """A batch of any size with a predicate a query (qid to predicate), sharing partition scans: post-filter for all.

    Queries with equal predicates share one flag column, computed in the attribute scan, and one matrix product a
    partition and record batch.
    """
    return _united(_hybrid_block(index, attributes, rows, k, n, predicates) for rows in query_blocks(queries))


def prefilter_batch(index: Index, attributes: DataFrame, queries: DataFrame, k: int, predicates: dict[int, Predicate]) -> DataFrame:
    """A batch of exact searches under predicates: every partition is read."""
    return hybrid_batch(index, attributes, queries, k, index.manifest["k"], predicates)


def hybrid_each(
    index: Index, attributes: DataFrame, stats: Statistics, queries: DataFrame, k: int, n: int, predicates: dict[int, Predicate]
) -> tuple[DataFrame, dict[int, Plan]]:
    """A batch in which every query goes the way that the planner chooses for it, and the plans."""
    plans = {q: choose(p, stats, n, index.average, None, index.manifest["n_delta"]) for q, p in predicates.items()}
    first = [q for q, plan in plans.items() if plan.kind == "pre"]
    asked = lambda wanted: queries.where(F.col("qid").isin(first) if wanted else ~F.col("qid").isin(first))
    pre = prefilter_batch(index, attributes, asked(True), k, predicates)
    return pre.unionByName(hybrid_batch(index, attributes, asked(False), k, n, predicates)), plans


def _hybrid_block(index: Index, attributes: DataFrame, asked: list, k: int, n: int, predicates: dict[int, Predicate]) -> DataFrame:
    if not asked:
        return index.spark.createDataFrame([], "qid long, rank int, vec_id long, dist double")
    distinct = list(dict.fromkeys(predicates[r.qid] for r in asked))
    numbers = {p: i for i, p in enumerate(distinct)}
    qids, qmat = np.array([r.qid for r in asked], np.int64), np.array([r.qvec for r in asked], np.float64)
    kinds = np.array([numbers[predicates[r.qid]] for r in asked], np.int64)
    probes = probes_for(index, qmat, n)
    flags = F.array(*[F.coalesce(p.to_column(), F.lit(False)) for p in distinct])
    rows = _joined(index, attributes, [int(p) for p in np.unique(probes) if p >= 0], F.exists(flags, lambda x: x), flags)
    shared = share(index.spark, (qids, qmat, kinds, asked_by(probes)), "query block")
    metric = index.metric

    def kernel(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        ids, q, kind, parts = shared.value
        for batch in batches:
            if not batch.num_rows:
                continue
            part, vec, x = batch.column(0).to_numpy(), batch.column(1).to_numpy(), matrix(batch.column(2))
            ok = matrix(batch.column(3).cast(pa.list_(pa.int8()))) > 0
            out = []
            for p in np.unique(part):
                places = np.arange(len(ids)) if p == DELTA_ID else parts.get(int(p), np.empty(0, np.int64))
                for number in np.unique(kind[places]):
                    mine, mates = np.flatnonzero((part == p) & ok[:, number]), places[kind[places] == number]
                    if len(mine):
                        out.append(nearest_in(vec[mine], x[mine], ids[mates], q[mates], k, metric))
            if out:
                columns = [np.concatenate(c) for c in zip(*out, strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in columns], ["qid", "vec_id", "dist"])

    return top_k_per_query(rows.select("part_id", "vec_id", "embedding", "ok").mapInArrow(kernel, RESULT), k)


def postings(attributes: DataFrame, column: str = "tokens") -> DataFrame:
    """Inverted index: ``(token, asset_id)``."""
    return attributes.select(F.explode(F.array_distinct(column)).alias("token"), "asset_id")


def assets_with_all(index_rows: DataFrame, words: list[str]) -> DataFrame:
    """Assets that hold every word, by counting postings."""
    words = list(dict.fromkeys(words))
    met = index_rows.where(F.col("token").isin(*words)).groupBy("asset_id").agg(F.count("*").alias("n"))
    return met.where(F.col("n") == len(words)).select("asset_id")
