"""Upserts, deletes, flushes, rebuilds, and the monitor that chooses between them."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ivfspark.config import DELTA_ID, FIXED_POINT, VECTORS
from ivfspark.functions.vectors import matrix
from ivfspark.operators.clustering import Centroids, assign_all, fixed_point, summed
from ivfspark.plans.metering import IoCounter, metered
from ivfspark.plans.scratch import discard, scratch_path
from ivfspark.sources import snapshots
from ivfspark.sources.index import Index, attach_attributes, build, table_name, write_centroids, write_vectors


def latest_per_asset(changes: DataFrame) -> DataFrame:
    """The change of greatest seq for every asset (partial aggregates before the shuffle)."""
    fields = [c for c in changes.columns if c not in ("asset_id", "seq")]
    best = F.max_by(F.struct(*fields), "seq").alias("_row") if fields else F.lit(None).alias("_row")
    grouped = changes.groupBy("asset_id").agg(F.max("seq").alias("seq"), best)
    return grouped.select("asset_id", "seq", *[F.col(f"_row.{c}").alias(c) for c in fields])


def _published(index: Index, **changes) -> Index:
    manifest = {**index.manifest, **changes, "parent": index.version}
    manifest.pop("version", None)
    return Index(index.store, snapshots.commit(index.store, manifest))


def apply_changes(index: Index, changes: DataFrame, ledger: tuple[str, int] | None = None) -> Index:
    """One version from a batch of changes ``(asset_id, seq, op, vec_id, embedding)``, op upsert or delete.

    The latest change of an asset wins, within the batch and against earlier versions. ``ledger`` (stream,
    batch) makes a replayed batch a no-op.
    """
    if ledger and index.manifest["ledger"].get(ledger[0], -1) >= ledger[1]:
        return index
    kept = scratch_path(index.spark, "changes")  # a cached plan keeps all shuffle partitions, however few rows there are
    try:
        latest = latest_per_asset(changes)
        latest.write.parquet(kept)
        last = index.spark.read.schema(latest.schema).parquet(kept)
        upserts, deletes = last.where("op = 'upsert'"), last.where("op = 'delete'")
        counts = last.groupBy("op").agg(F.count("*").alias("n"), F.max("seq").alias("seq")).collect()
        n = {r.op: r.n for r in counts}
        manifest: dict = {"last_seq": max([index.manifest["last_seq"], *(r.seq for r in counts)])}
        if n.get("upsert"):
            rows = upserts.withColumn("part_id", F.lit(DELTA_ID).cast("long"))
            manifest["delta"] = [*index.manifest["delta"], write_vectors(index.store, rows, n["upsert"], "delta")]
            manifest["n_delta"] = index.manifest["n_delta"] + n["upsert"]
        if n.get("delete"):
            name = table_name("tombstones")
            deletes.select("asset_id", "seq").write.parquet(f"{index.store.path}/{name}")
            manifest["tombstones"] = [*index.manifest["tombstones"], name]
        if ledger:
            manifest["ledger"] = {**index.manifest["ledger"], ledger[0]: ledger[1]}
        return _published(index, **manifest) if n or ledger else index
    finally:
        discard(index.spark, kept)


def upsert(index: Index, rows: DataFrame, first_seq: int | None = None) -> Index:
    """Insert or replace assets: ``rows(asset_id, vec_id, embedding[, seq])``."""
    dim = index.manifest["dim"]
    wrong = rows.where(F.col("embedding").isNull() | (F.size("embedding") != dim)).limit(1).count()
    if wrong:
        raise ValueError(f"vectors must have {dim} components")
    if "seq" not in rows.columns:
        base = index.manifest["last_seq"] + 1 if first_seq is None else first_seq
        rows = rows.withColumn("seq", F.lit(base).cast("long"))
    return apply_changes(index, rows.select("asset_id", "seq", F.lit("upsert").alias("op"), "vec_id", F.col("embedding").cast("array<float>").alias("embedding")))


def delete(index: Index, ids: DataFrame, seq: int | None = None) -> Index:
    """Remove assets ``ids(asset_id)``; unknown ids do nothing."""
    base = index.manifest["last_seq"] + 1 if seq is None else seq
    empty = F.lit(None)
    return apply_changes(
        index,
        ids.select("asset_id", F.lit(base).cast("long").alias("seq"), F.lit("delete").alias("op"), empty.cast("long").alias("vec_id"), empty.cast("array<float>").alias("embedding")),
    )


def drifted(centroids: Centroids, live: np.ndarray, flushed: DataFrame) -> tuple[Centroids, int]:
    """Centres after ``flushed(part_id, embedding)`` joined them: running means, weighted by ``live``, the members of each
    partition that are still visible. Sums are reduced on executors, one row a partition."""
    width = centroids.centers.shape[1]

    def kernel(batches):
        for batch in batches:
            parts, x = batch.column(0).to_numpy(), fixed_point(matrix(batch.column(1)))
            hit, place = np.unique(parts, return_inverse=True)
            sums = np.zeros((len(hit), width), np.int64)
            if len(hit):
                np.add.at(sums, place, x)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(len(hit) + 1, dtype=np.int32) * width), pa.array(sums.ravel(), pa.int64()))
            yield pa.RecordBatch.from_arrays([pa.array(hit), pa.array(np.bincount(place, minlength=len(hit)).astype(np.int64)), lists], ["part_id", "m", "s"])

    ids, m, sums = summed(flushed.select("part_id", "embedding").mapInArrow(kernel, "part_id long, m long, s array<long>"), width)
    centers, members = centroids.centers.copy(), live.copy()
    members[ids] += m
    centers[ids] = (live[ids, None] * centroids.centers[ids] + sums / FIXED_POINT) / (live[ids] + m)[:, None]
    return Centroids(centers, centroids.counts, centroids.metric, members), len(ids)


def live_members(index: Index) -> np.ndarray:
    """Visible main rows of every partition; ids and sequence numbers are read, vectors are not."""
    out = np.zeros(index.manifest["k"], np.int64)
    for r in index.live_main().groupBy("part_id").agg(F.count("*").alias("n")).collect():  # k rows
        out[r.part_id] = r.n
    return out


def flush(index: Index, io: IoCounter | None = None) -> Index:
    """Move live delta rows to the partitions of their nearest centres; main files are not rewritten.

    Deleted and replaced main rows stay hidden by the entries that replaced them, until a rebuild, and no longer
    count as members. ``io`` takes what the jobs read and wrote.
    """
    with metered(index.spark, io):
        rows = index.live_delta()
        n = rows.count()
        if not n and not index.manifest["tombstones"]:
            return index
        live = live_members(index)
        centroids = index.centroids()
        manifest = {"delta": [], "n_delta": 0, "n_main": int(live.sum()) + n}
        if not n:
            return index if manifest["n_main"] == index.manifest["n_main"] and not index.manifest["delta"] else _published(index, **manifest)
        name = write_vectors(index.store, assign_all(rows, centroids, ("asset_id", "vec_id", "seq")), n, "main")
        placed = index.store.table(name, VECTORS)
        new, _ = drifted(centroids, live, placed)
        marks = table_name("tombstones")
        # older copies of flushed assets are hidden by a mark just below the flushed rows' seq
        placed.select("asset_id", "seq").write.parquet(f"{index.store.path}/{marks}")
        if index.manifest.get("attributes"):
            moved = index.attributes().drop("part_id").join(placed.select("asset_id"), "asset_id", "left_semi").dropDuplicates(["asset_id"])
            manifest["attributes"] = [*index.manifest["attributes"], attach_attributes(index, moved, placed)]
        labels = index._supers if index.manifest["supers"] else None
        lists = {"main": [*index.manifest["main"], name], "tombstones": [*index.manifest["tombstones"], marks], "centroids": [write_centroids(index.store, new, labels)]}
        return _published(index, **manifest, **lists)


def rebuild(index: Index, io: IoCounter | None = None) -> Index:
    """Retrain on the live rows and reassign them all; deleted and replaced rows are gone afterwards."""
    with metered(index.spark, io):
        rows = index.live().select("asset_id", "vec_id", "seq", "embedding")
        new = build(index.spark, index.store.path, rows, index.config, two_level=index.manifest.get("two_level", 0), parent=index.manifest)
        if not index.manifest.get("attributes"):
            return new
        own = {c: index.manifest[c] for c in ("attribute_schema", "statistics")}
        return _published(new, **own, attributes=[attach_attributes(new, index.attributes().dropDuplicates(["asset_id"]))])


@dataclass(frozen=True)
class Health:
    average: float
    growth: float
    delta_share: float


def monitor(index: Index) -> Health:
    """Growth of the average partition since the last build, in rows that were visible at the last flush."""
    m = index.manifest
    average = m["n_main"] / m["k"]
    return Health(average, average / m["avg_at_build"] - 1, m["n_delta"] / max(1, m["n_main"] + m["n_delta"]))


def action(health: Health, growth_limit: float = 0.5, delta_limit: float | None = None, policy: str = "auto") -> str:
    """none, flush or rebuild. Growth beyond the limit (strictly) rebuilds."""
    if policy == "never":
        return "none"
    if policy == "rebuild_always":
        return "rebuild" if health.delta_share else "none"
    if health.growth > growth_limit:
        return "rebuild"
    if health.delta_share > (delta_limit or 0.0):
        return "flush"
    return "none"


def maintain(index: Index, growth_limit: float = 0.5, delta_limit: float | None = None, policy: str = "auto", io: IoCounter | None = None) -> tuple[Index, str]:
    """Flush or rebuild as the monitor says; a flush that passes the growth limit is followed by a rebuild."""
    first = action(monitor(index), growth_limit, delta_limit, policy)
    if first == "rebuild":
        return rebuild(index, io), "rebuild"
    if first == "flush":
        index = flush(index, io)
        if action(monitor(index), growth_limit, 1.0, policy) == "rebuild":
            return rebuild(index, io), "rebuild"
        return index, "flush"
    return index, "none"
