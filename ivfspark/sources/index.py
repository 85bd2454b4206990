"""The clustered index: building, opening, and its visible rows.

Vectors are written in order of partition, so a list of partition ids prunes files and row groups by
their statistics. New rows go to the reserved delta partition in files of their own. The live row of an
asset is the one of greatest sequence number among main and delta rows, if no tombstone is later.
"""

from __future__ import annotations

import uuid
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ivfspark.config import CENTROIDS, DELTA_ID, TOMBSTONES, VECTORS, IndexConfig
from ivfspark.operators.clustering import Centroids, assign_all, train, train_super
from ivfspark.sources import snapshots
from ivfspark.sources.snapshots import Store

#: Rows of a file of the main table, about a few hundred MB at 64 dimensions.
FILE_ROWS = 1_000_000
#: Row groups are what a list of partitions prunes, so they are kept small.
ROW_GROUP_BYTES = 1 << 20


@dataclass
class Index:
    """One version of an index."""

    store: Store
    manifest: dict

    @property
    def spark(self) -> SparkSession:
        return self.store.spark

    @property
    def config(self) -> IndexConfig:
        return IndexConfig(**self.manifest["config"])

    @property
    def version(self) -> int:
        return self.manifest["version"]

    @property
    def average(self) -> float:
        """Rows of a partition now, by the counts of the last flush."""
        return self.manifest["n_main"] / max(1, self.manifest["k"])

    @property
    def metric(self) -> str:
        return self.manifest["config"]["metric"]

    def _union(self, kind: str, schema: str) -> DataFrame:
        names = self.manifest.get(kind, [])
        if not names:
            return self.spark.createDataFrame([], schema)
        return self.spark.read.schema(schema).parquet(*[f"{self.store.path}/{n}" for n in names])

    def main(self) -> DataFrame:
        return self._union("main", VECTORS)

    def delta(self) -> DataFrame:
        return self._union("delta", VECTORS)

    def tombstones(self) -> DataFrame:
        return self._union("tombstones", TOMBSTONES)

    def centroid_rows(self) -> DataFrame:
        return self._union("centroids", CENTROIDS)

    def centroids(self) -> Centroids:
        """Centres on the driver: k * d numbers, kept with this version."""
        if not hasattr(self, "_centroids"):
            rows = sorted(self.centroid_rows().collect(), key=lambda r: r.part_id)
            members = np.array([r.n_members for r in rows], np.int64)
            self._centroids = Centroids(np.array([r.centroid for r in rows], np.float64), members.copy(), self.metric, members)
            self._supers = np.array([r.super_id if r.super_id is not None else 0 for r in rows], np.int64)
        return self._centroids

    def super_centroids(self) -> tuple[np.ndarray, np.ndarray]:
        """Centres of the second level, and the super id of every centre."""
        own = self.centroids()
        rows = sorted(self._union("supers", "super_id long, centroid array<double>").collect(), key=lambda r: r.super_id)
        return (np.array([r.centroid for r in rows], np.float64), self._supers) if rows else (own.centers[:0], self._supers)

    def _superseded(self) -> DataFrame:
        """Latest sequence number of every asset changed since the last rebuild."""
        changes = self.delta().select("asset_id", "seq").unionByName(self.tombstones())
        return changes.groupBy("asset_id").agg(F.max("seq").alias("last"))

    def changed(self) -> bool:
        return bool(self.manifest.get("delta") or self.manifest.get("tombstones"))

    def live_main(self, parts: list[int] | None = None) -> DataFrame:
        rows = self.main()
        if parts is not None:
            rows = rows.where(among(parts))
        if not self.changed():
            return rows
        late = self._superseded().withColumnRenamed("asset_id", "_asset")
        return rows.join(late, (rows.asset_id == F.col("_asset")) & (rows.seq < F.col("last")), "left_anti")

    def live_delta(self) -> DataFrame:
        rows = self.delta()
        late = self._superseded().withColumnRenamed("asset_id", "_asset")
        return rows.join(late, (rows.asset_id == F.col("_asset")) & (rows.seq < F.col("last")), "left_anti")

    def live(self, parts: list[int] | None = None, include_delta: bool = True) -> DataFrame:
        """Visible rows of the given partitions (all by default) and of the delta."""
        rows = self.live_main(parts)
        if include_delta and self.manifest.get("delta"):
            rows = rows.unionByName(self.live_delta())
        return rows

    def attributes(self, parts: list[int] | None = None) -> DataFrame:
        """Attribute rows, those of given partitions only if asked; an asset that moved may have several, all alike."""
        from pyspark.sql.types import StructType

        schema = StructType.fromDDL(self.manifest["attribute_schema"].removeprefix("struct<").removesuffix(">")).add("part_id", "long")
        rows = self.spark.read.schema(schema).parquet(*[f"{self.store.path}/{n}" for n in self.manifest["attributes"]])
        return rows if parts is None else rows.where(among(parts))

    def refreshed(self) -> Index:
        return open_index(self.spark, self.store.path)


def among(parts: list[int]) -> Column:
    """Rows of given partitions: one text, as a literal at a time takes seconds for thousands of partitions."""
    return F.expr(f"part_id IN ({', '.join(f'{int(p)}L' for p in parts)})") if len(parts) else F.lit(False)


def table_name(kind: str) -> str:
    return f"t-{kind}-{uuid.uuid4().hex[:12]}"


def attach_attributes(index: Index, attributes: DataFrame, placed: DataFrame | None = None) -> str:
    """Write attributes in the order of their assets' partitions (of ``placed``, all visible rows by default); assets
    without a vector stand in the delta's."""
    placed = index.live() if placed is None else placed
    where = placed.groupBy("asset_id").agg(F.max("part_id").alias("part_id"))
    name = table_name("attributes")
    rows = attributes.drop("part_id").join(where, "asset_id", "left").withColumn("part_id", F.coalesce("part_id", F.lit(DELTA_ID)))
    files = max(1, -(-index.manifest["n_main"] // FILE_ROWS))
    dealt = rows.repartitionByRange(files, "part_id", "asset_id") if files > 1 else rows.repartition(1)
    dealt.sortWithinPartitions("part_id", "asset_id").write.option("parquet.block.size", ROW_GROUP_BYTES).parquet(f"{index.store.path}/{name}")
    return name


def write_vectors(store: Store, rows: DataFrame, n_rows: int, kind: str) -> str:
    """Write rows clustered by partition; the one full shuffle of a build."""
    name = table_name(kind)
    files = max(1, -(-n_rows // FILE_ROWS))
    keys = ["part_id", "asset_id", "vec_id"]
    placed = rows.select("part_id", "asset_id", "vec_id", "embedding", "seq")
    placed = placed.repartitionByRange(files, *keys) if files > 1 else placed.coalesce(1) if kind == "delta" else placed.repartition(1)
    placed.sortWithinPartitions(*keys).write.option("parquet.block.size", ROW_GROUP_BYTES).parquet(f"{store.path}/{name}")
    return name


def write_centroids(store: Store, centroids: Centroids, supers: np.ndarray | None) -> str:
    name = table_name("centroids")
    members = centroids.members if centroids.members is not None else centroids.counts
    rows = [
        (i, c.tolist(), int(n), int(supers[i]) if supers is not None else None)
        for i, (c, n) in enumerate(zip(centroids.centers, members, strict=True))
    ]
    store.spark.createDataFrame(rows, CENTROIDS).coalesce(1).write.parquet(f"{store.path}/{name}")
    return name


def build(
    spark: SparkSession, path: str, vectors: DataFrame, cfg: IndexConfig, k: int | None = None, two_level: int = 0, parent: dict | None = None
) -> Index:
    """Train, assign, write and publish. ``vectors`` needs vec_id and embedding; asset_id and seq are
    taken if present, else asset_id = vec_id and seq = 0. ``two_level`` is the size of a super partition, 0
    for one level."""
    store = Store(spark, path)
    columns = set(vectors.columns)
    rows = vectors.select(
        (F.col("asset_id") if "asset_id" in columns else F.col("vec_id")).cast("long").alias("asset_id"),
        F.col("vec_id").cast("long").alias("vec_id"),
        (F.col("seq") if "seq" in columns else F.lit(0)).cast("long").alias("seq"),
        F.col("embedding").cast("array<float>").alias("embedding"),
    )
    n_rows, last_seq = rows.agg(F.count("*"), F.max("seq")).first()
    centroids = train(rows, cfg, k, n_rows=n_rows)
    supers, labels = train_super(centroids, two_level, cfg.seed) if two_level else (None, None)
    assigned = assign_all(rows, centroids, ("asset_id", "vec_id", "seq"), cfg if cfg.balanced_final else None)
    main = write_vectors(store, assigned, n_rows, "main")
    sizes = {r.part_id: r.n for r in store.table(main, VECTORS).groupBy("part_id").agg(F.count("*").alias("n")).collect()}
    centroids.members = np.array([sizes.get(i, 0) for i in range(centroids.k)], np.int64)
    names = {"main": [main], "centroids": [write_centroids(store, centroids, labels)], "delta": [], "tombstones": [], "supers": []}
    if two_level:
        top = table_name("supers")
        spark.createDataFrame([(i, c.tolist()) for i, c in enumerate(supers)], "super_id long, centroid array<double>").coalesce(1).write.parquet(f"{path}/{top}")
        names["supers"] = [top]
    manifest = {
        **names,
        "parent": parent["version"] if parent else None,
        "config": cfg.as_dict(),
        "dim": int(centroids.centers.shape[1]),
        "k": centroids.k,
        "n_main": n_rows,
        "n_delta": 0,
        "avg_at_build": n_rows / centroids.k,
        "last_seq": last_seq or 0,
        "two_level": two_level,
        "ledger": parent.get("ledger", {}) if parent else {},
    }
    return Index(store, snapshots.commit(store, manifest))


def open_index(spark: SparkSession, path: str, version: int | None = None) -> Index:
    store = Store(spark, path)
    return Index(store, snapshots.load(store, version))


__all__ = ["DELTA_ID", "Index", "attach_attributes", "build", "open_index", "write_centroids", "write_vectors"]
