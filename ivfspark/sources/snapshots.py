"""Versioned index folders: immutable parquet tables and one manifest a version.

A commit writes its tables first and its manifest last, under a lock file that only one writer can
create; a version exists once its manifest does. Readers pick a manifest and keep it. Everything goes
through the Hadoop file system of the path, so any store that Spark can write will do.
"""

from __future__ import annotations

import json
import uuid

from pyspark.sql import DataFrame, SparkSession


class ConcurrentWriter(RuntimeError):
    """Another writer holds or has committed the version."""


class Store:
    """Files below an index folder."""

    def __init__(self, spark: SparkSession, path: str):
        self.spark, self.path = spark, path.rstrip("/")
        self._jvm = spark.sparkContext._jvm
        self._fs = self._hadoop("").getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _hadoop(self, name: str):
        return self._jvm.org.apache.hadoop.fs.Path(f"{self.path}/{name}" if name else self.path)

    def exists(self, name: str) -> bool:
        return self._fs.exists(self._hadoop(name))

    def names(self) -> list[str]:
        if not self.exists(""):
            return []
        return [s.getPath().getName() for s in self._fs.listStatus(self._hadoop(""))]

    def read(self, name: str) -> str:
        stream = self._fs.open(self._hadoop(name))
        try:
            return self._jvm.org.apache.commons.io.IOUtils.toString(stream, "UTF-8")
        finally:
            stream.close()

    def create(self, name: str, text: str) -> None:
        """Write a new file; fails if it exists."""
        stream = self._fs.create(self._hadoop(name), False)
        stream.write(bytearray(text.encode()))
        stream.close()

    def rename(self, old: str, new: str) -> None:
        if self.exists(new) or not self._fs.rename(self._hadoop(old), self._hadoop(new)):
            raise ConcurrentWriter(new)

    def delete(self, name: str) -> None:
        self._fs.delete(self._hadoop(name), True)

    def table(self, name: str, schema: str) -> DataFrame:
        return self.spark.read.schema(schema).parquet(f"{self.path}/{name}")


def versions(store: Store) -> list[int]:
    return sorted(int(n[9:-5]) for n in store.names() if n.startswith("manifest-") and n.endswith(".json"))


def load(store: Store, version: int | None = None) -> dict:
    """A version's manifest, the latest by default."""
    known = versions(store)
    if not known:
        raise FileNotFoundError(f"no index at {store.path}")
    chosen = known[-1] if version is None else version
    if chosen not in known:
        raise FileNotFoundError(f"no version {chosen} at {store.path}")
    return json.loads(store.read(f"manifest-{chosen:08d}.json"))


def commit(store: Store, manifest: dict) -> dict:
    """Publish ``manifest`` as the version after its parent."""
    parent = manifest.get("parent")
    version = 0 if parent is None else parent + 1
    name = f"manifest-{version:08d}.json"
    lock = f"{name}.lock"
    try:
        store.create(lock, uuid.uuid4().hex)
    except Exception as e:
        raise ConcurrentWriter(name) from e
    try:
        if store.exists(name):
            raise ConcurrentWriter(name)
        full = {**manifest, "version": version}
        draft = f".{name}.{uuid.uuid4().hex}"
        store.create(draft, json.dumps(full, sort_keys=True))
        store.rename(draft, name)
        return full
    finally:
        store.delete(lock)


TABLES = ("main", "delta", "tombstones", "centroids", "supers", "attributes")


def referenced(manifest: dict) -> set[str]:
    stored = json.loads(manifest.get("statistics", "{}")).get("tokens", {})
    return {name for kind in TABLES for name in manifest.get(kind, [])} | set(stored.values())


def vacuum(store: Store, keep: int = 2) -> list[str]:
    """Delete manifests beyond the last ``keep`` and tables that no kept manifest names."""
    known = versions(store)
    kept = known[-keep:]
    used = set().union(*(referenced(load(store, v)) for v in kept)) if kept else set()
    gone = []
    for name in store.names():
        stale = name.startswith("manifest-") and name.endswith(".json") and int(name[9:-5]) not in kept
        orphan = name.startswith("t-") and name not in used
        if stale or orphan:
            store.delete(name)
            gone.append(name)
    return gone
