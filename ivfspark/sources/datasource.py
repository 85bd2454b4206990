"""``spark.read.format("ivf")``: an index folder as a data source that prunes by partition id.

Filters on part_id choose row groups by their statistics. The executors read with pyarrow, so the folder
must be reachable by an Arrow file system.
"""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, In, InputPartition
from pyspark.sql.types import StructType

from ivfspark.config import VECTORS


class FileOf(InputPartition):
    def __init__(self, path: str):
        super().__init__(path)


class IvfReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.parts = options["path"], None
        self.version = options.get("version")

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            if isinstance(f, EqualTo | In) and f.attribute == ("part_id",):
                wanted = {f.value} if isinstance(f, EqualTo) else set(f.value)
                self.parts = wanted if self.parts is None else self.parts & wanted
            else:
                yield f

    def _system(self):
        from pyarrow import fs

        path = self.path.replace("file:///", "/").replace("file:/", "/")
        return fs.FileSystem.from_uri(path)

    def partitions(self) -> list[FileOf]:
        from pyarrow import fs

        system, root = self._system()
        names = [i.base_name for i in system.get_file_info(fs.FileSelector(root))]
        manifests = sorted(n for n in names if n.startswith("manifest-") and n.endswith(".json"))
        chosen = manifests[-1] if self.version is None else f"manifest-{int(self.version):08d}.json"
        with system.open_input_stream(f"{root}/{chosen}") as source:
            manifest = json.loads(source.read())
        files = []
        for name in [*manifest["main"], *manifest["delta"]]:
            infos = system.get_file_info(fs.FileSelector(f"{root}/{name}"))
            files += [i.path for i in infos if i.base_name.endswith(".parquet")]
        return [FileOf(f) for f in sorted(files)]

    def read(self, partition: FileOf):
        import pyarrow.parquet as pq

        system, _ = self._system()
        filters = [("part_id", "in", sorted(self.parts))] if self.parts is not None else None
        if self.parts is not None and not self.parts:
            return
        yield from pq.read_table(partition.value, filesystem=system, filters=filters).to_batches()


class IvfSource(DataSource):
    """All stored rows of a version, delta included; replaced and deleted rows are not removed."""

    @classmethod
    def name(cls) -> str:
        return "ivf"

    def schema(self) -> str:
        return VECTORS

    def reader(self, schema: StructType) -> IvfReader:
        return IvfReader(self.options)
