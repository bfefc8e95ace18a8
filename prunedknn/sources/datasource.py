"""spark.read.format("prunedknn").option("path", ...): the rows of a table's live files.

Filters that Spark offers are not used to drop files: a DataFrame that is reused can be handed
those of an earlier query, and a reader that trusts them loses rows. Pruned reads go through
operators.search, which prunes by the plan at hand.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType


class File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class Reader(DataSourceReader):
    def __init__(self, files: list[str], schema: StructType):
        self.files, self.names = files, schema.names

    def partitions(self):
        return [File(f) for f in self.files] or [File("")]

    def read(self, partition: File) -> Iterator:
        from ..footer import read_columns

        if partition.path:
            yield from read_columns(partition.path, self.names).to_batches()


class TableSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "prunedknn"

    def _table(self):
        import json
        import posixpath

        import pyarrow.parquet as pq

        from ..footer import open_fs

        root = self.options["path"].rstrip("/")
        fs, own = open_fs(root)
        from pyarrow.fs import FileSelector

        found = fs.get_file_info(FileSelector(posixpath.join(own, "snapshots")))
        numbers = sorted(int(f.base_name[1:-5]) for f in found if f.base_name.startswith("v"))
        number = int(self.options.get("snapshot", numbers[-1]))
        with fs.open_input_file(posixpath.join(own, "snapshots", f"v{number}.json")) as f:
            meta = json.loads(f.read())
        manifest = pq.read_table(posixpath.join(own, "manifests", meta["manifest"]), filesystem=fs, columns=["file"])
        return StructType.fromJson(json.loads(meta["schema"])), sorted(manifest.column("file").to_pylist())

    def schema(self) -> StructType:
        return self._table()[0]

    def reader(self, schema: StructType) -> Reader:
        return Reader(self._table()[1], schema)


def register(spark) -> None:
    spark.dataSource.register(TableSource)
