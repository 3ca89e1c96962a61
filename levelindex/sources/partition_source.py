"""A Python data source that reads partitions of a stored level by pid: format 'levelpartitions'."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, In, InputPartition
from pyspark.sql.types import StructType

from levelindex.sources.store import unpack


def file_system(path: str):
    """Arrow's file system for a path of any scheme it knows; a bare path is local."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if ":" in path else (fs.LocalFileSystem(), path)


class PartitionSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "levelpartitions"

    def schema(self) -> str:
        return "pid long, vec_id long, vec array<double>"

    def reader(self, schema: StructType) -> "PartitionReader":
        return PartitionReader(self.options)


class Fragment(InputPartition):
    def __init__(self, file: str, pids: list[int] | None):
        super().__init__(file)
        self.file, self.pids = file, pids


class PartitionReader(DataSourceReader):
    """Files are read through Arrow's file systems; pids in filters become a row filter at the file."""

    def __init__(self, options: dict):
        self.width = options.get("width", "f8")
        self.path, self.pids = f"{options['path']}/packed/{options.get('level', '0')}", None

    def pushFilters(self, filters):
        for f in filters:
            wanted = [f.value] if isinstance(f, EqualTo) else list(f.value) if isinstance(f, In) else None
            if wanted is not None and f.attribute == ("pid",):  # further filters narrow the list
                self.pids = wanted if self.pids is None else [p for p in self.pids if p in wanted]
            else:
                yield f

    def partitions(self):
        import pyarrow.dataset as ds

        files, path = file_system(self.path)
        return [Fragment(f, self.pids) for f in ds.dataset(path, format="parquet", filesystem=files, exclude_invalid_files=True).files]

    def read(self, partition: Fragment):
        import pyarrow.dataset as ds

        rows = ds.dataset(partition.file, format="parquet", filesystem=file_system(self.path)[0]).to_table(filter=None if partition.pids is None else ds.field("pid").isin(partition.pids))
        for r in rows.to_pylist():
            ids, vecs = unpack(r["n"], r["ids"], r["block"], self.width)
            for i, v in zip(ids.tolist(), vecs.tolist()):
                yield r["pid"], i, v
