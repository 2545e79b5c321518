"""A Python data source over packed files: cells by rows, with level bounds pushed into the decoder."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, LessThan, LessThanOrEqual

from ..plans.pipeline import cells_of


class PackedSource(DataSource):
    """``spark.read.format("meshpack").option("path", folder).option("fields", "rho:float64").load()``.

    Reads Parquet files of packed rows from a folder that drivers and executors share; one
    partition a file.  A bound on ``level`` ends decoding there.
    """

    @classmethod
    def name(cls) -> str:
        return "meshpack"

    def fields(self) -> dict[str, str]:
        text = self.options.get("fields", "")
        return dict(p.split(":") for p in text.split(",") if p)

    def schema(self) -> str:
        kinds = {"float64": "double", "float32": "float"}
        return "domain int, level int, path bigint, refined boolean, masked boolean" + "".join(f", {f} {kinds[d]}" for f, d in self.fields().items())

    def reader(self, schema):
        return PackedReader(self.options["path"], self.fields())


class PackedReader(DataSourceReader):
    def __init__(self, folder: str, fields: dict[str, str]):
        self.folder, self.fields, self.max_level = folder, fields, None

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, (LessThan, LessThanOrEqual)) and f.attribute == ("level",):
                bound = f.value - isinstance(f, LessThan)
                self.max_level = bound if self.max_level is None else min(bound, self.max_level)
            else:
                yield f

    def partitions(self):
        import pyarrow.fs as fs

        system, path = fs.FileSystem.from_uri(self.folder) if "://" in self.folder or self.folder.startswith("file:") else (fs.LocalFileSystem(), self.folder)
        found = system.get_file_info(fs.FileSelector(path, recursive=True))
        return [InputPartition(f.path) for f in found if f.path.endswith(".parquet")]

    def read(self, partition):
        import pyarrow.fs as fs
        import pyarrow.parquet as pq

        system = fs.FileSystem.from_uri(self.folder)[0] if "://" in self.folder or self.folder.startswith("file:") else fs.LocalFileSystem()
        columns = ["domain", "dim", "root_level", "roots", "level_cells", "grid", "mask", *(f"f_{f}" for f in self.fields)]
        for batch in pq.ParquetFile(partition.value, filesystem=system).iter_batches(batch_size=16, columns=columns):
            for row in batch.to_pylist():
                if self.max_level is None or row["root_level"] <= self.max_level:
                    yield cells_of(row, self.fields, self.max_level)
