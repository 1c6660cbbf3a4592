"""A logical table by format name: spark.read.format("widefeat").option("table", ...).load(catalog file).

The reader plans one partition a physical file and reads it with Arrow in the executors; it serves plain scans of one
column set (the columns of the core group), where `Engine.table` isn't at hand. Paths must be readable by pyarrow.
"""

from __future__ import annotations

from collections.abc import Iterator, Sequence

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..catalog import Catalog, stored_name
from ..metastore import MetaStore
from ..model import KEYS


class FilePartition(InputPartition):
    def __init__(self, path: str, columns: Sequence[str]):
        self.path, self.columns = path, list(columns)


class WideTableReader(DataSourceReader):
    def __init__(self, parts: list[tuple[str, list[str]]]):
        self.parts = parts

    def partitions(self) -> Sequence[InputPartition]:
        return [FilePartition(p, c) for p, c in self.parts]

    def read(self, partition: FilePartition) -> Iterator:
        import pyarrow.dataset as ds

        yield from ds.dataset(partition.path, format="parquet", partitioning=None).to_batches(columns=partition.columns)


class WideTableSource(DataSource):
    """Options: path (the catalog's database file), table."""

    @classmethod
    def name(cls) -> str:
        return "widefeat"

    def _snapshot(self):
        return Catalog(MetaStore(self.options["path"])).snapshot(self.options["table"])

    def schema(self) -> str:
        snap = self._snapshot()
        return ", ".join(f"`{c.name}` {c.type}" for c in snap.columns if c.kind != "feature")

    def reader(self, schema) -> DataSourceReader:
        snap = self._snapshot()
        core = [p for p in snap.physical if p.group == "core"]
        return WideTableReader([(p.path.removeprefix("file://"), [*KEYS, *map(stored_name, p.columns)]) for p in core])
