"""A Python data source over a clustered layout that takes range filters on its clustering column.

``spark.read.format("cellspace_index").option("path", ..).option("by", "leaf").load()``: each file is a partition with
its statistics of ``by``; filters that Spark pushes drop files before they are opened, and the rows read are filtered
again by Spark, so pruning can only save work.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from pathlib import Path

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual
from pyspark.sql.types import StructType


@dataclass
class FilePart(InputPartition):
    path: str


class ClusteredReader(DataSourceReader):
    def __init__(self, folder: str, by: str, schema: StructType):
        self.folder, self.by, self.names = folder, by, schema.names
        self.low, self.high = float("-inf"), float("inf")

    def pushFilters(self, filters: list[Filter]):
        for f in filters:
            if getattr(f, "attribute", None) == (self.by,):
                if isinstance(f, EqualTo):
                    self.low, self.high = max(self.low, f.value), min(self.high, f.value)
                elif isinstance(f, GreaterThan | GreaterThanOrEqual):
                    self.low = max(self.low, f.value)
                elif isinstance(f, LessThan | LessThanOrEqual):
                    self.high = min(self.high, f.value)
            yield f  # Spark still applies each of them

    def partitions(self) -> list[FilePart]:
        import pyarrow.parquet as pq

        out = []
        for p in sorted(Path(self.folder).glob("*.parquet")):
            meta = pq.ParquetFile(p).metadata
            at = meta.schema.to_arrow_schema().names.index(self.by)
            stats = [meta.row_group(g).column(at).statistics for g in range(meta.num_row_groups)]
            known = [s for s in stats if s is not None and s.has_min_max]
            if len(known) < len(stats) or any(s.min <= self.high and s.max >= self.low for s in known):
                out.append(FilePart(str(p)))
        return out or [FilePart("")]

    def read(self, partition: FilePart) -> Iterator:
        import pyarrow.parquet as pq

        if partition.path:
            yield from pq.read_table(partition.path, columns=self.names).to_batches()


class ClusteredIndexSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "cellspace_index"

    def schema(self) -> StructType:
        import pyarrow.parquet as pq
        from pyspark.sql.pandas.types import from_arrow_schema

        first = sorted(Path(self._folder()).glob("*.parquet"))[0]
        return from_arrow_schema(pq.read_schema(first))

    def _folder(self) -> str:
        return self.options["path"].removeprefix("file://")

    def reader(self, schema: StructType) -> ClusteredReader:
        return ClusteredReader(self._folder(), self.options["by"], schema)


def register(spark) -> None:
    spark.dataSource.register(ClusteredIndexSource)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
