"""Stored indexes as a data source: spark.read.format("planegrid").option("index", path).option("table", name).load().

Tables are those of operators.index: points, x-keys and y-keys by level, and the tree's levels and dyads. A file is a
partition; a filter on chunk, the files' partition column, leaves out files where the session lets filters through.
"""

from __future__ import annotations

import json
from collections.abc import Iterable, Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, In, InputPartition
from pyspark.sql.types import StructType


def tables(spark: SparkSession, path: str) -> dict[str, dict]:
    """What load() needs to know of each table of an index: its place and schema."""
    about = json.loads(spark.read.parquet(f"{path}/about").first().about)
    tree = json.loads(spark.read.parquet(f"{path}/tree/about").first().about)
    found = {"points": about["points"]}
    for name in ("xkeys", "ykeys"):
        found |= {f"{name}-{j}": x for j, x in enumerate(about[name]["levels"])}
    for name in ("levels", "dyads"):
        found |= {f"{name}-{j}": x for j, x in enumerate(tree[name])}
    return found


def register(spark: SparkSession, path: str) -> None:
    """Makes the tables of an index readable in this session."""
    known = tables(spark, path)
    pushing = spark.conf.get("spark.sql.python.filterPushdown.enabled", "false") == "true"

    class IndexSource(DataSource):
        @classmethod
        def name(cls) -> str:
            return "planegrid"

        def schema(self) -> StructType:
            return StructType.fromJson(json.loads(known[self.options.get("table", "points")]["schema"]))

        def reader(self, schema: StructType) -> DataSourceReader:
            kind = FilteredReader if pushing else BlockReader
            return kind(known[self.options.get("table", "points")]["path"], schema)

    spark.dataSource.register(IndexSource)


class BlockReader(DataSourceReader):
    """Reads the Parquet files of a table of blocks; chunks: the ones asked for, or None."""

    def __init__(self, path: str, schema: StructType):
        self.path, self.names, self.chunks = path, schema.fieldNames(), None

    def _dataset(self):
        import pyarrow as pa
        import pyarrow.dataset as ds

        return ds.dataset(self.path, format="parquet", partitioning=ds.partitioning(pa.schema([("chunk", pa.int64())]), flavor="hive"))

    def partitions(self) -> list[InputPartition]:
        found = [f.path for f in self._dataset().get_fragments()]
        chunk = lambda p: int(p.rsplit("chunk=", 1)[1].split("/", 1)[0])
        return [InputPartition(p) for p in sorted(found) if self.chunks is None or chunk(p) in self.chunks]

    def read(self, partition: InputPartition) -> Iterator:
        for fragment in self._dataset().get_fragments():
            if fragment.path == partition.value:
                yield from fragment.to_batches(columns=self.names, schema=self._dataset().schema)


class FilteredReader(BlockReader):
    """Leaves out the files of chunks that no filter asks for."""

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        for f in filters:
            values = {f.value} if isinstance(f, EqualTo) else set(f.value) if isinstance(f, In) else None
            if values is not None and f.attribute == ("chunk",):
                self.chunks = values if self.chunks is None else self.chunks & values
            else:
                yield f
