"""A data source that reads the adjacency of a stored index, one partition for each segment: spark.read.format('vecgraph').load(path). It lists files with pyarrow,
so the path must be one that pyarrow reads; spark.read.parquet serves every other store."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class AdjacencySource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "vecgraph"

    def schema(self) -> str:
        return "segment int, layer int, src long, dst array<long>"

    def reader(self, schema) -> DataSourceReader:
        return AdjacencyReader(self.options["path"])


class AdjacencyReader(DataSourceReader):
    def __init__(self, path: str):
        self.path = path

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        store, root = fs.FileSystem.from_uri(self.path) if "://" in self.path else (fs.LocalFileSystem(), self.path)
        found = store.get_file_info(fs.FileSelector(f"{root}/adjacency"))
        return [InputPartition(i.base_name) for i in found if i.base_name.startswith("segment=")]

    def read(self, partition: InputPartition):
        import pyarrow.dataset as ds

        where = f"{self.path}/adjacency/{partition.value}"
        segment = int(partition.value.split("=")[1])
        for b in ds.dataset(where, format="parquet").to_batches(columns=["layer", "src", "nbrs"]):
            for layer, src, nbrs in zip(*(b[c].to_pylist() for c in ("layer", "src", "nbrs")), strict=True):
                yield segment, layer, src, [n["dst"] for n in nbrs]


def register(spark) -> None:
    spark.dataSource.register(AdjacencySource)
