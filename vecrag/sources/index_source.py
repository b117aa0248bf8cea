"""Python data source over saved index lists: a filter on cluster_id becomes the list of bucket files that are read.

Files are read by the executors through pyarrow's filesystem for the path's scheme, so it suits shared mounts and
object stores that pyarrow reaches; everything else goes through index.load_index, which only needs Spark.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, In, InputPartition

from vecrag import schema


class BucketPartition(InputPartition):
    def __init__(self, bucket: int, clusters: tuple[int, ...] | None):
        super().__init__(bucket)
        self.bucket, self.clusters = bucket, clusters


class IndexReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.buckets = options["path"], int(options.get("buckets", "16"))
        self.clusters: tuple[int, ...] | None = None

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("cluster_id",):
                self._narrow({int(f.value)})
            elif isinstance(f, In) and f.attribute == ("cluster_id",):
                self._narrow({int(v) for v in f.value})
            else:
                yield f

    def _narrow(self, wanted: set[int]) -> None:
        self.clusters = tuple(sorted(wanted if self.clusters is None else wanted & set(self.clusters)))

    def partitions(self) -> list[InputPartition]:
        if self.clusters is None:
            return [BucketPartition(b, None) for b in range(self.buckets)]
        by: dict[int, list[int]] = {}
        for c in self.clusters:
            by.setdefault(c % self.buckets, []).append(c)
        return [BucketPartition(b, tuple(cs)) for b, cs in sorted(by.items())]

    def read(self, partition: BucketPartition) -> Iterator[tuple]:
        import pyarrow.dataset as ds
        import pyarrow.fs as fs

        if "://" in self.path or self.path.startswith("file:"):
            system, base = fs.FileSystem.from_uri(self.path)
        else:
            system, base = fs.LocalFileSystem(), self.path
        folder = f"{base}/bucket={partition.bucket}"
        if system.get_file_info(folder).type == fs.FileType.NotFound:
            return
        data = ds.dataset(folder, filesystem=system, format="parquet")
        wanted = None if partition.clusters is None else ds.field("cluster_id").isin(list(partition.clusters))
        names = [c.split()[0] for c in schema.GRAPH.split(", ")]
        for batch in data.to_batches(filter=wanted):
            for row in batch.to_pylist():
                row["bucket"] = partition.bucket
                yield tuple(row[c] for c in names)


class IndexSource(DataSource):
    """spark.read.format("vecrag_index").option("path", ...).load()."""

    @classmethod
    def name(cls) -> str:
        return "vecrag_index"

    def schema(self) -> str:
        return schema.GRAPH

    def reader(self, schema) -> IndexReader:
        return IndexReader(self.options)
