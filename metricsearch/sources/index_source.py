"""A saved index as a SQL source: ``spark.read.format('metric_index').load(path)`` gives its members by part."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, InputPartition


class _Part(InputPartition):
    def __init__(self, number: int, files: list[str]):
        super().__init__(number)
        self.number, self.files = number, files


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.path, self.only = options["path"].removeprefix("file://"), None

    def pushFilters(self, filters):
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("part",):
                self.only = f.value
            else:
                yield f

    def partitions(self):
        import pyarrow.dataset as ds

        parts: dict[int, list[str]] = {}
        for file in ds.dataset(f"{self.path}/nodes", format="parquet").files:
            number = int(file.split("/part=")[1].split("/")[0])
            if self.only is None or number == self.only:
                parts.setdefault(number, []).append(file)
        return [_Part(n, f) for n, f in sorted(parts.items())]

    def read(self, partition):
        import pyarrow.parquet as pq

        for file in partition.files:
            for batch in pq.ParquetFile(file).iter_batches(columns=["node_id", "obj_id", "is_leaf", "members"]):
                for row in batch.to_pylist():
                    if row["is_leaf"]:
                        for i in [row["obj_id"], *row["members"]]:
                            yield partition.number, row["node_id"], i


class IndexSource(DataSource):
    """Reads through the file system of its workers; a path in another store is read with :func:`load_index`."""

    @classmethod
    def name(cls):
        return "metric_index"

    def schema(self):
        return "part bigint, node_id bigint, obj_id bigint"

    def reader(self, schema):
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(IndexSource)
