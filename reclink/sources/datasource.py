"""A given Parquet table as a Python data source: spark.read.format("linkage_customers")."""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def _dataset(path: str):
    import pyarrow.dataset

    return pyarrow.dataset.dataset(path.removeprefix("file://"), format="parquet", exclude_invalid_files=True)


class CustomerReader(DataSourceReader):
    """A partition a row group; the tasks read the rows."""

    def __init__(self, path: str):
        self.path = path

    def partitions(self):
        parts = [(f.path, g.id) for f in _dataset(self.path).get_fragments() for g in f.row_groups]
        return [InputPartition(p) for p in parts or [None]]

    def read(self, partition):
        if partition.value:
            path, group = partition.value
            fragment = next(_dataset(path).get_fragments()).subset(row_group_ids=[group])
            for batch in fragment.to_batches(columns=["c_custkey", "c_name", "c_mktsegment"]):
                yield batch.rename_columns(["record_id", "name", "segment"])


class CustomerSource(DataSource):
    @classmethod
    def name(cls):
        return "linkage_customers"

    def schema(self):
        return "record_id long, name string, segment string"

    def reader(self, schema):
        return CustomerReader(self.options["path"])
