"""A Python data source for stripe files: `spark.read.format("stripes")`, one partition a file, user ranges pushed down.

Needs spark.sql.python.filterPushdown.enabled; it is a runtime setting.
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThanOrEqual, InputPartition, LessThanOrEqual


class _File(InputPartition):
    def __init__(self, path: str) -> None:
        self.path = path


class StripeSource(DataSource):
    """Options: path, a folder of Parquet stripe files that every worker sees. Columns of the index, without arrays."""

    @classmethod
    def name(cls) -> str:
        return "stripes"

    def schema(self) -> str:
        return "user_id bigint, feature_group string, stripe_no bigint, first_us bigint, last_us bigint, n_events int, events_before bigint"

    def reader(self, schema) -> DataSourceReader:
        return StripeReader(self.options["path"])


class StripeReader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path, self.lo, self.hi = path, None, None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        """Takes bounds on user_id; the rest is left to Spark."""
        for f in filters:
            if getattr(f, "attribute", None) == ("user_id",) and isinstance(f, (EqualTo, GreaterThanOrEqual, LessThanOrEqual)):
                if isinstance(f, (EqualTo, GreaterThanOrEqual)):
                    self.lo = f.value if self.lo is None else max(self.lo, f.value)
                if isinstance(f, (EqualTo, LessThanOrEqual)):
                    self.hi = f.value if self.hi is None else min(self.hi, f.value)
            else:
                yield f

    def partitions(self) -> list[InputPartition]:
        import pyarrow.fs as fs

        store, path = fs.FileSystem.from_uri(self.path if "://" in self.path else f"file://{self.path}")
        found = store.get_file_info(fs.FileSelector(path, recursive=True))
        return [_File(x.path) for x in found if x.path.endswith(".parquet")]

    def read(self, partition: InputPartition) -> Iterator:
        import pyarrow.fs as fs
        import pyarrow.parquet as pq

        store, _ = fs.FileSystem.from_uri(self.path if "://" in self.path else f"file://{self.path}")
        bounds = [("user_id", ">=", self.lo)] * (self.lo is not None) + [("user_id", "<=", self.hi)] * (self.hi is not None)
        columns = ["user_id", "feature_group", "stripe_no", "first_us", "last_us", "n_events", "events_before"]
        yield from pq.read_table(partition.path, columns=columns, filters=bounds or None, filesystem=store).to_batches()
