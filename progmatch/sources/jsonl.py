"""A data source of profiles from a folder of JSON lines, and sinks for schedules and indexes."""

from __future__ import annotations

import json
from collections.abc import Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def _files(uri: str):
    from pyarrow import fs

    store, root = fs.FileSystem.from_uri(uri) if "://" in uri else (fs.LocalFileSystem(), uri)
    return store, [f.path for f in store.get_file_info(fs.FileSelector(root)) if f.is_file and f.path.endswith(".jsonl")]


class _File(InputPartition):
    def __init__(self, path: str):
        self.path = path


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.folder, self.source, self.id = options["path"], options.get("source", "L"), options.get("id", "id")

    def partitions(self) -> list[_File]:
        return [_File(p) for p in sorted(_files(self.folder)[1])]

    def read(self, partition: _File) -> Iterator[tuple]:
        store, _ = _files(self.folder)
        with store.open_input_stream(partition.path) as f:
            for line in f.read().decode().splitlines():
                if line.strip():
                    record = json.loads(line)
                    values = [v for k, v in record.items() if k != self.id and v is not None]
                    yield self.source, int(record[self.id]), " ".join(str(x) for v in values for x in (v.values() if isinstance(v, dict) else v if isinstance(v, list) else [v]))


class ProfileLines(DataSource):
    """format("profile_lines"): options path, id (default id), source (default L). A partition for each file."""

    @classmethod
    def name(cls) -> str:
        return "profile_lines"

    def schema(self) -> str:
        return "source string, pid long, text string"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(ProfileLines)


def write_schedule(schedule: DataFrame, path: str, bucket: int = 1_000_000) -> None:
    """Partitioned by position, so a budget prunes files: read with a filter on bucket."""
    schedule.withColumn("bucket", F.floor((F.col("pos") - 1) / bucket)).write.partitionBy("bucket").parquet(path)


def read_schedule(spark: SparkSession, path: str, budget: int, bucket: int = 1_000_000) -> DataFrame:
    return spark.read.parquet(path).where((F.col("bucket") <= (budget - 1) // bucket) & (F.col("pos") <= budget)).drop("bucket")


def save_index(vectors: DataFrame, name: str, buckets: int = 64) -> None:
    """A bucketed table of (gram, ...) rows: joins on the gram reuse its partitioning."""
    vectors.write.bucketBy(buckets, "gram").sortBy("gram").mode("overwrite").saveAsTable(name)
