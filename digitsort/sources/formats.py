"""Sources and sinks: file formats, sorted and bucketed tables, a generator source."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..session import scratch_dir


def round_trip(df: DataFrame, kind: str, **options) -> DataFrame:
    """Write in a format and read back with the same schema, without inference."""
    path = f"{scratch_dir(df.sparkSession)}/{kind}-{uuid.uuid4().hex[:8]}"
    df.write.format(kind).options(**options).save(path)
    return df.sparkSession.read.schema(df.schema).format(kind).options(**options).load(path)


def sorted_sink(ordered: DataFrame) -> DataFrame:
    """A sorted frame as Parquet: files follow partitions, so their key ranges don't overlap and statistics prune."""
    path = f"{scratch_dir(ordered.sparkSession)}/sorted-{uuid.uuid4().hex[:8]}"
    ordered.write.parquet(path)
    return ordered.sparkSession.read.schema(ordered.schema).parquet(path)


def bucketed(df: DataFrame, key: str, buckets: int = 8) -> DataFrame:
    """A bucketed, locally sorted table: joins and groups on the key need no exchange."""
    name = f"bucketed_{uuid.uuid4().hex[:8]}"
    path = f"{scratch_dir(df.sparkSession)}/{name}"
    df.write.bucketBy(buckets, key).sortBy(key).option("path", path).format("parquet").saveAsTable(name)
    return df.sparkSession.table(name)


class KeyReader(DataSourceReader):
    def __init__(self, options: dict) -> None:
        self.n, self.parts, self.universe, self.low = (int(options.get(o, x)) for o, x in (("rows", 1000), ("parts", 4), ("universe", 0), ("low", 0)))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(k) for k in range(self.parts)]

    def read(self, partition: InputPartition):
        import hashlib

        for k in range(self.low + partition.value, self.low + self.n, self.parts):
            h = int.from_bytes(hashlib.md5(str(k).encode()).digest()[:8], "big")
            u = ((h >> 32) + 0.5) / 2**32
            yield (k, int(self.universe * (u * u) * (u * u)) if self.universe else h - (1 << 63))


class KeySource(DataSource):
    """Uniform keys, or Zipf ranks if ``universe`` is given."""

    @classmethod
    def name(cls) -> str:
        return "digit_keys"

    def schema(self) -> str:
        return "id long, key long"

    def reader(self, schema) -> DataSourceReader:
        return KeyReader(self.options)


def generated(spark: SparkSession, rows: int, universe: int = 0, parts: int = 4, low: int = 0) -> DataFrame:
    """Keys of the ids from ``low`` on."""
    spark.dataSource.register(KeySource)
    return spark.read.format("digit_keys").option("rows", rows).option("parts", parts).option("universe", universe).option("low", low).load()
