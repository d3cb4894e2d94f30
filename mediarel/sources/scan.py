"""Scans and sinks of media relations."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

from mediarel.schema import media_ref

MANIFEST = "source_id bigint, uri string, duration_ms bigint"


def scan(spark: SparkSession, path_or_table: str, fmt: str = "parquet", schema: str | None = None, **options) -> DataFrame:
    """A relation from files of any format Spark reads, or from a catalog table."""
    if fmt == "table":
        return spark.table(path_or_table)
    reader = spark.read.format(fmt).options(**options)
    return (reader.schema(schema) if schema else reader).load(path_or_table)


def scan_manifest(spark: SparkSession, path: str, fmt: str = "json") -> DataFrame:
    """(source_id, duration_ms, v): media values from a manifest in any store that Spark reads."""
    listed = spark.read.schema(MANIFEST).format(fmt).load(path)
    return listed.select("source_id", "duration_ms", media_ref(F.col("source_id"), F.col("duration_ms"), F.col("uri")).alias("v"))


class MediaManifest(DataSource):
    """``spark.read.format('media_manifest')``: synthetic manifests of ``sources`` feeds of ``duration_ms`` under ``prefix``, in ``parts`` partitions.

    Stands in for a camera registry; partitions are ranges, so nothing is listed on the driver.
    """

    @classmethod
    def name(cls) -> str:
        return "media_manifest"

    def schema(self) -> str:
        return MANIFEST

    def reader(self, schema: StructType) -> DataSourceReader:
        return _ManifestReader(self.options)


class _Range(InputPartition):
    def __init__(self, low: int, high: int):
        self.low, self.high = low, high


class _ManifestReader(DataSourceReader):
    def __init__(self, options):
        self.n, self.parts = int(options.get("sources", 0)), max(1, int(options.get("parts", 4)))
        self.prefix, self.duration = options.get("prefix", "feed:"), int(options.get("duration_ms", 5000))

    def partitions(self):
        step = -(-self.n // self.parts) or 1
        return [_Range(i, min(i + step, self.n)) for i in range(0, self.n, step)] or [_Range(0, 0)]

    def read(self, part):
        for i in range(part.low, part.high):
            yield (i, f"{self.prefix}{i}", self.duration)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(MediaManifest)


def write_clustered(df: DataFrame, path: str, buckets: int, key: str = "source_id", order: Sequence[str] = ("segment_no",)) -> None:
    """Segment tables laid out for View: partition folders by source bucket, sorted inside, so windows prune files by min and max."""
    dealt = df.withColumn("source_bucket", F.pmod(F.xxhash64(key), F.lit(buckets)).cast("int"))
    dealt.repartition(buckets, "source_bucket").sortWithinPartitions("source_bucket", key, *order).write.partitionBy("source_bucket").parquet(path)


def write_bucketed(df: DataFrame, table: str, buckets: int, key: str = "source_id") -> None:
    """A bucketed catalog table: joins and reductions by ``key`` against a table with the same buckets need no shuffle."""
    df.write.bucketBy(buckets, key).sortBy(key).mode("overwrite").saveAsTable(table)
