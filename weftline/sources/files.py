"""Reading and writing tables in the formats that pipelines meet."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession

from ..runtime.cache import shared_root


def scratch(spark: SparkSession, what: str) -> str:
    return f"{shared_root(spark)}/{what}-{uuid.uuid4().hex}"


def round_trip(df: DataFrame, kind: str, partition_by: list[str] | None = None, **options: str) -> DataFrame:
    """Written and read again with the schema that is known; nothing is inferred."""
    path = scratch(df.sparkSession, kind)
    writer = df.write.format(kind).options(**options)
    (writer.partitionBy(*partition_by) if partition_by else writer).save(path)
    return df.sparkSession.read.format(kind).options(**options).schema(df.schema).load(path)


def read_csv(spark: SparkSession, path: str, sample: float = 0.01) -> DataFrame:
    """The schema is inferred once from a sample and then fixed."""
    schema = spark.read.csv(path, header=True, inferSchema=True, samplingRatio=sample).schema
    return spark.read.csv(path, header=True, schema=schema)


def binary_metadata(spark: SparkSession, path: str) -> DataFrame:
    """Path, size and time of files, images for example, without their contents."""
    return spark.read.format("binaryFile").option("recursiveFileLookup", "true").load(path).select("path", "length", "modificationTime")


def save_bucketed(df: DataFrame, table: str, key: str, buckets: int) -> DataFrame:
    """A bucketed table: later joins on the key need no shuffle of it."""
    df.write.mode("overwrite").bucketBy(buckets, key).sortBy(key).saveAsTable(table)
    return df.sparkSession.table(table)
