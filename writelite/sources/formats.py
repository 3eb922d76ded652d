"""Round trips through file formats and the layouts that later reads profit from."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from writelite.operators.prim import shared_folder


def scratch(spark: SparkSession, name: str) -> str:
    """A fresh path in the folder that all executors share; in local mode a temporary one where none is set."""
    return f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"


def roundtrip(df: DataFrame, kind: str, **options) -> DataFrame:
    """Written once in a format and read back with the declared schema; nothing is inferred."""
    path = scratch(df.sparkSession, kind)
    df.write.format(kind).options(**options).save(path)
    return df.sparkSession.read.format(kind).options(**options).schema(df.schema).load(path)


def range_sorted(df: DataFrame, partitions: int, *keys: str) -> DataFrame:
    """Files whose order is the key order, read back with the file of each row."""
    path = scratch(df.sparkSession, "sorted")
    df.repartitionByRange(partitions, *keys).sortWithinPartitions(*keys).write.parquet(path)
    return df.sparkSession.read.parquet(path).withColumn("file", F.input_file_name())


def partitioned(df: DataFrame, *by: str) -> DataFrame:
    """Directories by value; filters on them prune whole directories."""
    path = scratch(df.sparkSession, "partitioned")
    df.repartition(*by).write.partitionBy(*by).parquet(path)
    return df.sparkSession.read.parquet(path)


def bucketed(df: DataFrame, key: str, buckets: int = 8) -> DataFrame:
    """A table bucketed and sorted by key: joins of two such tables on it need no exchange."""
    name = f"bucketed_{uuid.uuid4().hex}"
    df.write.bucketBy(buckets, key).sortBy(key).saveAsTable(name)
    return df.sparkSession.table(name)
