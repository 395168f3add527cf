"""The key-value store behind everything: pairs (key BINARY, value BINARY) laid out by key prefix.

A bucket is the key's leading bits; keys are digests, so buckets are even whatever the contents are.
Reads and writes name the bucket too, so a stored table prunes to the buckets asked for, and a table that
is bucketed by it joins without moving its side.
"""

from __future__ import annotations

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

BUCKETS = 64
SCHEMA = "key binary, value binary, bucket int"


def bucket_expr(key: Column, buckets: int = BUCKETS) -> Column:
    return F.pmod(F.conv(F.hex(F.substring(key, 1, 2)), 16, 10).cast("int"), F.lit(buckets)).cast("int")


def empty(spark: SparkSession) -> DataFrame:
    return spark.createDataFrame([], SCHEMA)


def bucketed(pairs: DataFrame, buckets: int = BUCKETS) -> DataFrame:
    return pairs.select("key", "value", bucket_expr(F.col("key"), buckets).alias("bucket"))


def absent(kvs: DataFrame, pairs: DataFrame) -> DataFrame:
    """The pairs whose keys are not stored, one of each key. Only keys go through the exchange on the stored side."""
    return bucketed(pairs.dropDuplicates(["key"])).join(kvs.select("bucket", "key"), ["bucket", "key"], "left_anti").select("key", "value", "bucket")


def put(kvs: DataFrame, pairs: DataFrame) -> DataFrame:
    """The store with the pairs; a key that is stored keeps its value (keys name their values)."""
    return kvs.select("key", "value", "bucket").unionByName(absent(kvs, pairs))


put_absent = put


def get(kvs: DataFrame, keys: DataFrame) -> DataFrame:
    """keys (with a column key, and others) with value, null where there is none."""
    asked = keys.withColumn("bucket", bucket_expr(F.col("key")))
    return asked.join(kvs.select("bucket", "key", "value"), ["bucket", "key"], "left").drop("bucket")


def write(pairs: DataFrame, path: str) -> None:
    """Appends pairs to files by bucket, sorted by key, so row groups have narrow key ranges."""
    rows = bucketed(pairs)
    rows.repartition("bucket").sortWithinPartitions("bucket", "key").write.mode("append").partitionBy("bucket").option("compression", "uncompressed").parquet(path)


def read(spark: SparkSession, path: str) -> DataFrame:
    """The stored pairs; later copies of a key, from replays, are dropped."""
    rows = spark.read.schema(SCHEMA).parquet(path)
    return rows.select("key", "value", "bucket").dropDuplicates(["bucket", "key"])


def save_table(pairs: DataFrame, name: str, buckets: int = BUCKETS) -> None:
    """A catalogue table bucketed and sorted by key: joins on key leave it where it is."""
    bucketed(pairs).write.mode("overwrite").bucketBy(buckets, "key").sortBy("key").saveAsTable(name)


def saved(rows: DataFrame, buckets: int = BUCKETS) -> DataFrame:
    """The rows in a table of their own in the warehouse, bucketed by key: joins on key do not move them, however many there are."""
    name = f"kept_{uuid.uuid4().hex}"
    rows.repartition(buckets, "key").write.bucketBy(buckets, "key").saveAsTable(name)
    return rows.sparkSession.table(name)


def compact(spark: SparkSession, path: str, out: str) -> None:
    """One sorted file for each bucket out of many appended ones."""
    read(spark, path).repartition("bucket").sortWithinPartitions("bucket", "key").write.mode("overwrite").partitionBy("bucket").option("compression", "uncompressed").parquet(out)
