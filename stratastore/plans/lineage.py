"""Cutting lineage in the shared folder that the cluster names."""

from __future__ import annotations

import re
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager

import pyarrow as pa
import pyarrow.fs
import pyarrow.parquet as pq
from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; a temporary one of our own only where none is named (local tests)."""
    named = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if named:
        return named
    if not spark.sparkContext.master.startswith("local"):
        raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
    held = getattr(spark.sparkContext, "_store_shared_dir", None)
    if held is None:
        held = spark.sparkContext._store_shared_dir = tempfile.mkdtemp(prefix="store-")
    return held


def cut(df: DataFrame) -> DataFrame:
    """The frame, computed and kept in the shared folder: later steps start from there."""
    sc = df.sparkSession.sparkContext
    if sc._jsc.sc().getCheckpointDir().isEmpty():
        sc.setCheckpointDir(shared_dir(df.sparkSession))
    return df.checkpoint(eager=True)


@contextmanager
def released(spark: SparkSession) -> Iterator[None]:
    """What is computed in here to its end leaves no exchange files behind, and batches for Python are bounded in bytes."""
    own = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", "spark.sql.execution.arrow.maxBytesPerBatch": "8m"}
    before = {key: spark.conf.get(key) for key in own}
    for key, value in own.items():
        spark.conf.set(key, value)
    try:
        yield
    finally:
        for key, value in before.items():
            spark.conf.set(key, value)


@contextmanager
def in_order(df: DataFrame, by: list[str], parts: int) -> Iterator[list[str]]:
    """Files in the shared folder with the rows, from the first to the last; they are removed at the end. Tasks read them with ``rows_of``."""
    spark = df.sparkSession
    path = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(f"{shared_dir(spark).rstrip('/')}/ordered-{uuid.uuid4().hex}")
    try:
        with released(spark):
            df.repartitionByRange(parts, *by).sortWithinPartitions(*by).write.option("compression", "zstd").parquet(path.toString())
        files = spark.read.schema(df.schema).parquet(path.toString()).inputFiles()
        yield sorted(files, key=lambda x: int(re.findall(r"part-(\d+)", x)[-1]))
    finally:
        path.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(path, True)


def rows_of(files: list[str], columns: list[str]) -> Iterator[pa.RecordBatch]:
    """The rows of the files, in a task: one file after the other."""
    for uri in files:
        fs, path = pa.fs.FileSystem.from_uri(uri)
        with fs.open_input_file(path) as f:
            yield from pq.ParquetFile(f).iter_batches(batch_size=8192, columns=columns)
