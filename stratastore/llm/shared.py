"""Tables, shared folders and small plan helpers of the operators."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import types as T


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def shared_dir(spark: SparkSession) -> str:
    """The folder that the cluster names in spark.checkpoint.dir; a local one of our own only where none is named and all tasks run in this process."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if not named:
        named = spark.sparkContext.getConf().get("spark.checkpoint.dir", None)
    if not named:
        if not spark.sparkContext.master.startswith("local"):
            raise RuntimeError("spark.checkpoint.dir must name a folder that all executors share")
        named = getattr(spark.sparkContext, "_own_shared_dir", None) or tempfile.mkdtemp(prefix="shared-")
        spark.sparkContext._own_shared_dir = named
    return named.rstrip("/")


def written(df: DataFrame, what: str, fmt: str = "parquet", **options: str) -> DataFrame:
    """The frame, written to the shared folder and read again: cuts lineage, survives lost executors."""
    spark = df.sparkSession
    path = f"{shared_dir(spark)}/{what}-{uuid.uuid4().hex}"
    df.write.options(**options).format(fmt).save(path)
    out = spark.read.schema(df.schema).format(fmt).load(path)
    out._written_to = path
    return out


def released(df: DataFrame, what: str) -> DataFrame:
    """``written`` in small batches, after which the files of the frame's exchanges are removed: nothing else may start from them."""
    conf = df.sparkSession.conf
    own = {"spark.sql.classic.shuffleDependency.fileCleanup.enabled": "true", "spark.sql.execution.arrow.maxBytesPerBatch": "8m"}
    before = {key: conf.get(key) for key in own}
    for key, value in own.items():
        conf.set(key, value)
    try:
        return written(df, what)
    finally:
        for key, value in before.items():
            conf.set(key, value)


def forget(*frames: DataFrame) -> None:
    """Removes the folders of frames that ``written`` gave, once nothing that is still to be computed reads them."""
    for df in frames:
        jvm, conf = df.sparkSession.sparkContext._jvm, df.sparkSession.sparkContext._jsc.hadoopConfiguration()
        path = jvm.org.apache.hadoop.fs.Path(df._written_to)
        path.getFileSystem(conf).delete(path, True)


def n_shuffle(spark: SparkSession) -> int:
    return int(spark.conf.get("spark.sql.shuffle.partitions"))


def free_name(df: DataFrame, name: str) -> str:
    """``name``, or with underscores before it where the frame has such a column (in any case)."""
    have = {c.lower() for c in df.columns}
    while name.lower() in have:
        name = f"_{name}"
    return name


def crc32_text(text: Column) -> Column:
    return F.crc32(F.encode(F.coalesce(text, F.lit("")), "utf-8"))


def plus(df: DataFrame, added: dict[str, str]) -> T.StructType:
    """The frame's schema with columns added, by name and DDL type."""
    return T.StructType([*df.schema.fields, *[T.StructType.fromDDL(f"`{n}` {k}").fields[0] for n, k in added.items()]])
