"""Base chunkers: contents to chunks (content_id, seq, start_pos, end_pos, value)."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import rolling
from ..params import StoreParams

CHUNKS = "content_id string, seq bigint, start_pos bigint, end_pos bigint, value binary"
#: Chunks of a batch, at most.
PART = 1 << 16
_REGISTRY: dict[str, Callable[[DataFrame, StoreParams], DataFrame]] = {}


def register(name: str, chunker: Callable[[DataFrame, StoreParams], DataFrame]) -> None:
    """Adds a deterministic chunker with a target length."""
    _REGISTRY[name] = chunker


def chunk(contents: DataFrame, name: str, p: StoreParams) -> DataFrame:
    return _REGISTRY[name](contents, p)


def whole(contents: DataFrame, p: StoreParams | None = None) -> DataFrame:
    """One chunk a content."""
    n = F.octet_length("body").cast("long")
    return contents.where("body IS NOT NULL").select("content_id", F.lit(0).cast("long").alias("seq"), F.lit(0).cast("long").alias("start_pos"), n.alias("end_pos"), F.col("body").alias("value"))


def _spread(rows: DataFrame, ends: Column) -> DataFrame:
    """Chunks from an array of boundaries (the last one the length)."""
    out = rows.select("content_id", "body", F.posexplode(ends).alias("seq", "end_pos"), ends.alias("ends"))
    start = F.when(F.col("seq") == 0, F.lit(0).cast("long")).otherwise(F.col("ends")[F.col("seq") - 1])
    out = out.select("content_id", F.col("seq").cast("long").alias("seq"), start.alias("start_pos"), "end_pos", "body")
    return out.select("content_id", "seq", "start_pos", "end_pos", F.substring(F.col("body"), (F.col("start_pos") + 1).cast("int"), (F.col("end_pos") - F.col("start_pos")).cast("int")).alias("value"))


def fixed(contents: DataFrame, p: StoreParams) -> DataFrame:
    """Cuts every S bytes; empty contents have no chunk."""
    n = F.octet_length("body").cast("long")
    length = F.lit(p.chunk).cast("long")
    ends = F.transform(F.sequence(F.lit(1).cast("long"), F.ceil(n / length)), lambda i: F.least(i * length, n))
    return _spread(contents.where("octet_length(body) > 0"), ends)


def lines(contents: DataFrame, p: StoreParams | None = None) -> DataFrame:
    """Cuts after each line feed: a chunker of text by its own structure (bytes of multi-byte letters never hold a line feed)."""

    def run(batches):
        for batch in batches:
            for at in range(batch.num_rows):
                body = batch.column(1)[at].as_py()
                if not body:
                    continue
                # after each line feed and at the end, if no line feed is there
                ends = np.flatnonzero(np.frombuffer(body, np.uint8) == 10) + 1
                if not len(ends) or ends[-1] < len(body):
                    ends = np.append(ends, len(body))
                for k in range(0, len(ends), PART):
                    cuts = np.append(ends[k - 1] if k else 0, ends[k : k + PART])
                    ids = pa.array(np.zeros(len(cuts) - 1, np.int32))
                    value = pa.Array.from_buffers(pa.binary(), len(cuts) - 1, [None, pa.py_buffer((cuts - cuts[0]).astype(np.int32)), pa.py_buffer(body[cuts[0] : cuts[-1]])])
                    places = [pa.array(x.astype(np.int64)) for x in (np.arange(k, k + len(ids)), cuts[:-1], cuts[1:])]
                    yield pa.RecordBatch.from_arrays([batch.column(0).slice(at, 1).take(ids), *places, value], names=["content_id", "seq", "start_pos", "end_pos", "value"])

    return contents.select("content_id", "body").mapInArrow(run, CHUNKS)


def cdc(contents: DataFrame, p: StoreParams) -> DataFrame:
    """Content-defined cuts by the rolling hash (Arrow kernel)."""
    q = p.with_(scheme="cdc")

    def run(batches):
        for batch in batches:
            rows = []
            for cid, body in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows += [(cid, k, a, b, body[a:b]) for k, (a, b) in enumerate(rolling.single_level(body or b"", q, 0))]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.string(), *[pa.int64()] * 3, pa.binary()), strict=True)], names=["content_id", "seq", "start_pos", "end_pos", "value"])

    return contents.select("content_id", "body").mapInArrow(run, CHUNKS)


def byte_table(contents: DataFrame) -> DataFrame:
    """(content_id, i, v): the bytes of the contents, a row each."""
    # block by block, as places within a long text are found from its start
    block = 256
    blocks = contents.where("octet_length(body) > 0").select("content_id", "body", F.explode(F.sequence(F.lit(0), F.floor((F.octet_length("body") - 1) / block).cast("int"))).alias("b"))
    hexes = blocks.select("content_id", "b", F.hex(F.substring(F.col("body"), F.col("b") * block + 1, F.lit(block))).alias("hex"))
    pos = hexes.select("content_id", "b", "hex", F.explode(F.sequence(F.lit(0), (F.length("hex") / 2).cast("int") - 1)).alias("j"))
    return pos.select("content_id", (F.col("b").cast("long") * block + F.col("j")).alias("i"), F.conv(F.substring(F.col("hex"), F.col("j") * 2 + 1, F.lit(2)), 16, 10).cast("long").alias("v"))


def power_table(contents: DataFrame, p: StoreParams) -> DataFrame:
    """(i, up, down): B^(i+1) and B^-i modulo the prime, for all places of the longest content."""
    return _powers(contents, contents.agg(F.max(F.octet_length("body"))).first()[0] or 1)


def _powers(contents: DataFrame, longest: int) -> DataFrame:
    inv, up = rolling._tables("m31", 1 << max(10, int(longest).bit_length()))
    return contents.sparkSession.createDataFrame(pa.table({"i": pa.array(range(longest), pa.int64()), "up": pa.array(up[:longest]), "down": pa.array(inv[:longest])}))


#: Bytes of contents of which a partition makes its rows, about.
CHECKED_BYTES = 1 << 18


def cdc_sql(contents: DataFrame, p: StoreParams) -> DataFrame:
    """The same cuts by DataFrame operations in the prime ring: prefix sums and a difference W bytes back. For checks: a row a byte.

    Contents are dealt before they become rows of bytes, in so many partitions that these are sorted in
    memory: no row of a byte goes through an exchange.
    """
    sizes = contents.agg(F.max(F.octet_length("body")).alias("longest"), F.sum(F.octet_length("body").cast("long")).alias("total")).first()
    parts = max(contents.sparkSession.sparkContext.defaultParallelism, (sizes.total or 0) // CHECKED_BYTES + 1)
    rows = contents.where("octet_length(body) > 0").select("content_id", "body").repartition(parts, "content_id")
    bytes_ = byte_table(rows).join(F.broadcast(_powers(contents, sizes.longest or 1)), "i")
    own = Window.partitionBy("content_id").orderBy("i")
    sums = bytes_.withColumn("s", F.sum((F.col("v") + 1) * F.col("down") % rolling.M31).over(own))
    back = F.coalesce(F.lag("s", p.window).over(own), F.lit(0))
    hashed = sums.withColumn("h", (F.col("s") - back) % rolling.M31 * F.col("up") % rolling.M31)
    cuts = hashed.where(F.col("h") < rolling.threshold(p.with_(ring="m31"), 0)).groupBy("content_id").agg(F.array_sort(F.collect_list(F.col("i") + 1)).alias("cuts"))
    n = F.octet_length("body").cast("long")
    ends = F.array_distinct(F.concat(F.coalesce("cuts", F.array().cast("array<bigint>")), F.array(n)))
    return _spread(rows.join(cuts, "content_id", "left"), ends)


for _name, _f in (("whole", whole), ("fixed", fixed), ("lines", lines), ("cdc", cdc), ("cdc_sql", cdc_sql)):
    register(_name, _f)
