"""Contents from tables and files: every source gives content_id STRING, series STRING, version BIGINT, body BINARY, n BIGINT."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def views(spark: SparkSession, sf_dir: str) -> None:
    """All tables as temporary views."""
    for name in TABLES:
        table(spark, sf_dir, name).createOrReplaceTempView(name)


def contents(df: DataFrame, cid: Column, series: Column, version: Column, body: Column) -> DataFrame:
    out = df.select(cid.cast("string").alias("content_id"), series.alias("series"), version.cast("long").alias("version"), body.alias("body"))
    return out.withColumn("n", F.octet_length("body").cast("long"))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contents(table(spark, sf_dir, "documents"), F.col("doc_id"), F.lit("documents"), F.col("doc_id"), F.encode("text", "utf-8"))


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contents(table(spark, sf_dir, "pages"), F.col("page_id"), F.lit("pages"), F.col("page_id"), F.encode("html", "utf-8"))


def passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contents(table(spark, sf_dir, "benchmark"), F.col("item_id"), F.lit("benchmark"), F.col("item_id"), F.encode("text", "utf-8"))


def embedding_blobs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors as text of their millionths, so that every engine packs the same bytes."""
    text = F.array_join(F.transform("embedding", lambda x: F.floor(x.cast("double") * 1_000_000).cast("string")), ",")
    return contents(table(spark, sf_dir, "embeddings"), F.col("vec_id"), F.lit("embeddings"), F.col("vec_id"), F.encode(text, "utf-8"))


def conversation_versions(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Version t of a conversation: its turns 0 to t, a line each."""
    own = Window.partitionBy("conv_id").orderBy("turn").rowsBetween(Window.unboundedPreceding, 0)
    rows = table(spark, sf_dir, "conversations").withColumn("all", F.array_join(F.collect_list("text").over(own), "\n"))
    return contents(rows, F.concat_ws(":", "conv_id", "turn"), F.lit("conversations"), F.col("turn"), F.encode("all", "utf-8"))


def _money(name: str) -> Column:
    return F.col(name).cast("decimal(18,2)").cast("string")


def order_line() -> Column:
    return F.concat_ws("|", F.col("o_orderkey").cast("string"), F.col("o_custkey").cast("string"), "o_orderstatus", _money("o_totalprice"), F.date_format("o_orderdate", "yyyy-MM-dd"), "o_orderpriority")


def lineitem_line() -> Column:
    ints = [F.col(c).cast("string") for c in ("l_orderkey", "l_linenumber", "l_partkey", "l_suppkey")]
    return F.concat_ws("|", *ints, *[_money(c) for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax")], "l_returnflag", "l_linestatus", F.date_format("l_shipdate", "yyyy-MM-dd"))


def event_line() -> Column:
    return F.concat_ws("|", F.col("event_id").cast("string"), F.date_format("ts", "yyyy-MM-dd HH:mm:ss"), F.col("user_id").cast("string"), "event_type", F.col("value").cast("decimal(18,2)").cast("string"), "props")


def _snapshots(rows: DataFrame, period: Column, series: str, last: int | None = None) -> DataFrame:
    """A content for each period with a row: all lines up to it, in the order of ``at`` and then of the line itself.

    rows: at, line. Periods are few and given; a row goes to each period from its own on (a range join on
    the small list of periods). last: only the snapshots of so many last periods, each of all rows up to it.
    """
    dated = rows.withColumn("p", period)
    periods = dated.select("p").where("p IS NOT NULL").distinct().withColumn("version", F.row_number().over(Window.orderBy("p")))
    if last:
        periods = periods.withColumn("top", F.max("version").over(Window.partitionBy())).where(F.col("version") > F.col("top") - last).drop("top")
    periods = F.broadcast(periods)
    members = dated.select("at", "line", "p").join(periods.withColumnRenamed("p", "q"), F.col("p") <= F.col("q"))
    joined = members.groupBy("version").agg(F.expr("listagg(line, '\n') WITHIN GROUP (ORDER BY lpad(cast(at as string), 12, '0') || line)").alias("all"))
    return contents(joined, F.concat(F.lit(f"{series}:"), "version"), F.lit(series), F.col("version"), F.encode("all", "utf-8"))


@dataclass
class History:
    """The snapshots of ``_snapshots`` as their rows (at, line, p), for work that must not hold a snapshot in one value."""

    rows: DataFrame
    last: int | None = None

    def versions(self) -> list[tuple[int, int, int]]:
        """(p, version, length in bytes) of the snapshots: a row a period, summed where the rows lie."""
        sizes = self.rows.where("p IS NOT NULL").groupBy("p").agg(F.sum(F.octet_length("line").cast("long") + 1).alias("b")).orderBy("p").collect()
        out, total = [], -1
        for version, r in enumerate(sizes, 1):
            total += r.b
            out.append((r.p, version, total))
        return out[-self.last :] if self.last else out


def order_history(spark: SparkSession, sf_dir: str, months: int = 3, last: int | None = None) -> History:
    return History(table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("at"), order_line().alias("line"), _period("o_orderdate", months).alias("p")), last)


def lineitem_history(spark: SparkSession, sf_dir: str, months: int = 1) -> History:
    """A snapshot for each ship month."""
    return History(table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("at"), lineitem_line().alias("line"), _period("l_shipdate", months).alias("p")))


def event_history(spark: SparkSession, sf_dir: str) -> History:
    return History(table(spark, sf_dir, "events").select(F.col("event_id").alias("at"), event_line().alias("line"), F.date_format("ts", "yyyyMMdd").cast("long").alias("p")))


def order_snapshots(spark: SparkSession, sf_dir: str, months: int = 3, last: int | None = None) -> DataFrame:
    """Snapshots of orders every few months, in key order: rows come in amid old ones."""
    rows = table(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("at"), order_line().alias("line"), "o_orderdate")
    return _snapshots(rows, _period("o_orderdate", months), "orders", last)


def lineitem_snapshots(spark: SparkSession, sf_dir: str, months: int = 1) -> DataFrame:
    """Snapshots of lineitem by ship month, ordered by order key and all other columns."""
    rows = table(spark, sf_dir, "lineitem").select(F.col("l_orderkey").alias("at"), lineitem_line().alias("line"), "l_shipdate")
    return _snapshots(rows, _period("l_shipdate", months), "lineitem")


def event_days(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events up to each day: an append-only history."""
    rows = table(spark, sf_dir, "events").select(F.col("event_id").alias("at"), event_line().alias("line"), "ts")
    return _snapshots(rows, F.date_format("ts", "yyyyMMdd").cast("long"), "events")


def _period(column: str, months: int) -> Column:
    return F.floor((F.year(column) * 12 + F.month(column) - 1) / months).cast("long")


def random_bytes(seed: Column, n: int) -> Column:
    """n bytes from the seed's text: SHA-256 of 'seed:block' for block 0, 1, ..., cut to length."""
    blocks = F.transform(F.sequence(F.lit(0), F.lit(-(-n // 32) - 1)), lambda i: F.sha2(F.encode(F.concat(seed.cast("string"), F.lit(":"), i.cast("string")), "utf-8"), 256))
    return F.substring(F.unhex(F.array_join(blocks, "")), 1, n)


def random_contents(spark: SparkSession, seed: int, n: int, count: int) -> DataFrame:
    """count contents of n bytes each; seeds seed, seed + 1, ..."""
    rows = spark.range(seed, seed + count)
    return contents(rows, F.concat(F.lit("random:"), "id"), F.lit("random"), F.col("id"), random_bytes(F.col("id"), n))


def from_files(spark: SparkSession, path: str, glob: str = "*") -> DataFrame:
    """Every file as one content; Spark's file sources pass over empty files."""
    return contents(spark.read.format("binaryFile").option("pathGlobFilter", glob).load(path), F.col("path"), F.lit("files"), F.lit(None), F.col("content"))


def from_text_files(spark: SparkSession, path: str) -> DataFrame:
    """Every text file as one content, whole."""
    return contents(spark.read.text(path, wholetext=True).withColumn("path", F.col("_metadata.file_path")), F.col("path"), F.lit("text"), F.lit(None), F.encode("value", "utf-8"))


def from_lines(spark: SparkSession, path: str) -> DataFrame:
    """Every line of text files as one content."""
    rows = spark.read.text(path).withColumn("at", F.monotonically_increasing_id())
    return contents(rows, F.concat(F.lit("line:"), "at"), F.lit("lines"), F.col("at"), F.encode("value", "utf-8"))


def overwrite(body: Column, at: Column, new: Column) -> Column:
    """The body with the bytes from ``at`` (from 0) replaced by those of ``new``."""
    size = F.octet_length(new)
    return F.concat(F.substring(body, F.lit(1), at.cast("int")), new, F.substring(body, (at + size + 1).cast("int"), F.greatest(F.octet_length(body) - at - size, F.lit(0)).cast("int")))


def insert(body: Column, at: Column, new: Column) -> Column:
    """The body with ``new`` put in before byte ``at``."""
    return F.concat(F.substring(body, F.lit(1), at.cast("int")), new, F.substring(body, (at + 1).cast("int"), (F.octet_length(body) - at).cast("int")))


def flipped(body: Column, at: Column, size: int) -> Column:
    """The ``size`` bytes at ``at``, each another one: their complement."""
    return F.unhex(F.translate(F.hex(F.substring(body, (at + 1).cast("int"), F.lit(size))), "0123456789ABCDEF", "FEDCBA9876543210"))
