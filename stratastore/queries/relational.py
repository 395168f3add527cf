"""The relational operations that the store's users need around it, one query each."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..operators import kvs, measures, store, tree
from ..params import StoreParams
from ..sources import contents as src
from ..streaming import ingest
from . import oracle as o
from . import query
from .core import CUT, FIXED, TOP

SHORT = StoreParams(chunk=256, scheme="fixed", protect="hash")
_LEAVES = o.with_(o.keyed(o.DOCUMENTS, SHORT, 1)) + ""


def _leaves(spark: SparkSession, d: str) -> DataFrame:
    """(content_id, seq, start_pos, end_pos, size, key) of all fixed-size chunks of the documents."""
    return tree.build(src.documents(spark, d), SHORT).where("level = 0")


def _text(key: str = "key"):
    return F.lower(F.hex(key))


# ---- scalars ------------------------------------------------------------------------------------


@query("""SELECT doc_id, lang, CASE WHEN n_chars < 500 THEN 'short' WHEN n_chars BETWEEN 500 AND 5000 THEN 'middle' ELSE 'long' END AS kind
FROM documents WHERE lang IN ('en', 'de') AND source LIKE 'src1%' AND regexp_matches(text, '[A-Z][a-z]+') AND lang IS NOT DISTINCT FROM lang""")
def ops_filter_documents(spark: SparkSession, d: str) -> DataFrame:
    docs = src.table(spark, d, "documents")
    kind = F.when(F.col("n_chars") < 500, "short").when(F.col("n_chars").between(500, 5000), "middle").otherwise("long")
    return docs.where(F.col("lang").isin("en", "de") & F.col("source").like("src1%") & F.col("text").rlike("[A-Z][a-z]+") & F.col("lang").eqNullSafe(F.col("lang"))).select("doc_id", "lang", kind.alias("kind"))


@query("""SELECT item_id, octet_length(encode(text)) AS bytes, length(text) AS chars, hex(encode(text)[1:4]) AS head, lower(text) AS low, len(string_split(text, ' ')) AS parts,
  regexp_replace(text, '[aeiou]', '_', 'g') AS masked, base64(encode(text)[1:9]) AS b64, lpad(CAST(item_id AS VARCHAR), 6, '0') AS code FROM benchmark""")
def ops_binary_scalar(spark: SparkSession, d: str) -> DataFrame:
    raw = F.encode("text", "utf-8")
    return src.table(spark, d, "benchmark").select(
        "item_id", F.octet_length(raw).alias("bytes"), F.char_length("text").alias("chars"), F.hex(F.substring(raw, 1, 4)).alias("head"), F.lower("text").alias("low"), F.size(F.split("text", " ")).alias("parts"),
        F.regexp_replace("text", "[aeiou]", "_").alias("masked"), F.base64(F.substring(raw, 1, 9)).alias("b64"), F.lpad(F.col("item_id").cast("string"), 6, "0").alias("code"),
    )


@query("SELECT doc_id, sha256(text) AS h256, md5(text) AS h128, sha1(text) AS h160 FROM documents")
def ops_hash_scalar(spark: SparkSession, d: str) -> DataFrame:
    return src.table(spark, d, "documents").select("doc_id", F.sha2("text", 256).alias("h256"), F.md5("text").alias("h128"), F.sha1("text").alias("h160"))


@query("SELECT doc_id, ceil(n_chars / 256.0) AS up, floor(n_chars / 256.0) AS down, pow(2.0, n_chars % 5) AS p, round(ln(n_chars + 1.0), 6) AS l, greatest(n_chars, 1000) AS g, least(n_chars, 1000) AS s, n_chars << 2 AS sh, n_chars & 255 AS low, xor(n_chars, 170) AS x FROM documents")
def ops_math_model(spark: SparkSession, d: str) -> DataFrame:
    n = F.col("n_chars")
    return src.table(spark, d, "documents").select(
        "doc_id", F.ceil(n / 256).cast("double").alias("up"), F.floor(n / 256).cast("double").alias("down"), F.pow(F.lit(2.0), F.pmod(n, F.lit(5))).alias("p"), F.round(F.log(n + 1.0), 6).alias("l"),
        F.greatest(n, F.lit(1000)).alias("g"), F.least(n, F.lit(1000)).alias("s"), F.shiftleft(n, 2).alias("sh"), n.bitwiseAND(255).alias("low"), n.bitwiseXOR(170).alias("x"),
    )


@query("SELECT strftime(date_trunc('month', o_orderdate), '%Y-%m-%d') AS month, count(*) AS n, strftime(date_trunc('month', o_orderdate) + INTERVAL 3 MONTH, '%Y-%m-%d') AS later, strftime(last_day(min(o_orderdate)), '%Y-%m-%d') AS last FROM orders GROUP BY date_trunc('month', o_orderdate)")
def ops_snapshot_months(spark: SparkSession, d: str) -> DataFrame:
    month = F.date_trunc("month", "o_orderdate")
    out = src.table(spark, d, "orders").groupBy(month.alias("m")).agg(F.count("*").alias("n"), F.min("o_orderdate").alias("first"))
    day = lambda c: F.date_format(c, "yyyy-MM-dd")
    return out.select(day("m").alias("month"), "n", day(F.col("m") + F.expr("INTERVAL 3 MONTH")).alias("later"), day(F.last_day("first")).alias("last"))


_ARRAYS = o.with_(o.fixed_spans(o.DOCUMENTS, SHORT, 1)) + """SELECT content_id, count(*) AS n, CAST(sum(e - s) AS BIGINT) AS total, CAST(max(e - s) AS BIGINT) AS most, CAST(count(CASE WHEN e - s = 256 THEN 1 END) AS BIGINT) AS full_chunks,
  count(DISTINCT e - s) AS kinds, CAST(min(CASE WHEN s = 0 THEN e - s END) AS BIGINT) AS first FROM n WHERE level = 0 GROUP BY content_id"""


@query(_ARRAYS)
def ops_array_children(spark: SparkSession, d: str) -> DataFrame:
    """A content's chunk lengths as an array."""
    n = F.octet_length("body").cast("long")
    sizes = F.transform(F.sequence(F.lit(0).cast("long"), n - 1, F.lit(256).cast("long")), lambda s: F.least(n - s, F.lit(256).cast("long")))
    rows = src.documents(spark, d).where("octet_length(body) > 0").select("content_id", sizes.alias("a"))
    return rows.select(
        "content_id", F.size("a").cast("long").alias("n"), F.aggregate("a", F.lit(0).cast("long"), lambda x, y: x + y).alias("total"), F.array_max("a").alias("most"),
        F.size(F.filter("a", lambda x: x == 256)).cast("long").alias("full_chunks"), F.size(F.array_distinct("a")).cast("long").alias("kinds"), F.element_at("a", 1).alias("first"),
    )


_KEYED = o.with_(o.keyed(o.DOCUMENTS, FIXED, TOP))


@query(_KEYED + "SELECT content_id, CAST(level AS VARCHAR) AS level, count(*) AS nodes FROM k GROUP BY content_id, level")
def ops_level_map(spark: SparkSession, d: str) -> DataFrame:
    """Nodes by level as a map of each content, and back to rows."""
    per = tree.build(src.documents(spark, d), FIXED).groupBy("content_id", "level").agg(F.count("*").alias("n"))
    maps = per.groupBy("content_id").agg(F.map_from_entries(F.collect_list(F.struct(F.col("level").cast("string"), "n"))).alias("m"))
    doubled = maps.select("content_id", F.transform_values("m", lambda k, v: v * 2).alias("m"))
    return doubled.select("content_id", F.explode("m").alias("level", "v")).select("content_id", "level", (F.col("v") / 2).cast("long").alias("nodes"))


@query("SELECT event_type, CAST(json_extract(props, '$.k') AS BIGINT) AS k, count(*) AS n, '{\"t\":\"' || event_type || '\"}' AS back FROM events GROUP BY event_type, k")
def ops_events_json(spark: SparkSession, d: str) -> DataFrame:
    rows = src.table(spark, d, "events").withColumn("k", F.from_json("props", "k bigint")["k"])
    return rows.groupBy("event_type", "k").agg(F.count("*").alias("n")).withColumn("back", F.to_json(F.struct(F.col("event_type").alias("t"))))


# ---- joins --------------------------------------------------------------------------------------


@query(_LEAVES + "SELECT k.key, count(*) AS uses, count(DISTINCT d.lang) AS langs FROM k JOIN documents d ON k.content_id = CAST(d.doc_id AS VARCHAR) WHERE level = 0 GROUP BY k.key HAVING count(*) > 1")
def join_chunk_owner(spark: SparkSession, d: str) -> DataFrame:
    """Shared chunks with the languages of the documents they are in."""
    owners = src.table(spark, d, "documents").select(F.col("doc_id").cast("string").alias("content_id"), "lang")
    out = _leaves(spark, d).join(owners.hint("merge"), "content_id").groupBy("key").agg(F.count("*").alias("uses"), F.countDistinct("lang").alias("langs")).where("uses > 1")
    return out.select(_text().alias("key"), "uses", "langs")


@query("SELECT r_name, count(*) AS orders, CAST(sum(octet_length(encode(" + o.ORDER_LINE + ")) + 1) AS BIGINT) AS bytes FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey GROUP BY r_name")
def join_region_snapshots(spark: SparkSession, d: str) -> DataFrame:
    """Bytes that each region's orders bring to a snapshot; nation and region are fixed small tables."""
    t = lambda n: src.table(spark, d, n)
    rows = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey"))
    rows = rows.join(F.broadcast(t("nation")), F.col("c_nationkey") == F.col("n_nationkey")).join(F.broadcast(t("region")), F.col("n_regionkey") == F.col("r_regionkey"))
    return rows.groupBy("r_name").agg(F.count("*").alias("orders"), F.sum(F.octet_length(F.encode(src.order_line(), "utf-8")).cast("long") + 1).alias("bytes"))


_TWO = o.with_(o.keyed(o.DOCUMENTS, SHORT, 1, "_a"), o.keyed(o.PASSAGES, SHORT, 1, "_b"))
_SIDES = _TWO.rstrip() + ", x AS (SELECT DISTINCT key, size FROM k_a), y AS (SELECT DISTINCT key, size FROM k_b)\n"


def _sides(spark: SparkSession, d: str) -> tuple[DataFrame, DataFrame]:
    a, b = (measures.distinct_nodes(tree.build(s, SHORT)) for s in (src.documents(spark, d), src.passages(spark, d)))
    return a, b


@query(_SIDES + "SELECT CASE WHEN x.key IS NULL THEN 'right' WHEN y.key IS NULL THEN 'left' ELSE 'both' END AS side, count(*) AS pairs, CAST(sum(coalesce(x.size, y.size) + 32) AS BIGINT) AS cost FROM x FULL JOIN y ON x.key = y.key GROUP BY 1")
def join_store_compare(spark: SparkSession, d: str) -> DataFrame:
    a, b = _sides(spark, d)
    both = a.withColumnRenamed("size", "sa").join(b.withColumnRenamed("size", "sb"), "key", "full")
    side = F.when(F.col("sa").isNull(), "right").when(F.col("sb").isNull(), "left").otherwise("both")
    return both.groupBy(side.alias("side")).agg(F.count("*").alias("pairs"), F.sum(F.coalesce("sa", "sb") + 32).alias("cost"))


@query(_SIDES + "SELECT 'new' AS kind, count(*) AS pairs FROM y WHERE key NOT IN (SELECT key FROM x) UNION ALL SELECT 'known', count(*) FROM y WHERE key IN (SELECT key FROM x)")
def join_new_chunks(spark: SparkSession, d: str) -> DataFrame:
    a, b = _sides(spark, d)
    count = lambda kind, how: b.join(a, "key", how).agg(F.count("*").alias("pairs")).select(F.lit(kind).alias("kind"), "pairs")
    return count("new", "left_anti").unionByName(count("known", "left_semi"))


@query(_KEYED + "SELECT content_id, level, s AS start_pos, ps AS parent_start FROM k WHERE ps >= 0")
def join_range_parent(spark: SparkSession, d: str) -> DataFrame:
    """Each node's parent by its range: equal content and level, then start within the parent's bytes."""
    nodes = tree.build(src.documents(spark, d), FIXED)
    up = nodes.select("content_id", (F.col("level") - 1).alias("level"), F.col("start_pos").alias("a"), F.col("end_pos").alias("b"))
    rows = nodes.select("content_id", "level", "start_pos").join(up, ["content_id", "level"]).where((F.col("start_pos") >= F.col("a")) & (F.col("start_pos") < F.col("b")))
    return rows.select("content_id", "level", "start_pos", F.col("a").alias("parent_start"))


@query("""WITH s AS (SELECT DISTINCT date_trunc('day', ts) AS day FROM events WHERE CAST(strftime(ts, '%d') AS INTEGER) IN (1, 8, 15, 22, 29))
SELECT e.event_id, strftime(s.day, '%Y-%m-%d') AS snapshot FROM events e ASOF LEFT JOIN s ON e.ts >= s.day""")
def join_asof_snapshot(spark: SparkSession, d: str) -> DataFrame:
    """Each event with the latest weekly snapshot at or before it: both sides in one order, the last snapshot carried on.

    The carry is within a month of the event, so no window holds all rows; a month begins with what came before it.
    """
    events = src.table(spark, d, "events").select("event_id", "ts")
    days = events.where(F.dayofmonth("ts").isin(1, 8, 15, 22, 29)).select(F.date_trunc("day", "ts").alias("day")).distinct()
    marks = days.select(F.lit(None).cast("long").alias("event_id"), F.col("day").alias("ts"), F.col("day").alias("mark"))
    rows = events.withColumn("mark", F.lit(None).cast("timestamp")).unionByName(marks).withColumn("m", F.date_trunc("month", "ts"))
    own = Window.partitionBy("m").orderBy("ts", F.col("event_id").asc_nulls_first()).rowsBetween(Window.unboundedPreceding, 0)
    months = rows.groupBy("m").agg(F.max("mark").alias("top"))
    before = months.withColumn("earlier", F.max("top").over(Window.orderBy("m").rowsBetween(Window.unboundedPreceding, -1)))  # a row a month
    out = rows.withColumn("last", F.last("mark", True).over(own)).where("event_id IS NOT NULL").join(F.broadcast(before.select("m", "earlier")), "m")
    return out.select("event_id", F.date_format(F.coalesce("last", "earlier"), "yyyy-MM-dd").alias("snapshot"))


@query("SELECT scheme, s, delta FROM (VALUES ('whole'), ('fixed'), ('cdc'), ('fixed_tree'), ('cdc_tree')) a(scheme), (VALUES (64), (128), (256), (512)) b(s), (VALUES (1), (16), (256)) c(delta)")
def param_grid(spark: SparkSession, d: str) -> DataFrame:
    """All cells of an experiment: a product of three short lists."""
    from ..params import SCHEMES

    col = lambda rows, ddl: spark.createDataFrame([(x,) for x in rows], ddl)
    return col(SCHEMES, "scheme string").crossJoin(col((64, 128, 256, 512), "s int")).crossJoin(col((1, 16, 256), "delta int"))


@query(_LEAVES + ", l AS (SELECT DISTINCT content_id, key FROM k WHERE level = 0), f AS (SELECT key, min(content_id) AS hub, count(*) AS n FROM l GROUP BY key HAVING count(*) > 1) SELECT hub AS a, content_id AS b, count(*) AS shared FROM l JOIN f USING (key) WHERE content_id <> hub GROUP BY hub, content_id")
def pairs_shared_chunks(spark: SparkSession, d: str) -> DataFrame:
    """Contents tied by shared chunks: each with the least content of the chunk, so a chunk of many contents makes no square of pairs."""
    own = _leaves(spark, d).select("content_id", "key").distinct()
    hubs = own.groupBy("key").agg(F.min("content_id").alias("a"), F.count("*").alias("n")).where("n > 1").drop("n")
    return own.join(hubs, "key").where("content_id <> a").groupBy("a", F.col("content_id").alias("b")).agg(F.count("*").alias("shared"))


@query(o.with_(o.fixed_spans(o.DOCUMENTS, SHORT, 1)) + "SELECT content_id, s AS start_pos, e AS end_pos FROM n WHERE level = 0")
def lateral_chunks(spark: SparkSession, d: str) -> DataFrame:
    src.documents(spark, d).where("octet_length(body) > 0").createOrReplaceTempView("_lateral_contents")
    return spark.sql("SELECT c.content_id, x.start_pos, least(x.start_pos + 256, c.n) AS end_pos FROM _lateral_contents c, LATERAL (SELECT explode(sequence(0L, c.n - 1, 256L)) AS start_pos) x")


# ---- aggregation --------------------------------------------------------------------------------


@query(_LEAVES + "SELECT count(*) AS chunks, count(DISTINCT key) AS distinct_chunks FROM k WHERE level = 0")
def distinct_chunks(spark: SparkSession, d: str) -> DataFrame:
    return _leaves(spark, d).agg(F.count("*").alias("chunks"), F.countDistinct("key").alias("distinct_chunks"))


@query(_LEAVES + "SELECT true AS near FROM (SELECT 1)")
def approx_distinct_chunks(spark: SparkSession, d: str) -> DataFrame:
    """Whether sketches come within 5 % of the exact number of distinct chunks."""
    e = _leaves(spark, d).agg(F.countDistinct("key").alias("x"), F.approx_count_distinct("key", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("key", 14)).alias("h"))
    return e.select(((F.abs(F.col("a") - F.col("x")) < 0.05 * F.col("x")) & (F.abs(F.col("h") - F.col("x")) < 0.05 * F.col("x"))).alias("near"))


_GROUPED = "SELECT {cols}, count(*) AS n, CAST(sum(octet_length(encode(text))) AS BIGINT) AS bytes{extra} FROM documents GROUP BY {how}"


def _bytes(spark: SparkSession, d: str) -> DataFrame:
    return src.table(spark, d, "documents").withColumn("b", F.octet_length(F.encode("text", "utf-8")).cast("long"))


@query(_GROUPED.format(cols="lang, source", extra="", how="ROLLUP (lang, source)"))
def cost_rollup(spark: SparkSession, d: str) -> DataFrame:
    return _bytes(spark, d).rollup("lang", "source").agg(F.count("*").alias("n"), F.sum("b").alias("bytes"))


@query(_GROUPED.format(cols="lang, source", extra="", how="CUBE (lang, source)"))
def cost_cube(spark: SparkSession, d: str) -> DataFrame:
    return _bytes(spark, d).cube("lang", "source").agg(F.count("*").alias("n"), F.sum("b").alias("bytes"))


@query(_GROUPED.format(cols="lang, source", extra=", CAST(grouping(lang) * 2 + grouping(source) AS BIGINT) AS g", how="GROUPING SETS ((lang), (source), ())"))
def cost_grouping_sets(spark: SparkSession, d: str) -> DataFrame:
    _bytes(spark, d).createOrReplaceTempView("_byte_rows")
    return spark.sql("SELECT lang, source, count(*) AS n, sum(b) AS bytes, grouping_id() AS g FROM _byte_rows GROUP BY GROUPING SETS ((lang), (source), ())")


@query("SELECT source, count(CASE WHEN lang = 'de' THEN 1 END) AS de, count(CASE WHEN lang = 'en' THEN 1 END) AS en, count(CASE WHEN lang = 'es' THEN 1 END) AS es, count(CASE WHEN lang = 'fr' THEN 1 END) AS fr FROM documents GROUP BY source")
def cost_pivot(spark: SparkSession, d: str) -> DataFrame:
    out = src.table(spark, d, "documents").groupBy("source").pivot("lang", ["de", "en", "es", "fr"]).count()
    return out.na.fill(0, ["de", "en", "es", "fr"])


@query("SELECT source, lang, count(*) AS n FROM documents WHERE lang IN ('de', 'en', 'es', 'fr') GROUP BY source, lang")
def cost_unpivot(spark: SparkSession, d: str) -> DataFrame:
    return cost_pivot(spark, d).unpivot("source", ["de", "en", "es", "fr"], "lang", "n").where("n > 0")


# ---- windows, order, sets -----------------------------------------------------------------------


@query(f"WITH c AS ({o.CONVERSATIONS}) SELECT content_id, octet_length(body) - lag(octet_length(body)) OVER w AS grown, lead(octet_length(body)) OVER w - octet_length(body) AS grows, octet_length(first_value(body) OVER w) AS first FROM c WINDOW w AS (PARTITION BY split_part(content_id, ':', 1) ORDER BY version)")
def version_growth(spark: SparkSession, d: str) -> DataFrame:
    own = Window.partitionBy(F.split_part("content_id", F.lit(":"), F.lit(1))).orderBy("version")
    return src.conversation_versions(spark, d).select("content_id", (F.col("n") - F.lag("n").over(own)).alias("grown"), (F.lead("n").over(own) - F.col("n")).alias("grows"), F.first("n").over(own).alias("first"))


@query("SELECT doc_id, row_number() OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS rn, rank() OVER (PARTITION BY lang ORDER BY n_chars) AS rk, dense_rank() OVER (PARTITION BY lang ORDER BY n_chars) AS dr, ntile(4) OVER (PARTITION BY lang ORDER BY n_chars, doc_id) AS q, percent_rank() OVER (PARTITION BY lang ORDER BY n_chars) AS pr FROM documents")
def rank_contents(spark: SparkSession, d: str) -> DataFrame:
    tied, strict = Window.partitionBy("lang").orderBy("n_chars"), Window.partitionBy("lang").orderBy("n_chars", "doc_id")
    return src.table(spark, d, "documents").select("doc_id", F.row_number().over(strict).alias("rn"), F.rank().over(tied).alias("rk"), F.dense_rank().over(tied).alias("dr"), F.ntile(4).over(strict).alias("q"), F.percent_rank().over(tied).alias("pr"))


@query("SELECT source, doc_id, CAST(sum(octet_length(encode(text))) OVER (PARTITION BY source ORDER BY doc_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS BIGINT) AS running, CAST(sum(octet_length(encode(text))) OVER (PARTITION BY source ORDER BY doc_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW) AS BIGINT) AS three FROM documents")
def running_cost(spark: SparkSession, d: str) -> DataFrame:
    own = Window.partitionBy("source").orderBy("doc_id")
    return _bytes(spark, d).select("source", "doc_id", F.sum("b").over(own.rowsBetween(Window.unboundedPreceding, 0)).alias("running"), F.sum("b").over(own.rowsBetween(-2, 0)).alias("three"))


@query("SELECT CAST(ts AS DATE) AS day, event_type, count(*) AS n, CAST(sum(count(*)) OVER (PARTITION BY event_type ORDER BY CAST(ts AS DATE) RANGE BETWEEN INTERVAL 2 DAY PRECEDING AND CURRENT ROW) AS BIGINT) AS three_days FROM events GROUP BY CAST(ts AS DATE), event_type")
def running_days(spark: SparkSession, d: str) -> DataFrame:
    per = src.table(spark, d, "events").groupBy(F.to_date("ts").alias("day"), "event_type").agg(F.count("*").alias("n"))
    own = Window.partitionBy("event_type").orderBy(F.unix_date("day")).rangeBetween(-2, 0)
    return per.withColumn("three_days", F.sum("n").over(own))


@query(_LEAVES + "SELECT key, count(*) AS uses FROM k WHERE level = 0 GROUP BY key ORDER BY uses DESC, key LIMIT 20")
def topk_shared_chunks(spark: SparkSession, d: str) -> DataFrame:
    """The twenty chunks with the most uses."""
    return _leaves(spark, d).groupBy(_text().alias("key")).agg(F.count("*").alias("uses")).orderBy(F.desc("uses"), "key").limit(20)


@query(_SIDES + "SELECT CAST(sum(size + 32) AS BIGINT) AS cost FROM (SELECT * FROM x UNION SELECT * FROM y)")
def store_union_cost(spark: SparkSession, d: str) -> DataFrame:
    a, b = _sides(spark, d)
    return a.union(b).distinct().agg(F.sum(F.col("size") + 32).alias("cost"))


@query(_SIDES + "SELECT key FROM x INTERSECT SELECT key FROM y")
def store_intersect(spark: SparkSession, d: str) -> DataFrame:
    a, b = _sides(spark, d)
    return a.select(_text().alias("key")).intersect(b.select(_text().alias("key")))


@query(_SIDES + "SELECT key FROM y EXCEPT SELECT key FROM x")
def store_except(spark: SparkSession, d: str) -> DataFrame:
    a, b = _sides(spark, d)
    return b.select(_text().alias("key")).subtract(a.select(_text().alias("key")))


@query("SELECT doc_id FROM documents d WHERE n_chars > (SELECT avg(n_chars) FROM documents) AND EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.quality = 1) AND lang IN (SELECT lang FROM documents GROUP BY lang HAVING count(*) > 10)")
def ops_subqueries(spark: SparkSession, d: str) -> DataFrame:
    src.views(spark, d)
    return spark.sql("SELECT doc_id FROM documents d WHERE n_chars > (SELECT avg(n_chars) FROM documents) AND EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id AND l.quality = 1) AND lang IN (SELECT lang FROM documents GROUP BY lang HAVING count(*) > 10)")


@query("SELECT n_name, count(*) AS customers, CAST(sum(CAST(c_acctbal AS DECIMAL(18,2))) AS DECIMAL(28,2)) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")
def sql_surface(spark: SparkSession, d: str) -> DataFrame:
    """All tables as views, asked by SQL."""
    src.views(spark, d)
    return spark.sql("SELECT n_name, count(*) AS customers, CAST(sum(CAST(c_acctbal AS DECIMAL(18,2))) AS DECIMAL(28,2)) AS balance FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY n_name")


@query(_LEAVES + "SELECT count(DISTINCT key) AS sampled, CAST(sum(size) AS BIGINT) AS bytes FROM (SELECT key, any_value(size) AS size FROM k WHERE level = 0 AND (CAST('0x' || key[1:4] AS BIGINT) % 64) < 16 GROUP BY key)")
def estimate_ratio_by_bucket(spark: SparkSession, d: str) -> DataFrame:
    """A sampling operator: a quarter of the key space stands for the store, with every copy of its chunks."""
    part = _leaves(spark, d).where(kvs.bucket_expr(F.col("key")) < 16)
    return measures.distinct_nodes(part).agg(F.count("*").alias("sampled"), F.sum("size").alias("bytes"))


# ---- windows of time ----------------------------------------------------------------------------

_ROWS = "count(*) AS events, CAST(sum(octet_length(encode(props))) AS BIGINT) AS bytes_in"


@query(f"SELECT date_trunc('day', ts) AS window_start, event_type, {_ROWS} FROM events GROUP BY date_trunc('day', ts), event_type")
def events_tumbling(spark: SparkSession, d: str) -> DataFrame:
    return ingest.tumbling(src.table(spark, d, "events"))


@query(f"SELECT window_start, event_type, {_ROWS} FROM (SELECT date_trunc('day', ts) - INTERVAL (k) DAY AS window_start, event_type, props FROM events, range(2) r(k)) GROUP BY window_start, event_type")
def events_sliding(spark: SparkSession, d: str) -> DataFrame:
    return ingest.sliding(src.table(spark, d, "events"))


@query(f"""WITH f AS (SELECT user_id, ts, props, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events),
g AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS session FROM f)
SELECT user_id, min(ts) AS session_start, {_ROWS} FROM g GROUP BY user_id, session""")
def events_session(spark: SparkSession, d: str) -> DataFrame:
    return ingest.sessions(src.table(spark, d, "events"))


@query(f"SELECT content_id, sha256(body) AS digest FROM ({o.PASSAGES})")
def stream_insert_parity(spark: SparkSession, d: str) -> DataFrame:
    """Passages inserted by a stream and fetched from what it stored."""
    import uuid

    from ..plans.lineage import shared_dir

    path = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"
    rows = src.contents(ingest.read_table(spark, d, "benchmark"), F.col("item_id"), F.lit("benchmark"), F.col("item_id"), F.encode("text", "utf-8"))
    ingest.insert_stream(rows, f"{path}/store", CUT.with_(scheme="cdc_tree"), f"{path}/progress").awaitTermination()
    roots = spark.read.parquet(f"{path}/store/roots").dropDuplicates(["content_id"])
    got = store.fetch_contents(roots, kvs.read(spark, f"{path}/store/pairs"), CUT)
    return got.select("content_id", F.sha2("body", 256).alias("digest"))
