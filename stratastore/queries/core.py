"""Trees, chunkers, keys, the store and its protection."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import crypto
from ..operators import chunkers, kvs, measures, security, store, tree
from ..params import StoreParams
from ..plans import workloads
from ..sources import contents as src
from . import oracle as o
from . import query

FIXED = StoreParams(chunk=256, scheme="fixed_tree")
CDC = StoreParams(chunk=256, scheme="cdc_tree", ring="m31")
CUT = StoreParams(chunk=256, scheme="cdc", ring="m31")
SIZES = (64, 128, 256)
#: Levels that the SQL spells out at S = 256: contents up to 8 MiB.
TOP = 5


def hexed(df: DataFrame, *columns: str) -> DataFrame:
    return df.withColumns({c: F.lower(F.hex(c)) for c in columns})


def _union(frames: list[DataFrame]) -> DataFrame:
    return reduce(DataFrame.unionByName, frames)


# ---- heights and cuts ---------------------------------------------------------------------------


@query(" UNION ALL ".join(f"SELECT content_id, {s} AS s, {o.height('octet_length(body)', StoreParams(chunk=s), 40)} AS height FROM ({o.DOCUMENTS})" for s in SIZES))
def tree_height(spark: SparkSession, d: str) -> DataFrame:
    docs = src.documents(spark, d).where("body IS NOT NULL")
    return _union([docs.select("content_id", F.lit(s).alias("s"), tree.height_expr(F.col("n"), StoreParams(chunk=s)).alias("height")) for s in SIZES])


_HEIGHTS = " UNION ALL ".join(f"SELECT {s} AS s, {o.height('octet_length(body)', StoreParams(chunk=s), 40)} AS height FROM ({o.DOCUMENTS})" for s in SIZES)


@query(f"SELECT s, CAST(level AS INTEGER) AS level, count(*) AS contents, s * pow(s / 32.0, level) AS length FROM ({_HEIGHTS}), range(41) b(level) WHERE level <= height GROUP BY s, level")
def level_lengths(spark: SparkSession, d: str) -> DataFrame:
    """Expected node length at each level of the documents' trees, and how many documents have the level."""
    docs, parts = src.documents(spark, d).where("body IS NOT NULL"), []
    for s in SIZES:
        p = StoreParams(chunk=s)
        heights = docs.select(tree.height_expr(F.col("n"), p).alias("height")).groupBy("height").agg(F.count("*").alias("c"))
        levels = heights.select(F.explode(F.sequence(F.lit(0), F.col("height"))).alias("level"), "c").groupBy("level").agg(F.sum("c").alias("contents"))
        lengths = F.array(*[F.lit(float(x)) for _, x in tree.level_lengths(p, 40)])
        parts.append(levels.select(F.lit(s).alias("s"), "level", "contents", F.get(lengths, F.col("level")).alias("length")))
    return _union(parts)


@query(f"SELECT content_id, octet_length(body) AS n, sha256(body) AS key FROM ({o.DOCUMENTS})")
def chunks_whole(spark: SparkSession, d: str) -> DataFrame:
    out = chunkers.chunk(src.documents(spark, d), "whole", FIXED)
    return hexed(out.select("content_id", F.col("end_pos").alias("n"), crypto.digest_expr(F.col("value")).alias("key")), "key")


@query(o.with_(o.fixed_spans(o.DOCUMENTS, StoreParams(chunk=256, scheme="fixed"), 1)) + "SELECT n.content_id, row_number() OVER (PARTITION BY n.content_id ORDER BY s) - 1 AS seq, s AS start_pos, e AS end_pos, sha256(body[s + 1:e]) AS key FROM n JOIN c USING (content_id) WHERE level = 0")
def chunks_fixed(spark: SparkSession, d: str) -> DataFrame:
    out = chunkers.chunk(src.documents(spark, d), "fixed", StoreParams(chunk=256, scheme="fixed"))
    return hexed(out.withColumn("key", crypto.digest_expr(F.col("value"))), "key").drop("value")


_LINES = f"""WITH l AS (SELECT content_id, string_split(decode(body), chr(10)) AS parts FROM ({o.DOCUMENTS}) WHERE octet_length(body) > 0),
q AS (SELECT content_id, i - 1 AS seq, parts[i] || CASE WHEN i < len(parts) THEN chr(10) ELSE '' END AS part FROM l, unnest(range(1, len(parts) + 1)) u(i))
SELECT content_id, seq, CAST(sum(octet_length(encode(part))) OVER (PARTITION BY content_id ORDER BY seq) AS BIGINT) AS end_pos, sha256(encode(part)) AS key FROM q WHERE part <> ''"""


@query(_LINES)
def chunks_lines(spark: SparkSession, d: str) -> DataFrame:
    out = chunkers.chunk(src.documents(spark, d), "lines", FIXED)
    return hexed(out.select("content_id", "seq", "end_pos", crypto.digest_expr(F.col("value")).alias("key")), "key")


_CDC = o.with_(o.cdc_spans(o.DOCUMENTS, CUT, 1)) + "SELECT content_id, row_number() OVER (PARTITION BY content_id ORDER BY s) - 1 AS seq, s AS start_pos, e AS end_pos FROM n WHERE level = 0"


@query(_CDC)
def chunks_cdc(spark: SparkSession, d: str) -> DataFrame:
    return chunkers.chunk(src.documents(spark, d), "cdc", CUT).drop("value")


@query(_CDC)
def chunks_cdc_sql(spark: SparkSession, d: str) -> DataFrame:
    return chunkers.chunk(src.documents(spark, d), "cdc_sql", CUT).drop("value")


_FIXED_SPANS = o.with_(o.fixed_spans(o.DOCUMENTS, FIXED, TOP))


@query(_FIXED_SPANS + "SELECT content_id, level, s AS start_pos, e AS end_pos FROM n")
def tree_nodes_levelwise(spark: SparkSession, d: str) -> DataFrame:
    return tree.build_levelwise(src.documents(spark, d), FIXED)


_FIXED_KEYED = o.with_(o.keyed(o.DOCUMENTS, FIXED, TOP))
_CDC_KEYED = o.with_(o.keyed(o.DOCUMENTS, CDC, TOP))


@query(_FIXED_KEYED + "SELECT content_id, level, s AS start_pos, e AS end_pos, children, size, key FROM k")
def fixed_tree_nodes(spark: SparkSession, d: str) -> DataFrame:
    return hexed(tree.build(src.documents(spark, d), FIXED).select("content_id", "level", "start_pos", "end_pos", "children", "size", "key"), "key")


@query(_FIXED_KEYED + "SELECT content_id, level, s AS start_pos, e AS end_pos, ps AS parent_start, size, key FROM k")
def fixed_tree_nodes_sql(spark: SparkSession, d: str) -> DataFrame:
    docs = src.documents(spark, d)
    return hexed(tree.key_nodes_sql(docs, tree.fixed_tree_sql(docs, FIXED), FIXED), "key")


@query(_CDC_KEYED + "SELECT content_id, level, s AS start_pos, e AS end_pos, children, size, key FROM k", "cdc_tree_nodes")
def cdc_tree_nodes(spark: SparkSession, d: str) -> DataFrame:
    return hexed(tree.build(src.documents(spark, d), CDC).select("content_id", "level", "start_pos", "end_pos", "children", "size", "key"), "key")


@query(o.with_(o.cdc_spans(o.DOCUMENTS, CDC, TOP)) + "SELECT content_id, level, s AS start_pos, e AS end_pos FROM n", "tree_nodes")
def tree_nodes(spark: SparkSession, d: str) -> DataFrame:
    return tree.build_levelwise(src.documents(spark, d), CDC)


@query(_FIXED_KEYED + "SELECT content_id, level AS height, key FROM k WHERE ps = -1")
def tree_root_keys(spark: SparkSession, d: str) -> DataFrame:
    docs = src.documents(spark, d)
    keyed = tree.key_nodes_sql(docs, tree.fixed_tree_sql(docs, FIXED), FIXED)
    return hexed(keyed.where("parent_start = -1").select("content_id", F.col("level").alias("height"), "key"), "key")


def _fanout_sql(levels: int, g: int) -> str:
    out = [o.keyed(o.DOCUMENTS, CUT.with_(protect="hash"), 1, "_l"), "f0 AS (SELECT content_id, row_number() OVER (PARTITION BY content_id ORDER BY s) - 1 AS seq, key, size FROM k_l WHERE level = 0)"]
    for k in range(1, levels + 1):
        out.append(f"f{k} AS (SELECT content_id, seq // {g} AS seq, sha256(unhex(string_agg(key, '' ORDER BY seq))) AS key, count(*) * 32 AS size FROM f{k - 1} WHERE content_id IN (SELECT content_id FROM f{k - 1} GROUP BY content_id HAVING max(seq) > 0) GROUP BY content_id, seq // {g})")
    return o.with_(*out) + " UNION ALL ".join(f"SELECT content_id, {k} AS level, seq, size, key FROM f{k}" for k in range(levels + 1))


@query(_fanout_sql(5, 8))
def fanout_tree_nodes(spark: SparkSession, d: str) -> DataFrame:
    leaves = chunkers.cdc(src.documents(spark, d), CUT).select("content_id", "seq", crypto.digest_expr(F.col("value")).alias("key"), F.octet_length("value").cast("long").alias("size"))
    return hexed(tree.build_fanout(leaves, 8, FIXED.with_(protect="hash")), "key").select("content_id", "level", "seq", "size", "key")


_HELD = {"whole": 0, "fixed": 1, "cdc": 1}


def _equivalence_sql() -> str:
    params = [StoreParams(chunk=256, scheme=x, ring="m31") for x in _HELD]
    ctes, g = o.grid(o.DOCUMENTS, params, {256: 1})
    return ctes + f"SELECT scheme, count(*) AS pairs, CAST(sum(size + 32) AS BIGINT) AS cost FROM (SELECT DISTINCT scheme, key, size FROM {g}) GROUP BY scheme"


@query(_equivalence_sql())
def scheme_equivalence(spark: SparkSession, d: str) -> DataFrame:
    """Trees held to height 0 or 1 are the single-level schemes."""
    docs = src.documents(spark, d)
    rows = [measures.storage_cost(tree.build(docs, StoreParams(chunk=256, scheme="cdc_tree" if x == "cdc" else "fixed_tree", ring="m31"), height=h)).select(F.lit(x).alias("scheme"), "pairs", "cost") for x, h in _HELD.items()]
    return _union(rows)


# ---- the store ----------------------------------------------------------------------------------


@query(_CDC_KEYED + "SELECT content_id, key, level AS height, e AS n FROM k WHERE ps = -1")
def insert_roots(spark: SparkSession, d: str) -> DataFrame:
    roots, _ = store.insert_contents(src.documents(spark, d), kvs.empty(spark), CDC)
    return hexed(roots, "key")


def _two_stores(p: StoreParams, select: str) -> str:
    return o.with_(o.keyed(o.DOCUMENTS, p, TOP, "_a"), o.keyed(o.PASSAGES, p, TOP, "_b")) + select


@query(_two_stores(CDC, "SELECT DISTINCT key, size FROM k_b WHERE key NOT IN (SELECT key FROM k_a)"))
def insert_new_pairs(spark: SparkSession, d: str) -> DataFrame:
    """What the passages add to a store that holds the documents."""
    _, have = store.insert_contents(src.documents(spark, d), kvs.empty(spark), CDC)
    _, new = store.insert_contents(src.passages(spark, d), have, CDC)
    return hexed(new.select("key", F.octet_length("value").cast("long").alias("size")), "key")


@query(_two_stores(FIXED, "SELECT b.content_id, b.key, max(a.size) AS size FROM (SELECT content_id, key FROM k_b WHERE ps = -1) b LEFT JOIN k_a a ON a.key = b.key GROUP BY b.content_id, b.key"))
def kvs_put_get(spark: SparkSession, d: str) -> DataFrame:
    """Passages' root keys asked of a store of documents."""
    have = kvs.put(kvs.empty(spark), store.pairs_of(tree.build(src.documents(spark, d), FIXED, True), FIXED))
    asked = store.roots_of(tree.build(src.passages(spark, d), FIXED)).select("content_id", "key")
    return hexed(kvs.get(have, asked).select("content_id", "key", F.octet_length("value").cast("long").alias("size")), "key")


@query(_two_stores(FIXED, "SELECT count(*) AS pairs, CAST(sum(size) AS BIGINT) AS bytes FROM (SELECT DISTINCT key, size FROM (SELECT key, size FROM k_a UNION ALL SELECT key, size FROM k_b))"))
def kvs_put_absent(spark: SparkSession, d: str) -> DataFrame:
    """Documents put once, documents and passages put again."""
    first = store.pairs_of(tree.build(src.documents(spark, d), FIXED, True), FIXED)
    again = kvs.put_absent(kvs.put(kvs.empty(spark), first), first.unionByName(store.pairs_of(tree.build(src.passages(spark, d), FIXED, True), FIXED)))
    return again.agg(F.count("*").alias("pairs"), F.sum(F.octet_length("value")).alias("bytes"))


_TRIP = f"SELECT content_id, sha256(body) AS digest, 'ok' AS status FROM ({o.DOCUMENTS})"


def _trip(got: DataFrame) -> DataFrame:
    return got.select("content_id", F.sha2("body", 256).alias("digest"), "status")


@query(_TRIP)
def roundtrip_documents(spark: SparkSession, d: str) -> DataFrame:
    p = CDC.with_(protect="siv")
    roots, pairs = store.insert_contents(src.documents(spark, d), kvs.empty(spark), p)
    return _trip(store.fetch_contents(roots, pairs, p))


@query(_TRIP)
def roundtrip_recursive(spark: SparkSession, d: str) -> DataFrame:
    roots, pairs = store.insert_contents(src.documents(spark, d), kvs.empty(spark), CDC)
    return _trip(store.fetch_recursive(roots, pairs, CDC))


def _round_trip_of(name: str, sql: str, source) -> None:
    @query(f"SELECT content_id, sha256(body) AS digest, 'ok' AS status FROM ({sql})", f"roundtrip_{name}")
    def trip(spark: SparkSession, d: str) -> DataFrame:
        roots, pairs = store.insert_contents(source(spark, d), kvs.empty(spark), CDC)
        return _trip(store.fetch_contents(roots, pairs, CDC))


for _n, _s, _f in (("pages", o.PAGES, src.pages), ("conversations", o.CONVERSATIONS, src.conversation_versions), ("embeddings", o.EMBEDDINGS, src.embedding_blobs)):
    _round_trip_of(_n, _s, _f)


@query(f"SELECT content_id, sha256(body) AS digest, 'ok' AS status FROM ({o.ORDERS})")
def roundtrip_orders(spark: SparkSession, d: str) -> DataFrame:
    """Snapshots go in and come out in pieces: no snapshot is one value, and the store is made once."""
    roots, pairs = workloads.insert_history(src.order_history(spark, d), "orders", CDC)
    return store.fetch_digests(roots, pairs, CDC)


_REFS = """
, parents AS (SELECT key AS parent, min(content_id || ':' || lpad(CAST(level AS VARCHAR), 2, '0') || ':' || lpad(CAST(s AS VARCHAR), 12, '0')) AS own FROM k WHERE level > 0 GROUP BY key),
lists AS (SELECT c.key FROM k c JOIN k u ON c.content_id = u.content_id AND c.level + 1 = u.level AND c.ps = u.s
  JOIN parents ON parents.parent = u.key AND parents.own = u.content_id || ':' || lpad(CAST(u.level AS VARCHAR), 2, '0') || ':' || lpad(CAST(u.s AS VARCHAR), 12, '0'))
SELECT key, count(*) AS refs FROM (SELECT key FROM lists UNION ALL SELECT key FROM k WHERE ps = -1) GROUP BY key"""


@query(_FIXED_KEYED.rstrip() + _REFS)
def refcounts(spark: SparkSession, d: str) -> DataFrame:
    nodes = tree.build(src.documents(spark, d), FIXED)
    return hexed(store.refcounts(nodes, store.roots_of(nodes)), "key")


_KEPT = _FIXED_KEYED + "SELECT key, size FROM k JOIN documents d ON k.content_id = CAST(d.doc_id AS VARCHAR) WHERE d.lang <> 'fr' GROUP BY key, size"


def _deleted(spark: SparkSession, d: str, mode: str) -> DataFrame:
    roots, pairs = store.insert_contents(src.documents(spark, d), kvs.empty(spark), FIXED)
    gone = src.table(spark, d, "documents").where("lang = 'fr'").select(F.col("doc_id").cast("string").alias("content_id"))
    _, left = store.delete_contents(roots, pairs, gone, FIXED, mode)
    return hexed(left.select("key", F.octet_length("value").cast("long").alias("size")), "key")


@query(_KEPT)
def gc_sweep(spark: SparkSession, d: str) -> DataFrame:
    """The store after all French documents were deleted, by sweeping."""
    return _deleted(spark, d, "gc")


@query(_KEPT)
def delete_refcount(spark: SparkSession, d: str) -> DataFrame:
    """The same by reference counts."""
    return _deleted(spark, d, "refcount")


@query(f"SELECT content_id, lower(hex(body[101:400])) AS part FROM ({o.DOCUMENTS}) WHERE octet_length(body) > 100")
def read_range(spark: SparkSession, d: str) -> DataFrame:
    docs = src.documents(spark, d)
    nodes, (_, pairs) = tree.build(docs, CDC), store.insert_contents(docs, kvs.empty(spark), CDC)
    return hexed(store.read_range(nodes, pairs, CDC, 100, 300), "part")


_OVER = o.with_(o.keyed(o.DOCUMENTS, FIXED, TOP, "_a"), o.keyed("SELECT content_id, version, CASE WHEN octet_length(body) >= 4 THEN body[1:0] || unhex('00112233') || body[5:] ELSE unhex('00112233') END AS body FROM (" + o.DOCUMENTS + ")", FIXED, TOP, "_b"))


@query(_OVER + "SELECT count(*) AS pairs, CAST(sum(size + 32) AS BIGINT) AS cost FROM (SELECT DISTINCT key, size FROM k_b WHERE key NOT IN (SELECT key FROM k_a))")
def overwrite_range(spark: SparkSession, d: str) -> DataFrame:
    """What it adds to overwrite the first four bytes of every document."""
    docs = src.documents(spark, d)
    _, pairs = store.insert_contents(docs, kvs.empty(spark), FIXED)
    _, new = store.overwrite_range(docs, pairs, FIXED, 0, bytes.fromhex("00112233"))
    return new.agg(F.count("*").alias("pairs"), F.sum(F.octet_length("value").cast("long") + 32).alias("cost"))


@query(_two_stores(CDC, "SELECT level, count(*) AS new_nodes, CAST(sum(size + 32) AS BIGINT) AS new_bytes FROM (SELECT key, size, min(level) AS level FROM k_b WHERE key NOT IN (SELECT key FROM k_a) GROUP BY key, size) GROUP BY level"))
def tree_diff_levels(spark: SparkSession, d: str) -> DataFrame:
    return tree.diff(tree.build(src.documents(spark, d), CDC), tree.build(src.passages(spark, d), CDC))


# ---- protection ---------------------------------------------------------------------------------


@query(f"SELECT content_id, sha256(body) AS key FROM ({o.DOCUMENTS})")
def keys_hash(spark: SparkSession, d: str) -> DataFrame:
    return hexed(src.documents(spark, d).select("content_id", crypto.tag_expr(F.col("body"), FIXED.with_(protect="hash")).alias("key")), "key")


@query(f"SELECT content_id, {o.tag('body', FIXED)} AS key FROM ({o.DOCUMENTS})")
def keys_mac(spark: SparkSession, d: str) -> DataFrame:
    return hexed(src.documents(spark, d).select("content_id", crypto.tag_expr(F.col("body"), FIXED).alias("key")), "key")


@query(f"SELECT content_id, octet_length(body) AS sealed, octet_length(body) < 8 AS like_plain, true AS opened FROM ({o.DOCUMENTS})")
def siv_roundtrip(spark: SparkSession, d: str) -> DataFrame:
    p = FIXED.with_(protect="siv")
    rows = src.documents(spark, d).withColumn("tag", crypto.mac_expr(F.col("body"), p)).withColumn("c", crypto.seal_expr(F.col("body"), F.col("tag"), p))
    same = F.col("c") == F.col("body")
    return rows.select("content_id", F.octet_length("c").cast("long").alias("sealed"), (same | (F.octet_length("body") < 8)).alias("like_plain"), crypto.opened_expr(F.col("c"), F.col("tag"), p).eqNullSafe(F.col("body")).alias("opened"))


@query(f"SELECT count(*) AS pairs, CAST(sum(octet_length(body)) AS BIGINT) AS plain, CAST(sum(octet_length(body) + 28) AS BIGINT) AS stored FROM ({o.DOCUMENTS})")
def aead_overhead(spark: SparkSession, d: str) -> DataFrame:
    values = src.documents(spark, d).select(F.col("body").alias("value"))
    stored = crypto.compose(values, "aead_random", FIXED)
    return values.agg(F.count("*").alias("pairs"), F.sum(F.octet_length("value")).alias("plain")).crossJoin(stored.agg(F.sum(F.octet_length("value")).alias("stored")))


def _composition(mode: str, name: str, distinct: str) -> None:
    @query(f"SELECT count(*) AS contents, {distinct} AS keys FROM ({o.DOCUMENTS})", name)
    def compose(spark: SparkSession, d: str) -> DataFrame:
        out = crypto.compose(src.documents(spark, d).select(F.col("body").alias("value")), mode, FIXED)
        return out.agg(F.count("*").alias("contents"), F.countDistinct("key").alias("keys"))


_composition("encrypt_then_mac", "compose_etm_dedup", "count(*)")
_composition("mac_then_encrypt", "compose_mte_dedup", "count(*)")
_composition("encrypt_and_mac", "compose_eam_dedup", "count(DISTINCT body)")
_composition("whole_deterministic", "compose_whole_det", "count(DISTINCT body)")


@query("""SELECT kind, (SELECT count(*) FROM documents WHERE text IS NOT NULL) AS contents, 0 AS wins FROM (VALUES ('flip'), ('swap'), ('truncate'), ('replace'), ('delete'), ('rollback')) t(kind)""")
def tamper_detected(spark: SparkSession, d: str) -> DataFrame:
    """No forged store gives other bytes than were inserted."""
    return security.authenticity_game(src.documents(spark, d), FIXED.with_(protect="siv")).select("kind", "contents", "wins")


@query()
def tamper_outcomes(spark: SparkSession, d: str) -> DataFrame:
    return security.authenticity_game(src.documents(spark, d), CDC.with_(protect="siv"))


_PROFILE = """
, first AS (SELECT key, min({'c': content_id, 'l': level, 'q': seq}) AS f FROM kk GROUP BY key)
SELECT content_id, level, seq, s AS start_pos, e AS end_pos, size, sha256(f.c || ':' || CAST(f.l AS VARCHAR) || ':' || CAST(f.q AS VARCHAR)) AS same FROM kk JOIN first USING (key)"""
_KK = _FIXED_KEYED.rstrip() + ", kk AS (SELECT *, row_number() OVER (PARTITION BY content_id, level ORDER BY s) - 1 AS seq FROM k)"


@query(_KK + _PROFILE)
def leakage_profile(spark: SparkSession, d: str) -> DataFrame:
    return security.leakage_profile(tree.build(src.documents(spark, d), FIXED)).drop("parent_seq")


@query(_FIXED_KEYED + "SELECT size, members, count(*) AS classes FROM (SELECT key, size, count(*) AS members FROM k GROUP BY key, size) GROUP BY size, members")
def abstract_tree(spark: SparkSession, d: str) -> DataFrame:
    """Equality pattern of a made-up store: the same as the real one's."""
    fake = security.abstract_tree(security.leakage_profile(tree.build(src.documents(spark, d), FIXED)))
    checked = fake.withColumn("size", F.octet_length("value").cast("long"))
    return security.equality_pattern(checked)


def _trace_check(which: str) -> None:
    @query(f"SELECT '{which}' AS trace, 0 AS only_real, 0 AS only_simulated", f"trace_{which}")
    def check(spark: SparkSession, d: str) -> DataFrame:
        nodes = tree.build(src.documents(spark, d), CDC)
        trace = security.trace_insert if which == "insert" else security.trace_fetch
        real = security.trace_shape(trace(nodes, "key"))
        fake = security.trace_shape(trace(security.leakage_profile(nodes), "same"))
        a, b = real.exceptAll(fake), fake.exceptAll(real)
        return a.agg(F.count("*").alias("only_real")).crossJoin(b.agg(F.count("*").alias("only_simulated"))).select(F.lit(which).alias("trace"), "only_real", "only_simulated")


_trace_check("insert")
_trace_check("fetch")


def _leak_sql() -> str:
    params = [StoreParams(chunk=256, scheme=x, ring="m31") for x in ("whole", "fixed", "cdc", "fixed_tree", "cdc_tree")]
    ctes, g = o.grid(o.DOCUMENTS, params, {256: TOP})
    return ctes + f"SELECT scheme, s, count(*) AS nodes, count(DISTINCT key) AS classes, count(*) - count(DISTINCT key) AS shared FROM {g} GROUP BY scheme, s"


@query(_leak_sql())
def leakage_by_scheme(spark: SparkSession, d: str) -> DataFrame:
    params = [StoreParams(chunk=256, scheme=x, ring="m31") for x in ("whole", "fixed", "cdc", "fixed_tree", "cdc_tree")]
    return security.leakage_by_scheme(tree.build_grid(src.documents(spark, d), params))
