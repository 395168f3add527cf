"""Insertion, retrieval, deletion, and ranges of contents in a store."""

from __future__ import annotations

import hashlib
import warnings
from functools import reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import crypto
from ..params import TEST_KEY, StoreParams
from ..plans.lineage import cut
from ..sources.contents import overwrite
from . import kvs as kv
from . import tree

REF = 32


def roots_of(nodes: DataFrame) -> DataFrame:
    """(content_id, key, height, n) from node rows: the content keys."""
    return nodes.where("parent_seq = -1").select("content_id", "key", F.col("level").alias("height"), F.col("end_pos").alias("n"))


def pairs_of(nodes: DataFrame, p: StoreParams) -> DataFrame:
    """Distinct pairs as stored: sealed only after repeated keys are gone."""
    one = nodes.select("key", "value").dropDuplicates(["key"])
    return one.select("key", crypto.seal_expr(F.col("value"), F.col("key"), p).alias("value"))


def insert_contents(contents: DataFrame, kvs: DataFrame, p: StoreParams) -> tuple[DataFrame, DataFrame]:
    """(roots, pairs that were not stored).

    Keys and sizes decide what is new, 40 bytes a node; only then are values made, where the contents lie, and
    only those of new keys go on. While the new keys are few, as in a backup of what is mostly stored, Spark's
    own size check broadcasts them and no old value is moved at all.
    """
    if p.protect != "hash" and p.key == TEST_KEY:
        warnings.warn("the store's key is the public test key; init_store draws a secret one", stacklevel=2)
    dealt = tree.spread(contents)
    new = cut(new_keys(dealt, kvs, p).select("key"))
    nodes = tree.build(dealt, p, with_values=True)
    fresh = nodes.select("key", "value").join(new, "key", "left_semi").dropDuplicates(["key"])
    sealed = fresh.select("key", crypto.seal_expr(F.col("value"), F.col("key"), p).alias("value"), kv.bucket_expr(F.col("key")).alias("bucket"))
    return roots_of(tree.build(dealt, p)), sealed


def new_keys(contents: DataFrame, kvs: DataFrame, p: StoreParams) -> DataFrame:
    """(key, size) of what an insertion would add: 40 bytes a node through the exchange."""
    nodes = tree.build(contents, p).select("key", "size").groupBy("key").agg(F.first("size").alias("size"))
    return nodes.withColumn("bucket", kv.bucket_expr(F.col("key"))).join(kvs.select("bucket", "key"), ["bucket", "key"], "left_anti").select("key", "size")


def _children(value: Column) -> Column:
    return F.when(F.octet_length(value) > 0, F.transform(F.sequence(F.lit(1), F.octet_length(value), F.lit(REF)), lambda i: F.substring(value, i, F.lit(REF)))).otherwise(F.array().cast("array<binary>"))


def fetch_nodes(roots: DataFrame, kvs: DataFrame, p: StoreParams, tallest: int | None = None) -> DataFrame:
    """(content_id, path, level, key, value, ok) of all nodes reached from the roots, verified one by one."""
    if tallest is None:
        tallest = roots.agg(F.max("height")).first()[0] or 0
    front = roots.select("content_id", F.array().cast("array<int>").alias("path"), F.col("height").alias("level"), "key")
    seen = []
    for turn in range(tallest + 1):
        # each distinct key is asked for, opened and verified once, however many places it has
        asked = kv.get(kvs, front.select("key").distinct()).withColumn("value", crypto.opened_expr(F.col("value"), F.col("key"), p))
        got = front.join(asked, "key", "left").select("content_id", "path", "level", "key", "value", F.col("value").isNotNull().alias("ok"))
        seen.append(got)
        if turn == tallest:
            break
        inner = got.where("ok AND level > 0")
        below = inner.select("content_id", "path", F.col("level") - 1, F.posexplode(_children(F.col("value"))).alias("place", "child"))
        # kept, so that the next round starts from it: references, no payload
        front = cut(below.select("content_id", F.concat("path", F.array("place")).alias("path"), F.col("(level - 1)").alias("level"), F.col("child").alias("key")))
    return reduce(DataFrame.unionByName, seen)


def fetch_contents(roots: DataFrame, kvs: DataFrame, p: StoreParams, tallest: int | None = None) -> DataFrame:
    """(content_id, body, status): the bytes, or null and 'broken' if any node is missing or fails its tag."""
    nodes = fetch_nodes(roots, kvs, p, tallest)
    out = nodes.groupBy("content_id").agg(
        F.expr("listagg(value) WITHIN GROUP (ORDER BY path) FILTER (WHERE level = 0 AND ok)").alias("b"), F.min("ok").alias("ok")
    )
    return out.select("content_id", F.when(F.col("ok"), F.coalesce("b", F.lit(b""))).alias("body"), F.when(F.col("ok"), "ok").otherwise("broken").alias("status"))


def fetch_digests(roots: DataFrame, kvs: DataFrame, p: StoreParams) -> DataFrame:
    """(content_id, digest, status): the SHA-256 of what ``fetch_contents`` gives, in hex, leaf by leaf: no content is one value.

    kvs: bucketed by key (``kvs.saved``), as each level joins it. What is kept between levels is lists of references.
    """
    tallest = roots.agg(F.max("height")).first()[0] or 0
    open_ = lambda front: front.join(kvs.select("key", "value"), "key", "left").select("content_id", "path", "level", crypto.opened_expr(F.col("value"), F.col("key"), p).alias("value"))
    front = roots.select("content_id", F.array().cast("array<int>").alias("path"), F.col("height").alias("level"), "key")
    leaves, broken = [front.where("level = 0")], []
    for _ in range(tallest):
        lists = cut(open_(front.where("level > 0")))
        broken.append(lists.where("value IS NULL"))
        below = lists.where("value IS NOT NULL").select("content_id", "path", "level", F.posexplode(_children(F.col("value"))).alias("place", "key"))
        front = below.select("content_id", F.concat("path", F.array("place")).alias("path"), (F.col("level") - 1).alias("level"), "key")
        leaves.append(front.where("level = 0"))
    nodes = reduce(DataFrame.unionByName, [open_(reduce(DataFrame.unionByName, leaves)), *broken]).select("content_id", "path", "value")
    parts = int(roots.sparkSession.conf.get("spark.sql.shuffle.partitions"))

    def run(batches):
        own, digest, ok = None, None, True
        for batch in batches:
            ids, value, out = batch.column(0), batch.column(1), []
            starts = [0, *(np.flatnonzero(np.diff(ids.dictionary_encode().indices.to_numpy())) + 1).tolist(), len(ids)]
            at = np.frombuffer(value.buffers()[1], np.int32)[value.offset : value.offset + len(value) + 1]
            data = memoryview(value.buffers()[2] or b"")
            for a, b in zip(starts[:-1], starts[1:], strict=True):
                if b > a and (digest is None or ids[a].as_py() != own):
                    out += [] if digest is None else [(own, digest, ok)]
                    own, digest, ok = ids[a].as_py(), hashlib.sha256(), True
                if b > a:
                    digest.update(data[int(at[a]) : int(at[b])])
                    ok = ok and not value.slice(a, b - a).null_count
            yield ended(out)
        yield ended([] if digest is None else [(own, digest, ok)])

    def ended(out: list[tuple]) -> pa.RecordBatch:
        columns = [[i for i, _, _ in out], [d.hexdigest() if ok else None for _, d, ok in out], ["ok" if ok else "broken" for _, _, ok in out]]
        return pa.RecordBatch.from_arrays([pa.array(c, pa.string()) for c in columns], names=["content_id", "digest", "status"])

    return nodes.repartition(parts, "content_id").sortWithinPartitions("content_id", "path").select("content_id", "value").mapInArrow(run, "content_id string, digest string, status string")


def fetch_recursive(roots: DataFrame, kvs: DataFrame, p: StoreParams) -> DataFrame:
    """The same as one recursive SQL statement, for unsealed stores ('hash' or 'mac').

    LIMIT ALL lifts Spark's limit on the rows of a recursion (a million), which would fail larger stores.
    """
    if p.protect == "siv":
        raise ValueError("sealed stores are fetched by fetch_contents")
    spark = roots.sparkSession
    roots.createOrReplaceTempView("_fetch_roots")
    kvs.withColumn("ok", crypto.verify_expr(F.col("value"), F.col("key"), p)).createOrReplaceTempView("_fetch_pairs")
    return spark.sql("""
        WITH RECURSIVE walk(content_id, path, level, value, ok) AS (
          SELECT r.content_id, CAST(array() AS array<int>), r.height, k.value, coalesce(k.ok, false)
          FROM _fetch_roots r LEFT JOIN _fetch_pairs k ON r.key = k.key
          UNION ALL
          SELECT c.content_id, c.path, c.level, k.value, coalesce(k.ok, false)
          FROM (SELECT w.content_id, w.path || array(e.place) AS path, w.level - 1 AS level, substring(w.value, e.place * 32 + 1, 32) AS child
                FROM walk w LATERAL VIEW explode(sequence(0, CAST(octet_length(w.value) / 32 AS int) - 1)) e AS place
                WHERE w.level > 0 AND w.ok AND octet_length(w.value) > 0) c
          LEFT JOIN _fetch_pairs k ON c.child = k.key)
        SELECT content_id, CASE WHEN min(ok) THEN coalesce(listagg(value) WITHIN GROUP (ORDER BY path) FILTER (WHERE level = 0), X'') END AS body,
          CASE WHEN min(ok) THEN 'ok' ELSE 'broken' END AS status
        FROM (SELECT * FROM walk LIMIT ALL) GROUP BY content_id""")


def refcounts(nodes: DataFrame, roots: DataFrame) -> DataFrame:
    """(key, refs): references from distinct parents' child lists, counted with multiplicity, and from roots."""
    up = nodes.where("parent_seq >= 0").select("content_id", (F.col("level") + 1).alias("level"), F.col("parent_seq").alias("seq"), "key")
    parents = nodes.select("content_id", "level", "seq", F.col("key").alias("parent"))
    edges = up.join(parents, ["content_id", "level", "seq"])
    # a parent stored once holds its list once, whatever contents it is in
    first = edges.groupBy("parent").agg(F.min(F.struct("content_id", "level", "seq")).alias("own"))
    lists = edges.join(first, "parent").where(F.struct("content_id", "level", "seq") == F.col("own")).select("key")
    return lists.unionByName(roots.select("key")).groupBy("key").agg(F.count("*").alias("refs"))


def reachable(roots: DataFrame, kvs: DataFrame, p: StoreParams, tallest: int | None = None) -> DataFrame:
    """Distinct keys that some root reaches: a frontier of distinct (key, level) pairs, so shared subtrees are walked once."""
    if tallest is None:
        tallest = roots.agg(F.max("height")).first()[0] or 0
    front, seen = roots.select("key", F.col("height").alias("level")).distinct(), []
    for _ in range(tallest + 1):
        seen.append(front.select("key"))
        got = kv.get(kvs, front.where("level > 0")).withColumn("value", crypto.opened_expr(F.col("value"), F.col("key"), p)).where("value IS NOT NULL")
        front = cut(got.select(F.explode(_children(F.col("value"))).alias("key"), (F.col("level") - 1).alias("level")).distinct())
    return reduce(DataFrame.unionByName, seen).distinct()


def sweep(roots: DataFrame, kvs: DataFrame, p: StoreParams, tallest: int | None = None) -> DataFrame:
    """The store without pairs that no root reaches."""
    live = reachable(roots, kvs, p, tallest).withColumn("bucket", kv.bucket_expr(F.col("key")))
    return kvs.join(live, ["bucket", "key"], "left_semi").select("key", "value", "bucket")


def delete_contents(roots: DataFrame, kvs: DataFrame, gone: DataFrame, p: StoreParams, mode: str = "gc") -> tuple[DataFrame, DataFrame]:
    """(roots, store) without the contents whose content_id is in ``gone``. mode: 'gc' sweeps, 'refcount' takes counts down from the dropped roots."""
    kept = roots.join(gone.select("content_id").distinct(), "content_id", "left_anti")
    if mode == "gc":
        return kept, sweep(kept, kvs, p)
    if mode != "refcount":
        raise ValueError(f"unknown mode {mode!r}")
    dropped = roots.join(gone.select("content_id").distinct(), "content_id", "left_semi")
    lists = store_lists(roots, kvs, p)
    counts = cut(_references(roots.select("key"), lists))
    less, dead = dropped.groupBy("key").agg(F.count("*").alias("less")), []
    while True:
        # what the references taken so far leave; a key dies once, in the round that takes its last one
        counts = cut(counts.join(less, "key", "left").select("key", (F.col("refs") - F.coalesce("less", F.lit(0))).alias("refs"), (F.col("refs") > 0).alias("alive")))
        zero = counts.where("refs = 0 AND alive").select("key")
        if zero.isEmpty():
            break
        dead.append(zero)
        less = lists.join(zero, "key", "left_semi").select(F.explode("children").alias("key")).groupBy("key").agg(F.count("*").alias("less"))
        counts = counts.select("key", "refs")
    if not dead:
        return kept, kvs.select("key", "value", "bucket")
    all_dead = reduce(DataFrame.unionByName, dead).withColumn("bucket", kv.bucket_expr(F.col("key")))
    return kept, kvs.join(all_dead, ["bucket", "key"], "left_anti").select("key", "value", "bucket")


def store_lists(roots: DataFrame, kvs: DataFrame, p: StoreParams) -> DataFrame:
    """(key, children) of the reachable superchunks, each once, whatever levels and contents they are reached from."""
    tallest = roots.agg(F.max("height")).first()[0] or 0
    out, below = [], None
    for level in range(tallest, 0, -1):
        # level by level from the top: contents of other heights share subtrees, which are met in the same round this way
        front = roots.where(F.col("height") == level).select("key")
        front = (front if below is None else front.unionByName(below)).distinct()
        got = kv.get(kvs, front).withColumn("value", crypto.opened_expr(F.col("value"), F.col("key"), p))
        out.append(cut(got.where("value IS NOT NULL").select("key", _children(F.col("value")).alias("children"))))
        below = out[-1].select(F.explode("children").alias("key"))
    if not out:
        return roots.select("key", F.array().cast("array<binary>").alias("children")).where("false")
    lists = reduce(DataFrame.unionByName, out)
    # bytes that are also a list stand at more than one level
    return lists if len(out) == 1 else cut(lists.dropDuplicates(["key"]))


def _references(roots: DataFrame, lists: DataFrame) -> DataFrame:
    """(key, refs) from the store itself: references in the lists of reachable superchunks, and from roots."""
    return roots.unionByName(lists.select(F.explode("children").alias("key"))).groupBy("key").agg(F.count("*").alias("refs"))


def read_range(nodes: DataFrame, kvs: DataFrame, p: StoreParams, start: int, length: int) -> DataFrame:
    """(content_id, part): bytes start to start + length of each content, from the leaves that overlap them only.

    nodes: the node catalogue (positions and keys, no values).
    """
    end = start + length
    leaves = nodes.where((F.col("level") == 0) & (F.col("start_pos") < end) & (F.col("end_pos") > start)).select("content_id", "start_pos", "end_pos", "key")
    got = kv.get(kvs, leaves).withColumn("value", crypto.opened_expr(F.col("value"), F.col("key"), p))
    lo = F.greatest(F.lit(start).cast("long") - F.col("start_pos"), F.lit(0).cast("long"))
    hi = F.least(F.lit(end).cast("long"), F.col("end_pos")) - F.col("start_pos")
    part = F.substring(F.col("value"), (lo + 1).cast("int"), (hi - lo).cast("int"))
    out = got.withColumn("cut", part).groupBy("content_id").agg(F.expr("listagg(cut) WITHIN GROUP (ORDER BY start_pos)").alias("b"), F.min(F.col("value").isNotNull()).alias("ok"))
    return out.select("content_id", F.when(F.col("ok"), F.col("b")).alias("part"))


def overwrite_range(contents: DataFrame, kvs: DataFrame, p: StoreParams, at: int, new: bytes) -> tuple[DataFrame, DataFrame]:
    """(roots, new pairs) after the bytes at ``at`` of each content became ``new``: all that did not change is shared."""
    return insert_contents(contents.withColumn("body", overwrite(F.col("body"), F.lit(at), F.lit(new))), kvs, p)
