"""The store: insertion, retrieval, forgery, deletion, ranges, sinks and streams."""

from __future__ import annotations

import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from stratastore.functions import crypto
from stratastore.operators import kvs, measures, security, store, tree
from stratastore.params import StoreParams, init_store
from stratastore.plans import workloads
from stratastore.sources import contents as src
from stratastore.streaming import ingest

BODIES = [b"", b"one", np.random.default_rng(1).bytes(3000), np.random.default_rng(2).bytes(20_000), "grün".encode() * 400]


@pytest.fixture(scope="module")
def rows(spark):
    twice = [*BODIES, BODIES[3]]
    return spark.createDataFrame([(str(k), "t", k, b, len(b)) for k, b in enumerate(twice)], "content_id string, series string, version bigint, body binary, n bigint")


@pytest.mark.parametrize("protect", ["hash", "mac", "siv"])
@pytest.mark.parametrize("scheme", ["whole", "fixed", "cdc_tree"])
def test_what_goes_in_comes_out(spark, rows, protect, scheme):
    p = StoreParams(scheme=scheme, protect=protect)
    roots, pairs = store.insert_contents(rows, kvs.empty(spark), p)
    got = {r.content_id: (bytes(r.body), r.status) for r in store.fetch_contents(roots, pairs, p).collect()}
    assert got == {r.content_id: (bytes(r.body), "ok") for r in rows.collect()}
    again = store.insert_contents(rows, pairs, p)[1]
    assert again.isEmpty()


def test_sealing_keeps_lengths_and_hides_bytes(spark, rows):
    p = StoreParams(protect="siv")
    s = security.sealed_sizes(tree.build(rows, p, True), p).first()
    assert s.plain == s.sealed
    pairs = {bytes(r.value) for r in store.insert_contents(rows, kvs.empty(spark), p)[1].collect() if len(r.value) > 8}
    assert not pairs & {n[7] for b in BODIES for n in tree.nodes_of(b, p)}


def test_no_forgery_wins(spark, rows):
    out = {r.kind: r for r in security.authenticity_game(rows, StoreParams(protect="siv"), every=3).collect()}
    assert set(out) == set(security.TAMPERS) and all(r.wins == 0 for r in out.values())
    assert out["rollback"].intact == 6 and all(out[k].refused > 0 for k in ("flip", "truncate", "delete", "swap"))


def test_recursive_fetch(spark, rows):
    p = StoreParams(scheme="fixed_tree")
    roots, pairs = store.insert_contents(rows, kvs.empty(spark), p)
    got = {r.content_id: bytes(r.body) for r in store.fetch_recursive(roots, pairs, p).collect()}
    assert got == {r.content_id: bytes(r.body) for r in rows.collect()}
    with pytest.raises(ValueError):
        store.fetch_recursive(roots, pairs, p.with_(protect="siv"))


def test_recursive_fetch_is_not_limited_in_rows(spark, rows):
    p = StoreParams(scheme="fixed_tree")
    roots, pairs = store.insert_contents(rows, kvs.empty(spark), p)
    spark.conf.set("spark.sql.cteRecursionRowLimit", "50")
    try:
        got = {r.content_id: bytes(r.body) for r in store.fetch_recursive(roots, pairs, p).collect()}
    finally:
        spark.conf.unset("spark.sql.cteRecursionRowLimit")
    assert got == {r.content_id: bytes(r.body) for r in rows.collect()}


def test_deletion_by_both_ways(spark, rows):
    p = StoreParams()
    roots, pairs = store.insert_contents(rows, kvs.empty(spark), p)
    gone = rows.where("content_id IN ('3', '4')").select("content_id")
    keys = lambda df: {bytes(r.key) for r in df.collect()}
    (kept, a), (_, b) = (store.delete_contents(roots, pairs, gone, p, m) for m in ("gc", "refcount"))
    assert keys(a) == keys(b) and len(keys(a)) < len(keys(pairs))
    # content 5 equals the deleted content 3, and stays whole
    assert {r.content_id: r.status for r in store.fetch_contents(kept, a, p).collect()} == {k: "ok" for k in "0125"}
    with pytest.raises(ValueError):
        store.delete_contents(roots, pairs, gone, p, "never")


def test_deletion_of_a_subtree_shared_by_contents_of_other_heights(spark):
    p = StoreParams(scheme="fixed_tree", protect="hash")
    long = np.random.default_rng(6).bytes(20_000)
    # the first 2,048 bytes are a node of level 1 in all three: a root, and below roots of two other heights
    bodies = [long[:2048], long[:9000], long, b"kept", long[2048:2500]]
    rows = spark.createDataFrame([(str(k), "t", k, b, len(b)) for k, b in enumerate(bodies)], "content_id string, series string, version bigint, body binary, n bigint")
    roots, pairs = store.insert_contents(rows, kvs.empty(spark), p)
    assert len({r.height for r in roots.where("content_id < '3'").collect()}) == 3
    keys = lambda df: {bytes(r.key) for r in df.collect()}
    for ids in ("'0', '1', '2'", "'1', '2'", "'0', '1', '2', '3', '4'"):
        gone = rows.where(f"content_id IN ({ids})").select("content_id")
        a, b = (keys(store.delete_contents(roots, pairs, gone, p, m)[1]) for m in ("gc", "refcount"))
        assert a == b
    assert not b


@pytest.mark.parametrize(("at", "length"), [(0, 10), (2990, 100), (100, 0), (19_999, 5), (0, 1 << 20)])
def test_ranges(spark, rows, at, length):
    p = StoreParams(protect="siv")
    _, pairs = store.insert_contents(rows, kvs.empty(spark), p)
    got = {r.content_id: bytes(r.part) for r in store.read_range(tree.build(rows, p), pairs, p, at, length).collect() if r.part}
    assert got == {r.content_id: bytes(r.body[at : at + length]) for r in rows.collect() if r.body[at : at + length]}


def test_overwritten_range_shares_the_rest(spark, rows):
    p = StoreParams(chunk=128)
    big = rows.where("content_id = '3'")
    _, pairs = store.insert_contents(big, kvs.empty(spark), p)
    roots, new = store.overwrite_range(big, pairs, p, 9000, b"changed")
    body = bytes(store.fetch_contents(roots, kvs.put(pairs, new), p).first().body)
    assert body == BODIES[3][:9000] + b"changed" + BODIES[3][9007:] and new.count() < 30


def test_files_of_pairs(spark, rows, tmp_path):
    p = StoreParams()
    _, pairs = store.insert_contents(rows, kvs.empty(spark), p)
    kvs.write(pairs, f"{tmp_path}/kv")
    kvs.write(pairs, f"{tmp_path}/kv")  # a replay
    back = kvs.read(spark, f"{tmp_path}/kv")
    assert back.count() == pairs.count() and "PartitionFilters: [isnotnull(bucket" in back.where("bucket = 3")._jdf.queryExecution().executedPlan().toString()
    kvs.compact(spark, f"{tmp_path}/kv", f"{tmp_path}/one")
    assert spark.read.parquet(f"{tmp_path}/one").count() == pairs.count()
    kvs.save_table(pairs, "kv_table")
    assert spark.table("kv_table").count() == pairs.count()


def _plan(df):
    return df._jdf.queryExecution().toString()


def test_no_key_stands_in_a_plan(spark, rows):
    p = init_store()
    roots, pairs = store.insert_contents(rows, kvs.empty(spark), p)
    plans = _plan(pairs) + _plan(store.fetch_contents(roots, pairs, p)) + _plan(store.read_range(tree.build(rows, p), pairs, p, 0, 9))
    for secret in (p.key, p.mac_key, p.cipher_key, *crypto.pads(p.mac_key), *crypto.pads(p.cipher_key)):
        assert secret.hex() not in plans.lower() and " ".join(f"{x:02x}" for x in secret) not in plans.lower() and str(list(secret))[1:-1] not in plans


def test_values_move_after_it_is_known_what_is_new(spark, rows, tmp_path):
    p = init_store()
    assert p.protect == "siv"
    kvs.write(store.insert_contents(rows, kvs.empty(spark), p)[1], f"{tmp_path}/kv")
    stored = kvs.read(spark, f"{tmp_path}/kv")
    plan = store.new_keys(rows, stored, p)._jdf.queryExecution().executedPlan().toString()
    assert not re.search(r"\bvalue#", plan) and "Exchange" in plan
    # few new keys: they are sent to where the contents lie, and only values of theirs go on
    more = rows.limit(1).withColumn("body", F.lit(b"something new"))
    new = store.insert_contents(rows.unionByName(more), stored, p)[1]
    assert new.count() == 1 and "LeftSemi" in new._jdf.queryExecution().executedPlan().toString()


def test_the_public_key_is_warned_of(spark, rows):
    with pytest.warns(UserWarning, match="public test key"):
        store.insert_contents(rows, kvs.empty(spark), StoreParams(protect="siv"))


def test_a_folder_that_cannot_be_read_is_no_empty_store(spark, sf, tmp_path):
    (tmp_path / "s" / "pairs").mkdir(parents=True)
    (tmp_path / "s" / "pairs" / "part-0.parquet").write_bytes(b"not parquet")
    rows = src.contents(ingest.read_table(spark, sf, "benchmark"), F.col("item_id"), F.lit("benchmark"), F.col("item_id"), F.encode("text", "utf-8"))
    q = ingest.insert_stream(rows, f"{tmp_path}/s", init_store(), f"{tmp_path}/c")
    with pytest.raises(Exception):  # noqa: B017
        q.awaitTermination()


def test_measures_travel(spark, rows, tmp_path):
    costs = measures.storage_cost(tree.build_grid(rows, workloads.grid()), ["scheme", "s"])
    for kind in ("json", "csv", "orc"):
        costs.write.format(kind).option("header", "true").save(f"{tmp_path}/{kind}")
        assert spark.read.format(kind).option("header", "true").load(f"{tmp_path}/{kind}").count() == 15


def test_compositions(spark, rows):
    same = rows.unionByName(rows).select(F.col("body").alias("value"))
    keys = {m: crypto.compose(same, m, StoreParams()).select("key").distinct().count() for m in crypto.COMPOSITIONS}
    assert keys["encrypt_then_mac"] == keys["mac_then_encrypt"] == 12 and keys["encrypt_and_mac"] == keys["whole_deterministic"] == keys["aead_random"] == 5
    with pytest.raises(ValueError):
        crypto.compose(same, "rot13", StoreParams())


def test_null_and_clashing_columns(spark):
    odd = spark.createDataFrame([("a", None, 1), (None, b"x", 2)], "content_id string, body binary, key int")
    assert [(r.content_id, r.level) for r in tree.build(odd, StoreParams()).collect()] == [(None, 0)]
    assert tree.build(odd.limit(0), StoreParams()).isEmpty()


def test_file_sources(spark, tmp_path):
    (tmp_path / "a.txt").write_bytes(b"first\nsecond\n")
    (tmp_path / "b.txt").write_bytes(b"")
    assert {bytes(r.body) for r in src.from_files(spark, str(tmp_path)).collect()} == {b"first\nsecond\n"}
    assert {bytes(r.body) for r in src.from_lines(spark, str(tmp_path)).collect()} == {b"first", b"second"}
    assert b"first\nsecond\n" in {bytes(r.body) for r in src.from_text_files(spark, str(tmp_path)).collect()}


def test_stream_and_batch_agree(spark, sf, tmp_path):
    p = StoreParams(protect="siv")
    batch = src.passages(spark, sf)
    rows = src.contents(ingest.read_table(spark, sf, "benchmark"), F.col("item_id"), F.lit("benchmark"), F.col("item_id"), F.encode("text", "utf-8"))
    for _ in range(2):  # the second run finds nothing new
        ingest.insert_stream(rows, f"{tmp_path}/s", p, f"{tmp_path}/c").awaitTermination()
    want = {bytes(r.key) for r in store.insert_contents(batch, kvs.empty(spark), p)[1].collect()}
    assert {bytes(r.key) for r in kvs.read(spark, f"{tmp_path}/s/pairs").collect()} == want


def test_streaming_windows_and_state(spark, sf):
    events = ingest.read_table(spark, sf, "events")
    q = ingest.tumbling(events).writeStream.format("memory").queryName("tumbled").outputMode("complete").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("tumbled").agg(F.sum("events")).first()[0] == 1000
    rows = src.contents(ingest.read_table(spark, sf, "benchmark"), F.col("item_id"), F.lit("b"), F.col("item_id"), F.encode("text", "utf-8"))
    q = ingest.running_versions(rows).writeStream.format("memory").queryName("versions").outputMode("update").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("versions").agg(F.max("version")).first()[0] == 40
    everything, timed = ingest.split_late(events, "1 hour")
    new = ingest.new_chunks(everything.select(F.encode("props", "utf-8").alias("body"), "ts"), p := StoreParams(), "ts")
    q = new.select("key").writeStream.format("memory").queryName("chunks").outputMode("append").trigger(availableNow=True).start()
    q.awaitTermination()
    distinct = spark.read.parquet(f"{sf}/events.parquet").select("props").distinct().count()
    assert distinct <= spark.table("chunks").count() <= 1000 and p and timed.isStreaming
