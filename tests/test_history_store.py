"""Histories go into a store and come out of it in pieces, as whole snapshots would."""

from __future__ import annotations

import hashlib

import __spark_entry__ as entry
from pyspark.sql import functions as F

from stratastore.operators import kvs, store, tree
from stratastore.params import StoreParams
from stratastore.plans import workloads
from stratastore.sources import contents as src


def test_pairs_and_roots_are_those_of_whole_snapshots(spark, sf, monkeypatch):
    monkeypatch.setattr(workloads.stream_tree, "BLOCK", 7_000)
    monkeypatch.setattr(workloads, "SEEN", 50)
    p = StoreParams(scheme="cdc_tree", ring="m31")
    roots, pairs = workloads.insert_history(src.order_history(spark, sf, last=2), "orders", p)
    nodes = tree.build(src.order_snapshots(spark, sf, last=2), p, True)
    got = [(bytes(r.key), bytes(r.value)) for r in pairs.collect()]
    assert len(got) == len(set(got)) and set(got) == {(bytes(r.key), bytes(r.value)) for r in nodes.collect()}
    assert sorted(map(str, roots.collect())) == sorted(map(str, store.roots_of(nodes).collect()))


def test_digests_are_of_what_is_fetched(spark):
    p = StoreParams(scheme="fixed_tree")
    rows = spark.createDataFrame([(str(k), bytes(range(256)) * k + b"ab"[k % 3 :]) for k in range(22)], "content_id string, body binary")
    roots, pairs = store.insert_contents(rows, kvs.empty(spark), p)
    lost = store.roots_of(tree.build(rows, p)).where("content_id = '20'").select("key")
    gone = {bytes(r.key) for r in lost.collect()}
    forged = kvs.saved(pairs.join(lost, "key", "left_anti").withColumn("value", F.when(F.octet_length("value") == 1, F.lit(b"no")).otherwise(F.col("value"))).select("key", "value"))
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "3")
    try:
        got = {r.content_id: (r.digest, r.status) for r in store.fetch_digests(roots, forged, p).collect()}
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    body = {r.content_id: bytes(r.body) for r in rows.collect()}
    # those that end in one byte alone had it forged, and the root of content 20 is gone
    assert got["1"] == got["20"] == (None, "broken") and len(got) == 22 and got["3"][1] == "ok"
    assert {k for k, (_, s) in got.items() if s == "ok"} == {k for k in got if all(n[6] not in gone and len(n[7]) != 1 for n in tree.nodes_of(body[k], p))}
    assert all(d == hashlib.sha256(body[k]).hexdigest() for k, (d, s) in got.items() if s == "ok")


def test_no_snapshot_is_one_value(spark, sf, monkeypatch):
    monkeypatch.setattr(src, "_snapshots", None)
    assert entry.queries()["roundtrip_orders"](spark, sf).where("status = 'ok'").count() == 27
