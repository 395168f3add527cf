"""The game of forged stores: one walk for all of them, whatever ids the contents have."""

from __future__ import annotations

import numpy as np
from pyspark.sql import functions as F

from stratastore.operators import kvs, security, store
from stratastore.params import StoreParams

BODIES = [b"", b"one", b"one", *[np.random.default_rng(k).bytes(200 + 900 * k) for k in range(9)]]


def _rows(spark, ids):
    return spark.createDataFrame([(i, "t", k, b, len(b)) for k, (i, b) in enumerate(zip(ids, BODIES, strict=True))], "content_id string, series string, version bigint, body binary, n bigint")


def test_contents_of_one_id_or_none_are_judged_by_their_own_bytes(spark):
    ids = [None, None, "a", "a", "a", *"bcdefgh"]
    for r in security.authenticity_game(_rows(spark, ids), StoreParams(protect="siv"), every=3).collect():
        assert (r.contents, r.wins) == (len(BODIES), 0) and r.intact + r.refused == r.contents


def test_one_walk_gives_what_each_forged_store_gives(spark):
    rows, p = _rows(spark, [str(k) for k in range(len(BODIES))]), StoreParams(protect="siv", scheme="fixed_tree")
    roots, pairs = store.insert_contents(rows, kvs.empty(spark), p)
    game = {r.kind: r.intact for r in security.authenticity_game(rows, p, every=5).collect()}
    for kind in ("flip", "delete", "swap"):
        got = store.fetch_contents(roots, security.tamper(pairs, kind, 5), p).where("status = 'ok'").count()
        assert 0 < game[kind] == got < len(BODIES)
    assert game["rollback"] == len(BODIES)


def test_a_forgery_that_passes_wins(spark, monkeypatch):
    monkeypatch.setattr(security.crypto, "opened_expr", lambda c, tag, p: c)
    out = {r.kind: r for r in security.authenticity_game(_rows(spark, [str(k) for k in range(len(BODIES))]), StoreParams(scheme="whole"), every=2).collect()}
    hit = {kind: out[kind].wins for kind in ("flip", "truncate", "swap", "replace")}
    assert len(set(hit.values())) == 1 and hit["flip"] == out["delete"].refused > 0
    assert all(r.contents == len(BODIES) == r.intact + r.refused + r.wins for r in out.values()) and out["rollback"].wins == 0


def test_a_task_that_ends_amid_a_content(spark):
    nodes = [(f"{c}", None, 1, 0, 0, b"abcd") for c in range(8)] + [(f"{c}", [k], 0, 3, 0, b"abcd"[k : k + 1]) for c in range(8) for k in range(4)]
    rows = spark.createDataFrame([*nodes[:-1], ("7", [3], 0, 2, 1, b"d")], "content_id string, path array<int>, copies bigint, kinds int, lost int, value binary")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", "3")
    try:
        got = security._tally(rows.coalesce(1).sortWithinPartitions("content_id", F.asc_nulls_first("path")), ("flip", "rollback")).collect()
    finally:
        spark.conf.unset("spark.sql.execution.arrow.maxRecordsPerBatch")
    assert [(r.kind, r.contents, r.intact, r.refused, r.wins) for r in got] == [("flip", 8, 7, 1, 0), ("rollback", 8, 8, 0, 0)]
