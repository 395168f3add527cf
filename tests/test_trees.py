"""Cuts, heights, trees and keys."""

from __future__ import annotations

import hashlib
import time

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from stratastore.functions import crypto, rolling, udfs
from stratastore.operators import chunkers, tree
from stratastore.params import SCHEMES, StoreParams, init_store
from stratastore.plans import analytic


def body(n: int, seed: int = 0) -> bytes:
    return np.random.default_rng(seed).bytes(n)


@pytest.mark.parametrize(("n", "s", "h"), [(0, 128, 0), (1, 128, 0), (128, 128, 0), (129, 128, 1), (16384, 128, 4), (32768, 128, 4), (32769, 128, 5), (1 << 20, 128, 7), (1 << 20, 64, 14), (10 << 20, 4096, 2)])
def test_heights_at_exact_powers(n, s, h):
    assert StoreParams(chunk=s).height(n) == h == analytic.height(n, s)


def test_worked_examples():
    near = lambda a, b: abs(a - b) < 0.06
    assert analytic.added_fixed(1 << 20, 128) == 1280 and near(analytic.new_nodes_cdc(1 << 20, 128), 9.491) and near(analytic.added_cdc(1 << 20, 128), 2733.3)
    assert analytic.storage_full(1 << 20, 128) == 2621440 and analytic.added_fixed(16384, 128) == 800 and near(analytic.new_nodes_cdc(16384, 128), 6.485)
    assert analytic.storage_full(10 << 20, 4096) == 21135360 and analytic.added_delta(1 << 20, 128, 0) == 0


def test_parameters_are_checked():
    for bad in ({"chunk": 63}, {"scheme": "tree"}, {"head": "none"}, {"window": 0}, {"min_len": 9, "max_len": 3}):
        with pytest.raises(ValueError):
            StoreParams(**bad)
    assert init_store().key != init_store().key and "key" not in repr(init_store())


@settings(max_examples=60, deadline=None)
@given(st.binary(max_size=6000), st.sampled_from(["partial", "skip"]), st.sampled_from(["wrap64", "m31"]), st.sampled_from([64, 128, 256]), st.sampled_from(["cdc_tree", "fixed_tree", "cdc", "fixed"]))
def test_single_pass_is_the_definition(data, head, ring, s, scheme):
    p = StoreParams(chunk=s, head=head, ring=ring, scheme=scheme)
    if data:
        assert [x.tolist() for x in rolling.levels(data, p)] == [x.tolist() for x in rolling.levels_recursive(data, p)]


@pytest.mark.parametrize("data", [b"", b"x", b"\0" * 5000, b"ab" * 2400, bytes(range(48)) * 100, "äöü€".encode() * 300, body(256), body(257), body(2048), body(2049), body(100_000)])
@pytest.mark.parametrize("scheme", SCHEMES)
def test_levels_partition_and_leaves_give_the_content(data, scheme):
    p = StoreParams(scheme=scheme)
    nodes = list(tree.nodes_of(data, p))
    leaves = [v for level, *_, v in nodes if level == 0]
    assert b"".join(leaves) == data
    top = max(n[0] for n in nodes)
    assert top == p.height(len(data)) and sum(n[0] == top for n in nodes) == 1
    for level in range(top + 1):
        own = [n for n in nodes if n[0] == level]
        if own and data:
            assert own[0][2] == 0 and own[-1][3] == len(data) and all(a[3] == b[2] for a, b in zip(own, own[1:]))
    assert all(len(v) == 32 * children for level, *_, children, _, v in nodes if level > 0)


def test_length_limits_hold():
    p = StoreParams(scheme="cdc", min_len=64, max_len=512)
    sizes = [b - a for a, b in rolling.single_level(body(60_000), p, 0)]
    assert max(sizes) <= 512 and min(sizes[:-1]) >= 64


def test_mean_chunk_and_biased_mean():
    p = StoreParams(scheme="cdc", chunk=256)
    sizes = np.array([b - a for k in range(6) for a, b in rolling.single_level(body(300_000, k), p, 0)])
    assert abs(sizes.mean() / 256 - 1) < 0.05
    assert abs((sizes**2).sum() / sizes.sum() / analytic.length_biased_mean(0, 256) - 1) < 0.1


def test_one_changed_byte_changes_few_nodes():
    a = body(1 << 18)
    b = a[:70_000] + bytes([a[70_000] ^ 1]) + a[70_001:]
    c = a[:70_000] + b"!" + a[70_000:]
    keys = lambda x, scheme: {n[6] for n in tree.nodes_of(x, StoreParams(chunk=128, scheme=scheme))}
    assert len(keys(b, "cdc_tree") - keys(a, "cdc_tree")) < 40 > len(keys(c, "cdc_tree") - keys(a, "cdc_tree"))
    assert len(keys(c, "fixed_tree") - keys(a, "fixed_tree")) > 1000


def frame(spark, bodies):
    return spark.createDataFrame([(str(k), b) for k, b in enumerate(bodies)], "content_id string, body binary")


def test_plan_gives_the_kernels_nodes(spark):
    bodies = [b"", b"a", body(5000), body(40_000, 2), None]
    p = StoreParams()
    got = {(r.content_id, r.level, r.seq): (r.start_pos, bytes(r.key)) for r in tree.build(frame(spark, bodies), p).collect()}
    want = {(str(k), n[0], n[1]): (n[2], n[6]) for k, b in enumerate(bodies) if b is not None for n in tree.nodes_of(b, p)}
    assert got == want


def test_expressions_key_like_the_kernel(spark):
    bodies = [b"", b"a", body(5000), body(40_000, 2)]
    p = StoreParams(scheme="fixed_tree")
    rows = frame(spark, bodies)
    sql = {(r.content_id, r.level, r.start_pos, bytes(r.key)) for r in tree.key_nodes_sql(rows, tree.fixed_tree_sql(rows, p), p).collect()}
    assert sql == {(r.content_id, r.level, r.start_pos, bytes(r.key)) for r in tree.build(rows, p).collect()}


def test_sql_chunker_cuts_like_the_kernel(spark):
    p = StoreParams(scheme="cdc", ring="m31", chunk=128)
    rows = frame(spark, [b"", b"x" * 30, body(3000), body(700, 5)])
    key = lambda df: sorted((r.content_id, r.start_pos, r.end_pos, bytes(r.value)) for r in df.collect())
    assert key(chunkers.cdc_sql(rows, p)) == key(chunkers.cdc(rows, p))


def test_registered_chunker(spark):
    chunkers.register("halves", lambda rows, p: rows.selectExpr("content_id", "octet_length(body) div 2 AS half"))
    assert chunkers.chunk(frame(spark, [b"abcd"]), "halves", StoreParams()).first().half == 2


def test_udf_and_grouped_loess(spark):
    rows = frame(spark, [body(9000)]).select(F.size(udfs.rolling_cuts(StoreParams())("body")).alias("n"))
    assert rows.first().n == len(list(tree.nodes_of(body(9000), StoreParams())))


def test_mac_expression(spark):
    import hmac

    p = StoreParams()
    got = frame(spark, [b"", body(100)]).select(crypto.mac_expr(F.col("body"), p).alias("k"), crypto.digest_expr(F.col("body")).alias("h")).collect()
    assert [bytes(r.k) for r in got] == [hmac.digest(p.mac_key, b, "sha256") for b in (b"", body(100))] and bytes(got[0].h) == hashlib.sha256(b"").digest()


def test_exchange_free_plan(spark, sf):
    from stratastore.sources import contents as src

    plan = tree.build(src.documents(spark, sf), StoreParams())._jdf.queryExecution().executedPlan().toString()
    assert "Exchange" not in plan and "MapInArrow" in plan


@pytest.mark.parametrize("p", [StoreParams(chunk=64), StoreParams(chunk=64, scheme="fixed_tree"), StoreParams(chunk=128, scheme="cdc", head="skip"), StoreParams(scheme="whole"), StoreParams(chunk=64, ring="m31"), StoreParams(head="context"), StoreParams(min_len=64, max_len=1024)])
def test_contents_side_by_side_are_cut_like_each_alone(spark, p):
    rng = np.random.default_rng(9)
    bodies = [b"", b"z", b"ab" * 700, *[rng.bytes(int(n)) for n in rng.integers(1, 9000, 40)], rng.bytes(300_000), b"", b"z"]
    got = sorted((r.content_id, r.level, r.seq, r.start_pos, r.end_pos, r.parent_seq, r.children, r.size, bytes(r.key), bytes(r.value)) for r in tree.build(frame(spark, bodies).coalesce(1), p, True).collect())
    want = sorted((str(k), *n[:6], len(n[7]), *n[6:]) for k, b in enumerate(bodies) for n in tree.nodes_of(b, p))
    assert got == want
    grid = sorted((r.content_id, bytes(r.key), r.size, r.copies) for r in tree.build_grid(frame(spark, bodies), [p], named=False).collect())
    each = {}
    for x in want:
        each.setdefault((x[0], x[8], x[7]), []).append(x)
    assert grid == sorted((*k, len(v)) for k, v in each.items())


def test_lines_of_a_long_text(spark):
    """Cutting takes time in proportion to the lines, of which there are more than a batch holds."""
    body = b"".join(b"%d\n" % (k % 7) for k in range(150_000)) + b"end"
    rows = spark.createDataFrame([("a", body), ("b", b"\n\nx\n"), ("c", b""), ("d", None)], "content_id string, body binary")
    start = time.monotonic()
    got = chunkers.chunk(rows, "lines", StoreParams()).orderBy("content_id", "seq").collect()
    assert time.monotonic() - start < 30
    assert [(r.seq, r.start_pos, r.end_pos, bytes(r.value)) for r in got if r.content_id == "b"] == [(0, 0, 1, b"\n"), (1, 1, 2, b"\n"), (2, 2, 4, b"x\n")]
    own = [r for r in got if r.content_id == "a"]
    assert len(own) == 150_001 and b"".join(bytes(r.value) for r in own) == body and [r.seq for r in own] == list(range(150_001))
    assert all(body[r.start_pos : r.end_pos] == bytes(r.value) for r in own) and {r.content_id for r in got} == {"a", "b"}


def test_sql_chunker_exchanges_no_bytes(spark):
    rows = spark.createDataFrame([(str(k), bytes([k]) * 3000) for k in range(20)], "content_id string, body binary")
    plan = chunkers.cdc_sql(rows, StoreParams(chunk=256, scheme="cdc", ring="m31"))._jdf.queryExecution().executedPlan().toString()
    below = [x for x in plan.split("\n") if "Exchange hashpartitioning" in x]
    # what is dealt is contents: place and value of a byte are made above every exchange
    assert below and all("REPARTITION_BY_NUM" in x for x in below), plan
