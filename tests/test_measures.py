"""The orderings and bounds that the experiments must show."""

from __future__ import annotations

import random

import pytest
from pyspark.sql import functions as F

from stratastore.functions import udfs
from stratastore.operators import measures, security, tree
from stratastore.params import SCHEMES, StoreParams
from stratastore.plans import analytic, workloads
from stratastore.sources import contents as src


@pytest.fixture(scope="module")
def edits(spark):
    return {
        kind: {(r.scheme, r.s): r["mean"] for r in measures.summarise_runs(workloads.edit_experiment(spark, kind, 1, 131072, workloads.grid(SCHEMES, (64, 128, 256)), 20), ["scheme", "s"], "added").collect()}
        for kind in ("overwrite", "insert")
    }


def test_overwriting_a_byte(edits):
    for s in (64, 128, 256):
        c = {x: edits["overwrite"][x, s] for x in SCHEMES}
        assert c["whole"] == 131072 + 32 > c["fixed"] > 5 * c["cdc_tree"] and abs(c["fixed"] / c["cdc"] - 1) < 0.1 and c["fixed_tree"] <= analytic.added_fixed(131072, s)
    assert edits["overwrite"]["cdc_tree", 128] == min(edits["overwrite"]["cdc_tree", s] for s in (64, 128, 256))


def test_inserting_a_byte(edits):
    for s in (128, 256):
        c = {x: edits["insert"][x, s] for x in SCHEMES}
        assert 0.2 < c["fixed_tree"] / 131072 < 0.9 and c["cdc_tree"] < 3000
        assert abs(c["cdc"] / edits["overwrite"]["cdc", s] - 1) < 0.1
    assert edits["insert"]["fixed", 64] > 0.7 * edits["insert"]["whole", 64]


def test_growth_is_logarithmic(spark):
    points = [(n, workloads.edit_experiment(spark, "overwrite", 1, n, [StoreParams(chunk=128)], 20).agg(F.avg("added")).first()[0]) for n in (4096, 32768, 262144)]
    assert points[2][1] < 3 * points[0][1] and 0 < analytic.log_slope(points) < 300


def test_expansion(spark):
    got = {(r.scheme, r.s): r.expansion for r in workloads.expansion_experiment(src.random_contents(spark, 0, 131072, 8), workloads.grid()).groupBy("scheme", "s").agg(F.avg("expansion").alias("expansion")).collect()}
    for s, want in ((64, 2.0), (128, 1.5), (256, 1.25)):
        assert abs(got["fixed", s] - want) < 0.01 and abs(got["cdc", s] - want) < 0.05 and got["fixed_tree", s] > got["fixed", s] and got["cdc_tree", s] > got["cdc", s]
    assert got["whole", 64] == 1 + 32 / 131072 and got["cdc_tree", 64] > got["fixed_tree", 64]


def test_bounds_hold(spark):
    for delta in (1, 64, 1024):
        cells = workloads.edit_experiment(spark, "overwrite", delta, 32768, [StoreParams(chunk=128), StoreParams(chunk=128, scheme="fixed_tree")], 20)
        assert all(r.holds for r in measures.bound_check(cells, ["scheme", "s"], "added", "model").collect())


def test_scattered_edits(spark):
    one, many = (workloads.edit_experiment(spark, "scatter", x, 65536, [StoreParams(chunk=128)], 6).agg(F.avg("added")).first()[0] for x in (1, 16))
    assert one < many < 16 * one and many <= analytic.scattered(65536, 128, 16)


def test_versions(spark):
    costs = workloads.version_costs(workloads.edited_versions(spark, 3, 32768, 40), workloads.grid(("whole", "cdc", "cdc_tree"), (256, 1024)))
    last = {(r.scheme, r.s): r.cost for r in costs.where("version = 39").collect()}
    assert last["whole", 256] == 40 * (32768 + 32) and last["cdc_tree", 256] < last["cdc", 256] / 2
    even = measures.break_even(costs.where("scheme = 'cdc_tree'"), costs.where("scheme = 'cdc'"), ["s"], 0.5)
    assert {r.s for r in even.collect()} >= {256}


def test_backups_of_orders(spark, sf):
    cost = {(r.scheme, r.s): r.cost for r in workloads.total_costs(src.order_snapshots(spark, sf, 1, 12), workloads.grid(SCHEMES, (128, 256, 2048))).collect()}
    best = {x: min(c for (y, _), c in cost.items() if y == x) for x in SCHEMES}
    assert best["cdc_tree"] < best["cdc"] < 0.5 * best["fixed"] and best["fixed"] < best["whole"]
    assert best["cdc_tree"] == cost["cdc_tree", 256] and abs(cost["cdc_tree", 2048] / cost["cdc", 2048] - 1) < 0.01


def test_profile_children(spark):
    p = StoreParams(chunk=256)
    rows = {r.level: r for r in measures.level_profile(tree.build(src.random_contents(spark, 5, 262144, 6), p)).collect()}
    assert abs(rows[1].avg_children / 8 - 1) < 0.2 and abs(rows[0].avg_size / 256 - 1) < 0.1


def test_loess_by_two_ways(spark):
    random.seed(4)
    points = spark.createDataFrame([(float(x), x * x / 50 + random.random()) for x in range(30)], "x double, y double")
    plan = {r.x: r.fit for r in measures.loess(points, [], "x", "y").collect()}
    for x0 in (0.0, 7.0, 29.0):
        assert abs(points.agg(udfs.quadratic_at(x0)("x", "y")).first()[0] - plan[x0]) < 1e-4


def test_leak_grows_from_whole_to_chunks(spark, sf):
    rows = {r.scheme: r for r in security.leakage_by_scheme(tree.build_grid(src.documents(spark, sf), workloads.grid(SCHEMES, (256,)))).collect()}
    assert rows["whole"].classes < rows["fixed"].classes and rows["whole"].shared < rows["cdc"].shared


def test_model_columns_equal_scalars(spark):
    cells = spark.createDataFrame([(s, n, x) for s in (64, 128, 1024) for n in (1, 64, 5000, 1 << 20) for x in (1, 2, 300, 1 << 21)], "s int, n int, x int")
    for r in cells.select("s", "n", "x", analytic.added_delta_col(F.col("n"), F.col("s"), F.col("x")).alias("a"), analytic.added_delta_col(F.col("n"), F.col("s"), F.col("x"), True).alias("b")).collect():
        assert abs(r.a - analytic.added_delta(r.n, r.s, r.x)) < 1e-6 * r.a and abs(r.b - analytic.added_delta(r.n, r.s, r.x, True)) < 1e-6 * r.b


def test_scattered_edits_are_at_places_of_their_own(spark):
    row = workloads.edited(src.random_contents(spark, 2, 4096, 1), "scatter", 16).first()
    a, b = bytes(row.before), bytes(row.after)
    at = [k for k in range(4096) if a[k] != b[k]]
    assert len(a) == len(b) and [k // 256 for k in at] == list(range(16)) and len({k % 256 for k in at}) > 8


def test_overwritten_bytes_are_random_and_others(spark):
    rows = workloads.edited(src.random_contents(spark, 0, 512, 40), "overwrite", 1).collect()
    changed = [(x, y) for r in rows for x, y in zip(bytes(r.before), bytes(r.after)) if x != y]
    assert len(changed) == 40 and len({x ^ y for x, y in changed}) > 10
    whole = workloads.edited(src.random_contents(spark, 0, 512, 3), "overwrite", 512).collect()
    assert all(sum(x != y for x, y in zip(bytes(r.before), bytes(r.after))) > 480 and len(r.after) == 512 for r in whole)


def test_versions_by_insertion_and_break_even(spark):
    rows = workloads.edited_versions(spark, 5, 2048, 6, 2, "insert").collect()
    base = {r.run: bytes(r.body) for r in rows if r.version == 0}
    for r in rows:
        if r.version:
            own, body = base[r.run], bytes(r.body)
            k = next(i for i in range(2049) if i == 2048 or own[i] != body[i])
            assert len(body) == 2049 and any(body[:j] + body[j + 1 :] == own for j in range(max(0, k - 3), k + 1))
    costs = spark.createDataFrame([("cdc", 64, v, 100 * v) for v in range(1, 9)] + [("cdc", 128, v, 90 * v + 20) for v in range(1, 9)] + [("cdc_tree", 64, v, 200 + 10 * v) for v in range(1, 9)], "scheme string, s int, version long, cost long")
    assert [tuple(r) for r in workloads.break_even_versions(costs, 1.0).collect()] == [(64, 3, 128)]
    assert [tuple(r) for r in workloads.break_even_versions(costs, 0.5).collect()] == [(64, 6, 128)]


def test_names_and_tags_cost_the_same(spark, sf):
    docs = src.documents(spark, sf).limit(40)
    grid = workloads.grid(SCHEMES, (64, 256))
    by = lambda named: sorted(map(tuple, measures.storage_cost(tree.build_grid(docs, grid, named=named), ["scheme", "s"]).collect()))
    assert by(True) == by(False)


def test_small_inputs_are_spread(spark, sf):
    docs = src.documents(spark, sf)
    assert docs.rdd.getNumPartitions() == 1 < tree.spread(docs).rdd.getNumPartitions()
