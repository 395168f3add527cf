"""Contents in pieces, and histories made from their rows, against whole bodies."""

from __future__ import annotations

from collections import Counter

import numpy as np
import pytest

from stratastore.operators import stream_tree, tree
from stratastore.params import SCHEMES, StoreParams
from stratastore.plans import workloads
from stratastore.sources import contents as src


@pytest.mark.parametrize("block", [1, 7, 300, 5000])
@pytest.mark.parametrize("ring", ["wrap64", "m31"])
def test_pieces_give_the_nodes_of_the_whole(monkeypatch, block, ring):
    monkeypatch.setattr(stream_tree, "BLOCK", block)
    rng = np.random.default_rng(block)
    bodies = [b"", b"x", rng.bytes(64), rng.bytes(65), rng.bytes(9_000), b"12|ab\n" * 500, bytes(3000)]
    grid = [StoreParams(chunk=s, scheme=x, ring=ring) for x in SCHEMES for s in (64, 96, 256, 1024)]
    for body in bodies:
        got: list[Counter] = [Counter() for _ in grid]
        content = stream_tree.Content(len(body), grid, lambda k, names, sizes: got[k].update(zip(names, sizes, strict=True)))
        at = 0
        while at < len(body):
            step = int(rng.integers(1, 2 * block + 2))
            content.feed(body[at : at + step])
            at += step
        content.end()
        for k, p in enumerate(grid):
            want = Counter()
            for x in tree.levels_of(body, p, tag=tree.name_of):
                want.update(zip(x.keys, (np.diff(x.cuts) * (2 if x.level else 1)).tolist(), strict=True))
            assert got[k] == want, (p, len(body))


def test_histories_cost_the_same_from_rows(spark, sf):
    grid = workloads.grid(SCHEMES, (64, 256, 2048))
    for rows, bodies in ((src.order_history(spark, sf, 1, 12), src.order_snapshots(spark, sf, 1, 12)), (src.event_history(spark, sf), src.event_days(spark, sf)), (src.lineitem_history(spark, sf), src.lineitem_snapshots(spark, sf))):
        both = [sorted(map(tuple, f(x, grid).select("scheme", "s", "version", "added", "cost").collect())) for f, x in ((workloads.history_costs, rows), (workloads.version_costs, bodies))]
        assert both[0] == both[1] and both[0]


def test_a_history_is_never_one_value(spark, monkeypatch):
    rows = spark.range(20_000).selectExpr("id AS at", "concat('line ', id) AS line", "id % 3 AS p")
    plan = workloads.history_grid(history := src.History(rows), workloads.grid(("fixed_tree",), (256,)), history.versions())._jdf.queryExecution().executedPlan().toString()
    assert "listagg" not in plan
    # a column in order within a task, and each row once a task
    assert plan.count("MapInArrow") == 1 and plan.count("Exchange") == 1
