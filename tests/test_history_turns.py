"""Histories cost the same in turns, and a turn holds a bounded part of their nodes."""

from __future__ import annotations

import random
from pathlib import Path

import __spark_entry__ as entry
import numpy as np
import pytest

from stratastore.params import SCHEMES
from stratastore.plans import histories, lineage, workloads
from stratastore.sources import contents as src


@pytest.fixture
def small(monkeypatch):
    """Turns, buckets and files so small that the given tables need many."""
    sent: list[int] = []
    for name, value in {"TURN": 9_000, "TURN_BYTES": 1 << 40, "BUCKET": 500, "HELD": 700, "LOOSE": 90, "PART": 20_000}.items():
        monkeypatch.setattr(histories, name, value)
    turn = histories._turn

    def counted(*args):
        out = turn(*args).persist()
        # nodes are new once each, so a turn moves this many at least
        sent.append(sum(r.pairs for r in out.collect()))
        return out

    monkeypatch.setattr(histories, "_turn", counted)
    return sent


def _same(spark, history, snapshots, params, sent):
    for own, whole, by in ((workloads.history_costs, workloads.version_costs, ("scheme", "s", "version", "added", "cost")), (workloads.history_totals, workloads.total_costs, ("scheme", "s", "pairs", "cost"))):
        got, want = ([tuple(r) for r in f(x, params).select(*by).collect()] for f, x in ((own, history), (whole, snapshots)))
        assert sorted(got) == sorted(want) and got
    assert len(sent) > 4 and max(sent) <= 1.3 * histories.TURN
    assert not list(Path(lineage.shared_dir(spark)).glob("ordered-*"))


def test_orders_in_turns(spark, sf, small):
    _same(spark, src.order_history(spark, sf, 12), src.order_snapshots(spark, sf, 12), workloads.grid(SCHEMES, (64, 512)), small)


def test_all_queries_take_turns(spark, sf, small, monkeypatch):
    # no row goes to several tasks, and no node is a row
    monkeypatch.setattr(workloads, "history_grid", None)
    monkeypatch.setattr(workloads, "_by_task", None)
    rows = entry.queries()["wl_history_orders_all"](spark, sf).collect()
    assert len(rows) == 40 and len(small) > 10


def test_turns_have_every_part_of_every_set():
    rng = random.Random(1)
    for _ in range(50):
        expected = [rng.randrange(1, 400) for _ in range(12)]
        turns = histories.turns_of(expected, rng.sample(range(12), 12), 100)
        parts = [x for t in turns for x in t]
        assert len(set(parts)) == len(parts) and all(sum(-(-expected[k] // n) for k, _, n in t) <= 100 for t in turns) and all(turns)
        for k in range(12):
            own = [x for x in parts if x[0] == k]
            assert sorted(p for _, p, _ in own) == list(range(own[0][2])) and len({n for _, _, n in own}) == 1


def test_names_with_equal_high_words_are_told_apart():
    high, low = np.array([7, 7, 7, 3, 7], np.uint64), np.array([1, 2, 1, 1, 2], np.uint32)
    got = list(zip(*(x.tolist() for x in histories._first(high, low, np.array([5, 4, 3, 9, 8], np.int32), np.array([1, 2, 1, 4, 2]))), strict=True))
    assert got == [(3, 1, 9, 4), (7, 1, 3, 1), (7, 2, 4, 2)]


def test_no_rows_no_costs(spark):
    empty = src.History(spark.createDataFrame([(1, "a", None)], "at long, line string, p long"))
    assert workloads.history_costs(empty, workloads.grid()).count() == workloads.history_totals(empty, workloads.grid()).count() == 0


def test_lineitem_has_a_snapshot_for_each_ship_month(spark, sf):
    months = src.table(spark, sf, "lineitem").where("l_shipdate IS NOT NULL").selectExpr("year(l_shipdate) * 12 + month(l_shipdate) AS m").distinct().count()
    got = {r.version for r in entry.queries()["wl_history_lineitem"](spark, sf).collect()}
    assert got == set(range(1, months + 1)) and months > 60
    assert workloads.history_totals(src.lineitem_history(spark, sf), workloads.grid(("whole",), (1024,))).first().pairs == months


def test_backups_in_turns(spark, sf, small, monkeypatch):
    monkeypatch.setattr(workloads, "_by_task", None)
    got = sorted(tuple(r) for r in entry.queries()["wl_backups_orders"](spark, sf).select("scheme", "s", "pairs", "cost").collect())
    want = workloads.total_costs(src.order_snapshots(spark, sf, 1, 12), workloads.grid(SCHEMES, (64, 128, 256, 512, 1024, 2048, 8192, 32768)))
    assert got == sorted(tuple(r) for r in want.select("scheme", "s", "pairs", "cost").collect()) and len(small) > 5


def test_lineitem_in_turns(spark, sf, small):
    _same(spark, src.lineitem_history(spark, sf), src.lineitem_snapshots(spark, sf), workloads.grid(("cdc_tree", "fixed_tree"), (1024,)), small)
