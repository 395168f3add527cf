"""Queries that once made their rows up: what they give follows the given tables."""

from __future__ import annotations

import __spark_entry__ as entry
from stratastore.functions import rolling
from stratastore.operators import tree
from stratastore.params import StoreParams
from stratastore.plans import analytic, workloads
from stratastore.sources import contents as src


def _rows(spark, sf, name):
    return [r.asDict() for r in entry.queries()[name](spark, sf).collect()]


def _lengths(spark, sf):
    return {len(r.text.encode()) for r in spark.read.parquet(f"{sf}/documents.parquet").collect() if r.text}


def test_model_expected_nodes(spark, sf):
    rows = _rows(spark, sf, "model_expected_nodes")
    assert {r["n"] for r in rows} == _lengths(spark, sf) and len(rows) == 4 * len({r["n"] for r in rows})


def test_model_added_fixed(spark, sf):
    rows = _rows(spark, sf, "model_added_fixed")
    assert {r["n"] for r in rows} == _lengths(spark, sf) and len(rows) == 4 * len({r["n"] for r in rows})


def test_model_added_cdc(spark, sf):
    rows = _rows(spark, sf, "model_added_cdc")
    assert {r["n"] for r in rows} == _lengths(spark, sf) and len(rows) == 4 * len({r["n"] for r in rows})


def test_model_added_delta(spark, sf):
    rows = _rows(spark, sf, "model_added_delta")
    assert {r["n"] for r in rows} == _lengths(spark, sf) and len(rows) == 20 * len({r["n"] for r in rows})


def _levels(spark, sf, sizes, root):
    """Documents that have a node of level k (root: or their root), by (s, k)."""
    texts = [r.text.encode() for r in spark.read.parquet(f"{sf}/documents.parquet").collect() if r.text]
    out = {}
    for s in sizes:
        for n in map(len, texts):
            for k in range(StoreParams(chunk=s).height(n) + root):
                out[s, k] = out.get((s, k), 0) + 1
    return out


def test_model_boundary_prob(spark, sf):
    rows = _rows(spark, sf, "model_boundary_prob")
    assert {(r["s"], r["k"]): r["contents"] for r in rows} == _levels(spark, sf, (64, 128, 256, 1024), 0)
    for r in rows:
        for name, f in (("p", analytic.boundary_prob), ("flip", analytic.cut_flip), ("mean_at_random", analytic.length_biased_mean)):
            assert abs(r[name] / f(r["k"], r["s"]) - 1) < 1e-12


def test_model_cut_flip(spark, sf):
    rows = _rows(spark, sf, "model_cut_flip")
    assert {(r["s"], r["k"]): r["contents"] for r in rows} == _levels(spark, sf, (64, 128, 256, 1024), 0)
    assert all(abs(r["gained"] / analytic.cut_flip(r["k"], r["s"]) - 1) < 1e-12 for r in rows)


def test_level_lengths(spark, sf):
    rows, empty = _rows(spark, sf, "level_lengths"), spark.read.parquet(f"{sf}/documents.parquet").where("text = ''").count()
    want = {(s, k): c + (k == 0) * empty for (s, k), c in _levels(spark, sf, (64, 128, 256), 1).items()}
    assert {(r["s"], r["level"]): r["contents"] for r in rows} == want
    assert all(r["length"] == analytic.lam(r["level"], r["s"]) for r in rows)


def test_length_biased_share(spark, sf):
    p = StoreParams(chunk=256, scheme="cdc", ring="m31")
    sizes = [b - a for r in spark.read.parquet(f"{sf}/documents.parquet").collect() if r.text for a, b in rolling.single_level(r.text.encode(), p, 0)]
    for r in _rows(spark, sf, "length_biased_share"):
        assert abs(r["found"] - sum(x for x in sizes if x <= r["longest"]) / sum(sizes)) < 1e-12
        assert abs(r["share"] - sum(analytic.length_biased_share(c, 0, 256) for c in range(1, r["longest"] + 1))) < 1e-12


def _added(spark, sf):
    """(s, length class, added) of each document's edit, by the plan with an exchange."""
    docs = src.documents(spark, sf).where("n > 0")
    rows = workloads.edit_costs(workloads.edited(docs, "overwrite", 1), workloads.grid(("cdc_tree",), (64, 128, 256))).collect()
    return [(r.s, 1 << (r.n - 1).bit_length(), r.added) for r in rows]


def test_bound_check(spark, sf):
    rows, cells = _rows(spark, sf, "bound_check"), _added(spark, sf)
    assert {(r["s"], r["n"]) for r in rows} == {x[:2] for x in cells}
    for r in rows:
        own = [a for s, n, a in cells if (s, n) == (r["s"], r["n"])]
        assert r["samples"] == len(own) and abs(r["mean"] - sum(own) / len(own)) < 1e-6 and r["holds"] == (r["mean"] <= r["mean_bound"])


def test_boxplot_cost(spark, sf):
    rows, cells = _rows(spark, sf, "boxplot_cost"), _added(spark, sf)
    for r in rows:
        own = [a for s, n, a in cells if (s, n) == (r["s"], r["n"])]
        assert r["samples"] == len(own) and min(own) <= r["low"] <= r["q2"] <= r["high"] <= max(own)
    assert sum(r["samples"] for r in rows) == len(cells)


def test_loess_cost(spark, sf):
    rows, cells = _rows(spark, sf, "loess_cost"), _added(spark, sf)
    assert {(r["s"], r["n"]) for r in rows} == {x[:2] for x in cells} and all(r["fit"] is not None for r in rows)


def test_break_even_cdc(spark, sf):
    have: dict[tuple[str, int], set[bytes]] = {}
    cost: dict[tuple[str, int], int] = {}
    want: dict[int, int] = {}
    bodies = sorted((r.version, bytes(r.body)) for r in src.conversation_versions(spark, sf).collect() if r.body is not None)
    for version in sorted({v for v, _ in bodies}):
        for scheme in ("cdc", "cdc_tree"):
            for s in (64, 256, 1024):
                own = have.setdefault((scheme, s), set())
                for v, body in bodies:
                    for node in tree.nodes_of(body, StoreParams(chunk=s, scheme=scheme, ring="m31")) if v == version else ():
                        cost[scheme, s] = cost.get((scheme, s), 0) + (0 if node[6] in own else len(node[7]) + 32)
                        own.add(node[6])
        for s in (64, 256, 1024):
            if cost["cdc_tree", s] <= min(cost["cdc", x] for x in (64, 256, 1024)):
                want.setdefault(s, version)
    assert {r["s"]: r["version"] for r in _rows(spark, sf, "break_even_cdc")} == want and want
