"""Links between two tight groups are found though every list is full of closer ones."""

from __future__ import annotations

import numpy as np

from stratastore.llm import embed_dup


def test_full_lists_hide_no_link(spark):
    rng = np.random.default_rng(1)
    far = np.zeros((2, 64))
    far[0, 0], far[1, 0], far[1, 1] = 1, 0.986, np.sqrt(1 - 0.986**2)
    x = np.repeat(far, 60, axis=0) + 0.003 * rng.standard_normal((120, 64))
    x = x.astype(np.float32).astype(np.float64)
    unit = x / np.linalg.norm(x, axis=1, keepdims=True)
    true = unit @ unit.T >= 0.98
    np.fill_diagonal(true, False)
    assert true[:60, 60:].any()
    df = spark.createDataFrame([(k, v.tolist(), 1) for k, v in enumerate(x)], "vec_id long, embedding array<float>, label int")
    rows = sorted(embed_dup.near_duplicates(df).collect())
    assert [r.n_links for r in rows] == true.sum(axis=1).tolist()
    assert {r.component_id for r in rows} == {0} and sum(r.kept for r in rows) == 1
