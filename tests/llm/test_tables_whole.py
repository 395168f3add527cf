"""Tables of frequent dishes have no bound below their customers, and the parent takes what all shards have drawn."""

from __future__ import annotations

import numpy as np
import pyarrow as pa

from stratastore.llm import pitman_yor as P


def test_frequent_dishes_take_more_tables():
    d, x = 0.5, 2_500.0
    draws = P.draw_tables(np.random.default_rng(2), np.full(200, 200_000), np.full(200, np.log(x)), d)
    assert 1.5 * x < draws.mean() < 2 * x and draws.std() > 10  # few tables against the customers: x / d of them


def test_parent_counts_tables_of_all_shards():
    words = np.arange(0, 40, 4, dtype=np.int64)
    row = (0, P.SINGLES, P.pack(words), P.pack(np.full(10, 50, np.int64)), b"", b"", b"")
    told = pa.Table.from_batches([P._batch(P._arrow(P.STATE), [row])])
    few, many = (P.unpack(P._parent(told, 11, 3, scale).to_pylist()[0]["c"]).sum() for scale in (10.0, 5000.0))
    assert many > 2 * few
