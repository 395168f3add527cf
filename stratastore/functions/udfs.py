"""Functions for SQL and DataFrames that built-in ones cannot say: rolling cuts, chunk tables, LOESS values."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from ..params import StoreParams
from . import rolling

CUTS = "array<struct<level:int,start_pos:bigint,end_pos:bigint>>"


def rolling_cuts(p: StoreParams):
    """A column function body -> array of (level, start_pos, end_pos) of all nodes."""

    @F.pandas_udf(CUTS)
    def cuts(bodies: pd.Series) -> pd.Series:
        out = []
        for body in bodies:
            if body is None:
                out.append(None)
                continue
            rows = []
            for level, starts in enumerate(rolling.levels(bytes(body), p)):
                ends = np.append(starts[1:], len(body))[: len(starts)]
                rows += [{"level": level, "start_pos": int(a), "end_pos": int(b)} for a, b in zip(starts, ends, strict=True)]
            out.append(rows)
        return pd.Series(out)

    return cuts


@F.udtf(returnType="seq: bigint, start_pos: bigint, end_pos: bigint")
class ChunkTable:
    """chunk_table(body, scheme, s): the chunks of a content, for LATERAL in SQL."""

    def eval(self, body: bytes, scheme: str, s: int) -> Iterator[tuple[int, int, int]]:
        p = StoreParams(chunk=s, scheme=scheme, ring="m31")
        for k, (a, b) in enumerate(rolling.single_level(bytes(body or b""), p, 0)):
            yield k, a, b


def register(spark: SparkSession) -> None:
    spark.udtf.register("chunk_table", ChunkTable)


def quadratic_at(x0: float, span: float = 0.75):
    """A grouped aggregate (x, y) -> LOESS value at x0: the check of measures.loess."""

    @F.pandas_udf("double")
    def fit(x: pd.Series, y: pd.Series) -> float:
        d = (x - x0).abs().to_numpy()
        near = np.lexsort((y.to_numpy(), x.to_numpy(), d))[: max(1, int(np.ceil(len(x) * span)))]
        reach = d[near].max()
        u = d[near] / reach / 1.0000001 if reach else np.zeros(len(near))
        w = (1 - u**3) ** 3
        t = (x.to_numpy()[near] - x0) / reach if reach else np.zeros(len(near))
        a = np.stack([np.ones(len(near)), t, t * t], axis=1) * np.sqrt(w)[:, None]
        return float(np.linalg.lstsq(a, y.to_numpy()[near] * np.sqrt(w), rcond=None)[0][0])

    return fit
