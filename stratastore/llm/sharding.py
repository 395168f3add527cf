"""Uniform shuffle into shards of exact sizes by a hypergeometric communication matrix. DataFrame operations only.

Rows are dealt to ``parts`` partitions by a hash of all their columns. How many rows of partition i go to
shard j is drawn exactly, as in a uniform permutation of all rows: along a binary tree over partitions,
each node's shard counts are split by hypergeometric draws, so the matrix has the partitions' sizes as
row sums and the shard sizes (at most one apart) as column sums. A partition's rows, in random order, go
to the shards by their row of the matrix; a shard's rows are ordered again by a second random key.
Slots are counted block by block of that key, so no task gets a whole shard.

The driver handles the matrix, parts x shards numbers, and nothing that grows with the rows' contents.
Nulls are values like others. Repeated rows are dealt each for itself; equal rows are interchangeable, so
the outcome does not depend on the order in which they are read. Rows equal in all columns share a partition.
A seed makes it repeatable. Columns of any name are kept; the added ones avoid them.
"""

from __future__ import annotations

import json
import random

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .shared import free_name, n_shuffle

N_SHARDS = 16
#: Rows of a block within a shard, about; no more blocks than BLOCKS_PER_TASK for each shuffle partition.
BLOCK_ROWS, BLOCKS_PER_TASK = 1_000, 4


def hypergeometric(rng: random.Random, good: int, bad: int, draws: int) -> int:
    """Number of good ones among draws: inversion over the law's weights, which are products of whole-number ratios in double precision."""
    low, high = max(0, draws - bad), min(draws, good)
    mode = min(high, max(low, (draws + 1) * (good + 1) // (good + bad + 2)))
    # weights against the mode's, outwards until what is left is below the precision of their sum
    up, down, total = [], [], 1.0
    w, k = 1.0, mode
    while k < high and w > total * 1e-18:
        w *= (good - k) * (draws - k) / ((k + 1) * (bad - draws + k + 1))
        k += 1
        up.append(w)
        total += w
    w, k = 1.0, mode
    while k > low and w > total * 1e-18:
        w *= k * (bad - draws + k) / ((good - k + 1) * (draws - k + 1))
        k -= 1
        down.append(w)
        total += w
    u = rng.random() * total - 1.0
    if u < 0:
        return mode
    for sign, side in ((1, up), (-1, down)):
        for step, w in enumerate(side, 1):
            u -= w
            if u < 0:
                return mode + sign * step
    return mode


def communication_matrix(sizes: list[int], shards: list[int], seed: int) -> list[list[int]]:
    """Rows from each partition to each shard; sums: the partitions' sizes, and the shards' sizes."""
    rng = random.Random(seed)
    out: list[list[int]] = [[] for _ in sizes]

    def split(lo: int, hi: int, columns: list[int]) -> None:
        if hi - lo == 1:
            out[lo] = columns
            return
        mid = (lo + hi) // 2
        left, total, need = [], sum(columns), sum(sizes[lo:mid])
        for c in columns:
            k = hypergeometric(rng, c, total - c, need)
            left.append(k)
            total, need = total - c, need - k
        split(lo, mid, left)
        split(mid, hi, [c - k for c, k in zip(columns, left, strict=True)])

    if sizes:
        split(0, len(sizes), list(shards))
    return out


def shard_sizes(n: int, shards: int) -> list[int]:
    return [n // shards + (j < n % shards) for j in range(shards)]


def _random(columns: list[Column], seed: int) -> Column:
    return F.xxhash64(*columns, F.lit(seed))


def shuffle_into_shards(df: DataFrame, n_shards: int = N_SHARDS, seed: int = 7, parts: int | None = None, block_rows: int = BLOCK_ROWS) -> DataFrame:
    """The rows with shard (int) and slot (long, 0, 1, ... within each shard)."""
    spark = df.sparkSession
    parts = parts or max(n_shards, 2 * n_shuffle(spark))
    shard, slot = free_name(df, "shard"), free_name(df, "slot")
    part, first, second, place, block, n_here, begins = (free_name(df, f"__{x}") for x in ("part", "r1", "r2", "place", "block", "n", "cuts"))
    own = [F.col(f"`{c}`") for c in df.columns]
    part_of = lambda: F.pmod(_random(own, seed), F.lit(parts)).cast("int")
    found = {r["p"]: r["c"] for r in df.select(part_of().alias("p")).groupBy("p").agg(F.count("*").alias("c")).collect()}
    sizes = [found.get(p, 0) for p in range(parts)]
    n = sum(sizes)
    matrix = communication_matrix(sizes, shard_sizes(n, n_shards), seed)
    cuts = []
    for row in matrix:
        total, line = 0, []
        for k in row[:-1]:
            total += k
            line.append(total)
        cuts.append(line)
    # a row for each partition: the places at which the next shard begins
    table = F.broadcast(spark.range(1).select(F.posexplode(F.from_json(F.lit(json.dumps(cuts)), "array<array<bigint>>")).alias(part, begins)))
    local = Window.partitionBy(part).orderBy(first, second)
    blocks = max(1, min(-(-n // (n_shards * block_rows)), BLOCKS_PER_TASK * n_shuffle(spark) // n_shards))
    dealt = (
        df.withColumns({part: part_of(), first: _random(own, seed + 1), second: _random(own, seed + 2)})
        .withColumn(place, F.row_number().over(local) - 1)
        .join(table, part)
        .withColumn(shard, F.size(F.filter(begins, lambda c: c <= F.col(place))).cast("int"))
        # equal rows of one shard differ in their place, so their keys do not tie
        .withColumn(second, F.xxhash64(second, part, place, F.lit(seed + 3)))
        .withColumn(block, F.floor((F.col(second).cast("double") / 2.0**64 + 0.5) * blocks).cast("int"))
        .drop(begins, first)
    )
    within = Window.partitionBy(shard, block).orderBy(second, part, place)
    ordered = dealt.withColumn(n_here, F.row_number().over(within) - 1)
    starts = _block_starts(dealt, shard, block, begins)
    return ordered.join(F.broadcast(starts), [shard, block]).withColumn(slot, (F.col(begins) + F.col(n_here)).cast("long")).select(*own, shard, slot)


def _block_starts(dealt: DataFrame, shard: str, block: str, begins: str) -> DataFrame:
    """Where each block of each shard begins: one row for each, shards x blocks in all."""
    sizes = dealt.groupBy(shard, block).agg(F.count("*").alias(begins))
    before = Window.partitionBy(shard).orderBy(block).rowsBetween(Window.unboundedPreceding, -1)
    return sizes.select(shard, block, F.coalesce(F.sum(begins).over(before), F.lit(0)).alias(begins))
