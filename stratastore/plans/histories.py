"""What a history's snapshots cost, each node once, on bounded disk.

Rows are put in order once, in the shared folder, and every task reads all of them for the snapshots it cuts. Nodes
go to where equal names meet as twelve bytes of their name and their size, packed, in turns of so many nodes;
the exchange files of a turn are removed before the next. A turn has whole parameter sets, or one part of the
names of a set that is too large for a turn.
"""

from __future__ import annotations

import itertools
from collections import defaultdict
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators import measures, stream_tree
from ..params import HEIGHTS, StoreParams
from ..sources import contents as src
from . import lineage

#: Nodes of a turn at least, some 16 bytes each; a longer history has a node for every so many bytes of its last snapshot.
TURN = 1 << 27
TURN_BYTES = 16
#: Nodes that a task compares at a time, and those that it holds before it sends them on.
BUCKET = 1 << 20
HELD = 1 << 20
#: Names that are held as they come, before they are packed.
LOOSE = 1 << 17
#: Bytes of a file of ordered rows.
PART = 32 << 20

NAMED = np.dtype([("high", "<u8"), ("low", "<u4")])
SENT = "part int, k int, version int, names binary, sizes binary"
FOUND = "k int, version int, pairs bigint, cost bigint"


def _expected(p: StoreParams, lengths: list[int]) -> int:
    """About how many nodes contents of these lengths have."""
    total = sum(-(-n // p.chunk) for n in lengths)
    if p.scheme == "whole":
        return len(lengths)
    return len(lengths) + (total if HEIGHTS[p.scheme] == 1 else total * p.chunk // (p.chunk - p.ref))


def turns_of(expected: list[int], order: list[int], limit: int) -> list[list[tuple[int, int, int]]]:
    """Turns of (number of a set, which part of its names, of how many parts) with ``limit`` nodes at most."""
    out, room = [[]], limit
    for k in order:
        parts = -(-expected[k] // limit)
        for part in range(parts):
            own = -(-expected[k] // parts)
            if own > room:
                out.append([])
                room = limit
            out[-1].append((k, part, parts))
            room -= own
    return out


def _first(high: np.ndarray, low: np.ndarray, versions: np.ndarray, sizes: np.ndarray) -> tuple[np.ndarray, ...]:
    """The same names, each once, with the first of its versions."""
    at = np.argsort(high, kind="stable")
    same = high[at[1:]] == high[at[:-1]]
    if (same & (low[at[1:]] != low[at[:-1]])).any():
        at = np.lexsort((low, high))
        same = (high[at[1:]] == high[at[:-1]]) & (low[at[1:]] == low[at[:-1]])
    heads = np.flatnonzero(np.append(True, ~same)) if len(at) else at
    own = at[heads]
    return high[own], low[own], np.minimum.reduceat(versions[at], heads) if len(at) else versions, sizes[own]


class _Packed:
    """Nodes of one set that a task holds, as arrays."""

    def __init__(self) -> None:
        self.loose: list[tuple[int, list[bytes], list[int]]] = []
        self.arrays: list[tuple[np.ndarray, ...]] = []

    def pack(self, part: int, parts: int) -> int:
        """Makes arrays of the loose names that belong to the part; gives how many."""
        if not self.loose:
            return 0
        words = np.frombuffer(b"".join(itertools.chain.from_iterable(names for _, names, _ in self.loose)), "<u8").reshape(-1, 2)
        own = np.flatnonzero(_mixed(words[:, 0]) % np.uint64(parts) == part) if parts > 1 else slice(None)
        sizes = np.fromiter(itertools.chain.from_iterable(x for _, _, x in self.loose), np.int64, len(words))
        versions = np.repeat(np.array([v for v, _, _ in self.loose], np.int32), [len(x) for _, x, _ in self.loose])
        self.arrays.append((words[own, 0].copy(), words[own, 1].astype(np.uint32), versions[own], sizes[own]))
        self.loose.clear()
        return len(self.arrays[-1][0])

    def taken(self) -> tuple[np.ndarray, ...]:
        out = _first(*(np.concatenate(x) for x in zip(*self.arrays, strict=True)))
        self.arrays.clear()
        return out


def _mixed(high: np.ndarray) -> np.ndarray:
    return high >> np.uint64(20)


def _sent(k: int, first: int, buckets: int, parts: int, nodes: tuple[np.ndarray, ...]) -> Iterator[tuple]:
    """Rows of SENT: nodes of set k by version and bucket; the set's buckets are numbered from ``first`` on."""
    high, low, versions, sizes = nodes
    bucket = (_mixed(high) // np.uint64(parts) % np.uint64(buckets)).astype(np.int64)
    cell = versions * np.int64(buckets) + bucket
    at = np.argsort(cell, kind="stable")
    names = np.empty(len(at), NAMED)
    names["high"], names["low"], sizes, cell = high[at], low[at], sizes[at], cell[at]
    heads = np.flatnonzero(np.append(True, cell[1:] != cell[:-1]))
    for a, b in zip(heads.tolist(), [*heads[1:].tolist(), len(at)], strict=True):
        version, own = divmod(int(cell[a]), buckets)
        yield first + own, k, version, names[a:b].tobytes(), sizes[a:b].tobytes()


def _met(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of SENT, all of a bucket, to rows of FOUND: nodes by the first version that has them."""
    held = defaultdict(list)
    for batch in batches:
        for k, v, names, sizes in zip(*(batch.column(c).to_pylist() for c in ("k", "version", "names", "sizes")), strict=True):
            held[k].append((v, np.frombuffer(names, NAMED), np.frombuffer(sizes, np.int64)))
    out = []
    for k in list(held):
        rows = held.pop(k)
        versions = np.repeat(np.array([v for v, _, _ in rows], np.int32), [len(x) for _, x, _ in rows])
        high, low = (np.concatenate([x[c] for _, x, _ in rows]) for c in ("high", "low"))
        sizes = np.concatenate([x for _, _, x in rows])
        del rows
        _, _, versions, sizes = _first(high, low, versions, sizes)
        at = np.argsort(versions, kind="stable")
        versions = versions[at]
        heads = np.flatnonzero(np.append(True, versions[1:] != versions[:-1]))
        pairs = np.diff(heads, append=len(at))
        cost = np.add.reduceat(sizes[at], heads) + measures.REF * pairs
        out += zip([k] * len(heads), versions[heads].tolist(), pairs.tolist(), cost.tolist(), strict=True)
    if out:
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int32(), pa.int32(), pa.int64(), pa.int64()), strict=True)], names=["k", "version", "pairs", "cost"])


def _turn(spark: SparkSession, files: list[str], versions: list[tuple[int, int, int]], params: list[StoreParams], expected: list[int], pieces: list[tuple[int, int, int]]) -> DataFrame:
    """FOUND of one turn."""
    cores = spark.sparkContext.defaultParallelism
    groups = min(len(versions), 2 * cores)
    # sets are dealt too where there are fewer snapshots than tasks
    halves = min(len(pieces), -(-2 * cores // groups))
    pieces = sorted(pieces, key=lambda x: (-expected[x[0]], x))
    buckets = {k: max(1, -(-expected[k] // parts // BUCKET)) for k, _, parts in pieces}
    first = dict(zip(buckets, np.cumsum([0, *buckets.values()]).tolist(), strict=False))
    ranked = sorted(versions, key=lambda x: -x[2])

    def run(batches):
        for task in (x for batch in batches for x in batch.column(0).to_pylist()):
            g, half = task % groups, task // groups
            # from both ends, so that each task has long and short ones
            own = [x for i, x in enumerate(ranked) if min(i % (2 * groups), 2 * groups - 1 - i % (2 * groups)) == g]
            yield from _cut(files, own, params, pieces[half::halves], buckets, first)

    sent = spark.range(0, groups * halves, 1, groups * halves).mapInArrow(run, SENT)
    return sent.repartitionById(sum(buckets.values()), F.col("part")).mapInArrow(_met, FOUND)


def _cut(files: list[str], own: list[tuple[int, int, int]], params: list[StoreParams], pieces: list[tuple[int, int, int]], buckets: dict[int, int], first: dict[int, int]) -> Iterator[pa.RecordBatch]:
    """A task's snapshots under a turn's sets, as rows of SENT."""
    held, count = [_Packed() for _ in pieces], [0, 0]

    def taker(version: int):
        def take(i: int, names: list[bytes], sizes: list[int]) -> None:
            if names:
                held[i].loose.append((version, names, sizes))
                count[0] += len(names)

        return take

    def pack() -> None:
        count[1] += sum(x.pack(part, parts) for x, (_, part, parts) in zip(held, pieces, strict=True))
        count[0] = 0

    def out() -> Iterator[pa.RecordBatch]:
        count[1] = 0
        for x, (k, _, parts) in zip(held, pieces, strict=True):
            rows = list(_sent(k, first[k], buckets[k], parts, x.taken())) if sum(len(a[0]) for a in x.arrays) else []
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary()), strict=True)], names=["part", "k", "version", "names", "sizes"])

    contents = [(p, stream_tree.Content(n, [params[k] for k, _, _ in pieces], taker(v))) for p, v, n in own]
    for _ in stream_tree.fed(contents, lineage.rows_of(files, ["p", "line"])):
        if count[0] > LOOSE:
            pack()
            if count[1] > HELD:
                yield from out()
    pack()
    yield from out()


def first_costs(history: src.History, params: list[StoreParams]) -> tuple[list[int], dict[tuple[int, int], tuple[int, int]]]:
    """The versions, and (pairs, bytes) that a version adds by (number of the set, version), where it adds any."""
    versions = history.versions()
    if not versions:
        return [], {}
    spark, last = history.rows.sparkSession, versions[-1][2]
    expected = [_expected(p, [n for _, _, n in versions]) for p in params]
    # sets that share window sums side by side
    order = sorted(range(len(params)), key=lambda k: (params[k].scheme.startswith("cdc"), expected[k]), reverse=True)
    rows = history.rows.where("p IS NOT NULL").select("p", F.lpad(F.col("at").cast("string"), 12, "0").alias("at"), F.encode(F.concat("line", F.lit("\n")), "utf-8").alias("line"))
    out: dict[tuple[int, int], tuple[int, int]] = defaultdict(lambda: (0, 0))
    with lineage.in_order(rows, ["at", "line"], max(1, -(-last // PART))) as files:
        for pieces in turns_of(expected, order, max(TURN, last // TURN_BYTES)):
            with lineage.released(spark):
                for r in _turn(spark, files, versions, params, expected, pieces).collect():
                    pairs, cost = out[r.k, r.version]
                    out[r.k, r.version] = pairs + r.pairs, cost + r.cost
    return [v for _, v, _ in versions], dict(out)


def costs(history: src.History, params: list[StoreParams]) -> DataFrame:
    """(scheme, s, version, added, cost) like ``workloads.version_costs``, of snapshots too large for one value."""
    versions, found = first_costs(history, params)
    rows = []
    for k, p in enumerate(params):
        cost = 0
        for v in versions:
            added = found.get((k, v), (0, 0))[1]
            cost += added
            rows.append((p.scheme, p.chunk, v, added, cost))
    return history.rows.sparkSession.createDataFrame(rows, "scheme string, s int, version bigint, added bigint, cost bigint")


def totals(history: src.History, params: list[StoreParams]) -> DataFrame:
    """(scheme, s, pairs, cost) like ``workloads.total_costs``."""
    versions, found = first_costs(history, params)
    rows = [(p.scheme, p.chunk, *map(sum, zip(*(found.get((k, v), (0, 0)) for v in versions), strict=True))) for k, p in enumerate(params)] if versions else []
    return history.rows.sparkSession.createDataFrame(rows, "scheme string, s int, pairs bigint, cost bigint")
