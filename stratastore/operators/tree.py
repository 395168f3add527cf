"""Chunk trees as node tables.

A node row: content_id, level (0: leaf), seq (place in its level), start_pos, end_pos, parent_seq, children,
size (bytes stored), key (digest or tag), and value (plain bytes stored) where asked for. One Arrow pass makes
all levels and keys of a content where it lies: no exchange, and no value leaves the executor unless wanted.
"""

from __future__ import annotations

import hashlib
import hmac
from collections import Counter
from collections.abc import Callable, Iterable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import crypto, rolling
from ..params import HEIGHTS, StoreParams

NODES = "content_id string, level int, seq bigint, start_pos bigint, end_pos bigint, parent_seq bigint, children bigint, size bigint, key binary"


def height_expr(n: Column, p: StoreParams) -> Column:
    """Tree height of a content of n bytes, from exact thresholds; null for null."""
    if (held := HEIGHTS[p.scheme]) is not None:
        return F.when(n.isNotNull(), F.lit(held))
    limits = [t for t in p.thresholds() if t < 1 << 62]
    out = F.lit(len(limits))
    for h in range(len(limits) - 1, -1, -1):
        out = F.when(n <= F.lit(limits[h]), F.lit(h)).otherwise(out)
    return F.when(n.isNotNull(), out)


def level_lengths(p: StoreParams, top: int) -> list[tuple[int, float]]:
    """(level, expected node length) for levels 0 to top."""
    return [(k, p.lam(k)[0] / p.lam(k)[1]) for k in range(top + 1)]


def digest(p: StoreParams) -> Callable[[bytes], bytes]:
    if p.protect == "hash":
        return lambda v: hashlib.sha256(v).digest()
    key = p.mac_key
    return lambda v: hmac.digest(key, v, "sha256")


#: Names of nodes where only their equality counts: of 128 bits, and several times as fast as a tag.
NAME = 16


def name_of(v: bytes) -> bytes:
    return xxhash.xxh3_128_digest(v)


@dataclass
class Level:
    """The nodes of one level in order: places, and keys and values each in one buffer; values are cut at ``cuts``."""

    level: int
    start: np.ndarray
    end: np.ndarray
    parent: np.ndarray
    children: np.ndarray
    keys: list[bytes]
    values: bytes
    cuts: np.ndarray

    def __len__(self) -> int:
        return len(self.start)


def levels_of(body: bytes, p: StoreParams, h: int | None = None, prefix: rolling.Prefix | None = None, tag: Callable[[bytes], bytes] | None = None) -> list[Level]:
    """A content's nodes by level, leaves first. Leaves are slices of the content, the others of the keys below, so no value is copied."""
    return _levels(rolling.levels(body, p, h, prefix), body, tag or digest(p))


def _levels(starts: list[np.ndarray], body: bytes, tag: Callable[[bytes], bytes]) -> list[Level]:
    out: list[Level] = []
    n, values = len(body), body
    for level, own in enumerate(starts):
        ends = np.append(own[1:], n)[: len(own)]
        parent = np.searchsorted(starts[level + 1], own, "right") - 1 if level + 1 < len(starts) else np.full(len(own), -1)
        if level:
            first = np.searchsorted(starts[level - 1], np.append(own, n + 1))
            size = len(out[-1].keys[0]) if out[-1].keys else 0
            values, cuts, children = b"".join(out[-1].keys), first * size, np.diff(first)
        else:
            cuts, children = np.append(own, n) if len(own) else np.zeros(1, np.int64), np.zeros(len(own), np.int64)
        at = cuts.tolist()
        keys = [tag(values[a:b]) for a, b in zip(at[:-1], at[1:], strict=True)]
        out.append(Level(level, own, ends, parent, children, keys, values, cuts))
    return out


def nodes_of(body: bytes, p: StoreParams, h: int | None = None) -> Iterator[tuple[int, int, int, int, int, int, bytes, bytes]]:
    """(level, seq, start, end, parent_seq, children, key, value) of a content's nodes, leaves first."""
    for x in levels_of(body, p, h):
        at = x.cuts.tolist()
        values = [x.values[a:b] for a, b in zip(at[:-1], at[1:], strict=True)]
        yield from zip([x.level] * len(x), range(len(x)), x.start.tolist(), x.end.tolist(), x.parent.tolist(), x.children.tolist(), x.keys, values, strict=True)


def _binary(values: bytes, cuts: np.ndarray) -> pa.Array:
    """Slices of one buffer as a column; the buffer is shared."""
    return pa.Array.from_buffers(pa.binary(), len(cuts) - 1, [None, pa.py_buffer(cuts.astype(np.int32)), pa.py_buffer(values)])


def _keys(keys: list[bytes]) -> pa.Array:
    size = len(keys[0]) if keys else 0
    return _binary(b"".join(keys), np.arange(len(keys) + 1) * size)


#: Bytes of contents that are cut side by side, and of a batch; rows of a batch.
JOINED_BYTES, BATCH_BYTES, BATCH_ROWS = 1 << 20, 4 << 20, 1 << 17


def joined(bodies: Iterable[tuple[int, bytes]], p: StoreParams) -> Iterator[tuple[bytes, np.ndarray, np.ndarray, int]]:
    """(buffer, offsets, numbers, height) of numbered contents: those of one height side by side, as far as they fit; small contents cost no round of their own."""
    held: dict[int, list[tuple[int, bytes]]] = {}
    size: dict[int, int] = {}

    def out(h: int) -> tuple[bytes, np.ndarray, np.ndarray, int]:
        part, size[h] = held.pop(h), 0
        return b"".join(b for _, b in part), np.concatenate(([0], np.cumsum([len(b) for _, b in part]))), np.array([k for k, _ in part], np.int64), h

    together = rolling.joins(p)
    for k, body in bodies:
        h = p.height(len(body))
        if not body or not together:
            yield body, np.array([0, len(body)]), np.array([k], np.int64), h
            continue
        if held.get(h) and size[h] + len(body) > JOINED_BYTES:
            yield out(h)
        held.setdefault(h, []).append((k, body))
        size[h] = size.get(h, 0) + len(body)
    for h in list(held):
        yield out(h)


def _cut(body: bytes, offsets: np.ndarray, h: int, p: StoreParams, tag: Callable[[bytes], bytes], prefix: rolling.Prefix | None = None) -> list[Level]:
    starts = rolling.levels_many(body, offsets, h, p, prefix) if body and rolling.joins(p) else rolling.levels(body, p, h, prefix)
    return _levels(starts, body, tag)


def spread(contents: DataFrame, by: list[str] | None = None) -> DataFrame:
    """The contents dealt evenly where they are too few bytes for a split a core (one file, one row group); larger ones as they are."""
    cores = contents.sparkSession.sparkContext.defaultParallelism
    if contents.isStreaming or int(contents._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()) > cores * (128 << 20):
        return contents
    return contents.repartition(4 * cores, *(by or ["content_id"]))


def build(contents: DataFrame, p: StoreParams, with_values: bool = False, height: int | None = None) -> DataFrame:
    """All nodes of all contents. contents: content_id STRING, body BINARY; a null body has no nodes."""
    schema = NODES + (", value binary" if with_values else "")
    names = [x.split()[0] for x in schema.split(", ")]

    tag = digest(p)

    def rows(ids: pa.Array, body: bytes, offsets: np.ndarray, numbers: np.ndarray, h: int) -> Iterator[pa.RecordBatch]:
        found = _cut(body, offsets, h, p, tag)
        heads = [np.searchsorted(x.start, offsets[:-1]) for x in found]
        for x in found:
            own = np.searchsorted(offsets, x.start, "right") - 1 if body else np.zeros(len(x), np.int64)
            # places in the content and in its level
            seq = np.arange(len(x)) - heads[x.level][own]
            above = x.parent - heads[x.level + 1][own] if x.level + 1 < len(found) else np.full(len(x), -1)
            places = [seq, x.start - offsets[own], x.end - offsets[own], above, x.children, np.diff(x.cuts)]
            values = [_binary(x.values, x.cuts)] if with_values else []
            lead = [ids.take(pa.array(numbers[own])), pa.array(np.full(len(x), x.level, np.int32))]
            yield pa.RecordBatch.from_arrays([*lead, *[pa.array(c.astype(np.int64)) for c in places], _keys(x.keys), *values], names=names)

    def run(batches):
        for batch in batches:
            held: list[pa.RecordBatch] = []
            size, ids, bodies = 0, batch.column(0), batch.column(1)
            numbered = ((k, bodies[k].as_py()) for k in range(batch.num_rows) if bodies[k].is_valid)
            parts = joined(numbered, p) if height is None else ((b, np.array([0, len(b)]), np.array([k]), height) for k, b in numbered)
            for part in parts:
                held += rows(ids, *part)
                size += len(part[0])
                if size > BATCH_BYTES:
                    yield pa.concat_batches(held)
                    held, size = [], 0
            if held:
                yield pa.concat_batches(held)

    return contents.select("content_id", "body").mapInArrow(run, schema)


def build_grid(contents: DataFrame, grid: list[StoreParams], keep: list[str] | None = None, named: bool = True) -> DataFrame:
    """(…keep, scheme, s, key, size, copies) of the distinct nodes of each content under each parameter set: one scan, one pass.

    A node repeated within a content comes once with its count. named: keys are names for equality (see
    ``name_of``), not tags. Window hashes are made once for all sets of a ring.
    """
    keep = keep or ["content_id"]
    kept = contents.select(*keep, "body")
    fields = [f"`{f.name}` {f.dataType.simpleString()}" for f in kept.schema if f.name != "body"]
    tags = [name_of if named else digest(p) for p in grid]

    def rows(part: list[tuple[int, bytes]]) -> Iterator[tuple[np.ndarray, list[pa.Array]]]:
        """Of contents that go through all sets together: numbers, and (scheme, s, key, size, copies)."""
        # the least chunk sizes first: what they find holds what the others need
        shared: dict[tuple[str, bytes], rolling.Prefix] = {}
        for p, tag in sorted(zip(grid, tags, strict=True), key=lambda x: x[0].chunk):
            for body, offsets, numbers, h in joined(part, p):
                prefix = None
                if h and len(numbers) == 1 and p.scheme.startswith("cdc"):  # one large content: its sums serve all sets
                    prefix = shared.get((p.ring, numbers[0])) or shared.setdefault((p.ring, numbers[0]), rolling.Prefix(body, p.ring))
                found = _cut(body, offsets, h, p, tag, prefix)
                keys, size = [k for x in found for k in x.keys], np.concatenate([np.diff(x.cuts) for x in found])
                own = numbers[np.concatenate([np.searchsorted(offsets, x.start, "right") - 1 if body else np.zeros(len(x), np.int64) for x in found])]
                if named and len(found) > 1:  # lists are of references, whatever the names' size
                    size[len(found[0]) :] *= 32 // NAME
                copies = None
                both = list(zip(own.tolist(), keys, strict=True))
                if len(first := dict(zip(reversed(both), range(len(both) - 1, -1, -1), strict=True))) < len(both):
                    counts = Counter(both)
                    at = np.fromiter(first.values(), np.int64, len(first))[::-1]
                    copies = np.array([counts[both[k]] for k in at.tolist()], np.int64)
                    keys, own, size = [keys[k] for k in at.tolist()], own[at], size[at]
                n = len(keys)
                yield own, [pa.repeat(pa.scalar(p.scheme), n), pa.array(np.full(n, p.chunk, np.int32)), _keys(keys), pa.array(size.astype(np.int64)), pa.array(np.ones(n, np.int64) if copies is None else copies)]

    def run(batches):
        for batch in batches:
            bodies, held, which, total = batch.column(len(keep)), [], [], 0

            def out():
                lead = batch.select(keep).take(pa.array(np.concatenate(which)))
                return pa.RecordBatch.from_arrays([*lead.columns, *[pa.concat_arrays([x[c] for x in held]) for c in range(5)]], names=[*keep, "scheme", "s", "key", "size", "copies"])

            part, size = [], 0
            for at in range(batch.num_rows + 1):
                body = bodies[at].as_py() if at < batch.num_rows else None
                if body is not None:
                    part.append((at, body))
                    size += len(body)
                if part and (size >= JOINED_BYTES or at == batch.num_rows):
                    for own, x in rows(part):
                        held.append(x)
                        which.append(own)
                        total += len(own)
                        if total > BATCH_ROWS:
                            yield out()
                            held, which, total = [], [], 0
                    part, size = [], 0
            if held:
                yield out()

    return spread(kept, keep).mapInArrow(run, ", ".join([*fields, "scheme string, s int, key binary, size bigint, copies bigint"]))


def build_levelwise(contents: DataFrame, p: StoreParams) -> DataFrame:
    """The definition as a plan: level by level, each node cut by the base chunker; the check of ``build``. No keys."""
    schema = "content_id string, level int, start_pos bigint, end_pos bigint, body binary"
    nodes = contents.where("body IS NOT NULL").select("content_id", height_expr(F.octet_length("body").cast("long"), p).alias("level"), F.lit(0).cast("long").alias("start_pos"), F.octet_length("body").cast("long").alias("end_pos"), "body")
    top = max(1, len(p.thresholds(1 << 40))) if HEIGHTS[p.scheme] is None else HEIGHTS[p.scheme]
    biggest = nodes.agg(F.max("level")).first()[0] or 0
    out = [nodes]

    def cut(batches):
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                if r["level"] > 0:
                    rows += [(r["content_id"], r["level"] - 1, r["start_pos"] + a, r["start_pos"] + b, r["body"][a:b]) for a, b in rolling.single_level(r["body"], p, r["level"] - 1)]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(zip(*rows, strict=True), (pa.string(), pa.int32(), pa.int64(), pa.int64(), pa.binary()), strict=True)], names=["content_id", "level", "start_pos", "end_pos", "body"])

    for _ in range(min(biggest, top)):
        out.append(out[-1].mapInArrow(cut, schema))
    total = out[0]
    for x in out[1:]:
        total = total.unionByName(x)
    return total.select("content_id", "level", "start_pos", "end_pos")


def fixed_tree_sql(contents: DataFrame, p: StoreParams) -> DataFrame:
    """Nodes of a fixed-size tree by DataFrame operations alone: content_id, level, start_pos, end_pos, parent_start."""
    n = F.octet_length("body").cast("long")
    own = contents.where("body IS NOT NULL").select("content_id", n.alias("n"), height_expr(n, p).alias("h"))
    out = own.select("content_id", F.col("h").alias("level"), F.lit(0).cast("long").alias("start_pos"), F.col("n").alias("end_pos"), F.lit(-1).cast("long").alias("parent_start"))
    levels, top = [out], own.agg(F.max("h")).first()[0] or 0
    limits = F.array(*[F.lit(p.fixed_length(k)).cast("long") for k in range(max(1, top))])
    for _ in range(top):
        length = F.element_at(limits, F.col("level"))
        up = levels[-1].where("level > 0 AND end_pos > start_pos")
        down = up.withColumn("a", F.explode(F.sequence(F.col("start_pos"), F.col("end_pos") - 1, length)))
        levels.append(down.select("content_id", (F.col("level") - 1).alias("level"), F.col("a").alias("start_pos"), F.least(F.col("a") + length, "end_pos").alias("end_pos"), F.col("start_pos").alias("parent_start")))
    for x in levels[1:]:
        out = out.unionByName(x)
    return out


def key_nodes_sql(contents: DataFrame, nodes: DataFrame, p: StoreParams) -> DataFrame:
    """Keys of a node table bottom-up by expressions: leaves from their bytes, others from their children's keys in order.

    One exchange by content serves all levels. nodes: as fixed_tree_sql gives them.
    """
    top = nodes.agg(F.max("level")).first()[0] or 0
    bytes_of = F.substring(F.col("body"), (F.col("start_pos") + 1).cast("int"), (F.col("end_pos") - F.col("start_pos")).cast("int"))
    leaves = nodes.where("level = 0").join(contents.select("content_id", "body"), "content_id").withColumn("value", bytes_of)
    done = [leaves.select("content_id", "level", "start_pos", "end_pos", "parent_start", F.octet_length("value").cast("long").alias("size"), crypto.tag_expr(F.col("value"), p).alias("key"))]
    for level in range(1, top + 1):
        lists = done[-1].groupBy("content_id", F.col("parent_start").alias("start_pos")).agg(F.expr("listagg(key) WITHIN GROUP (ORDER BY start_pos)").alias("value"))
        own = nodes.where(F.col("level") == level).join(lists, ["content_id", "start_pos"], "left").withColumn("value", F.coalesce("value", F.lit(b"")))
        done.append(own.select("content_id", "level", "start_pos", "end_pos", "parent_start", F.octet_length("value").cast("long").alias("size"), crypto.tag_expr(F.col("value"), p).alias("key")))
    out = done[0]
    for x in done[1:]:
        out = out.unionByName(x)
    return out


def build_fanout(leaves: DataFrame, group: int, p: StoreParams) -> DataFrame:
    """Nodes over given leaves (content_id, seq, key) that always take ``group`` children: the scheme whose upper levels lose their place after a shift."""
    level, out = leaves.select("content_id", F.lit(0).alias("level"), "seq", "key", "size"), []
    out.append(level)
    most = leaves.agg(F.max("seq")).first()[0]
    while most is not None and most > 0:
        up = level.groupBy("content_id", F.floor(F.col("seq") / group).cast("long").alias("seq")).agg(F.expr("listagg(key) WITHIN GROUP (ORDER BY seq)").alias("value"), F.first("level").alias("level"), F.count("*").alias("children"))
        # a content that is down to one node is done
        done = level.groupBy("content_id").agg(F.max("seq").alias("m")).where("m > 0").select("content_id")
        level = up.join(done, "content_id", "left_semi").select("content_id", (F.col("level") + 1).alias("level"), "seq", crypto.tag_expr(F.col("value"), p).alias("key"), F.octet_length("value").cast("long").alias("size"))
        out.append(level)
        most //= group
    total = out[0]
    for x in out[1:]:
        total = total.unionByName(x)
    return total


def diff(left: DataFrame, right: DataFrame) -> DataFrame:
    """(level, nodes, bytes): nodes of right that left does not hold."""
    new = right.join(left.select("key").distinct(), "key", "left_anti").dropDuplicates(["key"])
    return new.groupBy("level").agg(F.count("*").alias("new_nodes"), F.sum(F.col("size") + 32).alias("new_bytes"))
