"""What a backend can learn and do: leakage profile, abstract trees, traces, tampering."""

from __future__ import annotations

import functools
import itertools

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..functions import crypto
from ..params import StoreParams
from ..plans.lineage import cut
from . import kvs as kv
from . import store


def leakage_profile(nodes: DataFrame) -> DataFrame:
    """(content_id, level, seq, start_pos, end_pos, size, same): lengths, cuts, and which nodes are equal; no payload and no key.

    ``same`` numbers the classes of equal nodes in the order of their first appearance.
    """
    first = nodes.groupBy("key").agg(F.min(F.struct("content_id", "level", "seq")).alias("first"))
    numbered = nodes.join(first, "key")
    return numbered.select("content_id", "level", "seq", "start_pos", "end_pos", "parent_seq", "size", F.sha2(F.concat_ws(":", F.col("first.content_id"), F.col("first.level").cast("string"), F.col("first.seq").cast("string")), 256).alias("same"))


def abstract_tree(profile: DataFrame, seed: int = 1) -> DataFrame:
    """(content_id, level, seq, parent_seq, size, key, value): payloads of random bytes of the same sizes, equal where the profile says equal."""
    fake = F.unhex(F.sha2(F.concat(F.col("same"), F.lit(f":{seed}")), 256))
    # a made-up value of the node's size, by repeating its digest
    value = F.expr("substring(unhex(repeat(hex(fake), cast(size / 32 as int) + 1)), 1, cast(size as int))")
    return profile.withColumn("fake", fake).select("content_id", "level", "seq", "parent_seq", "size", F.col("fake").alias("key"), value.alias("value"))


def equality_pattern(nodes: DataFrame, name: str = "key") -> DataFrame:
    """(size, members, classes): how many classes of equal nodes there are, by size and number of members."""
    return nodes.groupBy(name).agg(F.first("size").alias("size"), F.count("*").alias("members")).groupBy("size", "members").agg(F.count("*").alias("classes"))


def trace_insert(nodes: DataFrame, key: str = "key") -> DataFrame:
    """(content_id, step, op, ref, size): what the store sees when contents are inserted: a leaf is put, a superchunk is asked for and put if new.

    Children come before their parents; ``ref`` is the key or, for a profile, the class.
    """
    order = Window.partitionBy("content_id").orderBy("end_pos", "level", "seq")
    first = Window.partitionBy(key).orderBy("content_id", "end_pos", "level", "seq")
    rows = nodes.withColumns({"step": F.row_number().over(order), "nth": F.row_number().over(first)})
    ops = F.when(F.col("level") == 0, F.array(F.lit("put"))).when(F.col("nth") == 1, F.array(F.lit("get"), F.lit("put"))).otherwise(F.array(F.lit("get")))
    return rows.select("content_id", "step", F.explode(ops).alias("op"), F.col(key).alias("ref"), "size")


def trace_fetch(nodes: DataFrame, key: str = "key") -> DataFrame:
    """(content_id, step, op, ref, size) of fetching each content: parents before children, in order."""
    order = Window.partitionBy("content_id").orderBy("start_pos", F.desc("level"), "seq")
    return nodes.select("content_id", F.row_number().over(order).alias("step"), F.lit("get").alias("op"), F.col(key).alias("ref"), "size")


def trace_shape(trace: DataFrame) -> DataFrame:
    """A trace up to the names of references: each is its first place in the trace."""
    where = trace.groupBy("ref").agg(F.min(F.struct("content_id", "step")).alias("name"))
    return trace.join(where, "ref").select("content_id", "step", "op", F.concat_ws("/", F.col("name.content_id"), F.col("name.step").cast("string")).alias("name"), "size")


def leakage_by_scheme(grid: DataFrame) -> DataFrame:
    """(scheme, s, nodes, classes, shared): how much equality each scheme shows. grid: build_grid's rows."""
    return grid.groupBy("scheme", "s").agg(F.sum("copies").alias("nodes"), F.countDistinct("key").alias("classes")).withColumn("shared", F.col("nodes") - F.col("classes"))


TAMPERS = ("flip", "swap", "truncate", "replace", "delete", "rollback")


def _hit(every: int, seed: int) -> Column:
    return F.pmod(F.xxhash64("key", F.lit(seed)), F.lit(every)) == 0


def _with_other(kvs: DataFrame) -> DataFrame:
    """other: the value of the next pair of the same bucket by key; the last takes the first."""
    own = Window.partitionBy("bucket").orderBy("key")
    whole = own.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return kvs.withColumn("other", F.coalesce(F.lead("value").over(own), F.first("value").over(whole)))


def _forged(kind: str) -> Column:
    """The forged value of a pair; swap and replace ask for ``other``."""
    v = F.col("value")
    if kind == "flip":
        first = F.conv(F.hex(F.substring(v, 1, 1)), 16, 10).cast("int").bitwiseXOR(F.lit(1))
        return F.when(F.octet_length(v) > 0, F.concat(F.unhex(F.lpad(F.hex(first), 2, "0")), F.substring(v, F.lit(2), F.octet_length(v)))).otherwise(F.lit(b"\1"))
    if kind == "truncate":
        return F.when(F.octet_length(v) > 0, F.substring(v, F.lit(1), F.octet_length(v) - 1)).otherwise(F.lit(b"\1"))
    if kind in ("swap", "replace"):
        return F.when(F.col("other") == v, F.concat(v, F.lit(b"\0"))).otherwise(F.col("other"))
    raise ValueError(f"unknown tampering {kind!r}")


def tamper(kvs: DataFrame, kind: str, every: int = 7, seed: int = 0) -> DataFrame:
    """A store in which about one pair in ``every`` is forged.

    flip: a bit of the value; truncate: its last byte; swap and replace: another pair's value; delete: gone;
    rollback: the value an earlier put left, which is the same under the same key.
    """
    hit = _hit(every, seed)
    if kind == "delete":
        return kvs.where(~hit)
    if kind == "rollback":
        return kvs
    forged = _forged(kind)
    rows = _with_other(kvs) if kind in ("swap", "replace") else kvs
    return rows.withColumn("value", F.when(hit, forged).otherwise(F.col("value"))).select("key", "value", "bucket")


def opened_stores(kvs: DataFrame, p: StoreParams, kinds: tuple[str, ...] = TAMPERS, every: int = 7, seed: int = 0) -> DataFrame:
    """(key, found): what a key opens to in the stores that ``tamper`` makes, all at once.

    found: (kinds, value) for each value that passes the tag, kinds with a bit for each store that gives it. A
    value is opened once for all stores in which it is the same; a forgery that passed would stand beside it.
    """
    bits = lambda *names: sum(1 << k for k, kind in enumerate(kinds) if kind in names)
    hit, every_bit, kept = _hit(every, seed), (1 << len(kinds)) - 1, bits("rollback")
    if unknown := set(kinds) - set(TAMPERS):
        raise ValueError(f"unknown tampering {sorted(unknown)!r}")
    forged = [(b, _forged(names[0])) for names in (("flip",), ("truncate",), ("swap", "replace")) if (b := bits(*names))]
    rows = _with_other(kvs) if bits("swap", "replace") else kvs
    columns = [f"forged{k}" for k in range(len(forged))]
    rows = rows.select("key", hit.alias("hit"), "value", F.when(hit, F.col("key")).alias("tag"), *[F.when(hit, f).alias(c) for c, (_, f) in zip(columns, forged, strict=True)])
    opened = rows.select("key", "hit", crypto.opened_expr(F.col("value"), F.col("key"), p).alias("value"), *[crypto.opened_expr(F.col(c), F.col("tag"), p).alias(c) for c in columns])
    own = F.struct(F.when(F.col("hit"), F.lit(kept)).otherwise(F.lit(every_bit)).alias("kinds"), F.col("value"))
    others = [F.struct(F.lit(b).alias("kinds"), F.col(c).alias("value")) for c, (b, _) in zip(columns, forged, strict=True)]
    return opened.select("key", F.filter(F.array(own, *others), lambda x: x["value"].isNotNull() & (x["kinds"] != 0)).alias("found"))


def _asked(front: DataFrame, known: DataFrame) -> DataFrame:
    """front with what its keys open to in the stores it stands for (found), and the stores in which they open to nothing (lost)."""
    mine = F.transform(F.filter("found", lambda x: x["kinds"].bitwiseAND(F.col("kinds")) != 0), lambda x: F.struct(x["kinds"].bitwiseAND(F.col("kinds")).alias("kinds"), x["value"].alias("value")))
    got = front.join(known, "key", "left").withColumn("found", F.coalesce(mine, F.array().cast("array<struct<kinds:int,value:binary>>")))
    seen = F.aggregate("found", F.lit(0), lambda a, x: a.bitwiseOR(x["kinds"]))
    return got.select("content_id", "path", "level", "found", F.col("kinds").bitwiseAND(F.bitwise_not(seen)).alias("lost"))


def _tally(rows: DataFrame, kinds: tuple[str, ...]) -> DataFrame:
    """(kind, contents, intact, refused, wins) by task. rows: content_id, path (null: what was inserted), copies, kinds, lost, value; all of a content together, in order."""

    def judged(batch: pa.RecordBatch, starts: list[int], tally: np.ndarray) -> None:
        value = batch.column("value")
        at = np.frombuffer(value.buffers()[1], np.int32)[value.offset : value.offset + len(value) + 1].tolist()
        data = value.buffers()[2].to_pybytes() if value.buffers()[2] else b""
        copies, bits, lost = (batch.column(c).to_numpy() for c in ("copies", "kinds", "lost"))
        gone = np.bitwise_or.reduceat(lost[: starts[-1]], starts[:-1])
        for a, b, out in zip(starts[:-1], starts[1:], gone.tolist(), strict=True):
            inserted = a + int(np.count_nonzero(copies[a:b]))  # those first, then the nodes
            good = [k for k in range(len(kinds)) if not out >> k & 1]
            leaves = [k for k in range(inserted, b) if bits[k]]
            alike = all((int(bits[k]) | out) + 1 == 1 << len(kinds) for k in leaves)
            got = dict.fromkeys(good, data[at[inserted] : at[b]]) if alike else {g: b"".join(data[at[k] : at[k + 1]] for k in leaves if int(bits[k]) >> g & 1) for g in good}
            for k in range(a, inserted):
                body, n = data[at[k] : at[k + 1]], int(copies[k])
                tally[:, 0] += n
                tally[[g for g in range(len(kinds)) if g not in got], 2] += n
                same = got[good[0]] == body if alike and good else False
                for g in good:
                    tally[g, 1 if (same if alike else got[g] == body) else 3] += n

    def run(batches):
        tally, rest = np.zeros((len(kinds), 4), np.int64), None
        for batch in itertools.chain(batches, [None]):
            if batch is not None:
                rest = batch if rest is None else pa.concat_batches([rest, batch])
            if rest is None or not rest.num_rows:
                continue
            ids = rest.column("content_id").dictionary_encode().indices.to_numpy()
            starts = [0, *(np.flatnonzero(np.diff(ids)) + 1).tolist()]
            if batch is None:
                judged(rest, [*starts, rest.num_rows], tally)
            elif len(starts) > 1:  # the last one may go on
                judged(rest, starts, tally)
                rest = rest.slice(starts[-1])
        yield pa.RecordBatch.from_arrays([pa.array(list(kinds)), *[pa.array(tally[:, c]) for c in range(4)]], names=["kind", "contents", "intact", "refused", "wins"])

    return rows.select("content_id", "copies", "kinds", "lost", "value").mapInArrow(run, "kind string, contents bigint, intact bigint, refused bigint, wins bigint")


def authenticity_game(contents: DataFrame, p: StoreParams, kinds: tuple[str, ...] = TAMPERS, every: int = 7, seed: int = 0) -> DataFrame:
    """(kind, contents, intact, refused, wins): a win is a fetch that gives other bytes than were inserted under the id.

    The store is made, forged and opened once, and one walk fetches from all forged stores: a reference says
    by bits for which of them it stands. Contents are named by a digest, so equal ones are fetched once, and
    each is compared with its own bytes whatever ids the rows have.
    """
    own = contents.where("body IS NOT NULL").select(F.substring(F.sha2("body", 256), 1, 32).alias("content_id"), "body")
    roots, pairs = store.insert_contents(own, kv.empty(contents.sparkSession), p)
    known = kv.saved(opened_stores(pairs, p, kinds, every, seed))
    roots = cut(roots.dropDuplicates(["content_id"]))
    tallest = roots.agg(F.max("height")).first()[0] or 0
    front = roots.select("content_id", F.array().cast("array<int>").alias("path"), F.col("height").alias("level"), "key", F.lit((1 << len(kinds)) - 1).alias("kinds"))
    leaves, lists = [front.where("level = 0")], []
    for _ in range(tallest):
        # kept as lists of references, an eighth of the rows
        lists.append(cut(_asked(front.where("level > 0"), known)))
        each = lists[-1].select("content_id", "path", "level", F.explode("found").alias("x"))
        below = each.select("content_id", "path", "level", F.col("x.kinds").alias("kinds"), F.posexplode(store._children(F.col("x.value"))).alias("place", "key"))
        front = below.select("content_id", F.concat("path", F.array("place")).alias("path"), (F.col("level") - 1).alias("level"), "key", "kinds")
        leaves.append(front.where("level = 0"))
    out = _asked(functools.reduce(DataFrame.unionByName, leaves), known).select("content_id", "path", "lost", F.explode_outer("found").alias("x"))
    none = F.lit(0).cast("long").alias("copies")
    parts = [out.select("content_id", "path", none, F.coalesce("x.kinds", F.lit(0)).alias("kinds"), "lost", F.coalesce("x.value", F.lit(b"")).alias("value"))]
    parts += [x.where("lost <> 0").select("content_id", "path", none, F.lit(0).alias("kinds"), "lost", F.lit(b"").alias("value")) for x in lists]
    inserted = own.groupBy("content_id", "body").agg(F.count("*").alias("copies"))
    parts.append(inserted.select("content_id", F.lit(None).cast("array<int>").alias("path"), "copies", F.lit(0).alias("kinds"), F.lit(0).alias("lost"), F.col("body").alias("value")))
    rows = functools.reduce(DataFrame.unionByName, parts).repartition(_parts(contents), "content_id").sortWithinPartitions("content_id", F.asc_nulls_first("path"))
    counts = [F.sum(c).alias(c) for c in ("contents", "intact", "refused", "wins")]
    return _tally(rows, kinds).groupBy("kind").agg(*counts)


def _parts(df: DataFrame) -> int:
    return int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))


def sealed_sizes(nodes: DataFrame, p: StoreParams) -> DataFrame:
    """(pairs, plain, sealed): bytes before and after sealing."""
    q = p.with_(protect="siv")
    one = nodes.select("key", "value").dropDuplicates(["key"])
    return one.agg(F.count("*").alias("pairs"), F.sum(F.octet_length("value")).alias("plain"), F.sum(F.octet_length(crypto.seal_expr(F.col("value"), F.col("key"), q))).alias("sealed"))
