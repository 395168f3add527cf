"""The experiments, as plans: all cells and runs of an experiment are one DataFrame.

Edit experiments put two contents into a store of their own, so the cell is part of the grouping key.
Version series use that a store is a set union keyed by tag: what a version adds is the keys whose first
version it is.
"""

from __future__ import annotations

import hashlib
import itertools
from collections.abc import Callable
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..functions import rolling
from ..operators import kvs, measures, stream_tree, tree
from ..params import SCHEMES, StoreParams
from ..sources import contents as src
from . import analytic, histories

RUNS = 20


def grid(schemes: tuple[str, ...] = SCHEMES, sizes: tuple[int, ...] = (64, 128, 256), **options: object) -> list[StoreParams]:
    """All combinations; the chunk size means nothing to whole contents, which come once a size all the same."""
    return [StoreParams(chunk=s, scheme=x, **options) for x in schemes for s in sizes]  # type: ignore[arg-type]


def place_of(seed: Column, n: Column) -> Column:
    """A place in 0..n-1 that the seed's text fixes, the same in every engine."""
    word = F.conv(F.substring(F.sha2(F.encode(F.concat(seed.cast("string"), F.lit(":place")), "utf-8"), 256), 1, 12), 16, 10).cast("long")
    return F.pmod(word, n)


def edited(contents: DataFrame, kind: str, delta: int) -> DataFrame:
    """(content_id, run, n, before, after) of one edit of each content; contents: with version as the run's seed.

    kind: 'overwrite' (delta bytes become other random ones), 'insert' (delta bytes are put in), 'scatter' (a single
    byte in each of delta pieces of equal length, each at a place of its own).
    """
    n = F.octet_length("body").cast("long")
    rows = contents.select("content_id", F.col("version").alias("run"), n.alias("n"), F.col("body").alias("before"))
    if kind == "overwrite":
        at = place_of(F.col("run"), F.greatest(F.col("n") - delta + 1, F.lit(1)))
        new = src.random_bytes(F.concat(F.col("run").cast("string"), F.lit(":new")), delta)
        # as long as what is there, and not the same
        own = F.substring(F.col("before"), (at + 1).cast("int"), F.lit(delta))
        new = F.substring(new, F.lit(1), F.octet_length(own))
        after = src.overwrite(F.col("before"), at, F.when(new == own, src.flipped(F.col("before"), at, delta)).otherwise(new))
    elif kind == "insert":
        at = place_of(F.col("run"), F.col("n") + 1)
        after = src.insert(F.col("before"), at, src.random_bytes(F.concat(F.col("run").cast("string"), F.lit(":new")), delta))
    elif kind == "scatter":
        # piece by piece: each has one changed byte, and the rest of the division stays
        step = F.floor(F.col("n") / delta)

        def changed(k: Column) -> Column:
            at = place_of(F.concat_ws(":", F.col("run").cast("string"), k.cast("string")), step)
            piece = F.substring(F.col("before"), (k * step + 1).cast("int"), step.cast("int"))
            return F.hex(src.overwrite(piece, at, src.flipped(piece, at, 1)))

        rest = F.substring(F.col("before"), (step * delta + 1).cast("int"), F.lit(delta))
        after = F.concat(F.unhex(F.array_join(F.transform(F.sequence(F.lit(0), F.lit(delta - 1)), changed), "")), rest)
    else:
        raise ValueError(f"unknown edit {kind!r}")
    return rows.withColumn("after", after)


def edit_costs(pairs: DataFrame, params: list[StoreParams], model: bool = True, delta: int = 1) -> DataFrame:
    """(scheme, s, n, run, added, model): what inserting ``after`` adds to a store that holds ``before``."""
    both = pairs.select("run", "n", F.lit(0).alias("version"), F.col("before").alias("body")).unionByName(pairs.select("run", "n", F.lit(1).alias("version"), F.col("after").alias("body")))
    nodes = tree.build_grid(both, params, ["run", "n", "version"])
    first = nodes.groupBy("scheme", "s", "n", "run", "key").agg(F.min("version").alias("version"), F.first("size").alias("size"))
    out = first.groupBy("scheme", "s", "n", "run").agg(F.sum(F.when(F.col("version") == 1, measures.pair_cost(F.col("size"))).otherwise(0)).alias("added"))
    if not model:
        return out
    fixed = F.col("scheme") == "fixed_tree"
    bound = F.when(fixed, analytic.added_delta_col(F.col("n"), F.col("s"), F.lit(delta), True)).when(F.col("scheme") == "cdc_tree", analytic.added_delta_col(F.col("n"), F.col("s"), F.lit(delta)))
    return out.withColumn("model", bound)


def edit_costs_in_place(pairs: DataFrame, params: list[StoreParams]) -> DataFrame:
    """(scheme, s, n, run, added, model) of one changed byte like ``edit_costs``, each pair in a store of its own and compared where it lies: no exchange."""
    schema = "scheme string, s int, n bigint, run bigint, added bigint"

    def sizes(body: bytes, p: StoreParams, prefix: rolling.Prefix) -> dict[bytes, int]:
        found = tree.levels_of(body, p, None, prefix, tree.name_of)
        # lists are of references, whatever the names' size
        return {k: size * (measures.REF // tree.NAME if x.level else 1) for x in found for k, size in zip(x.keys, (x.cuts[1:] - x.cuts[:-1]).tolist(), strict=True)}

    def run(batches):
        for batch in batches:
            rows = []
            for r in batch.to_pylist():
                # the least chunk sizes first: what they find holds what the others need
                prefixes: dict[str, tuple[rolling.Prefix, rolling.Prefix]] = {}
                for p in sorted(params, key=lambda p: p.chunk):
                    sums = prefixes.get(p.ring) or prefixes.setdefault(p.ring, (rolling.Prefix(r["before"], p.ring), rolling.Prefix(r["after"], p.ring)))
                    old = sizes(r["before"], p, sums[0])
                    rows.append((p.scheme, p.chunk, r["n"], r["run"], sum(size + measures.REF for k, size in sizes(r["after"], p, sums[1]).items() if k not in old)))
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows, strict=True), (pa.string(), pa.int32(), pa.int64(), pa.int64(), pa.int64()), strict=True)], names=["scheme", "s", "n", "run", "added"])

    out = tree.spread(pairs.select("run", "n", "before", "after"), ["run"]).mapInArrow(run, schema)
    return out.withColumn("model", analytic.added_delta_col(F.col("n"), F.col("s"), F.lit(1)))


def edit_experiment(spark: SparkSession, kind: str, delta: int, n: int, params: list[StoreParams], runs: int = RUNS, seed: int = 0) -> DataFrame:
    """One size and edit over random contents."""
    return edit_costs(edited(src.random_contents(spark, seed, n, runs), kind, delta), params, kind == "overwrite", delta)


def expansion_experiment(contents: DataFrame, params: list[StoreParams]) -> DataFrame:
    """(content_id, scheme, s, cost, n, expansion)."""
    own = contents.where("octet_length(body) > 0")
    return measures.expansion_factor(tree.build_grid(own, params), own)


def version_costs(series: DataFrame, params: list[StoreParams], by: list[str] | None = None) -> DataFrame:
    """(by…, scheme, s, version, added, cost) of inserting a series' contents in the order of their versions."""
    keep = [*(by or []), "version"]
    return measures.cumulative_cost(tree.build_grid(series, params, keep), [*(by or []), "scheme", "s"])


def total_costs(contents: DataFrame, params: list[StoreParams], by: list[str] | None = None) -> DataFrame:
    """(by…, scheme, s, pairs, cost) of a store that holds all contents."""
    return measures.storage_cost(tree.build_grid(contents, params, [*(by or []), "n"] if by else ["n"]), [*(by or []), "scheme", "s"])


def _by_task(history: src.History, versions: list[tuple[int, int, int]], cut: Callable, schema: str) -> DataFrame:
    """What ``cut`` gives for each task: its snapshots, and batches of the rows of all of them in order.

    Snapshots are dealt to a task a core or two. A row goes once to each task that has a snapshot with it, and
    the tasks cut their snapshots side by side from rows in order, a block at a time.
    """
    spark = history.rows.sparkSession
    tasks = max(1, min(len(versions), 2 * spark.sparkContext.defaultParallelism))
    # from both ends, so that each task has long and short ones
    dealt = {v: min(k % (2 * tasks), 2 * tasks - 1 - k % (2 * tasks)) for k, (_, v, _) in enumerate(sorted(versions, key=lambda x: -x[2]))}
    last = [max((p for p, v, _ in versions if dealt[v] == g), default=None) for g in range(tasks)]
    rows = history.rows.where("p IS NOT NULL").withColumn("g", F.explode(F.filter(F.array(*[F.when(F.col("p") <= x, F.lit(g)) for g, x in enumerate(last)]), lambda x: x.isNotNull())))
    placed = rows.select("g", "p", F.lpad(F.col("at").cast("string"), 12, "0").alias("at"), F.encode(F.concat("line", F.lit("\n")), "utf-8").alias("line"))

    def run(batches):
        # a partition can have several tasks' rows, one after the other
        def parts():
            for batch in batches:
                g, at = batch.column("g").to_numpy(), 0
                while at < len(g):
                    end = int(np.searchsorted(g, g[at], "right"))
                    yield int(g[at]), batch.slice(at, end - at)
                    at = end

        for g, own in itertools.groupby(parts(), lambda x: x[0]):
            yield from cut([x for x in versions if dealt[x[1]] == g], (batch for _, batch in own))

    return placed.repartitionById(tasks, F.col("g")).sortWithinPartitions("g", "at", "line").mapInArrow(run, schema)


def history_grid(history: src.History, params: list[StoreParams], versions: list[tuple[int, int, int]]) -> DataFrame:
    """(version, scheme, s, key, size) of the nodes of a history's snapshots, as ``tree.build_grid`` makes them from whole bodies; a node can come more than once."""
    schema = "version bigint, scheme string, s int, key binary, size bigint"

    def cut(own: list[tuple[int, int, int]], batches):
        """Batches of rows of one task to batches of nodes of its snapshots."""
        held: list[tuple[int, int, list[bytes], list[int]]] = []
        count = [0]

        def taker(version: int):
            def take(k: int, names: list[bytes], sizes: list[int]) -> None:
                if names:
                    held.append((version, k, names, sizes))
                    count[0] += len(names)

            return take

        def out():
            lengths = np.array([len(x[2]) for x in held])
            sets = [params[x[1]] for x in held]
            spread = lambda values, t: pa.array(values, t).take(pa.array(np.repeat(np.arange(len(held)), lengths)))
            batch = pa.RecordBatch.from_arrays([
                spread([x[0] for x in held], pa.int64()), spread([p.scheme for p in sets], pa.string()), spread([p.chunk for p in sets], pa.int32()),
                pa.array([k for x in held for k in x[2]], pa.binary()), pa.array([n for x in held for n in x[3]], pa.int64()),
            ], names=["version", "scheme", "s", "key", "size"])
            held.clear()
            count[0] = 0
            return batch

        for _ in stream_tree.fed([(p, stream_tree.Content(n, params, taker(v))) for p, v, n in own], batches):
            if count[0] > tree.BATCH_ROWS:
                yield out()
        if held:
            yield out()

    return _by_task(history, versions, cut, schema)


#: Keys that a task remembers so as not to give a node again.
SEEN = 1 << 19


def insert_history(history: src.History, series: str, p: StoreParams) -> tuple[DataFrame, DataFrame]:
    """(roots, pairs) of an unsealed store of a history's snapshots, which are never one value each; the pairs are a table bucketed by key."""
    versions, tag = history.versions(), tree.digest(p)

    def cut(own: list[tuple[int, int, int]], batches):
        seen: set[bytes] = set()
        keys, values, roots = [], [], []

        def taker(version: int):
            def take(_: int, names: list[bytes], found: list[bytes]) -> None:
                for key, value in zip(names, found, strict=True):
                    if key not in seen:
                        seen.add(key)
                        keys.append(key)
                        values.append(value)
                        roots.append(None)

            return take

        def out():
            batch = pa.RecordBatch.from_arrays([pa.array(keys, pa.binary()), pa.array(values, pa.binary()), pa.array(roots, pa.int64())], names=["key", "value", "version"])
            for x in (keys, values, roots):
                x.clear()
            if len(seen) > SEEN:
                seen.clear()
            return batch

        contents = [(q, stream_tree.Content(n, [p], taker(v), tag)) for q, v, n in own]
        for _ in stream_tree.fed(contents, batches):
            if len(keys) > tree.BATCH_ROWS // 8:
                yield out()
        for (_, v, _), (_, content) in zip(own, contents, strict=True):
            keys.append(content.root[0])
            values.append(content.root[1])
            roots.append(v)
        yield out()

    nodes = _by_task(history, versions, cut, "key binary, value binary, version bigint")
    pairs = kvs.saved(nodes.groupBy("key").agg(F.first("value").alias("value"), F.max("version").alias("version")))
    spark = history.rows.sparkSession
    known = spark.createDataFrame([(f"{series}:{v}", v, p.height(n), n) for _, v, n in versions], "content_id string, version bigint, height int, n bigint")
    roots = pairs.where("version IS NOT NULL").select("key", "version").join(F.broadcast(known), "version").select("content_id", "key", "height", "n")
    return roots, pairs.select("key", "value")


def history_costs(history: src.History, params: list[StoreParams]) -> DataFrame:
    """(scheme, s, version, added, cost) like ``version_costs``, of snapshots too large for one value."""
    return histories.costs(history, params)


def history_totals(history: src.History, params: list[StoreParams]) -> DataFrame:
    """(scheme, s, pairs, cost) like ``total_costs``."""
    return histories.totals(history, params)


def edited_versions(spark: SparkSession, seed: int, n: int, versions: int, runs: int = 1, kind: str = "overwrite") -> DataFrame:
    """Random contents (one a run) and modifications of each: (run, version, body); version 0 is the content itself.

    kind: 'insert' (one random byte put in at a random place) or 'overwrite' (one byte becomes another). Bodies
    are made where they are used, from the run and the version.
    """
    if kind not in ("insert", "overwrite"):
        raise ValueError(f"unknown kind of versions {kind!r}")

    def make(batches):
        for batch in batches:
            for run, version in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                base, label = _random_body(run, n), f"{run}:{version}"
                if version:
                    at = int(hashlib.sha256(f"{label}:place".encode()).hexdigest()[:12], 16) % (n + (kind == "insert"))
                    new = hashlib.sha256(f"{label}:new:0".encode()).digest()[:1] if kind == "insert" else bytes([base[at] ^ 255])
                    base = base[:at] + new + base[at + (kind == "overwrite") :]
                yield pa.RecordBatch.from_arrays([pa.array([run]), pa.array([version]), pa.array([base], pa.binary())], names=["run", "version", "body"])

    cells = spark.range(seed, seed + runs).select(F.col("id").alias("run")).crossJoin(spark.range(versions).select(F.col("id").alias("version")))
    return cells.repartition(4 * spark.sparkContext.defaultParallelism, "run", "version").mapInArrow(make, "run bigint, version bigint, body binary")


@lru_cache(maxsize=4)
def _random_body(seed: int, n: int) -> bytes:
    """What src.random_bytes gives, kept by a worker for the versions of one content."""
    return b"".join(hashlib.sha256(f"{seed}:{i}".encode()).digest() for i in range(-(-n // 32)))[:n]


def break_even_versions(costs: DataFrame, factor: float, tree_scheme: str = "cdc_tree", flat_scheme: str = "cdc") -> DataFrame:
    """(s, version, flat_s): from which version on the tree with chunk size s costs at most ``factor`` times the best flat scheme.

    costs: scheme, s, version, cost, smoothed or means over runs. The best flat chunk size is that of each version.
    """
    flat = costs.where(F.col("scheme") == flat_scheme).groupBy("version").agg(F.min(F.struct(F.col("cost"), F.col("s"))).alias("best"))
    both = costs.where(F.col("scheme") == tree_scheme).join(flat, "version").where(F.col("cost") <= F.col("best.cost") * factor)
    first = both.groupBy("s").agg(F.min(F.struct("version", "best.s")).alias("f"))
    return first.select("s", F.col("f.version").alias("version"), F.col("f.s").alias("flat_s"))


def passage_overlap(docs: DataFrame, passages: DataFrame, p: StoreParams) -> DataFrame:
    """(content_id, chunks, found): how many of each passage's chunks are chunks of the documents."""
    have = tree.build(docs, p).where("level = 0").select("key").distinct().withColumn("hit", F.lit(1))
    own = tree.build(passages, p).where("level = 0").select("content_id", "key")
    return own.join(have, "key", "left").groupBy("content_id").agg(F.count("*").alias("chunks"), F.count("hit").alias("found"))


def dedup_by(contents: DataFrame, params: list[StoreParams], by: list[str]) -> DataFrame:
    """(by…, scheme, s, bytes_in, cost, ratio) of a store for each group."""
    nodes = tree.build_grid(contents, params, by)
    total = contents.groupBy(*by).agg(F.sum("n").alias("bytes_in"))
    cost = measures.storage_cost(nodes, [*by, "scheme", "s"])
    return cost.join(total, by).select(*by, "scheme", "s", "bytes_in", "cost", (F.col("bytes_in") / F.col("cost")).alias("ratio"))
