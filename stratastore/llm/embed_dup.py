"""Near-duplicate embeddings by NN-descent within labels.

Valid vectors (with a label; neither null nor zero, all components finite) of equal label and components
are one node. A neighbour graph starts from several tables of sign-hash cells; each round every node's
neighbours and reverse neighbours meet, and pairs that improve a list go into it. Lists are bounded, links
are not: every meeting also ties each node to the least one it is linked with there, directly or through
others, whether or not the pair stays in a list. The components of ties and listed links are compared
exactly in tiles, so no link inside a component is missed and no list of pairs leaves a task. Links are
cosines of at least the threshold in double precision, of components as they are stored (float or double).

The number of tables follows the number of cells, for ``RECALL`` of the pairs at the threshold. At the end
recall is audited: ``AUDIT`` nodes, those of the least hashes, are compared with all nodes; while fewer
than ``RECALL`` of their links are found, the search goes on with more tables of other seeds.

Vectors that are not valid link with nothing, and each is its own component. Rows of one vec_id are
separate vectors. Vectors of different lengths never link.
"""

from __future__ import annotations

import warnings

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .components import binned, connected_components, local_components, name_components, tiled
from .shared import forget, n_shuffle, written

THRESHOLD = 0.98
#: Length of the neighbour lists, and what they may grow to over links; links beyond are kept as ties.
LIST, LONG_LIST = 8, 32
TABLES, CELL, MEET, ROUNDS = 6, 128, 48, 6
#: Rounds end when fewer than this share of all list places changed.
SETTLED = 0.002
#: Share of links that are to be found, nodes that audit it (they are broadcast), and searches at most.
RECALL, AUDIT, SEARCHES = 0.9995, 256, 4
#: Queries of ``audit_recall`` that are compared in one pass.
BLOCK = 4_096
#: Bytes of vectors in a meeting task's group.
MEETING_BYTES = 4 << 20
_BITS = 24


def _unit(raw: list[bytes], kind: str) -> np.ndarray:
    """Rows of float64 unit vectors from the bytes of one length."""
    x = np.frombuffer(b"".join(raw), kind).reshape(len(raw), -1).astype(np.float64)
    # scaled first, so that squares neither overflow nor vanish
    x /= np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def nodes_of(vectors: DataFrame, id_col: str, vector_col: str, label_col: str) -> tuple[DataFrame, DataFrame, str]:
    """All rows as (id, h1, h2), null for vectors that link with nothing; the nodes as (node, h1, h2, lab, dim, mult, least_id, vec); and the components' type."""
    double = vectors.schema[vector_col].dataType.elementType.typeName() == "double"
    kind, arrow = ("<f8", "double") if double else ("<f4", "float")
    kept = vectors.select(F.col(id_col).alias("id"), F.col(label_col).alias("lab"), F.col(vector_col).cast(f"array<{arrow}>").alias("v"))

    def run(batches):
        for batch in batches:
            v = batch.column("v")
            length = pc.fill_null(pc.list_value_length(v), 0).to_numpy(zero_copy_only=False).astype(np.int64)
            flat = pc.fill_null(v.flatten(), float("nan")).to_numpy(zero_copy_only=False).astype(kind)
            flat = flat + np.zeros(1, kind)  # one zero
            off = np.concatenate(([0], np.cumsum(length)))
            bad = np.concatenate(([0], np.cumsum(~np.isfinite(flat))))
            some = np.concatenate(([0], np.cumsum(flat != 0)))
            ok = (bad[off[1:]] == bad[off[:-1]]) & (some[off[1:]] > some[off[:-1]]) & batch.column("lab").is_valid().to_numpy(zero_copy_only=False)
            raw = [flat[a:b].tobytes() if good else None for a, b, good in zip(off[:-1].tolist(), off[1:].tolist(), ok.tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column("id"), batch.column("lab"), pa.array(raw, pa.binary())], names=["id", "lab", "vec"])

    types = {f.name: f.dataType.simpleString() for f in kept.schema}
    rows = kept.mapInArrow(run, f"id {types['id']}, lab {types['lab']}, vec binary")
    # two hashes name a vector of a label
    rows = rows.withColumns({"h1": F.when(F.col("vec").isNotNull(), F.xxhash64("lab", "vec")), "h2": F.when(F.col("vec").isNotNull(), F.xxhash64(F.octet_length("vec"), "vec", "lab"))})
    rows = written(rows, "vectors")
    nodes = rows.where("h1 IS NOT NULL").groupBy("h1", "h2").agg(F.count("*").alias("mult"), F.min("id").alias("least_id"), F.first("lab").alias("lab"), F.first("vec").alias("vec"))
    nodes = written(nodes.withColumns({"dim": F.octet_length("vec"), "node": F.monotonically_increasing_id()}), "nodes")
    return rows.select("id", "h1", "h2"), nodes, kind


def tables_for(used: int, threshold: float, least: int) -> int:
    """Tables of so many sign bits that find a pair at the threshold with ``RECALL``."""
    same = (1 - np.arccos(threshold) / np.pi) ** used
    return max(least, int(np.ceil(np.log(1 - RECALL) / np.log(1 - same))) if same < 1 else 1)


def _first_graph(nodes: DataFrame, tables: int, seed: int, threshold: float, kind: str, total: int, width: int) -> DataFrame:
    """(v, u, s, tie): pairs that share a cell of some table, the best of each vector in each cell, and ties."""
    sizes = nodes.groupBy("lab", "dim").agg(F.least(F.greatest(F.ceil(F.log2(F.count("*") / CELL)), F.lit(0)), F.lit(_BITS)).cast("int").alias("used"))
    tables = tables_for(sizes.agg(F.max("used")).first()[0] or 0, threshold, tables)

    def cells(batches):
        planes: dict[int, np.ndarray] = {}
        for batch in batches:
            raw = batch.column("vec").to_pylist()
            bits = np.zeros((len(raw), tables), np.int64)
            dims = np.array([len(x) for x in raw])
            for d in np.unique(dims).tolist():
                p = planes.setdefault(d, np.random.default_rng(seed + d).standard_normal((d // np.dtype(kind).itemsize, tables * _BITS)))
                at = np.flatnonzero(dims == d)
                sign = (_unit([raw[k] for k in at], kind) @ p > 0).reshape(len(at), tables, _BITS)
                bits[at] = sign @ (1 << np.arange(_BITS)[::-1])
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.ListArray.from_arrays(pa.array(np.arange(len(raw) + 1) * tables, pa.int32()), pa.array(bits.ravel()))], names=[*batch.schema.names, "bits"])

    lab = nodes.schema["lab"].dataType.simpleString()
    signed = nodes.select("node", "lab", "dim", "vec").mapInArrow(cells, f"node bigint, lab {lab}, dim int, vec binary, bits array<bigint>")
    rows = signed.join(sizes, ["lab", "dim"]).select("node", "vec", "lab", "dim", "used", F.posexplode("bits").alias("tab", "bit"))
    rows = rows.withColumn("cell", F.xxhash64("lab", "dim", "tab", F.expr(f"shiftright(bit, {_BITS} - used)")))
    many = rows.groupBy("cell").agg(F.count("*").alias("n")).where(F.col("n") > 1)
    # a crowded cell is cut at random; its pieces meet again in the rounds
    rows = rows.join(many, "cell").withColumn("cell", F.xxhash64("cell", F.pmod(F.xxhash64("node", "tab"), F.ceil(F.col("n") / (4 * CELL)).cast("int"))))
    rows = rows.select("cell", F.col("node").alias("m"), "vec", F.lit(True).alias("fresh"), F.lit(-2.0).alias("worst"))
    return _meet(rows, LIST, threshold, kind, total * tables * width)


def _meet(rows: DataFrame, best: int, threshold: float, kind: str, size: int) -> DataFrame:
    """(v, u, s, tie) for the members m of each meeting (cell): pairs with a fresh one whose cosine beats the worst of v's list; the best of each v; and as ties each member with the least of its links' component there.

    size: bytes of vectors in all meetings, about; they are dealt to groups of ``MEETING_BYTES``, and to as many partitions up to those the session shuffles to.
    """

    def run(table: pa.Table) -> pa.Table:
        t = table.sort_by([("cell", "ascending"), ("m", "ascending")]).combine_chunks()
        cell, m, fresh, worst = (t.column(c).to_numpy(zero_copy_only=False) for c in ("cell", "m", "fresh", "worst"))
        raw = t.column("vec").combine_chunks().to_pylist()
        cut = np.flatnonzero(cell[1:] != cell[:-1]) + 1
        out: list[list[np.ndarray]] = [[], [], [], []]
        for a, b in zip([0, *cut.tolist()], [*cut.tolist(), len(m)], strict=True):
            if b - a < 2 or not fresh[a:b].any() or len(raw[a]) == 0:
                continue
            x = _unit(raw[a:b], kind)
            s = x @ x.T
            f = fresh[a:b].astype(bool)
            s[~(f[:, None] | f[None, :])] = -9
            s[m[a:b, None] == m[None, a:b]] = -9
            k = min(best, b - a - 1)
            top = np.argpartition(-s, k - 1, axis=1)[:, :k]
            value = np.take_along_axis(s, top, axis=1)
            good = value > worst[a:b, None]
            r, c = np.nonzero(good)
            out[0].append(m[a:b][r])
            out[1].append(m[a:b][top[r, c]])
            out[2].append(value[r, c])
            out[3].append(np.zeros(len(r), bool))
            least = local_components(s >= threshold)
            tied = np.flatnonzero(least != np.arange(b - a))
            out[0].append(m[a:b][tied])
            out[1].append(m[a:b][least[tied]])
            out[2].append(np.full(len(tied), threshold))
            out[3].append(np.ones(len(tied), bool))
        join = lambda x, kind: np.concatenate(x) if x else np.zeros(0, kind)
        return pa.table({"v": join(out[0], np.int64), "u": join(out[1], np.int64), "s": join(out[2], np.float64), "tie": join(out[3], bool)})

    count = max(1, size // MEETING_BYTES)
    dealt = rows.withColumn("bin", F.pmod(F.xxhash64("cell", F.lit(3)), F.lit(count))).repartition(min(n_shuffle(rows.sparkSession), count), "bin")
    return dealt.groupBy("bin").applyInArrow(run, "v bigint, u bigint, s double, tie boolean")


def _best(pairs: DataFrame, threshold: float) -> DataFrame:
    """The best of each v's pairs, with rank; lists that are full of links are longer."""
    one = pairs.groupBy("v", "u").agg(F.max("s").alias("s"), F.min("fresh").alias("fresh"))
    ranked = one.withColumn("rank", F.row_number().over(Window.partitionBy("v").orderBy(F.desc("s"), "u"))).where(F.col("rank") <= LONG_LIST)
    # a list goes on beyond LIST only over links
    return ranked.where((F.col("rank") <= LIST) | (F.col("s") >= threshold))


def neighbour_graph(nodes: DataFrame, kind: str, threshold: float = THRESHOLD, rounds: int = ROUNDS, tables: int = TABLES, seed: int = 17) -> DataFrame:
    """(v, u, s): the neighbour lists after NN-descent, and the ties of all meetings with s = threshold. tables: at least so many."""
    total, size = nodes.agg(F.count("*"), F.coalesce(F.sum("dim"), F.lit(0))).first()
    width = max(1, size // max(total, 1))
    vec = nodes.select(F.col("node").alias("m"), "vec")
    found = written(_first_graph(nodes, tables, seed, threshold, kind, total, width), "met")
    ties = found.where("tie").select("v", "u", "s")
    graph = written(_best(found.where("NOT tie").select("v", "u", "s", F.lit(True).alias("fresh")), threshold), "graph")
    for turn in range(rounds):
        worst = graph.groupBy("v").agg(F.when(F.count("*") >= LIST, F.min("s")).otherwise(F.lit(-2.0)).alias("w"), F.min((F.col("s") >= threshold).cast("int")).alias("full"))
        # saturated lists take any link; others what beats their last place
        worst = worst.select(F.col("v").alias("m"), F.when(F.col("full") == 1, F.lit(threshold - 1e-12)).otherwise(F.col("w")).alias("worst"))
        both = graph.select(F.col("v").alias("cell"), F.col("u").alias("m"), "fresh").union(graph.select(F.col("u").alias("cell"), F.col("v").alias("m"), "fresh"))
        both = both.groupBy("cell", "m").agg(F.max("fresh").alias("fresh"))
        degree = both.groupBy("cell").agg(F.count("*").alias("n"), F.max("fresh").alias("any")).where("any AND n > 1")
        met = both.join(degree, "cell").withColumn("cell", F.xxhash64("cell", F.pmod(F.xxhash64("m", F.lit(turn)), F.ceil(F.col("n") / MEET).cast("int"))))
        met = met.select("cell", "m", "fresh").join(vec, "m").join(worst, "m", "left").withColumn("worst", F.coalesce("worst", F.lit(-2.0)))
        found = written(_meet(met.select("cell", "m", "vec", "fresh", "worst"), LONG_LIST, threshold, kind, 2 * graph.count() * width), "met")
        ties = ties.union(found.where("tie").select("v", "u", "s"))
        pairs = graph.select("v", "u", "s", F.lit(False).alias("fresh")).union(found.where("NOT tie").select("v", "u", "s", F.lit(True).alias("fresh")))
        before, graph = graph, written(_best(pairs, threshold), "graph")
        forget(before)
        changed = graph.where("fresh").count()
        if changed <= SETTLED * total * LIST:
            break
    return graph.select("v", "u", "s").union(ties)


def _tile_links(group: pa.Table, threshold: float, kind: str) -> pa.Table:
    """(node, peer, links) of the groups, or pairs of tiles, in one bin; see near_dup.group_links."""
    t = group.sort_by([("grp", "ascending"), ("ti", "ascending"), ("tj", "ascending"), ("node", "ascending")]).combine_chunks()
    key = np.stack([t.column(c).to_numpy().astype(np.int64) for c in ("grp", "ti", "tj")])
    node, side, mult = (t.column(c).to_numpy() for c in ("node", "side", "mult"))
    raw = t.column("vec").combine_chunks().to_pylist()
    cut = np.flatnonzero((key[:, 1:] != key[:, :-1]).any(axis=0)) + 1
    nodes, peers, links = [], [], []
    for a, b in zip([0, *cut.tolist()], [*cut.tolist(), len(node)], strict=True):
        if b - a < 2:
            continue
        x, own = _unit(raw[a:b], kind), side[a:b]
        adjacent = x @ x.T >= threshold
        if key[1, a] != key[2, a]:
            adjacent &= own[:, None] != own[None, :]
        np.fill_diagonal(adjacent, False)
        least = local_components(adjacent)
        some = np.flatnonzero(adjacent.any(axis=1))
        nodes.append(node[a:b][some])
        peers.append(node[a:b][least[some]])
        links.append((adjacent[some] @ mult[a:b]).astype(np.int64))
    join = lambda x: np.concatenate(x) if x else np.zeros(0, np.int64)
    return pa.table({"node": join(nodes), "peer": join(peers), "links": join(links)})


def near_duplicates(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", threshold: float = THRESHOLD) -> DataFrame:
    """One row per vector: its id, n_links, component_id, kept."""
    rows, nodes, kind = nodes_of(vectors, id_col, vector_col, label_col)
    asked = nodes.select("node", "lab", "dim", "vec").orderBy(F.xxhash64("node"), "node").limit(AUDIT).collect()
    true = {r.node: r.n for r in count_links(nodes, asked, threshold, kind).collect()}
    ties, tables = None, TABLES
    for search in range(SEARCHES):
        graph = neighbour_graph(nodes, kind, threshold, tables=tables, seed=17 + search).where(F.col("s") >= threshold).select("v", "u")
        ties = graph if ties is None else ties.union(graph)
        groups = written(connected_components(ties, "v", "u").select("node", F.col("component").alias("grp")), "groups")
        tiles = binned(tiled(groups.join(nodes.select("node", "mult", "vec"), "node"), "grp", "node"), groups.count())
        links = written(tiles.groupBy("bin").applyInArrow(lambda t: _tile_links(t, threshold, kind), "node bigint, peer bigint, links bigint"), "verified")
        got = links.where(F.col("node").isin([int(k) for k in true])).groupBy("node").agg(F.sum("links").alias("n")).agg(F.sum("n")).first()[0] if true else 0
        if (got or 0) >= RECALL * sum(true.values()):
            break
        tables *= 2
    else:
        warnings.warn(f"the audit found {got} of {sum(true.values())} links", stacklevel=2)
    named = name_components(nodes, connected_components(links, "node", "peer"))
    per = nodes.select("node", "h1", "h2", "mult", "least_id").join(named, "node", "left").join(links.groupBy("node").agg(F.sum("links").alias("links")), "node", "left")
    per = per.select("h1", "h2", F.when(F.col("linked"), F.col("least")).otherwise(F.col("least_id")).alias("component_id"), (F.coalesce("links", F.lit(0)) + F.col("mult") - 1).alias("n"))
    joined = rows.join(written(per, "classes"), ["h1", "h2"], "left")
    out = joined.select(F.col("id").alias(id_col), F.coalesce("n", F.lit(0)).cast("long").alias("n_links"), F.when(F.col("h1").isNull(), F.col("id")).otherwise(F.col("component_id")).alias("component_id"))
    return out.withColumn("kept", F.col(id_col).eqNullSafe(F.col("component_id")))


def count_links(nodes: DataFrame, asked: list, threshold: float, kind: str) -> DataFrame:
    """(node, n): the vectors that each asked node (node, lab, dim, vec) is linked with, beside its own copies; by comparing with all nodes."""
    by: dict[tuple, list] = {}
    for r in asked:
        by.setdefault((r.lab, r.dim), []).append((r.node, bytes(r.vec)))
    packed = {k: (np.array([n for n, _ in x], np.int64), _unit([v for _, v in x], kind)) for k, x in by.items()}
    shared = nodes.sparkSession.sparkContext.broadcast(packed)

    def run(batches):
        for batch in batches:
            lab, dim, mult, node, raw = (batch.column(c).to_pylist() for c in ("lab", "dim", "mult", "node", "vec"))
            groups: dict[tuple, list[int]] = {}
            for k, key in enumerate(zip(lab, dim, strict=True)):
                if key in shared.value:
                    groups.setdefault(key, []).append(k)
            names, counts = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
            for key, at in groups.items():
                q, m = shared.value[key]
                near = _unit([raw[k] for k in at], kind) @ m.T >= threshold
                near &= np.array([node[k] for k in at])[:, None] != q[None, :]
                names.append(q)
                counts.append(np.array([mult[k] for k in at]) @ near)
            yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(names)), pa.array(np.concatenate(counts).astype(np.int64))], names=["node", "n"])

    return nodes.select("node", "lab", "dim", "mult", "vec").mapInArrow(run, "node bigint, n bigint").groupBy("node").agg(F.sum("n").alias("n"))


def audit_recall(vectors: DataFrame, found: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", label_col: str = "label", threshold: float = THRESHOLD, every: int = 100) -> DataFrame:
    """One row: links (true ones of the vectors whose id every divides, by comparing with all vectors, ``BLOCK`` queries a pass), links_found, recall. Ids are taken to be unique."""
    spark = vectors.sparkSession
    rows, nodes, kind = nodes_of(vectors, id_col, vector_col, label_col)
    asked = written(rows.where((F.col("id") % every == 0) & F.col("h1").isNotNull()).join(nodes, ["h1", "h2"]).select("id", "node", "lab", "dim", "mult", "vec"), "asked")
    total = spark.createDataFrame([(0, 0)], "links bigint, links_found bigint")
    block: list = []

    def passed(block: list) -> DataFrame:
        true = count_links(nodes, block, threshold, kind)
        each = asked.where(F.col("node").isin([int(r.node) for r in block])).join(true, "node", "left")
        each = each.select(F.col("id").alias(id_col), (F.coalesce("n", F.lit(0)) + F.col("mult") - 1).alias("n")).join(found.select(id_col, "n_links"), id_col)
        return each.agg(F.coalesce(F.sum("n"), F.lit(0)).alias("links"), F.coalesce(F.sum(F.least("n", "n_links")), F.lit(0)).alias("links_found"))

    for r in asked.dropDuplicates(["node"]).select("node", "lab", "dim", "vec").toLocalIterator():
        block.append(r)
        if len(block) == BLOCK:
            total, block = total.union(passed(block)), []
    if block:
        total = total.union(passed(block))
    out = total.agg(F.sum("links").alias("links"), F.sum("links_found").alias("links_found"))
    return out.withColumn("recall", F.when(F.col("links") > 0, F.col("links_found") / F.col("links")).otherwise(F.lit(1.0)))
