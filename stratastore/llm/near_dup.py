"""Similarity join of documents on word shingles: MinHash bands, exact verification, classes and link counts.

A document's set holds the hashes of its runs of five words (digits, letters and non-ASCII characters,
A-Z in lower case); a text of one to four words is one run. Documents of equal sets are one node, so
copies are never compared. Bands and rows are chosen for the target recall at the threshold. Band hashes
are shuffled; each bucket ties its nodes to its least one, and the components of these ties are candidate
groups, so no pair is ever listed; large groups are banded again with more rows. Within a group all pairs
are verified on the full sets, tile by tile; what leaves a tile is each node's number of links and one link
into its local component. A set is named by two 64-bit digests and its size.

Texts without words (null and empty ones too) have no set and link with nothing. Rows of one id with
different texts are different rows. Rows without an id are compared and counted, and their class has the
least id among its rows, which is null if it has none; a row alone has its own id as class.
"""

from __future__ import annotations

from fractions import Fraction

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .components import binned, connected_components, local_components, name_components, tiled
from .shared import forget, written

SHINGLE, THRESHOLD, RECALL, MAX_HASHES = 5, 0.8, 0.9995, 120
#: What names a set: two digests and its size.
SET = ["d1", "d2", "n"]
#: Candidate groups of more nodes are grouped anew with so many rows a band.
LARGE, STRICT_ROWS = 4_000, 10


def choose_bands(threshold: float = THRESHOLD, recall: float = RECALL, max_hashes: int = MAX_HASHES) -> tuple[int, int]:
    """(bands, rows): the most rows for which some number of bands within max_hashes finds a pair at the threshold with the recall."""
    best = (max_hashes, 1)
    for rows in range(1, max_hashes + 1):
        bands = next((b for b in range(1, max_hashes // rows + 1) if 1 - (1 - threshold**rows) ** b >= recall), None)
        if bands is None:
            break
        best = (bands, rows)
    return best


def shingle_sets(texts: pa.Array, width: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """Sorted distinct shingle hashes of all texts in a row, and the texts' offsets."""
    _, _, _, first, words = K.word_hashes(texts, K.WORD)
    count = np.diff(first)
    at, hashes = K.windows(words, first, width)
    owner = np.searchsorted(first, at, "right") - 1
    for w in range(1, width):
        if (count == w).any():
            p, h = K.windows(words, first, w)
            o = np.searchsorted(first, p, "right") - 1
            short = count[o] == w
            hashes, owner = np.concatenate((hashes, h[short] + K.U64(w))), np.concatenate((owner, o[short]))
    order = np.lexsort((hashes, owner))
    hashes, owner = hashes[order], owner[order]
    if len(hashes):
        new = np.ones(len(hashes), dtype=bool)
        new[1:] = (hashes[1:] != hashes[:-1]) | (owner[1:] != owner[:-1])
        hashes, owner = hashes[new], owner[new]
    return hashes, np.searchsorted(owner, np.arange(len(count) + 1))


def band_hashes(hashes: np.ndarray, offsets: np.ndarray, bands: int, rows: int, seed: int = 5) -> np.ndarray:
    """(texts, bands) hashes of the texts' least values under bands x rows hash functions; texts without a set get zeros."""
    out = np.zeros((len(offsets) - 1, bands), dtype=K.U64)
    full = np.flatnonzero(np.diff(offsets))
    if not len(full):
        return out
    keys = np.random.default_rng(seed).integers(0, 1 << 63, (2, bands * rows), dtype=np.uint64) | K.U64(1)
    starts = offsets[:-1][full]
    for b in range(bands):
        acc = np.full(len(full), b + 1, dtype=K.U64)
        for r in range(b * rows, (b + 1) * rows):
            acc = acc * K.U64(K.BASE) + np.minimum.reduceat((hashes ^ keys[0, r]) * keys[1, r], starts)
        out[full, b] = K.mix(acc)
    return out


def set_digests(hashes: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Two 64-bit digests of each set, which with its size name it."""
    sums = [np.concatenate((np.zeros(1, K.U64), np.cumsum(K.mix(hashes + K.U64(s))))) for s in (1, 2)]
    first, second = ((s[offsets[1:]] - s[offsets[:-1]]).view(np.int64) for s in sums)
    return first, second


def _signatures(docs: DataFrame, id_col: str, text_col: str, bands: int, rows: int) -> DataFrame:
    """(id, th, n, d1, d2, bands): hash of each document's text, size and digests of each document's set, and its band hashes."""
    kept = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"), F.xxhash64(text_col).alias("th"))

    def run(batches):
        for batch in batches:
            for part in K.slices(batch, "text"):
                hashes, offsets = shingle_sets(part.column("text"))
                n = np.diff(offsets)
                d1, d2 = set_digests(hashes, offsets)
                sig = band_hashes(hashes, offsets, bands, rows).view(np.int64)
                sig = pa.ListArray.from_arrays(pa.array(np.arange(len(n) + 1) * bands, pa.int32()), pa.array(sig.ravel()))
                yield pa.RecordBatch.from_arrays([part.column("id"), part.column("th"), pa.array(n, pa.int64()), pa.array(d1), pa.array(d2), sig], names=["id", "th", "n", "d1", "d2", "bands"])

    kind = kept.schema["id"].dataType.simpleString()
    return kept.mapInArrow(run, f"id {kind}, th bigint, n bigint, d1 bigint, d2 bigint, bands array<bigint>")


def verify(sets: list[np.ndarray], left: np.ndarray, right: np.ndarray, threshold: Fraction) -> np.ndarray:
    """Whether each left and right member reach the threshold: a boolean matrix over indices into sets."""
    size = np.array([len(s) for s in sets], dtype=np.int64)
    used = np.unique(np.concatenate((left, right)))
    owner = np.repeat(used, size[used])
    values, column, count = np.unique(np.concatenate([sets[k] for k in used]), return_inverse=True, return_counts=True)
    shared = count[column] > 1
    owner, column = owner[shared], (np.cumsum(count > 1) - 1)[column[shared]]
    width = int((count > 1).sum())
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    common = np.zeros((len(left), len(right)), dtype=np.float64)
    place_l, place_r = np.full(len(sets), -1), np.full(len(sets), -1)
    place_l[left], place_r[right] = np.arange(len(left)), np.arange(len(right))
    step = max(1, 4_000_000 // max(len(left), len(right)))
    for at in range(0, width, step):
        a, b = np.searchsorted(column, (at, at + step))
        o, c = owner[a:b], column[a:b] - at
        one, two = np.zeros((len(left), step), np.float32), np.zeros((len(right), step), np.float32)
        mine, yours = place_l[o] >= 0, place_r[o] >= 0
        one[place_l[o[mine]], c[mine]] = 1
        two[place_r[o[yours]], c[yours]] = 1
        common += one @ two.T
    both = size[left][:, None] + size[right][None, :] - common
    return common * threshold.denominator >= both * threshold.numerator


def group_links(group: pa.Table, threshold: Fraction) -> pa.Table:
    """All verified links of the groups (or pairs of tiles) in one bin: (node, peer, links), a row for each member that has any."""
    order = group.sort_by([("grp", "ascending"), ("ti", "ascending"), ("tj", "ascending"), ("node", "ascending")]).combine_chunks()
    key = np.stack([order.column(c).to_numpy().astype(np.int64) for c in ("grp", "ti", "tj")])
    node, side, mult = (order.column(c).to_numpy() for c in ("node", "side", "mult"))
    cut = np.flatnonzero((key[:, 1:] != key[:, :-1]).any(axis=0)) + 1
    nodes, peers, links = [], [], []
    for a, b in zip([0, *cut.tolist()], [*cut.tolist(), len(node)], strict=True):
        if b - a < 2:
            continue
        sets = [np.frombuffer(x, K.U64) for x in order.column("set").slice(a, b - a).to_pylist()]
        own, m = side[a:b], mult[a:b]
        if key[1, a] == key[2, a]:
            left = right = np.arange(b - a)
        else:
            left, right = np.flatnonzero(own == key[1, a]), np.flatnonzero(own == key[2, a])
        if not (len(left) and len(right)):
            continue
        found = verify(sets, left, right, threshold)
        adjacent = np.zeros((b - a, b - a), dtype=bool)
        adjacent[np.ix_(left, right)] = found
        adjacent |= adjacent.T
        np.fill_diagonal(adjacent, False)
        least = local_components(adjacent)
        some = np.flatnonzero(adjacent.any(axis=1))
        nodes.append(node[a:b][some])
        peers.append(node[a:b][least[some]])
        links.append((adjacent[some] @ m).astype(np.int64))
    join = lambda x: np.concatenate(x) if x else np.zeros(0, np.int64)
    return pa.table({"node": join(nodes), "peer": join(peers), "links": join(links)})


def similarity_classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, recall: float = RECALL) -> DataFrame:
    """One row per document: id, class_id, n_links (other documents at the threshold or above), node (of its set; null without words)."""
    out = _classes(docs, id_col, text_col, threshold, recall)
    return out.select(F.col("id").alias(id_col), "class_id", "n_links", "node")


def _classes(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", threshold: float = THRESHOLD, recall: float = RECALL) -> DataFrame:
    """One row per document: id, class_id, n_links, node, th (hash of its text), grp (of its class, also where ids are null; null without words)."""
    bands, rows = choose_bands(threshold, recall)
    exact = Fraction(threshold).limit_denominator(10_000)
    signed = written(_signatures(docs, id_col, text_col, bands, rows), "signatures")
    nodes = signed.where("n > 0").groupBy(*SET).agg(F.count("*").alias("mult"), F.min("id").alias("least_id"), F.first("bands").alias("bands"))
    # numbered once, by being written
    nodes = written(nodes.withColumn("node", F.monotonically_increasing_id()), "nodes")
    groups = written(_tied(nodes.select("node", "bands")), "groups")
    # one document of each candidate node gives its set; the texts of the others stay where they are
    wanted = groups.join(nodes.select("node", "mult", "least_id", *SET), "node")
    written_members = written(wanted.select("node", "grp", "mult").join(_sets_of(docs, wanted, id_col, text_col), "node"), "members")
    members = _regrouped(written_members, threshold, recall)
    tiles = binned(tiled(members, "grp", "node"), members.count())
    links = written(tiles.groupBy("bin").applyInArrow(lambda t: group_links(t, exact), "node bigint, peer bigint, links bigint"), "verified")
    forget(written_members)
    classes = connected_components(links.select(F.col("node").alias("a"), F.col("peer").alias("b")))
    per_node = links.groupBy("node").agg(F.sum("links").alias("links"))
    per = nodes.select("node", *SET, "mult", "least_id").join(name_components(nodes, classes), "node", "left").join(per_node, "node", "left")
    per = per.select("node", *SET, F.when(F.col("linked"), F.col("least")).otherwise(F.col("least_id")).alias("class_id"), (F.coalesce("links", F.lit(0)) + F.col("mult") - 1).alias("n_links"), F.coalesce("component", "node").alias("grp"))
    # written, so that the join with the documents can be split where one text has very many copies
    out = signed.select("id", "th", *SET).join(written(per, "classes"), SET, "left")
    return out.select("id", F.when(F.col("node").isNull(), F.col("id")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), "node", "th", "grp")


def _tied(banded: DataFrame) -> DataFrame:
    """(node, grp) of the nodes that share a bucket with another: the components of the buckets' ties. banded: node, bands."""
    keyed = banded.select("node", F.posexplode("bands").alias("band", "h"))
    hubs = keyed.groupBy("band", "h").agg(F.min("node").alias("hub"), F.count("*").alias("n")).where("n > 1").select("band", "h", "hub")
    ties = keyed.join(hubs, ["band", "h"]).where("node <> hub").select(F.col("node").alias("a"), F.col("hub").alias("b")).distinct()
    return connected_components(ties).withColumnRenamed("component", "grp")


def _regrouped(members: DataFrame, threshold: float, recall: float) -> DataFrame:
    """The members with groups of more than ``LARGE`` nodes grouped anew by more rows a band, at the same recall.

    Passages that many documents share chain unlike documents into one group; more rows part them, so what
    is compared in tiles is near copies. Groups that stay large are compared whole, tile by tile.
    """
    large = written(members.groupBy("grp").agg(F.count("*").alias("size")).where(F.col("size") > LARGE).select("grp"), "large")
    if large.isEmpty():
        return members
    bands = next(b for b in range(1, 10**6) if 1 - (1 - threshold**STRICT_ROWS) ** b >= recall)

    def strict(batches):
        for batch in batches:
            for part in K.slices(batch, "set", 1 << 20):
                data, at = K.buffers(part.column("set"))
                sig = band_hashes(data.view(K.U64), at // 8, bands, STRICT_ROWS, seed=6).view(np.int64)
                sig = pa.ListArray.from_arrays(pa.array(np.arange(part.num_rows + 1) * bands, pa.int32()), pa.array(sig.ravel()))
                yield pa.RecordBatch.from_arrays([part.column("node"), sig], names=["node", "bands"])

    again = members.join(large, "grp", "left_semi").select("node", "set").mapInArrow(strict, "node bigint, bands array<bigint>")
    banded = written(again, "strict")
    groups = written(_tied(banded), "groups")
    forget(banded)
    parted = members.join(large, "grp", "left_semi").drop("grp").join(groups, "node")
    return members.join(large, "grp", "left_anti").unionByName(parted)


def _sets_of(docs: DataFrame, wanted: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """(node, set) of the wanted nodes, each from the rows of its least id; of rows without an id all are read."""
    kept = docs.select(F.col(id_col).alias("id"), F.col(text_col).alias("text"))
    # ids are not unique in general: several rows may come along, and each node's rows give equal sets
    texts = kept.join(wanted.where("least_id IS NOT NULL").select(F.col("least_id").alias("id")).distinct(), "id", "left_semi")
    without = kept.where("id IS NULL")

    def run(batches):
        for batch in batches:
            for part in K.slices(batch, "text"):
                hashes, offsets = shingle_sets(part.column("text"))
                d1, d2 = set_digests(hashes, offsets)
                raw = [hashes[a:b].tobytes() for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True)]
                yield pa.RecordBatch.from_arrays([pa.array(np.diff(offsets), pa.int64()), pa.array(d1), pa.array(d2), pa.array(raw, pa.binary())], names=["n", "d1", "d2", "set"])

    rows = texts.unionByName(without).mapInArrow(run, "n bigint, d1 bigint, d2 bigint, set binary")
    return rows.join(wanted.select("node", *SET), SET).groupBy("node").agg(F.first("set").alias("set"))


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options: float) -> DataFrame:
    """One row of each class: that of the least id (rows without one last), of these that of the least text hash. Rows without words stay."""
    rows = _classes(docs, id_col, text_col, **options).where("node IS NOT NULL").groupBy("grp", "id", "th").agg(F.count("*").alias("copies"))
    rows = written(rows, "rows")
    first = rows.groupBy("grp").agg(F.min(F.struct(F.col("id").isNull().alias("none"), "id", "th")).alias("best"))
    fate = rows.join(written(first, "survivors"), "grp").withColumn("best", F.col("id").eqNullSafe(F.col("best.id")) & (F.col("th") == F.col("best.th")))
    # what goes, and survivors that are repeated: the latter come back once
    fate = written(fate.where("NOT best OR copies > 1").select("id", "th", "best"), "fates")
    same = lambda f: docs[id_col].eqNullSafe(f["id"]) & (F.xxhash64(docs[text_col]) == f["th"])
    repeated = fate.where("best")
    return docs.join(fate, same(fate), "left_anti").unionByName(docs.join(repeated, same(repeated), "left_semi").dropDuplicates([id_col, text_col]))
