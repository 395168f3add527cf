"""Connected components of a link table, and links within candidate groups counted tile by tile."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .shared import forget, n_shuffle, written

#: Rounds double the reach of a label; this many reach across any graph that fits the ids.
MAX_ROUNDS = 64
#: Members of a group that are compared in one go; larger groups are cut into tiles of about this many.
TILE = 1_536
#: Members of small groups that share a task, about.
BIN = 400


def connected_components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) of all nodes with a link; component is the smallest node reachable.

    Rounds of contraction: every node goes to its least neighbour if that is less, labels of labels are
    followed, and links are drawn anew between what is left, so each round has fewer. Tables are written
    to the shared folder between rounds, so a lost executor costs one round at most. Neighbours are folded
    by partial aggregation, so a hub is one row per task.
    """
    pair = links.select(F.greatest(a, b).alias("v"), F.least(a, b).alias("w")).where("v <> w").distinct()
    edges = written(pair, "links")
    labels = None
    for _ in range(MAX_ROUNDS):
        both = edges.union(edges.select(F.col("w").alias("v"), F.col("v").alias("w")))
        parent = written(both.groupBy("v").agg(F.min("w").alias("m")).select("v", F.least("v", "m").alias("p")), "parents")
        for _ in range(2):
            parent = parent.join(parent.select(F.col("v").alias("p"), F.col("p").alias("top")), "p").select("v", F.col("top").alias("p"))
        parent = written(parent, "parents")
        if labels is None:
            labels = parent.select(F.col("v").alias("node"), F.col("p").alias("l"))
        else:
            moved = labels.join(parent.select(F.col("v").alias("l"), "p"), "l", "left")
            labels = written(moved.select("node", F.coalesce("p", "l").alias("l")), "labels")
        drawn = edges.join(parent.select("v", F.col("p").alias("a")), "v").join(parent.select(F.col("v").alias("w"), F.col("p").alias("b")), "w")
        # where following was cut short, a label is tied to the one it is to become
        short = parent.select("p").distinct().join(parent.select(F.col("v").alias("p"), F.col("p").alias("b")), "p").where("p <> b").select(F.col("p").alias("a"), "b")
        drawn = drawn.select("a", "b").union(short)
        before, edges = edges, written(drawn.select(F.greatest("a", "b").alias("v"), F.least("a", "b").alias("w")).where("v <> w").distinct(), "links")
        forget(before)
        if edges.isEmpty():
            break
    else:
        raise RuntimeError(f"components are not settled after {MAX_ROUNDS} rounds")
    return labels.select("node", F.col("l").alias("component"))


def name_components(nodes: DataFrame, classes: DataFrame) -> DataFrame:
    """(node, least, linked, component): the least id of each linked node's component. nodes: node, least_id; classes: node, component.

    The names are written first, so the join back has an exchange on either side and a giant component can be split.
    """
    least = nodes.select("node", "least_id").join(classes, "node").groupBy("component").agg(F.min("least_id").alias("least"))
    return classes.join(written(least, "names"), "component").select("node", "least", F.lit(True).alias("linked"), "component")


def tiled(members: DataFrame, group: str, node: str) -> DataFrame:
    """The members of groups of two or more, once for each pair of tiles: with ti, tj, side (their own tile) and bin, the task's key."""
    sizes = members.groupBy(group).agg(F.count("*").alias("__size")).where("__size > 1")
    tiles = F.ceil(F.col("__size") / TILE).cast("int")
    rows = members.join(sizes, group).withColumn("__tiles", tiles).withColumn("side", F.pmod(F.xxhash64(node, F.lit(11)), F.col("__tiles")).cast("int"))
    rows = rows.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("__tiles") - 1)))
    rows = rows.withColumns({"ti": F.least("side", "other"), "tj": F.greatest("side", "other")})
    small = F.col("__tiles") == 1
    bins = F.when(small, F.pmod(F.xxhash64(group), F.lit(1 << 20)) * F.lit(2)).otherwise(F.xxhash64(group, "ti", "tj") * 0 + F.pmod(F.xxhash64(group, "ti", "tj"), F.lit(1 << 40)) * 2 + 1)
    return rows.withColumn("bin", bins).drop("__size", "__tiles", "other")


def binned(rows: DataFrame, n_small: int) -> DataFrame:
    """Small groups share as many bins as their members need, pairs of tiles have one each; dealt to enough partitions for few to share one (no more than the session shuffles to), which are not merged by their bytes."""
    count = max(1, n_small // BIN)
    dealt = rows.withColumn("bin", F.when(F.col("bin") % 2 == 0, F.pmod(F.col("bin") / 2, F.lit(count)).cast("long")).otherwise(F.col("bin") + (1 << 41)))
    return dealt.repartition(min(n_shuffle(rows.sparkSession), 4 * count), "bin")


def local_components(adjacent: np.ndarray) -> np.ndarray:
    """The least member of each member's component, by a boolean matrix."""
    n = len(adjacent)
    label = np.arange(n)
    while True:
        new = np.minimum(label, np.where(adjacent, label[None, :], n).min(axis=1, initial=n))
        new = new[new]
        if (new == label).all():
            return label
        label = new
