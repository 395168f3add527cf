"""The cost model: scalar functions of the parameters, and the same as columns over a parameter grid.

S: target chunk size, R: reference size, D: digest size, W: window. lam(k) = S*(S/R)^k, p(k) = 1/lam(k).
"""

from __future__ import annotations

import math

from pyspark.sql import Column
from pyspark.sql import functions as F

R = D = 32
W = 48


def lam(k: int, s: int, r: int = R) -> float:
    return s * (s / r) ** k


def boundary_prob(k: int, s: int, r: int = R) -> float:
    """Chance that a byte ends a node of level k."""
    return 1 / lam(k, s, r)


def height(n: int, s: int, r: int = R) -> int:
    h = 0
    while n * r**h > s ** (h + 1):
        h += 1
    return h


def expected_nodes(n: int, s: int) -> int:
    """Bound on the nodes of a content of which nothing is stored."""
    return max(0, -(-2 * n // s))


def storage_full(n: int, s: int, d: int = D) -> int:
    """Cost of such a content."""
    return (d + s) * expected_nodes(n, s)


def added_fixed(n: int, s: int, r: int = R, d: int = D) -> int:
    """Bound for one changed byte under fixed cuts."""
    return (d + s) * (height(n, s, r) + 1)


def cut_flip(k: int, s: int, r: int = R) -> float:
    """Chance that one changed window gains a boundary at level k; that it loses one is as likely."""
    p = boundary_prob(k, s, r)
    return (1 - p) * p


def new_nodes_cdc(n: int, s: int, w: int = W, r: int = R) -> float:
    """Expected nodes that one changed byte makes anew: a gained boundary adds one chunk, a lost one up to two."""
    return 1 + sum(1 + 3 * w * cut_flip(k, s, r) for k in range(height(n, s, r)))


def added_cdc(n: int, s: int, w: int = W, r: int = R, d: int = D) -> float:
    """Bound for one changed byte under content-defined cuts."""
    return (d + 2 * s) * new_nodes_cdc(n, s, w, r)


def length_law(c: int, k: int, s: int, r: int = R) -> float:
    """Chance that a chunk of level k has length c."""
    p = boundary_prob(k, s, r)
    return p * (1 - p) ** (c - 1)


def length_biased_share(c: int, k: int, s: int, r: int = R) -> float:
    """Share of all bytes that lie in such chunks."""
    p = boundary_prob(k, s, r)
    return c * p * p * (1 - p) ** (c - 1)


def length_biased_mean(k: int, s: int, r: int = R) -> float:
    """Expected length of the chunk at a random byte."""
    return 2 * lam(k, s, r) - 1


def hit_size(s: int) -> int:
    """Bound on the stored size of the node at a random byte."""
    return 2 * s


def added_delta(n: int, s: int, delta: int, fixed: bool = False, w: int = W, r: int = R, d: int = D) -> float:
    """Bound for delta changed bytes in a row; one byte and the whole content are the border cases."""
    one = added_fixed(n, s, r, d) if fixed else added_cdc(n, s, w, r, d)
    if delta <= 1:
        return one if delta == 1 else 0.0
    return storage_full(n, s, d) if delta >= n else 2 * one + storage_full(max(0, delta - 2), s, d)


def scattered(n: int, s: int, edits: int, delta: int = 1, fixed: bool = False) -> float:
    """Bound for edits at distinct places, each of delta bytes."""
    return edits * added_delta(n, s, delta, fixed)


def height_thresholds(s: int, top: int, r: int = R) -> list[int]:
    """Content lengths above which a level is added."""
    return [s ** (h + 1) // r**h for h in range(top + 1)]


def expansion(n: int, s: int, scheme: str, r: int = R, d: int = D) -> float:
    """Expected expansion factor of a random content under the single-level schemes."""
    return 1 + d / n if scheme == "whole" else 1 + (d + r) / s + d / n


# The same as columns: s and n are columns of positive integers.


def height_col(n: Column, s: Column, top: int = 24, r: int = R) -> Column:
    """Smallest h with n * R^h <= S^(h+1), in exact decimals for heights up to ``top``; sizes are powers of two here."""
    out = F.lit(top)
    for h in range(top - 1, -1, -1):
        # S^(h+1)/R^h = S * 2^(h * log2(S/R)), exact in doubles for powers of two
        out = F.when(n.cast("double") <= s.cast("double") * F.pow(s.cast("double") / r, F.lit(h)), F.lit(h)).otherwise(out)
    return out


def storage_full_col(n: Column, s: Column, d: int = D) -> Column:
    return (s + d) * F.ceil(n * 2 / s)


def added_fixed_col(n: Column, s: Column, d: int = D) -> Column:
    return (s + d) * (height_col(n, s) + 1)


def new_nodes_cdc_col(n: Column, s: Column, w: int = W, r: int = R) -> Column:
    def level(k: Column) -> Column:
        p = 1 / (s.cast("double") * F.pow(s.cast("double") / r, k))
        return 1 + F.lit(3.0 * w) * (1 - p) * p

    h = height_col(n, s)
    levels = F.when(h > 0, F.sequence(F.lit(0), h - 1)).otherwise(F.array().cast("array<int>"))
    return F.aggregate(levels, F.lit(1.0), lambda acc, k: acc + level(k))


def added_cdc_col(n: Column, s: Column, w: int = W, d: int = D) -> Column:
    return (s * 2 + d) * new_nodes_cdc_col(n, s, w)


def added_delta_col(n: Column, s: Column, delta: Column, fixed: bool = False) -> Column:
    one = (added_fixed_col(n, s) if fixed else added_cdc_col(n, s)).cast("double")
    rest = storage_full_col(F.greatest(delta - 2, F.lit(0)), s)
    return F.when(delta < 1, F.lit(0.0)).when(delta == 1, one).when(delta >= n, storage_full_col(n, s).cast("double")).otherwise(2 * one + rest)


def log_slope(points: list[tuple[float, float]]) -> float:
    """Slope of y over log2 x by least squares."""
    xs = [math.log2(x) for x, _ in points]
    mx, my = sum(xs) / len(xs), sum(y for _, y in points) / len(points)
    return sum((x - mx) * (y - my) for x, (_, y) in zip(xs, points, strict=True)) / sum((x - mx) ** 2 for x in xs)
