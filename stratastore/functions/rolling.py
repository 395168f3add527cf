"""Cut positions of one content at all levels, by a rolling hash over prefix sums.

The hash of the window that ends at byte i is the sum over the window's bytes of (byte + 1) * B^(j+1),
j counted backwards from i, in a ring. With prefix sums of (byte + 1) * B^-i it is one difference and one
product for every window, whole or cut short by a node's start, so all levels come from one pass.
A cut follows byte i when the hash is below modulus / target length; thresholds of upper levels are lower.
"""

from __future__ import annotations

from functools import lru_cache

import numpy as np

from ..params import StoreParams

#: The bases of the two rings, and the prime of the second.
BASE64 = 0xD1342543DE82EF95
M31 = (1 << 31) - 1
BASE31 = 1_103_515_245


@lru_cache(maxsize=8)
def _tables(ring: str, size: int) -> tuple[np.ndarray, np.ndarray]:
    """B^-i and B^(i+1) for i < size."""
    if ring == "wrap64":
        inv = np.full(size, pow(BASE64, -1, 1 << 64), dtype=np.uint64)
        inv[0] = 1
        return np.multiply.accumulate(inv), np.multiply.accumulate(np.full(size, BASE64, dtype=np.uint64))
    out = []
    for base, first in ((pow(BASE31, -1, M31), 1), (BASE31, BASE31)):
        t = np.empty(size, dtype=np.int64)
        t[0], n = first, 1
        while n < size:
            k = min(n, size - n)
            t[n : n + k] = t[:k] * pow(base, n, M31) % M31
            n += k
        out.append(t)
    return out[0], out[1]


class Prefix:
    """Hashes of all windows of a content; what several chunk sizes ask for is made once."""

    def __init__(self, body: bytes, ring: str):
        data = np.frombuffer(body, np.uint8)
        self.n, self.ring = len(data), ring
        size = 1 << max(10, int(self.n).bit_length())
        inv, self.pow = _tables(ring, size)
        kind = np.uint64 if ring == "wrap64" else np.int64
        self.sums = np.zeros(self.n + 1, dtype=kind)
        step = (data.astype(kind) + kind(1)) * inv[: self.n]
        np.cumsum(step if ring == "wrap64" else step % M31, out=self.sums[1:])
        self._full: dict[int, tuple[int, np.ndarray, np.ndarray]] = {}

    def hashes(self, ends: np.ndarray, starts: np.ndarray) -> np.ndarray:
        """Hash of bytes starts..ends, both inclusive."""
        d = self.sums[ends + 1] - self.sums[starts]
        return d * self.pow[ends] if self.ring == "wrap64" else d % M31 * self.pow[ends] % M31

    def full_below(self, window: int, limit: int) -> tuple[np.ndarray, np.ndarray]:
        """(places, hashes) of the whole windows with a hash below ``limit``; asked for in any order, made for the greatest so far."""
        if self.n < window:
            return np.zeros(0, np.int64), self.sums[:0]
        have = self._full.get(window)
        if have is None or have[0] < limit:
            hashes = self.all_full(window)
            at = np.flatnonzero(hashes < self.sums.dtype.type(limit))
            have = self._full[window] = (limit, at + window - 1, hashes[at])
        if have[0] == limit:
            return have[1], have[2]
        own = have[2] < self.sums.dtype.type(limit)
        return have[1][own], have[2][own]

    def all_full(self, window: int) -> np.ndarray:
        """Hash of the window that ends at each byte, from the first full one on."""
        d = self.sums[window:] - self.sums[:-window]
        p = self.pow[window - 1 : self.n]
        return d * p if self.ring == "wrap64" else d % M31 * p % M31


def threshold(p: StoreParams, level: int) -> int:
    a, b = p.lam(level)
    return ((1 << 64) if p.ring == "wrap64" else M31) * b // a


def _candidates(prefix: Prefix, p: StoreParams, level: int, full: np.ndarray, starts: np.ndarray) -> np.ndarray:
    """Boundaries (a byte's place + 1) within nodes that begin at ``starts``; full: places whose whole window is below the threshold."""
    limit = prefix.sums.dtype.type(threshold(p, level))
    own = starts[np.searchsorted(starts, full, "right") - 1]
    inner = full if p.head == "context" else full[full - own >= p.window - 1]
    if p.head == "skip":
        return inner + 1
    nodes = starts[:1] if p.head == "context" else starts
    reach = p.window - 1
    if not reach:
        return inner + 1
    ends = np.append(starts[1:], prefix.n)[: len(nodes)]
    at = nodes[:, None] + np.arange(reach)[None, :]
    ok = at < ends[:, None]
    heads = np.broadcast_to(nodes[:, None], at.shape)[ok]
    at = at[ok]
    return np.concatenate((inner, at[prefix.hashes(at, heads) < limit])) + 1


def _limited(cuts: np.ndarray, starts: np.ndarray, n: int, low: int, high: int) -> np.ndarray:
    """Cuts at least ``low`` and at most ``high`` after the one before, node by node."""
    out: list[int] = []
    cuts = np.unique(cuts)
    for s, e in zip(starts.tolist(), [*starts[1:].tolist(), n], strict=True):
        last = s
        for c in [*cuts[np.searchsorted(cuts, s, "right") : np.searchsorted(cuts, e, "left")].tolist(), e]:
            while c - last > high:
                last += high
                out.append(last)
            if c - last >= low and c < e:
                out.append(c)
                last = c
    return np.array(out, dtype=np.int64)


def levels_cdc(body: bytes, h: int, p: StoreParams, prefix: Prefix | None = None) -> list[np.ndarray]:
    """Node starts by level, 0 (leaves) to h (root), of a content-defined tree of height h."""
    starts = [np.zeros(1, np.int64)]
    if h and body:
        prefix = prefix or Prefix(body, p.ring)
        below, hashes = prefix.full_below(p.window, threshold(p, 0))
        for level in range(h - 1, -1, -1):
            full = below[hashes < prefix.sums.dtype.type(threshold(p, level))] if len(below) else below
            cuts = _candidates(prefix, p, level, full, starts[-1])
            if p.min_len or p.max_len:
                a, b = p.lam(level)
                grown = lambda x, k=level: x * p.chunk**k // p.ref**k
                cuts = _limited(cuts, starts[-1], prefix.n, grown(p.min_len or 1), grown(p.max_len or 1 << 40))
            cuts = cuts[cuts < prefix.n]
            starts.append(np.unique(np.concatenate((starts[-1], cuts))))
    elif h:
        starts += [np.zeros(0, np.int64)] * h
    return starts[::-1]


def levels_fixed(n: int, h: int, p: StoreParams) -> list[np.ndarray]:
    """Node starts by level of a tree whose nodes are cut every so many bytes from their own start."""
    starts = [np.zeros(1, np.int64)]
    for level in range(h - 1, -1, -1):
        length = p.fixed_length(level)
        above = starts[-1] if n else np.zeros(0, np.int64)
        ends = np.append(above[1:], n)[: len(above)]
        count = -(-(ends - above) // length)
        first = np.repeat(above - length * (np.cumsum(count) - count), count)
        starts.append(first + length * np.arange(int(count.sum())))
    return starts[::-1]


def levels(body: bytes, p: StoreParams, h: int | None = None, prefix: Prefix | None = None) -> list[np.ndarray]:
    """Node starts by level of a content under the scheme. prefix: that of the body, where several schemes share it."""
    h = p.height(len(body)) if h is None else h
    return levels_fixed(len(body), h, p) if p.scheme.startswith(("fixed", "whole")) else levels_cdc(body, h, p, prefix)


def joins(p: StoreParams) -> bool:
    """Whether contents can be cut side by side in one buffer: no window or length limit looks beyond a node's start."""
    return not (p.min_len or p.max_len or p.head == "context" and p.scheme.startswith("cdc"))


def levels_many(body: bytes, offsets: np.ndarray, h: int, p: StoreParams, prefix: Prefix | None = None) -> list[np.ndarray]:
    """Node starts by level of several contents of one height that lie side by side; offsets: where each begins, and the end. None is empty."""
    starts, n = [offsets[:-1].astype(np.int64)], len(body)
    if p.scheme.startswith(("fixed", "whole")):
        for level in range(h - 1, -1, -1):
            length, above = p.fixed_length(level), starts[-1]
            count = -(-(np.append(above[1:], n) - above) // length)
            first = np.repeat(above - length * (np.cumsum(count) - count), count)
            starts.append(first + length * np.arange(int(count.sum())))
    elif h:
        prefix = prefix or Prefix(body, p.ring)
        below, hashes = prefix.full_below(p.window, threshold(p, 0))
        for level in range(h - 1, -1, -1):
            full = below[hashes < prefix.sums.dtype.type(threshold(p, level))] if len(below) else below
            cuts = _candidates(prefix, p, level, full, starts[-1])
            starts.append(np.unique(np.concatenate((starts[-1], cuts[cuts < n]))))
    return starts[::-1]


def single_level(body: bytes, p: StoreParams, level: int) -> list[tuple[int, int]]:
    """Chunks of one application of the base chunker with the target length of a level."""
    n = len(body)
    if not n:
        return []
    if p.scheme.startswith("fixed"):
        length = p.fixed_length(level)
        cuts = np.arange(length, n, length)
    else:
        prefix, zero = Prefix(body, p.ring), np.zeros(1, np.int64)
        full = np.zeros(0, np.int64)
        if n >= p.window:
            full = np.flatnonzero(prefix.all_full(p.window) < prefix.sums.dtype.type(threshold(p, level))) + p.window - 1
        cuts = _candidates(prefix, p, level, full, zero)
        if p.min_len or p.max_len:
            grown = lambda x: x * p.chunk**level // p.ref**level
            cuts = _limited(cuts, zero, n, grown(p.min_len or 1), grown(p.max_len or 1 << 40))
    edges = [0, *np.unique(cuts[cuts < n]).tolist(), n]
    return list(zip(edges[:-1], edges[1:], strict=True))


def levels_recursive(body: bytes, p: StoreParams, h: int | None = None) -> list[np.ndarray]:
    """The definition itself, node by node from the root down: the check of ``levels``."""
    h = p.height(len(body)) if h is None else h
    nodes, out = [(0, len(body))], [np.zeros(1, np.int64)]
    for level in range(h - 1, -1, -1):
        nodes = [(s + a, s + b) for s, e in nodes for a, b in single_level(body[s:e], p, level)]
        out.append(np.array([s for s, _ in nodes], dtype=np.int64))
    return out[::-1]
