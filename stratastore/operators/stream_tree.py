"""Trees of contents that come in pieces: the names and sizes of ``tree.build_grid``, with one block of a content in memory."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash

from ..functions import rolling
from ..params import StoreParams
from . import tree

#: Bytes of a content that are cut at a time.
BLOCK = 1 << 20


class _Nodes:
    """Nodes of one level: those that end in a block, and the one that is still open."""

    def __init__(self) -> None:
        self.start, self.size, self.hash = 0, 0, xxhash.xxh3_128()

    def root(self, data: bytes, unit: int) -> tuple[bytes, int]:
        """Name and size of the node that is open, once ``data`` has come to it."""
        self.hash.update(data)
        return self.hash.digest(), self.size + len(data) * unit

    def close(self, data: bytes, cuts: list[int], unit: int) -> tuple[list[bytes], list]:
        """Names and sizes of the nodes that end at ``cuts`` of the data; the rest of it stays open. unit: bytes stored for a byte of data."""
        if not cuts:
            self.hash.update(data)
            self.size += len(data) * unit
            return [], []
        self.hash.update(data[: cuts[0]])
        names = [self.hash.digest(), *map(xxhash.xxh3_128_digest, map(data.__getitem__, map(slice, cuts[:-1], cuts[1:])))]
        sizes = [self.size + cuts[0] * unit, *(np.diff(cuts) * unit).tolist()]
        self.hash = xxhash.xxh3_128(data[cuts[-1] :])
        self.size = (len(data) - cuts[-1]) * unit
        return names, sizes


class _Valued:
    """The same with tags for names and, for sizes, the values themselves."""

    def __init__(self, tag: Callable[[bytes], bytes]) -> None:
        self.start, self.held, self.tag = 0, [], tag

    def root(self, data: bytes, unit: int) -> tuple[bytes, bytes]:
        value = b"".join([*self.held, data])
        return self.tag(value), value

    def close(self, data: bytes, cuts: list[int], unit: int) -> tuple[list[bytes], list]:
        if not cuts:
            self.held.append(data)
            return [], []
        values = [b"".join([*self.held, data[: cuts[0]]]), *[data[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]]
        self.held = [data[cuts[-1] :]]
        return [self.tag(v) for v in values], values


class _Tree:
    """One parameter set over one content of n bytes. tag: what names nodes whose values are wanted (none: names for equality, and sizes)."""

    def __init__(self, p: StoreParams, n: int, tag: Callable[[bytes], bytes] | None = None) -> None:
        if not rolling.joins(p) or p.head == "skip":
            raise ValueError("contents in pieces are cut by partial windows without limits")
        self.p, self.n, self.h = p, n, p.height(n)
        self.nodes = [_Valued(tag) if tag else _Nodes() for _ in range(self.h + 1)]
        self.name = p.ref if tag else tree.NAME

    def block(self, data: bytes, a: int, prefix: Callable[[str], rolling.Prefix], back: int) -> tuple[list[bytes], list[int]]:
        """Names and sizes of the nodes that the bytes from place a on end. back: bytes before them that the prefix sums hold."""
        starts = self._fixed(a + len(data)) if self.p.scheme.startswith(("fixed", "whole")) else self._cdc(a, a + len(data), prefix, back)
        return self._closed(data, a, starts)

    def _fixed(self, b: int) -> list[np.ndarray]:
        """New node starts by level, before place b; the root has none."""
        out = [np.zeros(0, np.int64)]
        for level in range(self.h - 1, -1, -1):
            # from the open node on, and from each new node of the level above on
            length, above = self.p.fixed_length(level), np.append(self.nodes[level].start, out[-1])
            count = -(-(np.append(above[1:], b) - above) // length)
            first = np.repeat(above - length * (np.cumsum(count) - count), count)
            out.append((first + length * np.arange(int(count.sum())))[1:])
        return out[::-1]

    def _cdc(self, a: int, b: int, prefix: Callable[[str], rolling.Prefix], back: int) -> list[np.ndarray]:
        """The same by content: a window is whole or begins at a node's start, so W - 1 bytes before the block are enough."""
        out = [np.zeros(0, np.int64)]
        if not self.h:
            return out
        p, low, reach = self.p, a - back, self.p.window - 1
        sums = prefix(p.ring)
        below, hashes = sums.full_below(p.window, rolling.threshold(p, 0))
        for level in range(self.h - 1, -1, -1):
            limit = sums.sums.dtype.type(rolling.threshold(p, level))
            above = np.append(self.nodes[level + 1].start, out[-1])
            full = below[hashes < limit] + low
            full = full[(full >= a) & (full - above[np.searchsorted(above, full, "right") - 1] >= reach)]
            at = above[:, None] + np.arange(reach)[None, :]
            ok = (at >= a) & (at < np.append(above[1:], b)[:, None])
            heads, at = np.broadcast_to(above[:, None], at.shape)[ok], at[ok]
            cuts = np.concatenate((full, at[sums.hashes(at - low, heads - low) < limit])) + 1
            out.append(np.unique(np.concatenate((out[-1], cuts[cuts < self.n]))))
        return out[::-1]

    def _closed(self, data: bytes, a: int, starts: list[np.ndarray]) -> tuple[list[bytes], list[int]]:
        names, sizes = [], []
        at = starts[0] - a
        for level, own in enumerate(starts):
            node = self.nodes[level]
            got, size = node.close(data, at.tolist(), 1 if level == 0 else 32 // self.name)
            names += got
            sizes += size
            if level < self.h:
                # the children that ended here, and where a new node of the level above begins among them
                begun = np.append(node.start, own[:-1])[: len(got)]
                data, at = b"".join(got), np.searchsorted(begun, starts[level + 1]) * self.name
            if len(own):
                node.start = int(own[-1])
        return names, sizes

    def end(self) -> tuple[list[bytes], list]:
        names, sizes, data = [], [], b""
        for level, node in enumerate(self.nodes):
            data, size = node.root(data, 1 if level == 0 else 32 // self.name)
            names.append(data)
            sizes.append(size)
        return names, sizes


class Content:
    """One content of n bytes under several parameter sets, fed piece by piece; ``take`` gets (number of the set, names, sizes), the root last. With a tag: values in the place of sizes."""

    def __init__(self, n: int, grid: list[StoreParams], take: Callable[[int, list[bytes], list], None], tag: Callable[[bytes], bytes] | None = None) -> None:
        self.n, self.at, self.take, self.left = n, 0, take, n
        self.sets = sorted(((k, _Tree(p, n, tag)) for k, p in enumerate(grid)), key=lambda x: x[1].p.chunk)
        self.keep = max((p.window for p in grid), default=1) - 1
        self.held, self.size, self.back, self.tag = [], 0, b"", tag

    def feed(self, piece: bytes) -> None:
        """Bytes beyond n are left out."""
        piece = piece[: self.left]
        self.left -= len(piece)
        self.held.append(piece)
        self.size += len(piece)
        if self.size >= BLOCK:
            self._run()

    def _run(self) -> None:
        data = b"".join(self.held)
        if data:
            made: dict[str, rolling.Prefix] = {}
            prefix = lambda ring: made.get(ring) or made.setdefault(ring, rolling.Prefix(self.back + data, ring))
            for k, x in self.sets:
                self.take(k, *x.block(data, self.at, prefix, len(self.back)))
            self.back = (self.back + data)[-self.keep :] if self.keep else b""
        self.at += len(data)
        self.held, self.size = [], 0

    def end(self) -> None:
        self._run()
        if self.at != self.n:
            raise ValueError(f"a content of {self.n} bytes came with {self.at}")
        for k, x in self.sets:
            if self.n:
                names, sizes = x.end()
                self.root = names[-1], sizes[-1]
                self.take(k, names, sizes)
            else:
                found = tree.levels_of(b"", x.p, tag=self.tag or tree.name_of)
                sizes = [int(s) for y in found for s in np.diff(y.cuts)]
                values = [y.values[a:b] for y in found for a, b in zip(y.cuts[:-1], y.cuts[1:], strict=True)]
                names, sizes = [key for y in found for key in y.keys], values if self.tag else sizes
                self.root = names[-1], sizes[-1]
                self.take(k, names, sizes)


def fed(contents: list[tuple[int, Content]], batches: Iterable[pa.RecordBatch]) -> Iterator[None]:
    """Feeds contents with the lines up to their periods; comes back after each batch, and after each content's end."""
    for batch in batches:
        periods, lines = batch.column("p"), batch.column("line")
        for p, content in contents:
            own = lines.filter(pc.less_equal(periods, p))
            if len(own):
                ends = np.frombuffer(own.buffers()[1], np.int32)[own.offset : own.offset + len(own) + 1]
                content.feed(own.buffers()[2].slice(int(ends[0]), int(ends[-1] - ends[0])).to_pybytes())
            yield
    for _, content in contents:
        content.end()
        yield
