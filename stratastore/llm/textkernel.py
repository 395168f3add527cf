"""Vectorised word spans, word hashes and window hashes over Arrow string batches.

All functions work on the raw UTF-8 bytes of a batch, so a word is a run of bytes of one class;
classes that contain every byte from 0x80 on never cut inside a character.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa

U64 = np.uint64
BASE = 0x9E3779B97F4A7C15 | 1
MASK = (1 << 64) - 1
BASE_INV = pow(BASE, -1, 1 << 64)
#: Bytes that are hashed with one power table.
BLOCK = 1 << 17

LOWER = np.arange(256, dtype=np.uint8)
LOWER[65:91] += 32

#: Words of the contamination contract and of shingles: digits, letters, and whatever is not ASCII.
WORD = np.zeros(256, dtype=bool)
WORD[48:58] = WORD[97:123] = WORD[65:91] = WORD[128:] = True
#: Words of the language-model contract: whatever is not ASCII white space.
NONSPACE = np.ones(256, dtype=bool)
NONSPACE[[32, *range(9, 14)]] = False


def _powers(base: int, n: int) -> np.ndarray:
    out = np.empty(n, dtype=U64)
    out[0] = 1
    if n > 1:
        out[1:] = U64(base)
    return np.multiply.accumulate(out)


_POW, _INV = _powers(BASE, BLOCK + 1), _powers(BASE_INV, BLOCK + 1)


def mix(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser over unsigned 64-bit words."""
    x = x.astype(U64, copy=True)
    x ^= x >> U64(30)
    x *= U64(0xBF58476D1CE4E5B9)
    x ^= x >> U64(27)
    x *= U64(0x94D049BB133111EB)
    x ^= x >> U64(31)
    return x


def buffers(arr: pa.Array | pa.ChunkedArray) -> tuple[np.ndarray, np.ndarray]:
    """Bytes and int64 offsets of a string column; a null is an empty text."""
    if isinstance(arr, pa.ChunkedArray):
        arr = arr.combine_chunks()
    if not len(arr):
        return np.zeros(0, np.uint8), np.zeros(1, np.int64)
    if arr.null_count:
        arr = arr.fill_null("")
    wide = pa.types.is_large_string(arr.type) or pa.types.is_large_binary(arr.type)
    _, off, data = arr.buffers()
    offsets = np.frombuffer(off, np.int64 if wide else np.int32)[arr.offset : arr.offset + len(arr) + 1].astype(np.int64)
    raw = np.frombuffer(data, np.uint8) if data is not None else np.zeros(0, np.uint8)
    return raw[offsets[0] : offsets[-1]], offsets - offsets[0]


def slices(batch: pa.RecordBatch, column: str, limit: int = 4 << 20) -> Iterator[pa.RecordBatch]:
    """Runs of rows with at most about ``limit`` bytes of text each; a longer text stands alone."""
    if not batch.num_rows:
        return
    _, off = buffers(batch.column(column))
    at = 0
    while at < batch.num_rows:
        end = max(at + 1, int(np.searchsorted(off, off[at] + limit, "right")) - 1)
        yield batch.slice(at, end - at)
        at = end


def spans(data: np.ndarray, offsets: np.ndarray, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Starts and ends of the words of a batch in order, and per text the index of its first word (length texts + 1)."""
    if not len(data):
        return np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(len(offsets), np.int64)
    isw = table[data]
    edge = isw.copy()
    edge[1:] &= ~isw[:-1]
    heads = offsets[:-1][offsets[:-1] < offsets[1:]]
    edge[heads] = isw[heads]
    starts = np.flatnonzero(edge)
    edge = isw.copy()
    edge[:-1] &= ~isw[1:]
    tails = heads_end = offsets[1:][offsets[:-1] < offsets[1:]] - 1
    edge[tails] = isw[heads_end]
    ends = np.flatnonzero(edge) + 1
    return starts, ends, np.searchsorted(starts, offsets)


def hash_spans(data: np.ndarray, starts: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """A 64-bit hash of each byte span; equal bytes give equal hashes wherever they stand."""
    out = np.empty(len(starts), dtype=U64)
    i, n = 0, len(starts)
    while i < n:
        j = int(np.searchsorted(ends, starts[i] + BLOCK, "right"))
        if j <= i:  # one word longer than a block: piece by piece
            total, at = 0, int(starts[i])
            while at < ends[i]:
                part = data[at : min(at + BLOCK, int(ends[i]))].astype(U64) + U64(1)
                total += int((part * _POW[: len(part)]).sum(dtype=U64)) * pow(BASE, at - int(starts[i]), 1 << 64)
                at += len(part)
            out[i] = total & MASK
            i += 1
            continue
        s, e = starts[i:j] - starts[i], ends[i:j] - starts[i]
        part = data[starts[i] : ends[j - 1]].astype(U64)
        part += U64(1)
        part *= _POW[: len(part)]
        run = np.zeros(len(part) + 1, dtype=U64)
        np.cumsum(part, out=run[1:])
        out[i:j] = (run[e] - run[s]) * _INV[s]
        i = j
    return mix(out ^ (ends - starts).astype(U64))


def windows(hashes: np.ndarray, first: np.ndarray, width: int) -> tuple[np.ndarray, np.ndarray]:
    """Positions (of their first word) and hashes of all runs of ``width`` words inside one text."""
    n = len(hashes) - width + 1
    if n <= 0:
        return np.zeros(0, np.int64), np.zeros(0, U64)
    acc = hashes[:n].copy()
    for k in range(1, width):
        acc *= U64(BASE)
        acc += hashes[k : k + n]
    ok = np.ones(n, dtype=bool)
    for k in range(1, width):  # windows that begin in the last words of a text would cross into the next
        tail = first[1:] - k
        tail = tail[(tail >= first[:-1]) & (tail < n)]
        ok[tail] = False
    at = np.flatnonzero(ok)
    return at, mix(acc[at])


def run_hash(hashes: np.ndarray) -> int:
    """What ``windows`` gives for one whole run of word hashes."""
    acc = 0
    for h in hashes.tolist():
        acc = (acc * BASE + h) & MASK
    return int(mix(np.array([acc], dtype=U64))[0])


def word_hashes(arr: pa.Array, table: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(lower-case bytes, starts, ends, first word of each text, hash of each word)."""
    data, offsets = buffers(arr)
    data = LOWER[data]
    starts, ends, first = spans(data, offsets, table)
    return data, starts, ends, first, hash_spans(data, starts, ends)


def ragged(offsets: np.ndarray, pick: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Index of every element of the picked runs, and the runs' lengths: for gathering ragged lists without a loop."""
    length = (offsets[1:] - offsets[:-1])[pick]
    total = int(length.sum())
    base = np.repeat(offsets[:-1][pick] - (np.cumsum(length) - length), length)
    return base + np.arange(total), length


def is_member(values: np.ndarray, sorted_set: np.ndarray) -> np.ndarray:
    """Whether each value is in the sorted set."""
    if not len(sorted_set):
        return np.zeros(len(values), dtype=bool)
    at = np.searchsorted(sorted_set, values)
    at[at == len(sorted_set)] = 0
    return sorted_set[at] == values


class HashIndex:
    """Open-addressing index over distinct unsigned 64-bit keys: key -> its place in the order of insertion, looked up in bulk."""

    def __init__(self, keys: np.ndarray | None = None, bits: int | None = None):
        keys = np.zeros(0, U64) if keys is None else keys
        self.bits = bits or max(4, int(2 * len(keys)).bit_length())
        self.slots = np.full(1 << self.bits, -1, dtype=np.int32)
        self.keys = np.zeros(1 << self.bits, dtype=U64)
        self.count = 0
        self.add(keys)

    def add(self, keys: np.ndarray) -> None:
        """Puts in new distinct keys; the index must have room for them."""
        left = np.arange(len(keys), dtype=np.int32)
        at = self._home(keys)
        while len(left):
            free = np.flatnonzero(self.slots[at] < 0)
            slot, first = np.unique(at[free], return_index=True)
            won = free[first]
            self.slots[slot], self.keys[slot] = self.count + left[won], keys[left[won]]
            rest = np.ones(len(left), dtype=bool)
            rest[won] = False
            left, at = left[rest], (at[rest] + 1) & ((1 << self.bits) - 1)
        self.count += len(keys)

    def _home(self, keys: np.ndarray) -> np.ndarray:
        return ((keys * U64(0xD6E8FEB86659FD93)) >> U64(64 - self.bits)).astype(np.int64)

    def find(self, keys: np.ndarray) -> np.ndarray:
        """The place of each key, or -1."""
        out = np.full(len(keys), -1, dtype=np.int32)
        if not len(keys):
            return out
        at, left = self._home(keys), None
        while True:
            slot = self.slots[at]
            same = (self.keys[at] == keys) & (slot >= 0)
            if left is None:
                out[same] = slot[same]
                left = np.flatnonzero(~same & (slot >= 0))
                keys, at = keys[left], at[left]
            else:
                out[left[same]] = slot[same]
                go = ~same & (slot >= 0)
                left, keys, at = left[go], keys[go], at[go]
            if not len(left):
                return out
            at = (at + 1) & ((1 << self.bits) - 1)
