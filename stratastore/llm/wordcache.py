"""Encodings of byte spans, made once and gathered in bulk: for tokenizers whose pieces never cross a span's border.

Spans are known by a 64-bit hash, so a batch is looked up without making a string for each word; only spans
that are new to the worker become strings. Long spans are never looked up, so no made-up text can choose its hash.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np

from . import textkernel as K

#: Slots of a worker's index, as a power of two, and how many of them are used at most.
BITS, LIMIT = 22, 1_800_000
#: New spans that go to the library at once.
AT_ONCE = 16_384
#: Longer spans, in bytes, are encoded each time.
LONGEST = 48


class SpanCache:
    """Remembered spans have a place in one flat array of ids, so a lookup in bulk is one gather."""

    def __init__(self, encode_many: Callable[[list[bytes]], list[list[int]]]):
        self.encode_many = encode_many
        self.index = K.HashIndex(bits=BITS)
        self.flat = np.zeros(1 << 16, np.int32)
        self.offsets = np.zeros(1 << 14, np.int64)

    def _keep(self, keys: np.ndarray, ids: np.ndarray, lengths: np.ndarray) -> None:
        n, used = self.index.count, int(self.offsets[self.index.count])
        while used + len(ids) > len(self.flat):
            self.flat = np.concatenate((self.flat, np.zeros_like(self.flat)))
        while n + len(keys) + 1 > len(self.offsets):
            self.offsets = np.concatenate((self.offsets, np.zeros_like(self.offsets)))
        self.flat[used : used + len(ids)] = ids
        self.offsets[n + 1 : n + len(keys) + 1] = used + np.cumsum(lengths)
        self.index.add(keys)

    def encode(self, data: np.ndarray, starts: np.ndarray, ends: np.ndarray, salt: np.ndarray | None = None, lead: bytes = b"") -> tuple[np.ndarray, np.ndarray]:
        """Ids of all spans in a row, and the spans' offsets. salt: spans that are encoded with ``lead`` before them."""
        keys = K.hash_spans(data, starts, ends)
        if salt is not None:
            keys[salt] = ~keys[salt]
        place = self.index.find(keys).astype(np.int64)
        long = ends - starts > LONGEST
        place[long] = -1
        new = np.flatnonzero(place < 0)
        extra_flat, extra_offsets = np.zeros(0, np.int32), np.zeros(1, np.int64)
        if len(new):
            # one of each new key; long spans each for itself
            _, first, back = np.unique(np.where(long[new], K.U64(0), keys[new]), return_index=True, return_inverse=True)
            if long[new].any():
                kept = np.flatnonzero(~long[new])
                _, f, b = np.unique(keys[new][kept], return_index=True, return_inverse=True)
                own = np.flatnonzero(long[new])
                first = np.concatenate((kept[f], own))
                back = np.empty(len(new), np.int64)
                back[kept], back[own] = b, len(f) + np.arange(len(own))
            pick = new[first]
            raw = data.tobytes() if len(pick) * 16 > len(data) else None
            words = [raw[a:b] if raw is not None else data[a:b].tobytes() for a, b in zip(starts[pick].tolist(), ends[pick].tolist(), strict=True)]
            if salt is not None:
                words = [lead + w if s else w for w, s in zip(words, salt[pick].tolist(), strict=True)]
            parts = []
            for at in range(0, len(words), AT_ONCE):
                lists = self.encode_many(words[at : at + AT_ONCE])
                sizes = np.fromiter(map(len, lists), np.int64, len(lists))
                parts.append((sizes, np.fromiter((i for x in lists for i in x), np.int32, int(sizes.sum()))))
            lengths, ids = (np.concatenate(x) for x in zip(*parts, strict=True))
            extra_flat, extra_offsets = ids, np.concatenate(([0], np.cumsum(lengths)))
            place[new] = -1 - back
            short = np.flatnonzero(~long[pick])[: max(0, LIMIT - self.index.count)]
            at, _ = K.ragged(extra_offsets, short)
            self._keep(keys[pick[short]], ids[at], lengths[short])
        begin, size = np.empty(len(place), np.int64), np.empty(len(place), np.int64)
        known = place >= 0
        begin[known], size[known] = self.offsets[place[known]], self.offsets[place[known] + 1] - self.offsets[place[known]]
        fresh = -1 - place[~known]
        begin[~known], size[~known] = extra_offsets[fresh], extra_offsets[fresh + 1] - extra_offsets[fresh]
        ends_out = np.concatenate(([0], np.cumsum(size)))
        at = np.repeat(begin - ends_out[:-1], size) + np.arange(int(ends_out[-1]))
        if known.all():
            return self.flat[at], ends_out
        from_cache = np.repeat(known, size)
        out = np.empty(len(at), np.int32)
        out[from_cache] = self.flat[at[from_cache]]
        out[~from_cache] = extra_flat[at[~from_cache]]
        return out, ends_out
