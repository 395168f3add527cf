"""SentencePiece encoding and decoding by a streaming Viterbi search.

The pieces and scores come from a public model file. Text is escaped as the library does (a space mark
before it and for each space), and the segmentation with the greatest sum of scores is found in one pass
that keeps only a window of back pointers: twice as wide as the longest piece, and wider only while no
boundary is common to all surviving paths. Ids are committed whenever there is one. Characters
without a piece become byte pieces. Of equal scores the longer last piece wins.

Where no piece can cross a border (before a run of space marks) every path converges, so whole segments
between such borders are remembered by a bounded cache.

Null and empty texts have no ids. Decoding gives the text back, but for the space mark itself
(U+2581), which becomes a space. Ids outside the vocabulary are an error.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from . import textkernel as K
from .shared import free_name, plus
from .wordcache import SpanCache

MARK = "▁"
#: What the library takes off the lowest score for a character without a piece.
UNKNOWN_PENALTY = 10.0


@dataclass
class Vocabulary:
    pieces: list[str]
    scores: list[float]
    byte_ids: list[int]
    plain: dict[str, tuple[int, float]] = field(default_factory=dict)
    heads: set[str] = field(default_factory=set)
    longest: int = 1
    unknown: float = 0.0
    crossing: bool = False

    @classmethod
    def load(cls, path: str) -> Vocabulary:
        from sentencepiece import SentencePieceProcessor

        model = SentencePieceProcessor(model_file=path)
        n = model.get_piece_size()
        pieces, scores = [model.id_to_piece(i) for i in range(n)], [model.get_score(i) for i in range(n)]
        byte_ids, kinds = [0] * 256, ["c" if model.is_control(i) or model.is_unused(i) else "u" if model.is_unknown(i) else "b" if model.is_byte(i) else "p" for i in range(n)]
        for i, kind in enumerate(kinds):
            if kind == "b":
                byte_ids[int(pieces[i][1:-1], 16)] = i
        return cls.of({p: (i, s) for i, (p, s, k) in enumerate(zip(pieces, scores, kinds, strict=True)) if k == "p"}, pieces, scores, byte_ids)

    @classmethod
    def of(cls, plain: dict[str, tuple[int, float]], pieces: list[str], scores: list[float], byte_ids: list[int]) -> Vocabulary:
        heads = {p[:k] for p in plain for k in range(1, len(p))}
        crossing = any(MARK in p.lstrip(MARK) for p in plain)
        return cls(pieces, scores, byte_ids, plain, heads, max(map(len, plain), default=1), min((s for _, s in plain.values()), default=0.0) - UNKNOWN_PENALTY, crossing)


class StreamingViterbi:
    """Feed characters with push(), take committed ids from ``out``, end with finish()."""

    def __init__(self, vocabulary: Vocabulary):
        self.v = vocabulary
        self.out: list[int] = []
        self.widest = 0
        self.reset()

    def reset(self) -> None:
        self.text = ""  # characters after the committed boundary
        self.best: list[float] = [0.0]  # by boundary after it
        self.back: list[int] = [-1]
        self.ids: list[int | None] = [None]
        self.reach = 0  # the farthest boundary that a piece begun so far may still get to
        self.done = 0  # boundaries from which pieces have been tried

    def push(self, chars: str) -> None:
        for at in range(0, len(chars), 4096):
            self.text += chars[at : at + 4096]
            self._extend(len(self.text) - self.v.longest)

    def finish(self) -> list[int]:
        self._extend(len(self.text))
        self._commit(len(self.text))
        return self.out

    def _extend(self, upto: int) -> None:
        """Tries the pieces that begin at each boundary before ``upto``, and commits where all paths meet."""
        plain, heads, unknown, longest = self.v.plain, self.v.heads, self.v.unknown, self.v.longest
        while self.done < upto:
            i, text, best, back, ids = self.done, self.text, self.best, self.back, self.ids
            n = len(text)
            if len(best) <= i + longest:
                more = i + longest + 1 - len(best)
                best += [-np.inf] * more
                back += [-1] * more
                ids += [None] * more
            here, end = best[i], i + 1
            single = False
            while True:
                piece = text[i:end]
                if found := plain.get(piece):
                    if (score := here + found[1]) > best[end]:
                        best[end], back[end], ids[end] = score, i, found[0]
                    self.reach = max(self.reach, end)
                    single = single or end == i + 1
                if end >= n or piece not in heads:
                    break
                end += 1
            if not single:
                if (score := here + unknown) > best[i + 1]:
                    best[i + 1], back[i + 1], ids[i + 1] = score, i, None
                self.reach = max(self.reach, i + 1)
            self.done = i + 1
            if self.reach == self.done and self.done >= longest:  # no piece goes on beyond this boundary
                self._commit(self.done)
                upto -= i + 1
            elif self.done >= 2 * longest and self.done % longest == 0 and (meet := self._meeting()):
                self._commit(meet)
                upto -= meet
            self.widest = max(self.widest, len(self.best))

    def _meeting(self) -> int:
        """The last boundary that the paths to all live boundaries share."""
        live = {j for j in range(self.done, len(self.best)) if self.best[j] > -np.inf}
        while len(live) > 1:
            live.remove(top := max(live))
            live.add(self.back[top])
        return live.pop() if live else 0

    def _commit(self, boundary: int) -> None:
        path, at = [], boundary
        while at > 0:
            path.append((self.back[at], at))
            at = self.back[at]
        for a, b in reversed(path):
            if (i := self.ids[b]) is not None:
                self.out.append(i)
            else:
                self.out.extend(self.v.byte_ids[x] for x in self.text[a:b].encode())
        base = self.best[boundary]
        self.text = self.text[boundary:]
        self.best = [0.0, *[x - base for x in self.best[boundary + 1 :]]]
        self.back = [-1, *[x - boundary for x in self.back[boundary + 1 :]]]
        self.ids = [None, *self.ids[boundary + 1 :]]
        self.done -= boundary
        self.reach -= boundary


def viterbi(vocabulary: Vocabulary, escaped: str) -> list[int]:
    """Ids of an escaped text."""
    search = StreamingViterbi(vocabulary)
    search.push(escaped)
    return search.finish()


#: Everything but the space, in bytes.
_SOLID = np.ones(256, dtype=bool)
_SOLID[32] = False


class PieceEncoder:
    def __init__(self, vocabulary: Vocabulary):
        self.v = vocabulary
        self.cache = SpanCache(lambda segments: [viterbi(vocabulary, s.decode().replace(" ", MARK)) for s in segments])

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row, and the texts' offsets."""
        texts = pc.replace_substring(texts.fill_null(""), MARK, " ")
        if self.v.crossing:  # a piece may cross spaces: no borders are certain
            lists = [viterbi(self.v, (" " + t).replace(" ", MARK)) if t else [] for t in texts.to_pylist()]
            return np.fromiter((i for x in lists for i in x), np.int32), np.concatenate(([0], np.cumsum([len(x) for x in lists])))
        data, offsets = K.buffers(texts)
        if not len(data):
            return np.zeros(0, np.int32), np.zeros(len(offsets), np.int64)
        # a segment is a run of spaces with what follows it; the first of a text has the mark before the text too
        solid = _SOLID[data]
        begins = ~solid
        begins[1:] &= solid[:-1]
        heads = offsets[:-1][offsets[:-1] < offsets[1:]]
        begins[heads] = True
        starts = np.flatnonzero(begins)
        ends = np.append(starts[1:], len(data))
        first = np.zeros(len(starts), dtype=bool)
        first[np.searchsorted(starts, heads)] = True
        ids, by_segment = self.cache.encode(data, starts, ends, first, b" ")
        return ids, by_segment[np.searchsorted(starts, offsets)]

    def decode(self, ids: np.ndarray, offsets: np.ndarray) -> list[str]:
        """Texts of id runs."""
        out, pieces, is_byte = [], self.v.pieces, {i: b for b, i in enumerate(self.v.byte_ids)}
        if len(ids) and (ids.min() < 0 or ids.max() >= len(pieces)):
            raise ValueError("an id is not in the vocabulary")
        byte_table = np.zeros(len(pieces), dtype=bool)
        byte_table[list(is_byte)] = True
        bytes_here = np.concatenate(([0], np.cumsum(byte_table[ids]))) if len(ids) else np.zeros(1, int)
        for a, b in zip(offsets[:-1].tolist(), offsets[1:].tolist(), strict=True):
            run = ids[a:b].tolist()
            if bytes_here[b] == bytes_here[a]:
                text = "".join([pieces[i] for i in run])
            else:
                text = b"".join([bytes([is_byte[i]]) if i in is_byte else pieces[i].encode() for i in run]).decode("utf-8", "replace")
            text = text.replace(MARK, " ")
            out.append(text[1:] if text[:1] == " " else text)
        return out


_ENCODERS: dict[str, PieceEncoder] = {}


def encoder_of(path: str) -> PieceEncoder:
    """This worker's encoder: it keeps the segments it knows from task to task."""
    if path not in _ENCODERS:
        _ENCODERS[path] = PieceEncoder(Vocabulary.load(path))
    return _ENCODERS[path]


def encode(docs: DataFrame, path: str, text_col: str = "text") -> DataFrame:
    """The documents with their ids in a new column ``ids``."""
    name = free_name(docs, "ids")

    def run(batches):
        encoder = encoder_of(path)
        for batch in batches:
            for part in K.slices(batch, text_col, 4 << 20):
                ids, offsets = encoder.encode(part.column(text_col))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(ids, pa.int32()))], names=[*part.schema.names, name])

    return docs.mapInArrow(run, plus(docs, {name: "array<int>"}))


def decode(tokens: DataFrame, path: str, ids_col: str = "ids") -> DataFrame:
    """The rows with the text of their ids in a new column ``decoded``; null ids give a null."""
    name = free_name(tokens, "decoded")

    def run(batches):
        encoder = encoder_of(path)
        for batch in batches:
            ids = batch.column(ids_col)
            off = np.concatenate(([0], np.cumsum(pc.fill_null(pc.list_value_length(ids), 0).to_numpy(zero_copy_only=False))))
            texts = encoder.decode(ids.flatten().to_numpy(), off)
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, pa.string(), mask=ids.is_null().to_numpy(zero_copy_only=False))], names=[*batch.schema.names, name])

    return tokens.mapInArrow(run, plus(tokens, {name: "string"}))


def round_trip(docs: DataFrame, path: str, text_col: str = "text") -> DataFrame:
    """What encode and decode give, in one pass: the documents with n_tokens, ids_crc32 (of the ids as little-endian 32-bit integers) and same (decoded text equals the text)."""
    names = [free_name(docs, n) for n in ("n_tokens", "ids_crc32", "same")]

    def run(batches):
        encoder = encoder_of(path)
        for batch in batches:
            for part in K.slices(batch, text_col, 4 << 20):
                texts = part.column(text_col).fill_null("")
                ids, off = encoder.encode(texts)
                raw = ids.astype("<u4")
                crc = [zlib.crc32(raw[a:b].tobytes()) for a, b in zip(off[:-1].tolist(), off[1:].tolist(), strict=True)]
                same = pc.equal(pa.array(encoder.decode(ids, off), pa.string()), pc.replace_substring(texts, MARK, " ").cast(pa.string()))
                yield pa.RecordBatch.from_arrays([*part.columns, pa.array(np.diff(off), pa.int64()), pa.array(crc, pa.int64()), same], names=[*part.schema.names, *names])

    return docs.mapInArrow(run, plus(docs, dict(zip(names, ("bigint", "bigint", "boolean"), strict=True))))
