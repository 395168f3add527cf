"""Benchmark decontamination by a broadcast set of benchmark word windows.

A window is ``WINDOW`` consecutive words of a benchmark item (an item of fewer words is one window).
The set is broadcast only while its size is within ``MAX_WINDOWS`` (each takes its words and about 300 bytes);
a larger benchmark is dealt over several passes of such sets, each over all documents as the one before left
them, so one set is held at a time. An item of more windows is cut where no window is lost.
Hits of the hash set are verified on the words themselves.

Nulls and texts without words have no windows. Repeated rows are judged each for itself; an item
without an id hits words but adds nothing to the item list. Columns that clash with the added ones
are kept, and the added ones get an underscore before their names.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .shared import free_name, plus, written

WINDOW = 13
#: A document is contaminated from this share of hit words on: 1 in SHARE.
SHARE = 20
#: Proven bound of one broadcast set.
MAX_WINDOWS = 2_000_000


class WindowSet:
    """Hashes of windows by width, with the words and the items of each."""

    def __init__(self, items: list[tuple[object, str | None]]):
        self.by_width: dict[int, tuple[np.ndarray, list[list[tuple[bytes, int]]]]] = {}
        self.ids = [None if i is None else str(i) for i, _ in items]
        found: dict[int, dict[int, dict[bytes, list[int]]]] = {}
        for k, (_, text) in enumerate(items):
            data, starts, ends, first, hashes = K.word_hashes(pa.array([text], pa.string()), K.WORD)
            width = min(WINDOW, len(hashes))
            if not width:
                continue
            at, window = K.windows(hashes, first, width)
            for p, h in zip(at.tolist(), window.tolist(), strict=True):
                words = b" ".join(bytes(data[a:b]) for a, b in zip(starts[p : p + width], ends[p : p + width], strict=True))
                owners = found.setdefault(width, {}).setdefault(h, {}).setdefault(words, [])
                if not owners or owners[-1] != k:
                    owners.append(k)
        for width, hashes in found.items():
            keys = np.array(sorted(hashes), dtype=K.U64)
            self.by_width[width] = keys, [hashes[h] for h in keys.tolist()]

    def scan(self, texts: pa.Array) -> tuple[np.ndarray, list[list[tuple[int, int]]], list[set[int]]]:
        """Per text: its number of words, the hit runs of words as (first, end) byte offsets in it, and the indices of its items."""
        data, starts, ends, first, hashes = K.word_hashes(texts, K.WORD)
        hit = np.zeros(len(hashes) + 1, dtype=np.int64)
        owners: list[set[int]] = [set() for _ in range(len(texts))]
        for width, (keys, words) in self.by_width.items():
            at, window = K.windows(hashes, first, width)
            sure = K.is_member(window, keys)
            at, window = at[sure], window[sure]
            of = np.searchsorted(first, at, "right") - 1
            for p, h, doc in zip(at.tolist(), np.searchsorted(keys, window).tolist(), of.tolist(), strict=True):
                seen = b" ".join(bytes(data[a:b]) for a, b in zip(starts[p : p + width], ends[p : p + width], strict=True))
                if mine := words[h].get(seen):
                    hit[p] += 1
                    hit[p + width] -= 1
                    owners[doc].update(mine)
        covered = np.cumsum(hit[:-1]) > 0
        _, offsets = K.buffers(texts)
        runs: list[list[tuple[int, int, int]]] = [[] for _ in range(len(texts))]
        edge = np.diff(np.concatenate(([0], covered.view(np.int8), [0])))
        for a, b in zip(np.flatnonzero(edge == 1).tolist(), np.flatnonzero(edge == -1).tolist(), strict=True):
            while a < b:  # a run of hit words may go on into the next text
                doc = int(np.searchsorted(first, a, "right")) - 1
                end = min(b, int(first[doc + 1]))
                runs[doc].append((int(starts[a] - offsets[doc]), int(ends[end - 1] - offsets[doc]), end - a))
                a = end
        return np.diff(first), runs, owners


def _scan(docs: DataFrame, items: list[tuple[object, str | None]], text_col: str, names: dict[str, str]) -> DataFrame:
    """All columns of the documents, and what WindowSet.scan finds."""
    if any(f.name == text_col and f.dataType.typeName() != "string" for f in docs.schema):
        raise TypeError(f"{text_col} must be a string column")
    shared = docs.sparkSession.sparkContext.broadcast(WindowSet(items))

    def run(batches):
        for batch in batches:
            for part in K.slices(batch, text_col):
                n_words, runs, owners = shared.value.scan(part.column(text_col))
                ids = shared.value.ids
                added = [
                    pa.array(n_words, pa.int64()),
                    pa.array([sum(r[2] for r in x) for x in runs], pa.int64()),
                    pa.array([sorted({ids[k] for k in x if ids[k] is not None}) for x in owners], pa.list_(pa.string())),
                    pa.array([[{"start": a, "end": b} for a, b, _ in x] for x in runs], pa.list_(pa.struct([("start", pa.int64()), ("end", pa.int64())]))),
                ]
                yield pa.RecordBatch.from_arrays([*part.columns, *added], names=[*part.schema.names, *list(names.values())[:4]])

    kinds = {"n_words": "bigint", "n_hit": "bigint", "items": "array<string>", "spans": "array<struct<start:bigint,end:bigint>>"}
    schema = plus(docs, {names[k]: kind for k, kind in kinds.items()})
    return docs.mapInArrow(run, schema)


def find_contamination(docs: DataFrame, benchmark: DataFrame, text_col: str = "text", item_col: str = "item_id", item_text_col: str = "text") -> DataFrame:
    """The documents with n_words, n_hit, items (ids as strings, sorted), spans (hit byte ranges) and contaminated.

    The items are read to the driver as they are needed, a pass of at most MAX_WINDOWS windows at a time.
    """
    names = {k: free_name(docs, k) for k in ("n_words", "n_hit", "items", "spans", "contaminated")}
    out, room, one, further = None, MAX_WINDOWS, [], False
    for item, text, windows in _items(benchmark, item_col, item_text_col):
        if windows > room and one:
            # written, so that the next pass starts from it and this one's set can go
            out, one, room, further = written(_pass(docs, out, one, text_col, names), "scanned"), [], MAX_WINDOWS, True
        one.append((item, text))
        room -= windows
    out = _pass(docs, out, one, text_col, names)
    if further:  # hit runs of several passes can overlap
        out = _recount(out, text_col, names)
    return out.withColumn(names["contaminated"], (F.col(names["n_hit"]) > 0) & (F.col(names["n_hit"]) * SHARE >= F.col(names["n_words"])))


def _items(benchmark: DataFrame, item_col: str, item_text_col: str) -> Iterator[tuple[object, str | None, int]]:
    """(id, text, windows at most) of the items; one of more windows than a pass takes comes in parts that share ``WINDOW`` - 1 words."""
    for row in benchmark.select(F.col(item_col).alias("i"), F.col(item_text_col).alias("t")).toLocalIterator():
        if len(row.t or "") <= MAX_WINDOWS:
            yield row.i, row.t, len(row.t or "")
            continue
        data, starts, ends, _, _ = K.word_hashes(pa.array([row.t], pa.string()), K.WORD)
        raw = data.tobytes()
        for at in range(0, max(1, len(starts) - WINDOW + 1), MAX_WINDOWS):
            part = slice(at, at + MAX_WINDOWS + WINDOW - 1)
            yield row.i, b" ".join(raw[a:b] for a, b in zip(starts[part].tolist(), ends[part].tolist(), strict=True)).decode(), MAX_WINDOWS


def _pass(docs: DataFrame, before: DataFrame | None, items: list[tuple[object, str | None]], text_col: str, names: dict[str, str]) -> DataFrame:
    """One pass over the documents, or over what the passes before it found."""
    if before is None:
        return _scan(docs, items, text_col, names)
    again = {k: free_name(before, k) for k in names}
    out = _scan(before, items, text_col, again)
    both = F.concat(F.col(names["spans"]), F.col(again["spans"]))
    merged = {names["items"]: F.array_sort(F.array_union(names["items"], again["items"])), names["spans"]: both}
    return out.withColumns(merged).drop(*[again[k] for k in ("n_words", "n_hit", "items", "spans")])


def _recount(df: DataFrame, text_col: str, names: dict[str, str]) -> DataFrame:
    """Merges overlapping spans and counts the words in them."""
    at_hit, at_span = df.columns.index(names["n_hit"]), df.columns.index(names["spans"])

    def run(batches):
        for batch in batches:
            for part in K.slices(batch, text_col):
                data, offsets = K.buffers(part.column(text_col))
                starts, _, first = K.spans(K.LOWER[data], offsets, K.WORD)
                counts, merged = [], []
                for doc, found in enumerate(part.column(at_span).to_pylist()):
                    mine: list[list[int]] = []
                    for x in sorted((x["start"], x["end"]) for x in found):
                        if mine and x[0] <= mine[-1][1]:
                            mine[-1][1] = max(mine[-1][1], x[1])
                        else:
                            mine.append(list(x))
                    own = starts[first[doc] : first[doc + 1]] - offsets[doc]
                    counts.append(sum(int(np.searchsorted(own, b) - np.searchsorted(own, a)) for a, b in mine))
                    merged.append([{"start": a, "end": b} for a, b in mine])
                part = part.set_column(at_hit, part.schema.field(at_hit), pa.array(counts, pa.int64()))
                yield part.set_column(at_span, part.schema.field(at_span), pa.array(merged, part.schema.field(at_span).type))

    return df.mapInArrow(run, df.schema)


def remove_documents(found: DataFrame, flag: str = "contaminated") -> DataFrame:
    """Drops contaminated documents."""
    return found.where(~F.col(flag))


def remove_spans(found: DataFrame, text_col: str = "text", spans_col: str = "spans") -> DataFrame:
    """Cuts the hit byte ranges out of the texts; a null text stays null."""
    kind = found.schema[text_col]

    def run(batches):
        for batch in batches:
            at = batch.schema.get_field_index(text_col)
            texts = []
            for text, cut in zip(batch.column(at).to_pylist(), batch.column(batch.schema.get_field_index(spans_col)).to_pylist(), strict=True):
                if text is not None and cut:
                    raw, out, last = text.encode(), [], 0
                    for x in cut:
                        out.append(raw[last : x["start"]])
                        last = x["end"]
                    text = b"".join([*out, raw[last:]]).decode()
                texts.append(text)
            yield batch.set_column(at, batch.schema.field(at), pa.array(texts, batch.schema.field(at).type))

    assert kind.dataType.typeName() == "string"
    return found.mapInArrow(run, found.schema)


def items_digest(items: list[str]) -> str:
    """SHA-256 of the sorted ids, joined by commas; the plan uses sha2 and array_join for the same."""
    return hashlib.sha256(",".join(items).encode()).hexdigest()
