"""Token ids in ORC files: encode whole texts, write them in id order, read them back by stripes.

Layout: rows (doc_id, part, local_start, n_tokens, ids) in ascending doc_id order; ``part`` numbers the
range of doc_ids that a task wrote, ``local_start`` counts the ids before a row in its part, and a small
manifest beside the data holds each part's first global position. ORC stores the ids with its integer
run-length encoding, keeps min/max row indexes for every ``ROW_INDEX_STRIDE`` rows and Bloom filters on
doc_id; readers get stripes in parallel and skip stripes and row groups by metadata.

Null texts are empty and hold the end id alone. Rows without a doc_id come first. Rows of one doc_id stand
in the order of their texts' hashes. Extra columns are not written.
"""

from __future__ import annotations

import json
import re
import uuid
import zlib
from pathlib import Path

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from . import textkernel as K
from .shared import n_shuffle, plus, shared_dir
from .wordcache import SpanCache

END_ID = 2
ROW_INDEX_STRIDE = 1_000
STRIPE_BYTES = 16 << 20


def splits_at_space(tokenizer: dict) -> bool:
    """Whether a tokenizers file is known never to join what ASCII white space separates, and to drop the latter: by its parts, those not known to count as joining."""

    def parts(x: dict | None, name: str) -> list[dict]:
        return [] if x is None else x[name] if x["type"] == "Sequence" else [x]

    def splits(x: dict) -> bool:
        if x["type"] == "Split" and x["behavior"] == "Removed" and x["invert"] and "Regex" in x["pattern"]:
            # what is kept is matched; a match of anything white would have to say so
            left = re.sub(r"\[\^\\s(?:\\p\{[A-Z]\})*\]", "", x["pattern"]["Regex"])
            return not re.search(r"\\[sSWDPX]|[.\s]|\[\^|\\[tnrfv]|\\x|\\u", left)
        return x["type"] in ("Whitespace", "WhitespaceSplit", "BertPreTokenizer")

    def harmless(x: dict) -> bool:
        return x["type"] in ("NFC", "Lowercase") or x["type"] == "Replace" and x["pattern"] == {"Regex": "\\s+"} and x["content"] == " "

    before = parts(tokenizer.get("pre_tokenizer"), "pretokenizers")
    marks = tokenizer.get("added_tokens") or []
    return (
        bool(before) and splits(before[0]) and all(harmless(x) for x in parts(tokenizer.get("normalizer"), "normalizers"))
        and not any(m["lstrip"] or m["rstrip"] or re.search(r"\s", m["content"]) for m in marks)
    )


class WordTokenizer:
    """A tokenizers file. Where its parts are known to split at white space, words are encoded once and remembered; else texts are encoded whole."""

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.by_word = splits_at_space(json.loads(Path(path).read_text(encoding="utf-8")))
        self.cache = SpanCache(lambda words: [e.ids for e in self.library.encode_batch_fast([w.decode() for w in words], add_special_tokens=False)])

    def _ids(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        if not self.by_word:
            lists = [e.ids for e in self.library.encode_batch_fast([t or "" for t in texts.to_pylist()], add_special_tokens=False)]
            return np.fromiter((i for x in lists for i in x), np.int32), np.concatenate(([0], np.cumsum([len(x) for x in lists]))).astype(np.int64)
        data, offsets = K.buffers(texts)
        starts, ends, first = K.spans(data, offsets, K.NONSPACE)
        ids, by_word = self.cache.encode(data, starts, ends)
        return ids, by_word[first]

    def encode(self, texts: pa.Array, end_id: int | None = END_ID) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts in a row and the texts' offsets; end_id closes each text."""
        ids, offsets = self._ids(texts)
        if end_id is None:
            return ids, offsets
        out = np.full(len(ids) + len(texts), end_id, dtype=np.int32)
        is_end = np.zeros(len(out), dtype=bool)
        is_end[offsets[1:] + np.arange(len(texts))] = True
        out[~is_end] = ids
        return out, offsets + np.arange(len(texts) + 1)


_TOKENIZERS: dict[str, WordTokenizer] = {}


def tokenizer(path: str) -> WordTokenizer:
    """This worker's tokenizer: it keeps the words it knows from task to task."""
    if path not in _TOKENIZERS:
        _TOKENIZERS[path] = WordTokenizer(path)
    return _TOKENIZERS[path]


def encode(docs: DataFrame, path: str, text_col: str = "text", id_col: str = "doc_id", end_id: int = END_ID) -> DataFrame:
    """(doc_id, ids) of each document, in the rows' order."""
    kept = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))

    def run(batches):
        own = tokenizer(path)
        for batch in batches:
            for part in K.slices(batch, "text", 2 << 20):
                ids, offsets = own.encode(part.column("text"), end_id)
                yield pa.RecordBatch.from_arrays([part.column("doc_id"), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(ids, pa.int32()))], names=["doc_id", "ids"])

    return kept.mapInArrow(run, plus(kept.select("doc_id"), {"ids": "array<int>"}))


def write(docs: DataFrame, out: str, path: str, text_col: str = "text", id_col: str = "doc_id", end_id: int = END_ID, n_parts: int | None = None) -> str:
    """Writes the documents' ids under ``out``: data/ in ascending doc_id order, manifest/ with the parts' starts. Returns out."""
    spark = docs.sparkSession
    kept = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    ranged = kept.repartitionByRange(n_parts or n_shuffle(spark), F.col("doc_id").asc_nulls_first(), F.xxhash64("text")).sortWithinPartitions(F.col("doc_id").asc_nulls_first(), F.xxhash64("text"))
    id_type = kept.schema["doc_id"].dataType.simpleString()

    def run(batches):
        from pyspark import TaskContext

        own, part_no, start = tokenizer(path), TaskContext.get().partitionId(), 0
        for batch in batches:
            for part in K.slices(batch, "text", 2 << 20):
                ids, offsets = own.encode(part.column("text"), end_id)
                columns = [part.column("doc_id"), np.full(part.num_rows, part_no, np.int32), start + offsets[:-1], np.diff(offsets), pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(ids, pa.int32()))]
                start += int(offsets[-1])
                yield pa.RecordBatch.from_arrays([c if isinstance(c, pa.Array) else pa.array(c) for c in columns], names=["doc_id", "part", "local_start", "n_tokens", "ids"])

    rows = ranged.mapInArrow(run, f"doc_id {id_type}, part int, local_start bigint, n_tokens bigint, ids array<int>")
    options = {
        "orc.compress": "ZSTD", "orc.stripe.size": str(STRIPE_BYTES), "orc.row.index.stride": str(ROW_INDEX_STRIDE),
        "orc.bloom.filter.columns": "doc_id", "orc.bloom.filter.fpp": "0.01",
    }
    rows.write.options(**options).orc(f"{out}/data")
    sizes = spark.read.orc(f"{out}/data").groupBy("part").agg(F.sum("n_tokens").alias("n"), F.count("*").alias("n_rows"), F.min("doc_id").alias("first_id"), F.max("doc_id").alias("last_id"))
    start = F.coalesce(F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))  # one row a file
    sizes.select("part", "n", "n_rows", "first_id", "last_id", start.alias("part_start")).write.orc(f"{out}/manifest")
    return out


def read(spark: SparkSession, out: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids); filters on doc_id reach the stripes' metadata and Bloom filters."""
    manifest = F.broadcast(spark.read.orc(f"{out}/manifest").select("part", "part_start"))
    return spark.read.orc(f"{out}/data").join(manifest, "part").select("doc_id", (F.col("part_start") + F.col("local_start")).alias("start"), "n_tokens", "ids")


def crc_of_ids(tokens: DataFrame) -> DataFrame:
    """ids_crc32 in place of ids: crc32 over them as little-endian unsigned 32-bit integers."""
    keep = [c for c in tokens.columns if c != "ids"]

    def run(batches):
        for batch in batches:
            ids = batch.column("ids")
            raw, off = ids.flatten().to_numpy().astype("<u4"), np.concatenate(([0], np.cumsum(pc.list_value_length(ids).to_numpy(zero_copy_only=False))))
            crc = [zlib.crc32(raw[a:b].tobytes()) for a, b in zip(off[:-1].tolist(), off[1:].tolist(), strict=True)]
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in keep], pa.array(crc, pa.int64())], names=[*keep, "ids_crc32"])

    return tokens.mapInArrow(run, plus(tokens.select(*keep), {"ids_crc32": "bigint"}))


def place(spark: SparkSession) -> str:
    """A new place for token files in the shared folder."""
    return f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}"
