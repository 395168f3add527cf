"""Quality classifier: interpolated modified Kneser-Ney language model of trusted text.

The model is fitted on all trusted rows but one fold in ``FOLDS`` by the id's checksum, which is held out for
the thresholds: no trusted row is left out of both. Tokens are dealt over shards by the word before them, so
all n-grams of a context, all n-grams that continue one, and their counts of every order above the first lie
in one shard: one exchange counts them all. There are ``SHARDS`` of them, or more where the trusted text asks
for it (``SHARD_BYTES``). Only words are counted across shards, by a second exchange of one count a word and shard.

Scoring joins documents with the counts by shard, in ``TURNS`` turns of so many of the shards each; the files
of a turn's exchanges are removed before the next, and the n-grams are counted again where they are asked for,
so the table is never stored and disk holds a turn at most. Documents become chunks of tokens, dealt as trusted
text is; a shard gives back a sum for each document. The first order is known to all for ``FREQUENT`` words, and
asked of the word's own shard for the rest, those filtered first by a bitmap of known words (``FILTER_BITS``
bits). Where documents are many for the shards, groups of chunks meet copies of a shard (``CHUNK_GROUP``).
Sums are of whole numbers (``FIXED`` to one), so they do not depend on how rows are dealt.

A document's perplexity is compared with the quantile of the held-out trusted documents of its language.

Tokens are the runs of non-white-space characters, A-Z in lower case, and one end a text. Null and
empty texts are one end token. Languages of fewer than ``MIN_HELD_OUT`` held-out rows, and null ones, are
held against the quantile over all held-out rows. Equal texts of one language are judged alike.
"""

from __future__ import annotations

import zlib
from dataclasses import dataclass
from functools import cached_property, reduce

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from . import textkernel as K
from .pitman_yor import pack, steps, unpack
from .shared import free_name, plus, released, written

ORDER = 3
#: Trusted rows whose id's checksum leaves HELD_OUT when divided by FOLDS are for the thresholds, all others for the counts.
FOLDS, HELD_OUT = 7, 2
QUANTILE = 0.995
#: Held-out rows from which a language has a cut of its own: as many as put one row above the quantile.
MIN_HELD_OUT = 200
#: Tokens of a chunk; least shards of the counts, a power of two; chunks whose text one copy of a shard meets, about; bits of the filter.
CHUNK_TOKENS, SHARDS, CHUNK_GROUP, FILTER_BITS = 1_000_000, 32, 16, 26
#: Bytes of text of a chunk, about.
CHUNK_BYTES = 4 << 20
#: Bytes of trusted text that a shard of the counts is for, at most.
SHARD_BYTES = 8 << 20
#: Turns of scoring; words whose counts all tasks are given, at most about; whole numbers to one of a logarithm.
TURNS, FREQUENT, FIXED = 4, 1 << 18, float(1 << 32)
BEGIN, END = K.U64(0x9AE16A3B2F90404F), K.U64(0xC3A5C85C97CB3127)


def token_runs(texts: pa.Array, order: int) -> tuple[list[np.ndarray], np.ndarray]:
    """For k = 0..order - 1 the token k places before each token, begin marks before a text; and the tokens of each text."""
    _, _, _, first, words = K.word_hashes(texts, K.NONSPACE)
    n = np.diff(first) + 1
    offsets = np.concatenate(([0], np.cumsum(n + order - 1)))
    flat = np.full(int(offsets[-1]), BEGIN, dtype=K.U64)
    at = np.arange(int(n.sum())) + np.repeat(np.arange(1, len(n) + 1), n) * (order - 1)
    last = offsets[1:] - 1
    is_end = np.zeros(len(flat), dtype=bool)
    is_end[last] = True
    flat[at[~is_end[at]]] = words
    flat[last] = END
    return [flat[at - k] for k in range(order)], n


def gram_hashes(runs: list[np.ndarray]) -> list[np.ndarray]:
    """For k = 1..len(runs) the hashes of the last k tokens."""
    grams, acc = [runs[0]], runs[0]
    for k, before in enumerate(runs[1:], 1):
        acc = acc * K.U64(K.BASE) + before
        grams.append(K.mix(acc + K.U64(k)))
    return grams


def token_grid(texts: pa.Array, order: int) -> tuple[list[np.ndarray], np.ndarray]:
    """For k = 1..order the hash of the last k tokens at each token, and the tokens of each text."""
    runs, n = token_runs(texts, order)
    return gram_hashes(runs), n


@dataclass
class Level:
    """One order: discounted shares of its n-grams, and the weight each context leaves to the order below."""

    gram_keys: np.ndarray
    share: np.ndarray
    context_keys: np.ndarray
    weight: np.ndarray

    @cached_property
    def grams(self) -> K.HashIndex:
        return K.HashIndex(self.gram_keys)

    @cached_property
    def contexts(self) -> K.HashIndex:
        return K.HashIndex(self.context_keys)


@dataclass
class KneserNey:
    """The whole table in one place, for small models: levels[k] is for k + 1 tokens; ``floor`` is the uniform share below the first order."""

    levels: list[Level]
    floor: float

    def log10(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Tokens and log10 probability of each text."""
        order = len(self.levels)
        grams, n = token_grid(texts, order)
        known = self.levels[0].grams.find(grams[0])
        p = np.append(self.levels[0].share, 0.0)[known] + self.floor  # place -1 is the appended zero
        before = [_shifted(g, n, k) for k, g in enumerate(grams[:-1], 1)]
        for k in range(1, order):
            level = self.levels[k]
            ctx = level.contexts.find(before[k - 1])
            some = np.flatnonzero(ctx >= 0)
            own = level.grams.find(grams[k][some])
            p[some] = level.weight[ctx[some]] * p[some] + np.append(level.share, 0.0)[own]
        logs = np.log10(p)
        ends = np.cumsum(n)
        total = np.concatenate(([0.0], np.cumsum(logs)))
        return n, total[ends] - total[ends - n]


def _begin_contexts(order: int) -> list[np.ndarray]:
    """Hash of the last k tokens where all are begin marks."""
    out, acc = [np.array([BEGIN], K.U64)], np.array([BEGIN], K.U64)
    for k in range(1, order):
        acc = acc * K.U64(K.BASE) + BEGIN
        out.append(K.mix(acc + K.U64(k)))
    return out


def _shifted(gram: np.ndarray, n: np.ndarray, k: int) -> np.ndarray:
    """The k-token context of each token: what ``gram`` is one token earlier, begin marks at a text's first token."""
    out = np.empty_like(gram)
    out[1:] = gram[:-1]
    out[np.concatenate(([0], np.cumsum(n)[:-1]))] = _begin_contexts(k)[k - 1][0]
    return out


def training_ids(docs: DataFrame, labels: DataFrame, good: Column, max_train: int, max_bytes: int) -> list:
    """Ids of the trusted rows to train on: every second by the hash of the id, those whose text still fits in max_bytes."""
    known = labels.where(good & F.col("doc_id").isNotNull()).select("doc_id").distinct().orderBy(F.xxhash64("doc_id"), "doc_id").limit(min(2 * max_train, (1 << 31) - 1))
    rows = docs.select("doc_id", F.octet_length(F.coalesce("text", F.lit(""))).cast("long").alias("b")).join(F.broadcast(known), "doc_id")
    sizes = rows.groupBy("doc_id").agg(F.sum("b").alias("b"), F.count("*").alias("n")).orderBy(F.xxhash64("doc_id"), "doc_id").collect()  # two of each id to be trained on, at most
    out, left, places = [], max_bytes, max_train
    for r in sizes[::2]:
        if r.b <= left and r.n <= places:
            out.append(r.doc_id)
            left, places = left - r.b, places - r.n
    return out


def upper_quantiles(rows: DataFrame, group: str, value: str, quantile: float) -> dict[object, tuple[int, float]]:
    """Rows and exact (interpolated) quantile of each group. Only rows near the quantile and above are sorted."""
    near = F.when(F.count("*") < 10_000, F.lit(float("-inf"))).otherwise(F.percentile_approx(value, max(quantile - 0.002, 0.0), 10_000))
    bounds = {r.g: (r.n, r.low) for r in rows.groupBy(F.col(group).alias("g")).agg(F.count("*").alias("n"), near.alias("low")).collect()}
    if not bounds:
        return {}
    schema = T.StructType([T.StructField("g", rows.schema[group].dataType), T.StructField("n", T.LongType()), T.StructField("low", T.DoubleType())])
    table = rows.sparkSession.createDataFrame([(g, n, low) for g, (n, low) in bounds.items()], schema)
    tail = rows.select(F.col(group).alias("g"), F.col(value).alias("x")).join(F.broadcast(table), "g").where("x >= low")
    down = F.row_number().over(Window.partitionBy("g").orderBy(F.desc("x"))) - 1
    at = (F.col("n") - 1) * F.lit(quantile)
    place = tail.withColumn("up", F.col("n") - 1 - down).where((F.col("up") == F.floor(at)) | (F.col("up") == F.ceil(at)))
    got = place.withColumn("part", at - F.floor(at)).groupBy("g").agg(F.min("x").alias("lo"), F.max("x").alias("hi"), F.first("part").alias("part"))
    return {r.g: (bounds[r.g][0], r.lo + (r.hi - r.lo) * r.part) for r in got.collect()}


def _shard_of(keys: np.ndarray, shards: int) -> np.ndarray:
    return (keys >> K.U64(64 - shards.bit_length() + 1)).astype(np.int32)


def _table(rows: list[tuple], ddl: str) -> pa.Table:
    kinds = {"int": pa.int32(), "bigint": pa.int64(), "binary": pa.binary()}
    fields = [x.split() for x in ddl.split(", ")]
    return pa.table([pa.array([r[c] for r in rows], kinds[t]) for c, (_, t) in enumerate(fields)], names=[n for n, _ in fields])


def _chunks(batches, text_col: str):
    """Chunks of a partition's texts: number, batches without the texts, words of each text, hashes of the words.
    Which rows make a chunk depends on the rows before alone, not on how they come in batches."""
    from pyspark import TaskContext

    number, held, counts, hashes, size = TaskContext.get().partitionId() << 32, [], [], [], 0
    now = 0
    for batch in batches:
        for part in K.slices(batch, text_col):
            _, _, _, first, words = K.word_hashes(part.column(text_col), K.NONSPACE)
            n, rest = np.diff(first), part.drop_columns([text_col])
            before = size + np.cumsum(n + 1) - n - 1
            own = before // CHUNK_TOKENS
            size = int(before[-1] + n[-1] + 1)
            cuts = np.concatenate(([0], np.flatnonzero(np.diff(own)) + 1, [len(own)])).tolist()
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                if held and own[a] != now:
                    yield number + now, held, np.concatenate(counts), np.concatenate(hashes)
                    held, counts, hashes = [], [], []
                now = int(own[a])
                held.append(rest.slice(a, b - a))
                counts.append(n[a:b])
                hashes.append(words[int(first[a]) : int(first[b])])
    if held:
        yield number + now, held, np.concatenate(counts), np.concatenate(hashes)


@dataclass
class Frequent:
    """Words whose counts all tasks are given: ascending, their counts, and each one's rank by count."""

    keys: np.ndarray
    counts: np.ndarray
    rank: np.ndarray

    def ranks(self, at: np.ndarray) -> np.ndarray:
        """Ranks of places among the keys, -1 for -1."""
        return np.append(self.rank.astype(np.int64), -1)[at]

    @cached_property
    def ranked(self) -> np.ndarray:
        out = np.empty_like(self.keys)
        out[self.rank] = self.keys
        return out


NONE = Frequent(np.zeros(0, K.U64), np.zeros(0, np.int64), np.zeros(0, np.uint32))


def _order(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The stable ascending order of hashes, and the hashes in it: values are sorted, each with its place for its lowest bits.
    Where the bits that are left do not tell two hashes apart, the order is made from whole ones."""
    low = K.U64((1 << len(keys).bit_length()) - 1)
    by = keys & ~low
    by |= np.arange(len(keys), dtype=K.U64)
    by.sort()
    by &= low
    by = by.view(np.int64)
    out = keys[by]
    if (out[1:] < out[:-1]).any():
        by = np.argsort(keys, kind="stable")
        out = keys[by]
    return by, out


def _heads(ascending: np.ndarray) -> np.ndarray:
    """Whether each value is the first of its kind."""
    out = np.ones(len(ascending), dtype=bool)
    np.not_equal(ascending[1:], ascending[:-1], out=out[1:])
    return out


def _distinct(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The distinct hashes, ascending, where each stands first, and how many there are of each."""
    by, keys = _order(keys)
    heads = np.flatnonzero(_heads(keys))
    return keys[heads], by[heads], np.diff(heads, append=len(keys))


def _inverse(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct hashes, ascending, and the place of each hash among them."""
    by, keys = _order(keys)
    heads = _heads(keys)
    place = np.empty(len(keys), np.int64)
    ascending = np.cumsum(heads)
    ascending -= 1
    place[by] = ascending
    return keys[heads], place


class Places:
    """Places of keys in ascending distinct ones, looked for from the first of those that are alike in their leading bits."""

    def __init__(self, keys: np.ndarray):
        self.keys = keys
        if len(keys):
            self.low = keys[0]
            self.span = keys[-1] - self.low
            self.shift = K.U64(max(0, int(self.span).bit_length() - len(keys).bit_length()))
            own = ((keys - self.low) >> self.shift).astype(np.int64)
            self.start = np.zeros(int(own[-1]) + 1, np.int64)
            np.cumsum(np.bincount(own)[:-1], out=self.start[1:])

    def find(self, asked: np.ndarray) -> np.ndarray:
        """The place of each asked key, -1 where it is none of them."""
        out = np.full(len(asked), -1, np.int64)
        if not len(self.keys) or not len(asked):
            return out
        far = asked - self.low
        at = self.start[np.minimum(far >> self.shift, K.U64(len(self.start) - 1)).astype(np.int64)]
        key = self.keys[at]
        same = key == asked
        out[same] = at[same]
        left = np.flatnonzero((key < asked) & (far <= self.span))
        at, far = at[left], asked[left]
        for _ in range(8):
            if not len(left):
                return out
            at += 1  # the last key is not less than what is looked for, so there is one more
            key = self.keys[at]
            same = key == far
            out[left[same]] = at[same]
            go = key < far
            left, at, far = left[go], at[go], far[go]
        out[left] = _find(self.keys, far)  # many keys are alike
        return out


def _places(n: np.ndarray, words: np.ndarray, order: int, frequent: Frequent) -> tuple[np.ndarray, np.ndarray, list[np.ndarray], np.ndarray]:
    """Of a chunk: its distinct words and marks, first the frequent ones by rank, then the others ascending; the place of
    each among the frequent keys or -1; for k = 0..order - 1 the place of the token k before each token; each token's text."""
    distinct, place = _inverse(np.concatenate((words, [BEGIN, END])))
    at = _find(frequent.keys, distinct)
    rank = frequent.ranks(at)
    by = np.argsort(np.where(rank >= 0, rank, 1 << 40), kind="stable")
    new = np.empty(len(by), np.uint32)
    new[by] = np.arange(len(by), dtype=np.uint32)
    place = new[place]
    n = n + 1
    ends = np.cumsum(n)
    flat = np.full(int(ends[-1]), place[-1])
    word = np.ones(len(flat), dtype=bool)
    word[ends - 1] = False
    flat[word] = place[:-2]
    runs = [flat]
    for k in range(1, order):
        before = np.empty_like(flat)
        before[k:] = flat[: len(flat) - k]
        for since in range(k):
            before[(ends - n + since)[n > since]] = place[-2]
        runs.append(before)
    return distinct[by], at[by], runs, np.repeat(np.arange(len(n), dtype=np.uint32), n)


def _packed_words(words: np.ndarray, rank: np.ndarray) -> bytes:
    """Words of a chunk, in its order: ranks of the frequent ones, and the others, which are -1."""
    some = int((rank >= 0).sum())
    first, rest = pack(steps(rank[:some].astype(np.uint32))), pack(steps(words[some:]))
    return len(first).to_bytes(4, "little") + first + rest


def _unpacked_words(b: bytes, frequent: Frequent) -> np.ndarray:
    end = 4 + int.from_bytes(b[:4], "little")
    return np.concatenate((frequent.ranked[np.cumsum(unpack(b[4:end]), dtype=np.int64)], np.cumsum(unpack(b[end:]), dtype=K.U64)))


class _Row:
    """A row of a table, whose values are taken out when they are asked for."""

    def __init__(self, table: pa.Table, at: int):
        self.table, self.at = table, at

    def __getitem__(self, name: str):
        return self.table.column(name)[self.at].as_py()


#: What is dealt to a shard. Kinds 0 and -1 are rows of WORDS; then tokens to count, tokens to score, words to score, and sums that need no shard.
MESSAGES = "shard int, kind int, chunk bigint, texts binary, words binary, tokens binary"
COUNTED, SCORED, ASKED, SUMS = 1, 2, 3, 4


def _dealt(chunk: int, kind: int, words: np.ndarray, rank: np.ndarray, runs: list[np.ndarray], texts: np.ndarray | None, shard: np.ndarray, wanted: np.ndarray) -> list[tuple]:
    """The wanted tokens of a chunk by shard, each shard's as places in the words they use."""
    at = np.flatnonzero(wanted)
    at = at[np.argsort(shard[at].astype(np.min_scalar_type(int(shard.max(initial=0)))), kind="stable")]
    own = shard[at]
    cuts = np.concatenate(([0], np.flatnonzero(np.diff(own)) + 1, [len(own)])) if len(own) else [0]
    out, new = [], np.zeros(len(words), np.uint32)
    for a, b in zip(cuts[:-1], cuts[1:], strict=True):
        cols = [r[at[a:b]] for r in runs]
        used = np.zeros(len(words), dtype=bool)
        for c in cols:
            used[c] = True
        ids = np.flatnonzero(used)
        new[ids] = np.arange(len(ids), dtype=np.uint32)
        tokens = np.concatenate([new[c] for c in cols]).astype(np.uint16 if len(ids) <= 1 << 16 else np.uint32)
        out.append((int(own[a]), kind, chunk, None if texts is None else pack(steps(texts[at[a:b]])), _packed_words(words[ids], rank[ids]), pack(tokens)))
    return out


def _by_shard(words: np.ndarray, runs: list[np.ndarray], shards: int) -> np.ndarray:
    """The shard of each token, by the word before it: all n-grams of a context and all that continue one lie together."""
    return _shard_of(words, shards)[runs[min(1, len(runs) - 1)]]


def _to_count(train: DataFrame, order: int, shards: int, frequent=None, turn: int = 0, turns: int = 1) -> DataFrame:
    """The tokens to count, as messages to the shards of a turn. frequent: a broadcast."""

    def run(batches):
        for number, _, n, hashes in _chunks(batches, "text"):
            words, at, runs, _ = _places(n, hashes, order, own := frequent.value if frequent else NONE)
            shard = _by_shard(words, runs, shards)
            yield from _table(_dealt(number, COUNTED, words, own.ranks(at), runs, None, shard, shard % turns == turn), MESSAGES).to_batches()

    return train.select("text").mapInArrow(run, MESSAGES)


def _last_hash(words: np.ndarray, places: list[np.ndarray]) -> np.ndarray:
    """The hashes of all tokens given by their places among words, as the last of ``gram_hashes``."""
    acc = words[places[0]]
    for before in places[1:]:
        acc *= K.U64(K.BASE)
        acc += words[before]
    return K.mix(acc + K.U64(len(places) - 1)) if len(places) > 1 else acc


def _grouped(rows: list, order: int, use, frequent: Frequent = NONE) -> tuple[list, np.ndarray, np.ndarray]:
    """From messages: for k = order..2 what ``use`` makes of k, the n-grams, their counts, and a function that gives
    their contexts and which is each one's; and the words, with how many n-grams of two each ends."""
    own = [_unpacked_words(r["words"], frequent) for r in rows]
    words = np.sort(np.concatenate([np.zeros(0, K.U64), *own]))
    words = words[_heads(words)]
    index = Places(words)
    ids = [index.find(w).astype(np.uint32) for w in own]
    del own
    columns = [[] for _ in range(order)]
    for r, place in zip(rows, ids, strict=True):
        for column, tokens in zip(columns, unpack(r["tokens"]).reshape(order, -1), strict=True):
            column.append(place[tokens])
    for k in range(order):
        columns[k] = np.concatenate([np.zeros(0, np.uint32), *columns[k]])
    out = []
    for k in range(order, 1, -1):
        keys, first, n = _distinct(_last_hash(words, columns))
        columns = [c[first] for c in columns]
        del first
        out.append(use(k, keys, n, lambda: _inverse(_last_hash(words, columns[1:]))))
        columns = columns[: k - 1]
    ends, n = np.unique(columns[0], return_counts=True)
    return out, words[ends], n


def _cut(n: np.ndarray, d: tuple[float, float, float]) -> np.ndarray:
    return np.array([0.0, *d])[np.minimum(n, 3)]


def _levels(rows: list, order: int, cuts: list[tuple[float, float, float]], frequent: Frequent = NONE) -> tuple[list[Level], np.ndarray]:
    """Of a shard's messages: the orders from the second on, and the words that their n-grams end with."""

    def shares(k, keys, n, contexts):
        contexts, own = contexts()
        cut = _cut(n, cuts[k - 1])
        total = np.bincount(own, n, len(contexts))
        weight = np.bincount(own, cut, len(contexts)) / total
        return Level(keys, (n - cut) / total[own], contexts, weight)

    out, words, _ = _grouped(rows, order, shares, frequent)
    return out[::-1], words


def discounts(counts: dict[int, int]) -> tuple[float, float, float]:
    """The three discounts from how many n-grams occur 1 to 4 times; half where the counts are degenerate."""
    n1, n2, n3, n4 = (counts.get(k, 0) for k in (1, 2, 3, 4))
    if not (n1 and n2):
        return 0.5, 0.5, 0.5
    y = n1 / (n1 + 2 * n2)
    d = [1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2 if n2 else 0.5, 3 - 4 * y * n4 / n3 if n3 else 0.5]
    return tuple(min(max(x, 0.05), k + 0.95) for k, x in enumerate(d))  # type: ignore[return-value]


#: Words and their counts (kind 0), the counts of the words that a shard's n-grams end with (-1, source: whose shard counts these words),
#: a shard's most frequent words (-2), and how many n-grams of k tokens occur 1, 2, 3, 4 times and more often, with their sum (k).
WORDS = "shard int, kind int, source int, keys binary, value binary"


@dataclass
class Counts:
    """A fitted model: the trusted text, whose n-grams are counted by shard where they are asked for, and of all orders what no shard knows alone."""

    train: DataFrame
    words: DataFrame
    order: int
    floor: float
    cuts: list[tuple[float, float, float]]
    total: int
    frequent: Frequent
    bits: np.ndarray
    shards: int

    def in_memory(self) -> KneserNey:
        """The table gathered in one place."""
        order, cuts = self.order, self.cuts

        def run(table: pa.Table) -> pa.Table:
            levels, _ = _levels(table.to_pylist(), order, cuts)
            return _table([(k, *map(pack, (x.gram_keys, x.share, x.context_keys, x.weight))) for k, x in enumerate(levels, 2)], "k int, grams binary, share binary, contexts binary, weight binary")

        rows = _to_count(self.train, order, self.shards).groupBy("shard").applyInArrow(run, "k int, grams binary, share binary, contexts binary, weight binary").collect()
        joined = lambda k, c: np.concatenate([np.zeros(0, K.U64 if c in ("grams", "contexts") else float), *[unpack(bytes(r[c])) for r in rows if r.k == k]])
        known = [(np.cumsum(unpack(bytes(r["keys"])), dtype=K.U64), unpack(bytes(r["value"]))) for r in self.words.where("kind = 0").collect()]
        keys, n = (np.concatenate([np.zeros(0, t), *[x[c] for x in known]]) for c, t in enumerate((K.U64, np.int64)))
        first = Level(keys, _first(n, self.cuts[0], self.total, 0.0), np.zeros(0, K.U64), np.zeros(0))
        return KneserNey([first, *[Level(*(joined(k, c) for c in ("grams", "share", "contexts", "weight"))) for k in range(2, order + 1)]], self.floor)


def _first(n: np.ndarray, d: tuple[float, float, float], total: int, floor: float) -> np.ndarray:
    """Probabilities of words by their counts."""
    return (n - _cut(n, d)) / max(total, 1) + floor


def fit_counts(train: DataFrame, order: int = ORDER) -> Counts:
    """Fits the model: one exchange of packed tokens to the shards, one of the words they end with; the driver gets discounts, totals, frequent words and the filter."""
    size = train.agg(F.coalesce(F.sum(F.octet_length("text").cast("long")), F.lit(0))).first()[0]
    shards = max(SHARDS, 1 << max(0, -(-size // SHARD_BYTES) - 1).bit_length())
    numbers = np.arange(shards + 1)
    often = lambda n: pack(np.append(np.bincount(np.minimum(n, 5), minlength=6)[1:], n.sum()).astype(np.int64))

    def count(table: pa.Table) -> pa.Table:
        shard = table.column("shard")[0].as_py()
        seen, words, n = _grouped([_Row(table, i) for i in range(len(table))], order, lambda k, _, n, contexts: (k, often(n)))
        cut = np.searchsorted(_shard_of(words, shards), numbers)
        out = [(s, 0, shard, pack(steps(words[a:b])), pack(n[a:b])) for s, (a, b) in enumerate(zip(cut[:-1], cut[1:], strict=True)) if b > a]
        return _table(out + [(shard, k, shard, None, x) for k, x in seen], WORDS)

    def add(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        out = [tuple(r.values()) for r in rows if r["kind"]]
        rows = [r for r in rows if not r["kind"]]
        if rows:
            shard, each = rows[0]["shard"], [np.cumsum(unpack(r["keys"]), dtype=K.U64) for r in rows]
            words, own = np.unique(np.concatenate(each), return_inverse=True)
            n = np.zeros(len(words), np.int64)
            np.add.at(n, own, np.concatenate([unpack(r["value"]) for r in rows]))
            at = 0
            for r, keys in zip(rows, each, strict=True):
                out.append((r["source"], -1, shard, None, pack(n[own[at : at + len(keys)]])))
                at += len(keys)
            top = np.sort(np.argsort(-n, kind="stable")[: max(1, FREQUENT // shards)])
            out += [(shard, 0, -1, pack(steps(words)), pack(n)), (shard, -2, -1, pack(steps(words[top])), pack(n[top])), (shard, 1, -1, None, often(n))]
        return _table(out, WORDS)

    words = released(_to_count(train, order, shards).groupBy("shard").applyInArrow(count, WORDS).groupBy("shard").applyInArrow(add, WORDS), "words")
    seen = np.zeros((order + 1, 6), np.int64)
    for r in words.where("kind > 0").toLocalIterator():
        seen[r.kind] += unpack(bytes(r.value))
    cuts = [discounts({m + 1: int(x) for m, x in enumerate(level[:5])}) for level in seen[1:]]
    kinds, total = seen[1, :5], int(seen[1, 5])
    # what the first order leaves is shared by its kinds and one for what was never seen
    left = kinds[0] * cuts[0][0] + kinds[1] * cuts[0][1] + kinds[2:].sum() * cuts[0][2]
    floor = float(left / total / (kinds.sum() + 1)) if total else 1.0
    top = [(np.cumsum(unpack(bytes(r["keys"])), dtype=K.U64), unpack(bytes(r["value"]))) for r in words.where("kind = -2").orderBy("shard").toLocalIterator()]
    keys, n = (np.concatenate([np.zeros(0, t), *[x[c] for x in top]]) for c, t in enumerate((K.U64, np.int64)))
    rank = np.empty(len(n), np.uint32)
    rank[np.argsort(-n, kind="stable")] = np.arange(len(n), dtype=np.uint32)
    return Counts(train, words, order, floor, cuts, total, Frequent(keys, n, rank), _filter(words.where("kind = 0"), shards), shards)


def fit_kneser_ney(train: DataFrame, order: int = ORDER) -> KneserNey:
    return fit_counts(train, order).in_memory()


def _filter(words: DataFrame, shards: int) -> np.ndarray:
    """A bitmap of the leading bits of the words: of a size that does not grow. A shard's words fill a part of their own."""
    width = 1 << FILTER_BITS - shards.bit_length() + 1

    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                part = np.zeros(width, bool)
                part[(np.cumsum(unpack(r["keys"]), dtype=K.U64) >> K.U64(64 - FILTER_BITS)).astype(np.int64) & (width - 1)] = True
                yield pa.RecordBatch.from_arrays([pa.array([r["shard"]], pa.int32()), pa.array([pack(np.packbits(part))], pa.binary())], names=["shard", "part"])

    out = np.zeros((shards, width // 8), np.uint8)
    for r in words.mapInArrow(run, "shard int, part binary").toLocalIterator():
        out[r.shard] |= unpack(bytes(r.part))
    return out.ravel()


def _may_hold(bits: np.ndarray, keys: np.ndarray) -> np.ndarray:
    at = (keys >> K.U64(64 - FILTER_BITS)).astype(np.int64)
    return (bits[at >> 3] >> (7 - (at & 7)).astype(np.uint8)) & 1 == 1


def _find(keys: np.ndarray, asked: np.ndarray) -> np.ndarray:
    """The place of each asked key in ascending keys, -1 where it is none of them."""
    if not len(keys):
        return np.full(len(asked), -1)
    at = np.searchsorted(keys, asked)
    at[at == len(keys)] = 0
    return np.where(keys[at] == asked, at, -1)


def _whole(logs: np.ndarray) -> np.ndarray:
    """Logarithms as whole numbers: their sums are the same in any order."""
    return np.rint(logs * FIXED).astype(np.int64)


def _summed(texts: np.ndarray, logs: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The ascending texts without repetition, and the sum of each."""
    if not len(texts):
        return texts, logs
    first = np.concatenate(([0], np.flatnonzero(np.diff(texts)) + 1))
    return texts[first], np.add.reduceat(logs, first)


def _added(parts: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Texts and sums of several parts as one."""
    texts, own = np.unique(np.concatenate([t for t, _ in parts]), return_inverse=True)
    out = np.zeros(len(texts), np.int64)
    np.add.at(out, own, np.concatenate([s for _, s in parts]))
    return texts, out


RESULTS = "chunk bigint, texts binary, sums binary, mark binary"


def score(docs: DataFrame, model: Counts, text_col: str = "text") -> DataFrame:
    """The documents without their texts, with n_tokens, log10_prob and perplexity (per token)."""
    names = [free_name(docs, n) for n in ("n_tokens", "log10_prob", "perplexity")]
    if "Exchange" in docs._jdf.queryExecution().executedPlan().toString():
        docs = written(docs, "documents")  # rows must lie alike in each turn
    spark, order, floor, shards, cuts, total = docs.sparkSession, model.order, model.floor, model.shards, model.cuts, model.total
    bits, frequent = spark.sparkContext.broadcast(model.bits), spark.sparkContext.broadcast(model.frequent)
    carried = docs.drop(text_col) if len(docs.columns) > 1 else docs.select(F.lit(None).cast("int").alias("none"), text_col).drop(text_col)
    rows = docs if len(docs.columns) > 1 else docs.withColumn("none", F.lit(None).cast("int"))
    size = docs.agg(F.coalesce(F.sum(F.octet_length(text_col).cast("long")), F.lit(0))).first()[0]
    groups = max(1, -(-size // (shards * CHUNK_GROUP * CHUNK_BYTES)))
    mark_of = lambda n: str(zlib.crc32(n.astype(np.int64).tobytes())).encode()

    def ask(turn: int):
        def run(batches):
            own = frequent.value
            for number, _, n, hashes in _chunks(batches, text_col):
                words, at, runs, texts = _places(n, hashes, order, own)
                out, rank = [], own.ranks(at)
                if order > 1:
                    shard = _by_shard(words, runs, shards)
                    out += _dealt(number, SCORED, words, rank, runs, texts, shard, shard % TURNS == turn)
                remote = (at < 0) & _may_hold(bits.value, words)
                shard = _shard_of(words, shards)[runs[0]]
                out += _dealt(number, ASKED, words, rank, runs[:1], texts, shard, remote[runs[0]] & (shard % TURNS == turn))
                here = np.flatnonzero(~remote[runs[0]]) if turn == 0 else np.zeros(0, np.int64)
                logs = _whole(np.log10(_first(np.append(own.counts, 0)[at], cuts[0], total, floor)))  # place -1 is the appended zero
                some, sums = _summed(texts[here], logs[runs[0][here]])
                out.append((turn, SUMS, number, pack(steps(some)), mark_of(n), pack(sums)))
                yield from _table(out, MESSAGES).to_batches()

        return run

    def answer(table: pa.Table) -> pa.Table:
        kinds = table.column("kind").to_pylist()
        rows = {kind: [_Row(table, i) for i, x in enumerate(kinds) if x == kind] for kind in (0, -1, COUNTED, SCORED, ASKED, SUMS)}
        levels, words = _levels(rows[COUNTED], order, cuts, frequent.value)
        n = np.concatenate([np.zeros(0, np.int64), *[unpack(r["tokens"]) for r in sorted(rows[-1], key=lambda r: r["chunk"])]])
        first = np.append(_first(n, cuts[0], total, floor), 1.0)
        logs_first, words = _whole(np.log10(first)), Places(words)
        grams_of, contexts_of = [Places(x.gram_keys) for x in levels], [Places(x.context_keys) for x in levels]
        share, weight = ([np.append(getattr(x, c), last) for x in levels] for c, last in (("share", 0.0), ("weight", 1.0)))
        del levels
        known = [(np.cumsum(unpack(r["words"]), dtype=K.U64), unpack(r["tokens"])) for r in rows[0]]
        out = [(r["chunk"], r["texts"], r["tokens"], r["words"]) for r in rows[SUMS]]
        for r in rows[SCORED] + rows[ASKED]:
            texts = np.cumsum(unpack(r["texts"]), dtype=np.uint32)
            own, tokens = _unpacked_words(r["words"], frequent.value), unpack(r["tokens"])
            if r["kind"] == SCORED:
                places = tokens.reshape(order, -1)
                run = [own[p] for p in places]
                grams, contexts = gram_hashes(run), gram_hashes(run[1:])
                # a pair that was never seen leaves weights only: its first order is a factor, which is summed apart
                found = grams_of[0].find(grams[1])
                low = np.where(found >= 0, words.find(own)[places[0]], -1)
                p = first[low]
                own_context = contexts_of[0].find(own)[places[1]]  # -1: weight 1 and share 0
                p = weight[0][own_context] * p + share[0][found]
                for k in range(1, len(weight)):
                    own_context = contexts_of[k].find(contexts[k])
                    some = np.flatnonzero(own_context >= 0)
                    p[some] = weight[k][own_context[some]] * p[some] + share[k][grams_of[k].find(grams[k + 1][some])]
                logs = _whole(np.log10(p)) - logs_first[low]
            else:
                keys, counts = known[0] if known else (np.zeros(0, K.U64), np.zeros(0, np.int64))
                logs = _whole(np.log10(_first(np.append(counts, 0)[_find(keys, own)], cuts[0], total, floor)))[tokens]
            texts, sums = _summed(texts, logs)
            out.append((r["chunk"], pack(steps(texts)), pack(sums), None))
        return _table(out, RESULTS)

    def merge(table: pa.Table) -> pa.Table:
        rows = table.to_pylist()
        texts, sums = _added([(np.cumsum(unpack(r["texts"]), dtype=np.uint32), unpack(r["sums"])) for r in rows])
        return _table([(rows[0]["chunk"], pack(steps(texts)), pack(sums), next(r["mark"] for r in rows if r["mark"]))], RESULTS)

    done = []
    for turn in range(TURNS):
        known = model.words.where(F.col("kind").isin(0, -1) & (F.col("shard") % TURNS == turn)).select("shard", "kind", F.col("source").cast("long").alias("chunk"), F.lit(None).cast("binary").alias("texts"), F.col("keys").alias("words"), F.col("value").alias("tokens"))
        if order > 1:
            known = known.unionByName(_to_count(model.train, order, shards, frequent, turn, TURNS))
        copies = known.withColumn("grp", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))))
        messages = docs.select(text_col).mapInArrow(ask(turn), MESSAGES).withColumn("grp", F.pmod(F.hash("chunk"), F.lit(groups)).cast("int")).unionByName(copies)
        done.append(released(messages.groupBy("shard", "grp").applyInArrow(lambda t: answer(t.drop_columns(["grp"])), RESULTS).groupBy("chunk").applyInArrow(merge, RESULTS), "sums"))

    def carry(batches):
        for number, held, n, _ in _chunks(batches, text_col):
            sink = pa.BufferOutputStream()
            with pa.ipc.new_stream(sink, held[0].schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as w:
                for b in held:
                    w.write_batch(b)
            yield from _table([(number, sink.getvalue().to_pybytes(), pack(n))], "chunk bigint, carried binary, n binary").to_batches()

    def scored(left: pa.Table, right: pa.Table) -> pa.Table:
        tables, parts = [], right.to_pylist()
        for c in left.to_pylist():
            n = unpack(c["n"])
            if [r["mark"] for r in parts] != [mark_of(n)] * TURNS:
                break
            texts, sums = _added([(np.cumsum(unpack(r["texts"]), dtype=np.uint32), unpack(r["sums"])) for r in parts])
            logs, n = np.zeros(len(n)), n + 1
            logs[texts] = sums / FIXED
            rows = pa.ipc.open_stream(c["carried"]).read_all()
            for name, column in zip(names, (pa.array(n, pa.int64()), pa.array(logs), pa.array(10 ** np.minimum(-logs / n, 300))), strict=True):
                rows = rows.append_column(name, column)
            tables.append(rows)
        if len(tables) != 1:
            raise RuntimeError("the documents were not dealt alike in each turn")
        return tables[0]

    chunks = rows.mapInArrow(carry, "chunk bigint, carried binary, n binary")
    sums = reduce(DataFrame.unionByName, done)
    out = chunks.groupBy("chunk").cogroup(sums.groupBy("chunk")).applyInArrow(scored, plus(carried, dict(zip(names, ("bigint", "double", "double"), strict=True))))
    return out if len(docs.columns) > 1 else out.drop("none")


@dataclass
class QualityModel:
    model: Counts
    thresholds: dict[str, float]
    overall: float


def _fit(docs: DataFrame, labels: DataFrame, good: Column, order: int, max_train: int | None, max_bytes: int | None) -> tuple[Counts, DataFrame]:
    """The model, and the ids it was fitted on: all trusted ones outside the held-out fold, or those of a sample where a bound is given."""
    if max_train is None and max_bytes is None:
        fold = F.pmod(F.crc32(F.encode(F.col("doc_id").cast("string"), "utf-8")), F.lit(FOLDS))
        trained = labels.where(good & F.col("doc_id").isNotNull() & (fold != HELD_OUT)).select("doc_id").distinct()
    else:
        ids = training_ids(docs, labels, good, *(1 << 62 if x is None else x for x in (max_train, max_bytes)))
        key = T.StructType([T.StructField("doc_id", docs.schema["doc_id"].dataType)])
        trained = docs.sparkSession.createDataFrame([(i,) for i in ids], key)
    # ids are sent to the texts, not texts to the ids
    return fit_counts(docs.select("doc_id", "text").join(F.broadcast(trained), "doc_id", "left_semi").select("text"), order), trained


def _cuts(scored: DataFrame, labels: DataFrame, good: Column, trained: DataFrame, quantile: float, min_held_out: int) -> tuple[dict, float]:
    """The cut of each language, and that over all. scored: doc_id, lang, perplexity; what is joined with the labels is no text."""
    trusted = labels.where(good).select("doc_id").join(trained, "doc_id", "left_anti").distinct()
    held = scored.select("doc_id", "lang", "perplexity").join(trusted, "doc_id", "left_semi").select("lang", "perplexity").persist()
    try:
        cuts = upper_quantiles(held.where("lang IS NOT NULL"), "lang", "perplexity", quantile)
        overall = upper_quantiles(held.withColumn("all", F.lit(0)), "all", "perplexity", quantile)
    finally:
        held.unpersist()
    return {lang: cut for lang, (n, cut) in cuts.items() if n >= min_held_out}, overall[0][1] if overall else float("inf")


def fit_quality(docs: DataFrame, labels: DataFrame, good: Column | None = None, order: int = ORDER, quantile: float = QUANTILE, max_train: int | None = None, max_bytes: int | None = None, min_held_out: int = MIN_HELD_OUT) -> QualityModel:
    """The model of trusted text (quality = 1 where nothing else is given) and the cut of each language."""
    good = F.col("quality") == 1 if good is None else good
    model, trained = _fit(docs, labels, good, order, max_train, max_bytes)
    return QualityModel(model, *_cuts(score(docs.select("doc_id", "lang", "text"), model), labels, good, trained, quantile, min_held_out))


def _with_verdict(scored: DataFrame, perplexity: str, thresholds: dict[str, float], overall: float) -> DataFrame:
    threshold = F.lit(overall)
    for lang, cut in sorted(thresholds.items()):
        threshold = F.when(F.col("lang") == lang, F.lit(cut)).otherwise(threshold)
    t, keep = free_name(scored, "threshold"), free_name(scored, "keep")
    return scored.withColumn(t, threshold).withColumn(keep, F.col(perplexity) <= F.col(t))


def classify(docs: DataFrame, quality: QualityModel) -> DataFrame:
    """The documents without their texts, with n_tokens, log10_prob, perplexity, threshold and keep."""
    out = score(docs, quality.model)
    return _with_verdict(out, out.columns[-1], quality.thresholds, quality.overall)


def judge(docs: DataFrame, labels: DataFrame, good: Column | None = None, order: int = ORDER, quantile: float = QUANTILE, max_train: int | None = None, max_bytes: int | None = None, min_held_out: int = MIN_HELD_OUT) -> DataFrame:
    """fit_quality and classify over the same documents, which are scored once."""
    good = F.col("quality") == 1 if good is None else good
    model, trained = _fit(docs, labels, good, order, max_train, max_bytes)
    scored = written(score(docs, model), "scored")
    name = scored.columns[-1]
    return _with_verdict(scored, name, *_cuts(scored.select("doc_id", "lang", F.col(name).alias("perplexity")), labels, good, trained, quantile, min_held_out))


def keep_good(docs: DataFrame, labels: DataFrame, **options: float) -> DataFrame:
    """The documents that ``judge`` keeps, whole. What it rejects is known by two hashes of the text and the language, as equal ones are judged alike."""
    hashes = [F.xxhash64("text").alias("a"), F.xxhash64(F.lit(1), "text").alias("b")]
    judged = judge(docs.select("doc_id", "lang", "text", *hashes), labels, **options)
    bad = written(judged.where(~F.col(judged.columns[-1])).select("a", "b", "lang").distinct(), "rejected")
    same = (F.xxhash64(docs["text"]) == bad["a"]) & (F.xxhash64(F.lit(1), docs["text"]) == bad["b"]) & docs["lang"].eqNullSafe(bad["lang"])
    return docs.join(bad, same, "left_anti")
