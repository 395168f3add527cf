"""Language-model scoring by a hierarchical Pitman-Yor process over words.

Each preceding word has a restaurant; all of them share one parent, whose base is uniform over the
training vocabulary and one unseen word. Customers are training tokens; a dish's tables in a context are
customers of the parent.

A Gibbs sweep draws the seatings in blocks. Given the customers at the parent, the parent's tables and then
its measure itself are drawn: gamma masses for its words, by the gamma form of the process. Given that
measure, contexts have nothing to do with each other. A gamma variable for each context (its full
conditional given its number of tables) parts its dishes too, so each dish's number of tables has the law
S(c, t) x^t, S the generalised Stirling numbers, over seatings of equal table counts. It is drawn from
that law at every count: the numbers are tabled up to ``EXACT`` customers and computed beyond. The gamma
variable of the parent goes on from the sweep before, one step behind the contexts. During the burn-in
the discount and the strength of the contexts are drawn too, by turns, from lattices; then they are held.
After it, predictive probabilities given the seating are averaged over the sweeps.

Plan. Documents become chunks of tokens (one row each). Chunks ask word shards for ids and counts, and
context shards for table counts; requests and answers are packed arrays of distinct keys, so a frequent
word or pair is one entry a chunk. Contexts with more than their share of all tokens are split over shards
by their next word. What goes through the exchanges grows with the corpus, and no table of words or pairs
is ever in one place.

Tokens: the contract's. Null and empty texts are one end token. Rows with a null id are training rows.
Repeated rows count as often as they occur. Sums of equal counts do not depend on the order of rows; the
draws are seeded by shard, so a rerun over the same chunks is the same.
"""

from __future__ import annotations

import math
import zlib
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import textkernel as K
from .shared import forget, written

CHUNK_TOKENS = 2_000_000
#: Tokens of a shard, about.
SHARD_TOKENS = 1_200_000
BURN_IN, SAMPLES = 4, 2
#: The parent's own parameters; its discount of a half gives its rest a law that can be drawn as it is.
ROOT_STRENGTH, ROOT_DISCOUNT = 1.0, 0.5
#: Values that the contexts' discount and strength can take, all alike beforehand, and how many are tried at once.
DISCOUNTS = [k / 100 for k in range(30, 96)]
STRENGTHS = [2.0 ** (k / 2) for k in range(-10, 21)]
TRIALS = 5
HELD_OUT_OF, HELD_OUT_IS = 7, 2
BEGIN, END = K.U64(0x1D8AF066F7A3C0E1), K.U64(0x6A09E667F3BCC909)
#: Counts up to this one have their Stirling numbers from a table; beyond, each is computed on its own.
EXACT = 600

_CODEC = pa.Codec("zstd", compression_level=1)


def pack(x: np.ndarray) -> bytes:
    """Bytes of an array: its kind, length and compressed byte planes."""
    x = np.ascontiguousarray(x)
    raw = np.ascontiguousarray(x.view(np.uint8).reshape(len(x), -1).T).tobytes() if len(x) else b""
    return f"{x.dtype.str}{len(x)}:".encode() + (_CODEC.compress(raw, asbytes=True) if raw else b"")


def unpack(b: bytes) -> np.ndarray:
    head, _, body = b.partition(b":")
    kind, n = np.dtype(head[:3].decode()), int(head[3:])
    if not n:
        return np.zeros(0, kind)
    raw = np.frombuffer(_CODEC.decompress(body, n * kind.itemsize, asbytes=True), np.uint8)
    return np.ascontiguousarray(raw.reshape(kind.itemsize, n).T).view(kind).ravel()


def steps(x: np.ndarray) -> np.ndarray:
    """Differences of an ascending array, for packing."""
    return np.diff(x, prepend=x[:0].dtype.type(0) if len(x) else 0).astype(x.dtype) if len(x) else x


def _batch(schema: pa.Schema, rows: list[tuple]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], f.type) for k, f in enumerate(schema)], schema=schema)


def _arrow(ddl: str) -> pa.Schema:
    kinds = {"bigint": pa.int64(), "int": pa.int32(), "binary": pa.binary(), "double": pa.float64(), "boolean": pa.bool_()}
    return pa.schema([(n, kinds[k]) for n, k in (x.split() for x in ddl.split(", "))])


# ---- chunks -------------------------------------------------------------------------------------

CHUNKS = "chunk bigint, size bigint, ids binary, known binary, held binary, length binary, words binary, trained binary, tokens binary"


def _held(ids: list, known: list) -> np.ndarray:
    return np.array([k and zlib.crc32(str(i).encode()) % HELD_OUT_OF == HELD_OUT_IS for i, k in zip(ids, known, strict=True)], dtype=bool)


def _chunk_row(number: int, ids: list[np.ndarray], known: list[np.ndarray], counts: list[np.ndarray], hashes: list[np.ndarray]) -> tuple:
    """One chunk: tokens are places in its distinct words, frequent words first; the begin mark is a word of it."""
    i, k, n = np.concatenate(ids), np.concatenate(known), np.concatenate(counts) + 1
    held = _held(i.tolist(), k.tolist())
    ends = np.cumsum(n) - 1
    flat = np.full(int(n.sum()), END, K.U64)
    word = np.ones(len(flat), bool)
    word[ends] = False
    flat[word] = np.concatenate(hashes)
    words, place, count = np.unique(flat, return_inverse=True, return_counts=True)
    order = np.argsort(-count, kind="stable")
    rank = np.empty(len(order), np.uint32)
    rank[order] = np.arange(len(order), dtype=np.uint32)
    tokens = rank[place]
    trained = np.bincount(tokens[~np.repeat(held, n)], minlength=len(words))
    words = np.concatenate((words[order], [BEGIN]))
    trained = np.concatenate((trained, [int((~held).sum())])).astype(np.int64)
    return (number, len(flat), pack(i), pack(k), pack(held), pack(n), pack(words), pack(trained), pack(tokens))


def chunks_of(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    kept = docs.select(F.col(id_col).cast("bigint").alias("id"), F.col(text_col).alias("text"))
    schema = _arrow(CHUNKS)

    def run(batches):
        from pyspark import TaskContext

        number, ids, known, counts, hashes, size = TaskContext.get().partitionId() << 32, [], [], [], [], 0
        for batch in batches:
            for part in K.slices(batch, "text"):
                _, _, _, first, words = K.word_hashes(part.column("text"), K.NONSPACE)
                ids.append(part.column("id").fill_null(0).to_numpy(zero_copy_only=False))
                known.append(part.column("id").is_valid().to_numpy(zero_copy_only=False))
                counts.append(np.diff(first))
                hashes.append(words)
                size += len(words) + part.num_rows
                if size >= CHUNK_TOKENS:
                    yield _batch(schema, [_chunk_row(number, ids, known, counts, hashes)])
                    number, ids, known, counts, hashes, size = number + 1, [], [], [], [], 0
        if ids:
            yield _batch(schema, [_chunk_row(number, ids, known, counts, hashes)])

    return kept.mapInArrow(run, CHUNKS)


# ---- word shards --------------------------------------------------------------------------------

ASK = "shard int, chunk bigint, a binary, b binary"
WORD = "chunk bigint, shard int, place binary, count binary"


def _ask_words(chunks: DataFrame, shards: int) -> DataFrame:
    schema = _arrow(ASK)

    def run(batches):
        for batch in batches:
            for chunk, words, trained in zip(*(batch.column(c).to_pylist() for c in ("chunk", "words", "trained")), strict=True):
                w, c = unpack(words), unpack(trained)
                to = (w % K.U64(shards)).astype(np.int64)
                yield _batch(schema, [(s, chunk, pack(w[to == s]), pack(c[to == s])) for s in np.unique(to).tolist()])

    return chunks.select("chunk", "words", "trained").mapInArrow(run, ASK)


def _answer_words(table: pa.Table) -> pa.Table:
    """Each chunk's words of one shard: their places in the shard and their training counts; chunk -1 has the shard's totals."""
    rows = table.select(["shard", "chunk", "a", "b"]).to_pylist()
    shard, keys, counts = rows[0]["shard"], [unpack(r["a"]) for r in rows], [unpack(r["b"]) for r in rows]
    words, place = np.unique(np.concatenate(keys), return_inverse=True)
    total = np.zeros(len(words), np.int64)
    np.add.at(total, place, np.concatenate(counts))
    out, at = [], 0
    for r, k in zip(rows, keys, strict=True):
        mine = place[at : at + len(k)]
        out.append((r["chunk"], shard, pack(mine.astype(np.uint32 if len(words) < 1 << 32 else np.uint64)), pack(total[mine])))
        at += len(k)
    own = words != BEGIN
    out.append((-1, shard, pack(np.array([len(words), int((total[own] > 0).sum()), int(total[own].sum())], np.int64)), b""))
    return pa.Table.from_batches([_batch(_arrow(WORD), out)])


# ---- chunks with ids ----------------------------------------------------------------------------

CODED = "chunk bigint, ids binary, known binary, held binary, length binary, tokens binary, wid binary, wcount binary"


def _code(left: pa.Table, right: pa.Table, base: np.ndarray) -> pa.Table:
    """A chunk and its words' answers: wid and wcount hold the id and the training count of each of its words."""
    out = []
    answers: dict[int, list[dict]] = {}
    for r in right.to_pylist():
        answers.setdefault(r["chunk"], []).append(r)
    shards = len(base) - 1
    for c in left.to_pylist():
        words = unpack(c["words"])
        to = (words % K.U64(shards)).astype(np.int64)
        wid, count = np.zeros(len(words), np.int64), np.zeros(len(words), np.int64)
        for r in answers.get(c["chunk"], []):
            at = np.flatnonzero(to == r["shard"])
            wid[at], count[at] = base[r["shard"]] + unpack(r["place"]).astype(np.int64), unpack(r["count"])
        out.append((c["chunk"], c["ids"], c["known"], c["held"], c["length"], c["tokens"], pack(wid.astype(np.uint32 if base[-1] < 1 << 32 else np.uint64)), pack(count)))
    return pa.Table.from_batches([_batch(_arrow(CODED), out)])


# ---- context shards -----------------------------------------------------------------------------

PAIRS = "shard int, chunk bigint, u binary, run binary, w binary, c binary"


def _pairs(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Of a coded chunk: its distinct pairs as (u, w) ids, ascending, their training counts, the place of each token's pair, and each token's word."""
    tokens, n, held, wid = unpack(row["tokens"]), unpack(row["length"]), unpack(row["held"]), unpack(row["wid"])
    before = np.empty_like(tokens)
    before[1:] = tokens[:-1]
    before[np.cumsum(n) - n] = len(wid) - 1
    by_id = np.argsort(wid, kind="stable")
    rank = np.empty(len(wid), np.uint64)
    rank[by_id] = np.arange(len(wid), dtype=np.uint64)
    key = rank[before] * np.uint64(len(wid)) + rank[tokens]
    pair, place = np.unique(key, return_inverse=True)
    trained = np.bincount(place[~np.repeat(held, n)], minlength=len(pair))
    u, w = wid[by_id[(pair // np.uint64(len(wid))).astype(np.int64)]], wid[by_id[(pair % np.uint64(len(wid))).astype(np.int64)]]
    return u, w, trained, place, tokens


def _shard_of(u: np.ndarray, w: np.ndarray, shards: int, hot: np.ndarray) -> np.ndarray:
    to = K.mix(u.astype(K.U64)) % K.U64(shards)
    split = K.is_member(u, hot)
    if split.any():
        to[split] = K.mix(u[split].astype(K.U64) * K.U64(K.BASE) + w[split].astype(K.U64)) % K.U64(shards)
    return to.astype(np.int64)


def _ask_pairs(coded: DataFrame, shards: int, hot: np.ndarray) -> DataFrame:
    schema = _arrow(PAIRS)

    def run(batches):
        for batch in batches:
            for row in batch.select(["chunk", "held", "length", "tokens", "wid"]).to_pylist():
                u, w, c, _, _ = _pairs(row)
                to = _shard_of(u, w, shards, hot)
                order = np.argsort(to, kind="stable")
                cut = np.searchsorted(to[order], np.arange(shards + 1))
                out = []
                for s in np.flatnonzero(np.diff(cut)).tolist():
                    mine = order[cut[s] : cut[s + 1]]
                    heads = np.flatnonzero(np.concatenate(([True], u[mine][1:] != u[mine][:-1])))
                    run_length = np.diff(np.concatenate((heads, [len(mine)]))).astype(np.uint32)
                    out.append((s, row["chunk"], pack(steps(u[mine][heads])), pack(run_length), pack(w[mine]), pack(c[mine].astype(np.uint32))))
                yield _batch(schema, out)

    return coded.select("chunk", "held", "length", "tokens", "wid").mapInArrow(run, PAIRS)


def _open_pairs(row: dict) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    u = unpack(row["u"])
    u = np.cumsum(u, dtype=u.dtype)
    return np.repeat(u, unpack(row["run"])), unpack(row["w"]), unpack(row["c"]).astype(np.int64)


class Pairs:
    """Distinct trained pairs of a shard, ascending, with their counts; pairs are looked up in bulk."""

    def __init__(self, parts: list[tuple[np.ndarray, np.ndarray, np.ndarray]]):
        parts = [(u[c > 0], w[c > 0], c[c > 0]) for u, w, c in parts]
        self.u, self.w, self.c = (np.concatenate(x) for x in zip(*parts, strict=True)) if parts else (np.zeros(0, np.uint32), np.zeros(0, np.uint32), np.zeros(0, np.int64))
        self.contexts = self.words = None
        if self.u.dtype != np.uint32:  # ids too wide for two in a key: their ranks instead
            self.contexts, self.words = np.unique(self.u), np.unique(self.w)
        self.key = self._key(self.u, self.w)[0]
        order = np.argsort(self.key, kind="stable")  # the parts are ascending runs
        self.u, self.w, self.c, self.key = self.u[order], self.w[order], self.c[order], self.key[order]
        if len(self.key):
            heads = np.flatnonzero(np.concatenate(([True], self.key[1:] != self.key[:-1])))
            self.u, self.w, self.key, self.c = self.u[heads], self.w[heads], self.key[heads], np.add.reduceat(self.c, heads)

    def _key(self, u: np.ndarray, w: np.ndarray) -> tuple[np.ndarray, np.ndarray | bool]:
        if self.contexts is None:
            return (u.astype(np.uint64) << np.uint64(32)) | w.astype(np.uint64), True
        i, j = np.searchsorted(self.contexts, u), np.searchsorted(self.words, w)
        i[i == len(self.contexts)], j[j == len(self.words)] = 0, 0
        known = (self.contexts[i] == u) & (self.words[j] == w) if len(self.u) else np.zeros(len(u), bool)
        return (i.astype(np.uint64) << np.uint64(32)) | j.astype(np.uint64), known

    def find(self, u: np.ndarray, w: np.ndarray) -> np.ndarray:
        """Places of pairs, or -1."""
        if not len(self.key):
            return np.full(len(u), -1, np.int64)
        ask, known = self._key(u, w)
        at = np.searchsorted(self.key, ask)
        at[at == len(self.key)] = 0
        return np.where((self.key[at] == ask) & known, at, -1)


STATE = "shard int, kind int, a binary, b binary, c binary, d binary, e binary"
#: Kinds of rows that meet at a shard.
REPEATED, SINGLES, TABLES, PARENT, BASES = range(5)


def _runs(ascending: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct values of an ascending array, and each element's place among them."""
    head = np.ones(len(ascending), dtype=bool)
    head[1:] = ascending[1:] != ascending[:-1]
    return ascending[head], np.cumsum(head) - 1


def _first_state(table: pa.Table, shards: int) -> pa.Table:
    """A context shard's state: its repeated pairs with counts and tables; and to the word shards the pairs that occur once."""
    rows = table.to_pylist()
    shard = rows[0]["shard"]
    pairs = Pairs([_open_pairs(r) for r in rows])
    u, w, c = pairs.u, pairs.w, pairs.c
    many = c > 1
    contexts, place = _runs(u)
    total, once = np.bincount(place, c, len(contexts)), np.bincount(place[~many], minlength=len(contexts))
    out = [(shard, REPEATED, pack(steps(u[many])), pack(w[many]), pack(c[many]), pack(np.ones(int(many.sum()), np.int32)), pack(np.concatenate((contexts.astype(np.int64), total.astype(np.int64), once.astype(np.int64)))))]
    words, count = np.unique(w[~many], return_counts=True)
    to = words % words.dtype.type(shards) if len(words) else words
    for s in np.unique(to).tolist():
        out.append((int(s), SINGLES, pack(words[to == s]), pack(count[to == s]), b"", b"", b""))
    out += _to_parent(shard, w[many], np.ones(int(many.sum()), np.int64), shards)
    # how often pairs occur once and twice, for the discount
    out.append((-1, BASES, pack(np.array([(c == 1).sum(), (c == 2).sum()], np.int64)), b"", b"", b"", b""))
    return pa.Table.from_batches([_batch(_arrow(STATE), out)])


def _to_parent(shard: int, w: np.ndarray, tables: np.ndarray, shards: int) -> list[tuple]:
    """Tables of repeated pairs by word, to the word's shard; the sender is in d."""
    words, place = np.unique(w, return_inverse=True)
    count = np.bincount(place, tables, len(words)).astype(np.int64)
    to = words % words.dtype.type(shards) if len(words) else words
    return [(int(s), TABLES, pack(words[to == s]), pack(count[to == s]), b"", str(shard).encode(), b"") for s in np.unique(to).tolist()]


def _lgamma(x: np.ndarray | float) -> np.ndarray:
    """log of the gamma function of positive numbers."""
    x = np.asarray(x, np.float64)
    low = x < 10
    y = np.where(low, x + 10, x)
    series = (y - 0.5) * np.log(y) - y + 0.5 * np.log(2 * np.pi) + (1 / 12 - (1 / 360 - (1 / 1260 - 1 / 1680 / y**2) / y**2) / y**2) / y
    if not low.any():
        return series
    z = np.where(low, x, 1.0)
    steps_up = z.copy()
    for k in range(1, 10):
        steps_up = steps_up * (z + k)
    return series - np.where(low, np.log(steps_up), 0.0)


@lru_cache(maxsize=12)
def _stirling(discount: float) -> np.ndarray:
    """log of generalised Stirling numbers S(c, t) for c, t up to EXACT, by their recurrence."""
    out = np.full((EXACT + 1, EXACT + 1), -np.inf)
    out[0, 0] = 0
    t = np.arange(1, EXACT + 1)
    for c in range(EXACT):
        stay = out[c, 1:] + np.log(np.maximum(c - discount * t, 1e-300))
        out[c + 1, 1:] = np.logaddexp(out[c, :-1], np.where(t <= c, stay, -np.inf))
    return out


def _tilt(count: float, discount: float, weight: float | None = None, tables: float | None = None) -> float:
    """s = 1 - r where r makes ``count`` the mean number of customers: of Poisson many tables under a weight, or of so many tables."""
    goal = math.log(count / weight) if weight is not None else math.log(count / tables / discount)
    lo, hi = -690.0, 690.0
    for _ in range(90):
        v = (lo + hi) / 2
        # logs of s and r at log-odds v
        low = math.log1p(math.exp(-abs(v)))
        log_s, log_r = min(v, 0.0) - low, min(-v, 0.0) - low
        mean = log_r + (discount - 1) * log_s
        if weight is None:
            mean -= math.log(-math.expm1(discount * log_s))
        lo, hi = (v, hi) if mean > goal else (lo, v)
    return math.exp(min(lo, 0.0) - math.log1p(math.exp(-abs(lo))))


def log_coefficients(count: int, t: np.ndarray, discount: float, s: float) -> np.ndarray:
    """log of S(count, t) * t! * discount^t / count! for consecutive t: the coefficient of z^count in (1 - (1 - z)^discount)^t.

    A sum over a circle of radius 1 - s, as many of its points as matter; where tables are few against
    count^discount the coefficients' alternating series, which then converges fast. Either is right to
    about 1e-9 of the law's mass.
    """
    t = np.asarray(t, np.float64)
    y = t[-1] * float(count) ** -discount
    if y <= 0 or np.log(1 - discount) + (discount * np.log(discount) + np.log(y)) / (1 - discount) < np.log(10.0):
        k = np.arange(1, int(min(t[-1], 1200, count)) + 1, dtype=np.float64)
        a = k * discount
        # log of gamma(count - a) / gamma(count) without the loss of a difference of large numbers
        x = count - a
        ratio = np.where(x > 30, (x - 0.5) * np.log1p(-a / count) - a * np.log(count) + a + (1 / x - 1 / count) / 12 - (1 / x**3 - 1 / float(count) ** 3) / 360, _lgamma(np.maximum(x, 1e-9)) - _lgamma(count))
        fixed = ratio + _lgamma(1 + a)
        # terms that matter for the most tables, which has the most of them
        most = fixed + np.cumsum(np.log(np.maximum(t[-1] - k + 1, 1e-300)) - np.log(k))
        n = int(np.flatnonzero(most > most.max() - 70)[-1]) + 1
        k, a, fixed = k[:n], a[:n], fixed[:n]
        sine = np.sin(np.pi * np.mod(a, 2.0)) * np.where(k % 2 == 1, 1.0, -1.0) / np.pi
        out = np.empty(len(t))
        for at in range(0, len(t), 4096):
            own = t[at : at + 4096, None]
            choose = np.cumsum(np.log(np.maximum(own - k + 1, 1e-300)) - np.log(k), axis=1)
            term = np.where(own >= k, choose + fixed, -np.inf)
            top = term.max(axis=1, keepdims=True)
            total = (np.exp(term - top) * sine).sum(axis=1)
            out[at : at + 4096] = np.where(total > 0, top[:, 0] + np.log(np.maximum(total, 1e-300)), -np.inf)
        return out - np.log(count)
    r = 1 - s
    log_r = np.log1p(-s)
    phi_r = -np.expm1(discount * np.log(s))
    spread = np.sqrt(t[-1] / phi_r * discount * (r * s ** (discount - 1) + r * r * (1 - discount) * s ** (discount - 2)))
    points = int(min(max(64.0, 24 * spread + 45 / -log_r), 2.0**52))
    step = 2 * np.pi / points

    def log_ratio(k: np.ndarray) -> np.ndarray:
        # 1 - r e^(i angle), without loss where the angle is small
        half = np.sin(k * step / 2)
        return np.log(1 - (s + 2 * r * half * half - 1j * r * np.sin(k * step)) ** discount) - np.log(phi_r)

    far = 16
    while far < points // 2 and t[0] * log_ratio(np.array([float(far)])).real[0] > -42:
        far *= 2
    k = np.arange(1, min(far, (points - 1) // 2) + 1, dtype=np.int64)
    logs = log_ratio(k.astype(np.float64))
    turn = np.array([(count * j) % points for j in k.tolist()], np.float64) * step if count * len(k) * points >= 1 << 62 else (count * k) % points * step
    out = np.empty(len(t))
    for at in range(0, len(t), max(1, (1 << 21) // max(len(k), 1))):
        own = t[at : at + max(1, (1 << 21) // max(len(k), 1))]
        z = np.empty((len(own), len(k)), np.complex128)
        z[0], z[1:] = np.exp(own[0] * logs - 1j * turn), np.exp(logs)
        total = 1 + 2 * np.multiply.accumulate(z, axis=0, out=z).real.sum(axis=1)
        if points % 2 == 0 and len(k) == (points - 1) // 2:
            total += (np.exp(own * log_ratio(np.array([points / 2.0]))) * (1 if count % 2 == 0 else -1)).real
        out[at : at + len(own)] = np.where(total > 0, np.log(np.maximum(total, 1e-300) / points), -np.inf)
    return out + t * np.log(phi_r) - count * log_r


def log_stirling(count: int, t: int, discount: float) -> float:
    """log S(count, t) of any size."""
    if count <= EXACT:
        return float(_stirling(discount)[count, t])
    if t == count:
        return 0.0
    one = log_coefficients(count, np.array([t]), discount, _tilt(count, discount, tables=t))[0]
    return float(one + _lgamma(count + 1.0) - _lgamma(t + 1.0) - t * np.log(discount))


def draw_tables(rng: np.random.Generator, count: np.ndarray, log_x: np.ndarray, discount: float) -> np.ndarray:
    """Numbers of tables t of dishes with ``count`` customers, from the law S(count, t) x^t; no dish has a bound below its customers."""
    out = np.ones(len(count), np.int64)
    table = _stirling(discount)
    for lo, hi in ((2, 2), (3, 3), (4, 5), (6, 8), (9, 16), (17, 32), (33, 64), (65, 128), (129, EXACT)):
        pick = np.flatnonzero((count >= lo) & (count <= hi))
        t = np.arange(1, hi + 1)
        step = max(1, (1 << 21) // hi)
        for at in range(0, len(pick), step):
            k = pick[at : at + step]
            weight = table[count[k], 1 : hi + 1] + t * log_x[k][:, None]
            out[k] = 1 + np.argmax(weight + rng.gumbel(size=weight.shape), axis=1)
    for k in np.flatnonzero(count > EXACT).tolist():
        out[k] = _draw_large(rng, int(count[k]), float(np.exp(log_x[k])), discount)
    return out


def large_law(count: int, x: float, discount: float) -> tuple[np.ndarray, np.ndarray]:
    """(numbers of tables, their log weights) for a dish of many customers: all numbers but those of less than 1e-15 of the mass."""
    x = max(x, 1e-290)
    s = _tilt(count, discount, weight=x)
    if s >= 1:
        return np.array([count]), np.zeros(1)
    mean = x * -np.expm1(discount * np.log(s)) / discount
    second = x * ((1 - s) * s ** (discount - 1) + (1 - s) ** 2 * (1 - discount) * s ** (discount - 2))
    reach = 9 * np.sqrt(max(mean - count * (count / second), 0.0)) + 30
    t = np.arange(max(1, int(mean - reach)), min(count, int(mean + reach) + 2) + 1)
    return t, log_coefficients(count, t, discount, s) + t * np.log(x / discount) - _lgamma(t + 1.0)


def _draw_large(rng: np.random.Generator, count: int, x: float, discount: float) -> int:
    t, weight = large_law(count, x, discount)
    return int(t[np.argmax(weight + rng.gumbel(size=len(t)))])


def context_terms(total: np.ndarray, tables: np.ndarray, discount: float, strength: float) -> float:
    """log probability of the restaurants' tables, but for the Stirling numbers."""
    a = strength / discount
    return float((_lgamma(strength) - _lgamma(strength + total) + tables * np.log(discount) + _lgamma(a + tables) - _lgamma(a)).sum())


def stirling_terms(count: np.ndarray, tables: np.ndarray, discount: float) -> float:
    small = count <= EXACT
    out = float(_stirling(discount)[count[small], tables[small]].sum())
    return out + sum(log_stirling(c, t, discount) for c, t in zip(count[~small].tolist(), tables[~small].tolist(), strict=True))


def block_of(rng: np.random.Generator, lattice: list[float], now: float) -> list[float]:
    """The part of a lattice that holds ``now`` in a division at random into runs of TRIALS; drawing from it is a step that keeps the law."""
    k, shift = lattice.index(now), int(rng.integers(TRIALS))
    first = (k + shift) // TRIALS * TRIALS - shift
    return lattice[max(0, first) : first + TRIALS]


def _parent(table: pa.Table, kinds: int, seed: int, scale: float) -> pa.Table:
    """A word shard: draws its words' tables at the parent and the parent's own weights; tells the context shards that asked the weights (BASES), and keeps customers and tables (PARENT)."""
    rows = table.to_pylist()
    shard = rows[0]["shard"]
    parts = [(unpack(r["a"]), unpack(r["b"]).astype(np.int64), r) for r in rows if r["kind"] in (SINGLES, TABLES)]
    words, place = np.unique(np.concatenate([p[0] for p in parts]), return_inverse=True)
    customers = np.bincount(place, np.concatenate([p[1] for p in parts]), len(words)).astype(np.int64)
    rng = np.random.default_rng((seed, shard))
    tables = draw_tables(rng, customers, np.full(len(words), np.log(ROOT_DISCOUNT * scale / kinds)), ROOT_DISCOUNT)
    weight = rng.standard_gamma(customers - ROOT_DISCOUNT * tables) + _rest(rng, scale / kinds, len(words))
    out = [(shard, PARENT, pack(words), pack(customers), pack(tables), b"", pack(np.array([customers.sum(), tables.sum(), weight.sum()], np.float64)))]
    for a, _, r in parts:
        if r["kind"] == TABLES:
            out.append((int(r["d"]), BASES, pack(a), pack(weight[np.searchsorted(words, a)].astype(np.float32)), b"", b"", b""))
    return pa.Table.from_batches([_batch(_arrow(STATE), out)])


def _rest(rng: np.random.Generator, time: float, n: int) -> np.ndarray:
    """What a word has of the parent's mass outside all tables: an inverse Gaussian draw, as the parent's discount is a half."""
    return rng.wald(time / 2, time * time / 2, n)


def _seat_parents(kinds: int, seed: int, scale: float):
    return lambda t: _parent(t, kinds, seed, scale)


class Sweep:
    """What a sweep needs beside the shard's rows: the parent's totals, what it leaves to each kind, and the draws for split contexts."""

    def __init__(self, kinds: int, discount: float, strength: float, totals: np.ndarray, hot: np.ndarray, hot_scale: np.ndarray, shards: int, seed: int, trial: list[tuple[float, float]]):
        self.kinds, self.discount, self.strength = kinds, discount, strength
        self.customers, self.tables, self.weight = (float(x) for x in totals)
        self.hot, self.hot_scale, self.shards, self.seed, self.trial = hot, hot_scale, shards, seed, trial

    def base(self, customers: np.ndarray, tables: np.ndarray) -> np.ndarray:
        """The parent's predictive probability of words by their customers and tables there."""
        own = np.maximum(customers - ROOT_DISCOUNT * tables, 0)
        return (own + (ROOT_STRENGTH + ROOT_DISCOUNT * self.tables) / self.kinds) / (ROOT_STRENGTH + self.customers)

    def run(self, table: pa.Table) -> pa.Table:
        """A context shard: draws the tables of its repeated pairs, and tells the word shards; to shard -1 the log probabilities of the trial parameters."""
        rows = table.to_pylist()
        state = next((r for r in rows if r["kind"] == REPEATED), None)
        if state is None:
            return pa.Table.from_batches([_batch(_arrow(STATE), [])])
        u, w, c, t = (unpack(state[k]) for k in "abcd")
        u = np.cumsum(u, dtype=u.dtype)
        contexts, total, once = unpack(state["e"]).reshape(3, -1)
        place = np.searchsorted(contexts, u.astype(np.int64))
        split = K.is_member(contexts, self.hot)
        if len(u):
            asked = [(unpack(r["a"]), unpack(r["b"])) for r in rows if r["kind"] == BASES]
            words = np.concatenate([x[0] for x in asked])
            order = np.argsort(words)
            base = np.concatenate([x[1] for x in asked])[order[np.searchsorted(words[order], w)]].astype(np.float64) / self.weight
            rng = np.random.default_rng((self.seed, state["shard"]))
            scale = rng.standard_gamma(self.strength / self.discount + np.bincount(place, t, len(contexts)) + once)
            scale[split] = self.hot_scale[np.searchsorted(self.hot, contexts[split])]
            t = draw_tables(rng, c, np.log(self.discount * np.maximum(scale[place] * base, 1e-280)), self.discount).astype(np.int32)
        out = [(state["shard"], REPEATED, state["a"], state["b"], state["c"], pack(t), state["e"])]
        if self.trial:
            present = np.bincount(place, t, len(contexts)) + once
            by_discount = {d: stirling_terms(c, t, d) for d in {d for d, _ in self.trial}}
            logs = [by_discount[d] + context_terms(total[~split], present[~split], d, a) for d, a in self.trial]
            out.append((-1, BASES, pack(np.array(logs, np.float64)), b"", b"", b"", b""))
        return pa.Table.from_batches([_batch(_arrow(STATE), out + _to_parent(state["shard"], w, t.astype(np.int64), self.shards))])


def _hot_tables(state: DataFrame, hot: np.ndarray) -> np.ndarray:
    """Tables of the split contexts over all shards: as many numbers as there are split contexts."""
    if not len(hot):
        return np.zeros(0, np.int64)

    def run(batches):
        for batch in batches:
            for r in batch.to_pylist():
                contexts, _, once = unpack(r["e"]).reshape(3, -1)
                u, t = unpack(r["a"]), unpack(r["d"])
                u = np.cumsum(u, dtype=u.dtype)
                mine = np.flatnonzero(K.is_member(contexts, hot))
                tables = np.bincount(np.searchsorted(contexts, u.astype(np.int64)), t, len(contexts)) + once
                yield pa.RecordBatch.from_arrays([pa.array(contexts[mine]), pa.array(tables[mine].astype(np.int64))], names=["u", "t"])

    found = state.where(F.col("kind") == REPEATED).mapInArrow(run, "u bigint, t bigint").groupBy("u").agg(F.sum("t").alias("t")).collect()
    out = np.zeros(len(hot), np.int64)
    for r in found:
        out[np.searchsorted(hot, r.u)] = r.t
    return out


# ---- answers ------------------------------------------------------------------------------------

ANSWER = "chunk bigint, shard int, kind int, a binary, b binary, c binary"


def _answer_pairs(table: pa.Table, states: int) -> pa.Table:
    """To each chunk, in the order it asked: of each pair its count and its tables summed over the samples; of each context its tables in each sample."""
    asked = [r for r in table.to_pylist() if r["kind"] < 0]
    kept = sorted((r for r in table.to_pylist() if r["kind"] >= 0), key=lambda r: r["kind"])
    opened = [_open_pairs({"u": r["a"], "run": r["b"], "w": r["c"], "c": r["d"]}) for r in asked]
    pairs = Pairs(opened)
    many = pairs.c > 1
    tables = np.full(len(pairs.c), states, np.int64)
    tables[many] = 0
    contexts, place = _runs(pairs.u)
    by_state = []
    for r in kept:
        t = unpack(r["d"])
        tables[many] += t
        each = np.ones(len(pairs.c), np.int64)
        each[many] = t
        by_state.append(np.bincount(place, each, len(contexts)).astype(np.int64))
    out = []
    for r, (qu, qw, _) in zip(asked, opened, strict=True):
        heads = _runs(qu)[0]
        at = pairs.find(qu, qw)
        seen = at >= 0
        pair_count, pair_tables = np.zeros(len(qu), np.uint32), np.zeros(len(qu), np.uint32)
        pair_count[seen], pair_tables[seen] = pairs.c[at[seen]], tables[at[seen]]
        context = np.zeros((states, len(heads)), np.int64)
        if len(contexts):
            k = np.searchsorted(contexts, heads)
            k[k == len(contexts)] = 0
            for s, x in enumerate(by_state):
                context[s] = np.where(contexts[k] == heads, x[k], 0)
        context[1:] -= context[0]
        out.append((r["chunk"], r["shard"], 0, pack(pair_count), pack(pair_tables), pack(context.astype(np.int32).ravel())))
    return pa.Table.from_batches([_batch(_arrow(ANSWER), out)])


def _ask_parents(coded: DataFrame, shards: int) -> DataFrame:
    schema = _arrow("shard int, kind int, chunk bigint, a binary")

    def run(batches):
        for batch in batches:
            for chunk, wid in zip(*(batch.column(c).to_pylist() for c in ("chunk", "wid")), strict=True):
                ids = np.sort(unpack(wid))
                to = ids % ids.dtype.type(shards)
                yield _batch(schema, [(int(s), -1, chunk, pack(steps(ids[to == s]))) for s in np.unique(to).tolist()])

    return coded.select("chunk", "wid").mapInArrow(run, "shard int, kind int, chunk bigint, a binary")


def _answer_parents(table: pa.Table, states: int) -> pa.Table:
    """To each chunk: customers and tables of its words at the parent in each sample."""
    rows = table.to_pylist()
    kept = [(unpack(r["a"]), unpack(r["b"]), unpack(r["c"])) for r in sorted((r for r in rows if r["kind"] >= 0), key=lambda r: r["kind"])]
    out = []
    for r in rows:
        if r["kind"] < 0:
            ids = unpack(r["a"])
            ids = np.cumsum(ids, dtype=ids.dtype)
            both = [np.zeros((states, len(ids)), np.int64) for _ in range(2)]
            for s, (words, customers, tables) in enumerate(kept):
                at = np.searchsorted(words, ids)
                at[at == len(words)] = 0
                seen = words[at] == ids
                both[0][s], both[1][s] = np.where(seen, customers[at], 0), np.where(seen, tables[at], 0)
            out.append((r["chunk"], r["shard"], 1, pack(both[0].astype(np.uint32).ravel()), pack(both[1].astype(np.uint32).ravel()), b""))
    return pa.Table.from_batches([_batch(_arrow(ANSWER), out)])


RESULT = "id bigint, known boolean, held_out boolean, n_tokens bigint, n_known bigint, base_score double, score double"


class Scorer:
    def __init__(self, shards: int, hot: np.ndarray, hot_tables: list[np.ndarray], sweeps: list[Sweep], train_tokens: int, vocabulary: int):
        self.shards, self.hot, self.hot_tables, self.sweeps = shards, hot, hot_tables, sweeps
        self.train_tokens, self.vocabulary = train_tokens, vocabulary

    def run(self, left: pa.Table, right: pa.Table) -> pa.Table:
        answers: dict[int, list[dict]] = {}
        for r in right.to_pylist():
            answers.setdefault(r["chunk"], []).append(r)
        out = [self.chunk(row, answers.get(row["chunk"], [])) for row in left.to_pylist()]
        return pa.concat_tables(out)

    def chunk(self, row: dict, answers: list[dict]) -> pa.Table:
        states = len(self.sweeps)
        u, w, _, place, tokens = _pairs(row)
        wid, wcount, n = unpack(row["wid"]), unpack(row["wcount"]), unpack(row["length"])
        by_id = np.argsort(wid, kind="stable")
        ids = wid[by_id]
        to = ids % ids.dtype.type(self.shards)
        parents = [np.zeros(len(ids)) for _ in range(states)]
        for r in answers:
            if r["kind"] == 1:
                mine = np.flatnonzero(to == r["shard"])
                customers, tables = unpack(r["a"]).reshape(states, -1), unpack(r["b"]).reshape(states, -1)
                for s, sweep in enumerate(self.sweeps):
                    parents[s][mine] = sweep.base(customers[s].astype(np.int64), tables[s].astype(np.int64))
        shard = _shard_of(u, w, self.shards, self.hot)
        # the training count of a context, and where its word stands among the ascending ids
        total = wcount[by_id][np.searchsorted(ids, u)]
        below = np.searchsorted(ids, w)
        share, left = np.zeros(len(u)), [np.zeros(len(u)) for _ in range(states)]
        discount, strength = self.sweeps[0].discount, self.sweeps[0].strength  # held after the burn-in
        for r in answers:
            if r["kind"] == 0:
                mine = np.flatnonzero(shard == r["shard"])
                heads = np.concatenate(([True], u[mine][1:] != u[mine][:-1]))
                context = unpack(r["c"]).reshape(states, -1).astype(np.int64)
                context[1:] += context[0]
                share[mine] = unpack(r["a"]) - discount * (unpack(r["b"]) / states)
                for s in range(states):
                    left[s][mine] = context[s][np.cumsum(heads) - 1]
        split = K.is_member(u, self.hot)
        for s in range(states):
            left[s][split] = self.hot_tables[s][np.searchsorted(self.hot, u[split])]
        p = share
        for s in range(states):
            p = p + (strength + discount * left[s]) * parents[s][below] / states
        p /= strength + total
        ends = np.cumsum(n)
        add = lambda x: (t := np.concatenate(([0.0], np.cumsum(x))))[ends] - t[ends - n]
        seen = wcount[tokens]
        base = np.log10((seen + 1) / (self.train_tokens + self.vocabulary + 1))
        columns = [unpack(row["ids"]), unpack(row["known"]), unpack(row["held"]), n, np.round(add(seen > 0)).astype(np.int64), add(base), add(np.log10(p)[place])]
        return pa.table([pa.array(c) for c in columns], names=[x.split()[0] for x in RESULT.split(", ")])


def score_corpus(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", burn_in: int = BURN_IN, samples: int = SAMPLES, seed: int = 29, shards: int | None = None) -> DataFrame:
    """One row per document: its id, held_out, n_tokens, n_known, train_tokens, base_score, score (log10), perplexity (per token)."""
    if docs.schema[id_col].dataType.typeName() not in ("byte", "short", "integer", "long"):
        raise TypeError(f"{id_col} must be an integer column")
    chunks = written(chunks_of(docs, id_col, text_col), "chunks")
    tokens = chunks.agg(F.sum("size")).first()[0] or 0
    shards = shards or max(4, -(-tokens // SHARD_TOKENS))
    words = written(_ask_words(chunks, shards).groupBy("shard").applyInArrow(_answer_words, WORD), "words")
    sizes = np.zeros((shards, 3), np.int64)
    for r in words.where("chunk = -1").collect():  # one small row a shard
        sizes[r.shard] = unpack(bytes(r.place))
    base = np.concatenate(([0], np.cumsum(sizes[:, 0])))
    vocabulary, train_tokens = int(sizes[:, 1].sum()), int(sizes[:, 2].sum())
    left, right = chunks.groupBy("chunk"), words.where("chunk >= 0").groupBy("chunk")
    coded = written(left.cogroup(right).applyInArrow(lambda a, b: _code(a, b, base), CODED), "coded")
    forget(chunks, words)
    hot, hot_total = _hot_words(coded, max(1, train_tokens // (2 * shards)))

    asked = _ask_pairs(coded, shards, hot)
    state = written(asked.groupBy("shard").applyInArrow(lambda t: _first_state(t, shards), STATE), "state")
    first, singles = state, state.where(F.col("kind") == SINGLES)
    ones = np.sum([unpack(bytes(r.a)) for r in state.where("shard = -1").select("a").collect()] or [[1, 1]], axis=0)
    discount = min(DISCOUNTS, key=lambda d: abs(d - ones[0] / max(ones[0] + 2 * ones[1], 1)))
    strength, kinds, trial = 1.0, vocabulary + 1, []
    driver = np.random.default_rng((seed, 1 << 31))
    scale = ROOT_STRENGTH / ROOT_DISCOUNT + vocabulary  # a table a word at first
    sweeps, hot_tables, kept, parents = [], [], [], []
    for turn in range(burn_in + samples + 1):
        told = singles.union(state.where(F.col("kind") == TABLES))
        parent = written(told.groupBy("shard").applyInArrow(_seat_parents(kinds, seed + turn, scale), STATE), "parent")
        totals = np.sum([unpack(bytes(r.e)) for r in parent.where(F.col("kind") == PARENT).select("e").collect()] or [[0.0, 0.0, 0.0]], axis=0)
        totals[2] += _rest(driver, scale / kinds, 1)[0]  # the kind that was never seen
        scale = float(driver.standard_gamma(ROOT_STRENGTH / ROOT_DISCOUNT + totals[1]))
        at_hot = _hot_tables(state, hot)
        if trial:
            logs = np.sum([unpack(bytes(r.a)) for r in state.where("shard = -1").select("a").collect()] or [np.zeros(len(trial))], axis=0)
            logs = logs + np.array([context_terms(hot_total, at_hot, d, a) for d, a in trial])
            discount, strength = trial[int(np.argmax(logs + driver.gumbel(size=len(trial))))]
        # the discount and the strength are drawn by turns up to the last sweep of the burn-in
        trial = [] if turn >= burn_in else [(d, strength) for d in block_of(driver, DISCOUNTS, discount)] if turn % 2 else [(discount, a) for a in block_of(driver, STRENGTHS, strength)]
        hot_scale = driver.standard_gamma(strength / discount + at_hot)
        sweep = Sweep(kinds, discount, strength, totals, hot, hot_scale, shards, seed + 1000 + turn, trial)
        if turn > burn_in:
            sweeps.append(sweep)
            hot_tables.append(at_hot)
            kept.append(state.where(F.col("kind") == REPEATED).select("shard", F.lit(len(kept)).alias("kind"), F.lit(None).cast("bigint").alias("chunk"), F.lit(None).cast("binary").alias("a"), F.lit(None).cast("binary").alias("b"), F.lit(None).cast("binary").alias("c"), "d"))
            parents.append(parent.where(F.col("kind") == PARENT).select("shard", F.lit(len(parents)).alias("kind"), F.lit(None).cast("bigint").alias("chunk"), "a", "b", "c"))
        if turn < burn_in + samples:
            own = state.where(F.col("kind") == REPEATED).union(parent.where(F.col("kind") == BASES))
            before, state = state, written(own.groupBy("shard").applyInArrow(_swept(sweep), STATE), "state")
            if turn <= burn_in:
                forget(parent, *[before] * (before is not first))

    ask = asked.select("shard", F.lit(-1).alias("kind"), "chunk", F.col("u").alias("a"), F.col("run").alias("b"), F.col("w").alias("c"), F.col("c").alias("d"))
    for k in kept:
        ask = ask.union(k)
    pairs = ask.groupBy("shard").applyInArrow(lambda t: _answer_pairs(t, samples), ANSWER)
    ask = _ask_parents(coded, shards).select("shard", "kind", "chunk", "a", F.lit(None).cast("binary").alias("b"), F.lit(None).cast("binary").alias("c"))
    for p in parents:
        ask = ask.union(p)
    roots = ask.groupBy("shard").applyInArrow(lambda t: _answer_parents(t, samples), ANSWER)
    scorer = Scorer(shards, hot, hot_tables, sweeps, train_tokens, vocabulary)
    out = coded.groupBy("chunk").cogroup(pairs.union(roots).groupBy("chunk")).applyInArrow(lambda a, b: scorer.run(a, b), RESULT)
    return out.select(
        F.when(F.col("known"), F.col("id")).alias(id_col), "held_out", "n_tokens", "n_known", F.lit(train_tokens).cast("bigint").alias("train_tokens"),
        "base_score", "score", F.pow(F.lit(10.0), -F.col("score") / F.col("n_tokens")).alias("perplexity"),
    )


def _swept(sweep: Sweep):
    return lambda t: sweep.run(t)


def _hot_words(coded: DataFrame, limit: int) -> tuple[np.ndarray, np.ndarray]:
    """Ids and training counts of the words (and the begin mark) with more than ``limit`` training occurrences: fewer than two a shard."""

    def run(batches):
        for batch in batches:
            for wid, count in zip(*(batch.column(c).to_pylist() for c in ("wid", "wcount")), strict=True):
                i, c = unpack(wid), unpack(count)
                yield pa.RecordBatch.from_arrays([pa.array(i[c > limit].astype(np.int64)), pa.array(c[c > limit])], names=["u", "c"])

    found = sorted((r.u, r.c) for r in coded.select("wid", "wcount").mapInArrow(run, "u bigint, c bigint").distinct().collect())
    return np.array([u for u, _ in found], dtype=np.int64), np.array([c for _, c in found], dtype=np.int64)
