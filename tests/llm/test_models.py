"""Toxicity, quality, language model, near duplicates and the pipeline: held-out accuracy and brute force."""

from __future__ import annotations

import math
import random
import re
import zlib
from collections import Counter

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from stratastore.llm import embed_dup, near_dup, pitman_yor, quality, toxicity
from stratastore.llm.components import connected_components
from stratastore.llm.queries import op9_embedding_near_dedup

SMALL = "/root/testdata/sf0.01"


@pytest.fixture(scope="module")
def tables(spark):
    return tuple(spark.read.parquet(f"{SMALL}/{t}.parquet") for t in ("documents", "labels"))


def test_chain_on_held_out_rows(spark):
    docs, labels = (spark.read.parquet(f"/root/testdata/sf0.1/{t}.parquet") for t in ("documents", "labels"))
    cats = labels.select("doc_id", (1 - F.col("quality")).alias("low"), F.col("toxic").alias("bad"))
    train = cats.where("doc_id % 3 <> 0")
    chain = toxicity.fit_chain(docs, train, ["low", "bad"])
    assert len(chain.models[1].w) == len(chain.columns[1]) + 2  # the earlier category feeds the later
    rows = toxicity.score_chain(docs, chain).join(cats.where("doc_id % 3 = 0"), "doc_id").collect()
    hits = sum(r.is_bad and r.bad for r in rows)
    assert hits >= 0.85 * sum(r.bad for r in rows) and sum(r.is_bad and not r.bad for r in rows) <= 12


def test_chain_on_odd_rows(spark):
    docs = spark.createDataFrame([(k, f"fine day n{k}" if k % 5 else f"you scum m{k}") for k in range(60)] + [(90, None), (91, ""), (None, "you scum")], "doc_id long, text string")
    labels = spark.createDataFrame([(k, int(k % 5 == 0)) for k in range(60)] + [(90, 0), (None, 1), (3, None), (5, 1)], "doc_id long, bad int")
    chain = toxicity.fit_chain(docs, labels, ["bad"])
    got = {r.doc_id: r.is_bad for r in toxicity.score_chain(docs.withColumn("p_bad", F.lit(0)), chain).collect()}
    assert got[10] and not got[2] and not got[90] and not got[91] and got[None]
    nobody = toxicity.fit_chain(docs, labels.limit(0), ["bad"])
    assert toxicity.score_chain(docs, nobody).count() == 63


def test_chain_against_the_definition(spark):
    """Two categories: features by rank of association, out-of-fold probabilities of the first as input of the second."""
    rng = np.random.default_rng(8)
    docs, labels = [], []
    for k in range(240):
        one, two = int(rng.random() < 0.3), int(rng.random() < 0.3)
        words = [f"w{x}" for x in rng.integers(0, 30, 6)] + ["vile"] * (one and rng.random() < 0.9) + ["brute"] * (two and rng.random() < 0.8)
        docs.append((k, " ".join(words)))
        labels.append((k, one, int(one or two)))
    labels += [(5, 1, 1), (5, 0, 1)]  # of several labels the greatest
    d, want = spark.createDataFrame(docs, "doc_id long, text string"), {}
    chain = toxicity.fit_chain(d, spark.createDataFrame(labels, "doc_id long, first int, second int"), ["first", "second"], max_features=20)
    y = {k: [0, 0] for k, _ in docs}
    for k, a, b in labels:
        y[k] = [max(y[k][0], a), max(y[k][1], b)]
    feats = [toxicity.features_of(t) for _, t in docs]
    ys = np.array([y[k] for k, _ in docs], float)
    n, df = len(docs), Counter(f for x in feats for f in x)
    fold = np.array([r.f for r in d.select("doc_id", F.pmod(F.xxhash64("text"), F.lit(toxicity.FOLDS)).alias("f")).orderBy("doc_id").collect()])
    sigmoid = lambda z: 1 / (1 + np.exp(-z))
    fed, models = np.zeros((n, 0)), []
    for c in range(2):
        def g2(f):
            a = sum(ys[i, c] for i in range(n) if f in feats[i])
            cells = [(a, df[f], ys[:, c].sum()), (df[f] - a, df[f], n - ys[:, c].sum()), (ys[:, c].sum() - a, n - df[f], ys[:, c].sum()), (n - df[f] - ys[:, c].sum() + a, n - df[f], n - ys[:, c].sum())]
            return math.sqrt(max(0.0, 2 * sum(o * math.log(o * n / (r * q)) for o, r, q in cells if o > 0)))
        best = sorted(((-g2(f), f) for f, k in df.items() if k >= 3))
        chosen = [f for s, f in best if -s > 3.3][:10]
        assert sorted(chosen) == sorted(f for f, i in chain.vocabulary.items() if i in chain.columns[c])
        x = np.hstack([np.array([[f in t for f in chosen] for t in feats], float).reshape(n, -1), fed])
        out = np.zeros(n)
        for f in range(toxicity.FOLDS):
            if (fold == f).any():
                out[fold == f] = sigmoid(toxicity.fit_linear(x[fold != f], ys[fold != f, c]).logit(x[fold == f]))
        models.append((chosen, toxicity.fit_linear(x, ys[:, c])))
        fed = np.hstack([fed, out[:, None]])
    for (k, t), f in zip(docs, feats):
        p = []
        for chosen, m in models:
            p.append(float(sigmoid(m.logit(np.array([[*[g in f for g in chosen], *p]], float)))[0]))
        want[k] = p
    got = {r.doc_id: [r.p_first, r.p_second] for r in toxicity.score_chain(d, chain).collect()}
    assert max(abs(a - b) for k in want for a, b in zip(want[k], got[k])) < 1e-5


def test_linear_fit_is_the_optimum():
    rng = np.random.default_rng(0)
    x, y = rng.integers(0, 2, (700, 5)).astype(float), rng.integers(0, 2, 700).astype(float)
    m = toxicity.fit_linear(x, y)
    p = 1 / (1 + np.exp(-m.logit(x)))
    assert np.abs(x.T @ (p - y) + m.w[:-1]).max() < 1e-5


def naive_kneser_ney(texts):
    """Order two, straight from the definition."""
    toks = [["<b>", *t.lower().split(), "<e>"] for t in texts]
    pairs = Counter(p for t in toks for p in zip(t, t[1:]))
    follow = Counter(w for _, w in pairs)

    def cut(c):
        n = Counter(min(v, 5) for v in c.values())
        return quality.discounts(n)

    d2, d1 = cut(pairs), cut(follow)
    disc = lambda d, c: d[min(c, 3) - 1]
    total1, left1 = sum(follow.values()), sum(disc(d1, c) for c in follow.values())

    def p1(w):
        c = follow.get(w, 0)
        return ((c - disc(d1, c)) / total1 if c else 0) + left1 / total1 / (len(follow) + 1)

    def p2(u, w):
        own = {b: c for (a, b), c in pairs.items() if a == u}
        if not own:
            return p1(w)
        t, c = sum(own.values()), own.get(w, 0)
        return ((c - disc(d2, c)) / t if c else 0) + sum(disc(d2, x) for x in own.values()) / t * p1(w)

    return p1, p2, follow


def test_kneser_ney_against_the_definition(spark):
    texts = ["a b c a b", "a b d", "c a b a", "", "b b b c", "d a"] * 2 + ["e f a"]
    model = quality.fit_kneser_ney(spark.createDataFrame([(t,) for t in texts], "text string"), 2)
    _, p2, _ = naive_kneser_ney(texts)
    for t in ["a b c", "", "zz a", "B B e"]:
        run = ["<b>", *t.lower().split(), "<e>"]
        n, logs = model.log10(pa.array([t]))
        assert n[0] == len(run) - 1 and abs(logs[0] - sum(math.log10(p2(a, b)) for a, b in zip(run, run[1:]))) < 1e-5


@pytest.mark.parametrize("order", [1, 3])
def test_kneser_ney_sums_to_one(spark, order):
    texts = ["a b c a b", "a b d", "c a b a", "b b b c"]
    model = quality.fit_kneser_ney(spark.createDataFrame([(t,) for t in texts], "text string"), order)
    total = 0.0
    for w in ["a", "b", "c", "d", "never"]:  # the end token is the rest
        _, logs = model.log10(pa.array([f"a b {w}", "a b"]))
        before = model.log10(pa.array(["a b"]))[1][0]
        end = 10 ** (before - _prefix(model, "a b"))
        total += 10 ** (_prefix(model, f"a b {w}") - _prefix(model, "a b"))
    assert abs(total + end - 1) < 1e-5


def _prefix(model, text):
    """log10 probability of a text's words without its end."""
    order = len(model.levels)
    grams, n = quality.token_grid(pa.array([text]), order)
    logs = model.log10(pa.array([text]))[1][0]
    # the end's share, from a model call on the same context
    keep = [g[:-1] for g in grams]
    p = np.where(model.levels[0].grams.find(keep[0]) >= 0, model.levels[0].share[model.levels[0].grams.find(keep[0])], 0.0) + model.floor
    before = [quality._shifted(g, n, k)[:-1] for k, g in enumerate(grams[:-1], 1)]
    for k in range(1, order):
        level = model.levels[k]
        ctx = level.contexts.find(before[k - 1])
        own = level.grams.find(keep[k])
        p = np.where(ctx >= 0, level.weight[ctx] * p + np.where(own >= 0, level.share[own], 0.0), p)
    assert logs <= np.log10(p).sum() + 1e-9
    return np.log10(p).sum()


def test_quality_keeps_good_and_drops_bad(spark, tables):
    docs, labels = tables
    model = quality.fit_quality(docs, labels)
    rows = quality.classify(docs, model).join(labels, "doc_id").collect()
    good, bad = [r.keep for r in rows if r.quality], [r.keep for r in rows if not r.quality]
    assert sum(good) > 0.98 * len(good) and sum(bad) < 0.5 * len(bad)
    odd = spark.createDataFrame([(1, None, None), (2, "", "xx"), (3, "word", "en")], "doc_id long, text string, lang string")
    assert {r.doc_id: r.n_tokens for r in quality.classify(odd, model).collect()} == {1: 1, 2: 1, 3: 2}


def test_pitman_yor_base_and_gain(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet").select("doc_id", "text").union(spark.createDataFrame([(5000, None), (5001, ""), (None, "the of")], "doc_id long, text string"))
    rows = pitman_yor.score_corpus(docs).collect()
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    toks = {r.doc_id: [*re.findall(r"[^\x20\x09-\x0D]+", (r.text or "").translate(low)), None] for r in docs.collect()}
    held = {k: k is not None and zlib.crc32(str(k).encode()) % 7 == 2 for k in toks}
    count = Counter(w for k, t in toks.items() if not held[k] for w in t)
    n, v = sum(count.values()), len(count)
    for r in rows:
        t = toks[r.doc_id]
        want = sum(math.log10((count[w] + 1) / (n + v + 1)) for w in t)
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[r.doc_id], len(t), sum(count[w] > 0 for w in t), n) and abs(r.base_score - want) < 1e-6 * max(1, -want)
    out = [r for r in rows if r.held_out]
    assert sum(r.score for r in out) > sum(r.base_score for r in out)


def test_pitman_yor_sums_to_one(spark):
    """Texts of one word and of none: their scores over all words, an unseen one, and the end add up."""
    train = ["a b a c", "a a", "b c", "c", "a b"] * 5
    train_ids = [k for k in range(200) if zlib.crc32(str(k).encode()) % 7 != 2][: len(train)]
    held_ids = iter([k for k in range(2000) if zlib.crc32(str(k).encode()) % 7 == 2])
    probes = {next(held_ids): t for t in ("", "a", "b", "c", "zz", "a a", "a b", "a c", "a zz")}
    docs = spark.createDataFrame([*zip(train_ids, train), *probes.items()], "doc_id long, text string")
    for shards in (1, 5):  # five shards split the frequent contexts
        got = {probes[r.doc_id]: 10**r.score for r in pitman_yor.score_corpus(docs, shards=shards).collect() if r.doc_id in probes}
        # P(a) from P(a, end) needs P(end | a): one of the four words or the end follows a
        after_a = {w: got[f"a {w}"] for w in "abc"}
        assert 0 < got[""] < 1 and all(0 < x < 1 for x in after_a.values()) and got["a b"] > got["a zz"]
        assert sum(got[t] for t in ("", "a", "b", "c", "zz")) <= 1


def seat_one_by_one(rng, count, others, base, d, strength, sweeps):
    """Gibbs sampling of one dish by taking out and seating each customer in turn: its numbers of tables."""
    of, size, free, out = list(range(count)), [1] * count, [], []
    tables = count
    for _ in range(sweeps):
        for k in range(count):
            size[of[k]] -= 1
            if not size[of[k]]:
                free.append(of[k])
                tables -= 1
            new, join = (strength + d * (others + tables)) * base, count - 1 - d * tables
            if rng.random() * (new + join) < new:
                of[k] = free.pop()
                size[of[k]], tables = 1, tables + 1
                continue
            while True:  # a table by its customers, kept by (n - d) / n
                j = rng.randrange(count - 1)
                t = of[j + (j >= k)]
                if rng.random() * size[t] < size[t] - d:
                    break
            of[k] = t
            size[t] += 1
        out.append(tables)
    return out


@pytest.mark.parametrize(("count", "others", "base", "d", "sweeps"), [(3, 4, 0.3, 0.6, 40_000), (300, 2_000, 0.02, 0.8, 1_500), (300, 40, 0.3, 0.5, 1_500), (5_000, 50_000, 0.05, 0.75, 60)])
def test_tables_against_seating_one_by_one(count, others, base, d, sweeps):
    seated = np.array(seat_one_by_one(random.Random(count), count, others, base, d, 1.0, sweeps)[sweeps // 6 :])
    rng, drawn, t = np.random.default_rng(5), [], 1
    for _ in range(max(400, min(sweeps, 20_000))):
        scale = rng.standard_gamma(1.0 / d + others + t)
        t = int(pitman_yor.draw_tables(rng, np.array([count]), np.log([d * scale * base]), d)[0])
        drawn.append(t)
    drawn = np.array(drawn[100:])
    noise = 5 * seated.std() / math.sqrt(len(seated) / 4) + 0.002 * seated.mean()
    assert abs(seated.mean() - drawn.mean()) < noise, (seated.mean(), drawn.mean())
    if count == 3:
        assert np.abs(np.bincount(seated, minlength=4) / len(seated) - np.bincount(drawn, minlength=4) / len(drawn)).max() < 0.015


@pytest.mark.parametrize("d", [0.3, 0.6, 0.9])
def test_computed_numbers_equal_the_recurrence(monkeypatch, d):
    monkeypatch.setattr(pitman_yor, "EXACT", 1500)
    pitman_yor._stirling.cache_clear()
    full, t = pitman_yor._stirling(d), np.arange(1, 1501)
    monkeypatch.setattr(pitman_yor, "EXACT", 8)
    for x in (1e-6, 0.5, 20.0, 600.0, 1e6):
        some, weight = pitman_yor.large_law(1500, x, d)
        want = full[1500, 1:] + t * math.log(x)
        want, got = np.exp(want - want.max()), np.exp(weight - weight.max())
        want /= want.sum()
        assert np.abs(want[some - 1] - got / got.sum()).max() < 1e-9 and want[some - 1].sum() > 1 - 1e-9
    for k in (1, 2, 40, 700, 1500):
        assert abs(pitman_yor.log_stirling(1500, k, d) - full[1500, k]) < 1e-8 * max(1, abs(full[1500, k]))
    monkeypatch.undo()
    pitman_yor._stirling.cache_clear()


def test_scores_against_a_plain_sampler(spark, monkeypatch):
    """Scores of held-out texts, against customers seated one by one in all restaurants, with the parameters held."""
    d, strength, root_d, root_s = 0.6, 1.0, pitman_yor.ROOT_DISCOUNT, pitman_yor.ROOT_STRENGTH
    monkeypatch.setattr(pitman_yor, "DISCOUNTS", [d])
    monkeypatch.setattr(pitman_yor, "STRENGTHS", [strength])
    train = ["a b a c a b", "a a b", "b c a b", "c c", "a b", "d a b"] * 3
    probes = ["a b", "c a", "b b d", "zz a", "", "d d d", "a c c"]
    of = lambda held: (k for k in range(10**6) if (zlib.crc32(str(k).encode()) % 7 == 2) is held)
    docs = [*zip(of(False), train), *zip(of(True), probes)]
    got = {r.doc_id: r.score for r in pitman_yor.score_corpus(spark.createDataFrame(docs, "doc_id long, text string"), burn_in=4, samples=14, shards=2).collect()}
    rng = random.Random(4)
    tokens = [(u, w) for t in train for u, w in zip(["<", *t.split()], [*t.split(), ">"])]
    kinds = len({w for _, w in tokens}) + 1
    seats, parent, at = {}, {}, [None] * len(tokens)  # lists of table sizes

    def pick(weights):
        x = rng.random() * sum(weights)
        for k, y in enumerate(weights):
            x -= y
            if x < 0:
                return k
        return len(weights) - 1

    def root_p(w):
        own, n, t = parent.get(w, []), sum(map(sum, parent.values())), sum(map(len, parent.values()))
        return (sum(own) - root_d * len(own) + (root_s + root_d * t) / kinds) / (root_s + n)

    def p(u, w):
        here, own = seats.get(u, {}), seats.get(u, {}).get(w, [])
        n, t = sum(sum(x) for x in here.values()), sum(map(len, here.values()))
        return (sum(own) - d * len(own) + (strength + d * t) * root_p(w)) / (strength + n)

    def seat(table_sizes, total_tables, discount, s, base):
        k = pick([n - discount for n in table_sizes] + [(s + discount * total_tables) * base])
        if k == len(table_sizes):
            table_sizes.append(1)
            return True
        table_sizes[k] += 1
        return False

    def leave(table_sizes):
        k = pick(table_sizes)
        table_sizes[k] -= 1
        if not table_sizes[k]:
            del table_sizes[k]
            return True
        return False

    logs = dict.fromkeys(probes, 0.0)
    for sweep in range(900):
        for i, (u, w) in enumerate(tokens):
            own = seats.setdefault(u, {}).setdefault(w, [])
            # customers of a dish are alike, so which one leaves is drawn
            if at[i] and leave(own):
                leave(parent[w])
            at[i] = True
            if seat(own, sum(map(len, seats[u].values())), d, strength, root_p(w)):
                seat(parent.setdefault(w, []), sum(map(len, parent.values())), root_d, root_s, 1 / kinds)
        if sweep >= 100:
            for t in probes:
                for u, w in set(zip(["<", *t.split()], [*t.split(), ">"])):
                    logs[t, u, w] = logs.get((t, u, w), 0.0) + p(u, w) / 800
    for (k, t) in docs[len(train) :]:
        want = sum(math.log10(logs[t, u, w]) for u, w in zip(["<", *t.split()], [*t.split(), ">"]))
        assert abs(got[k] - want) < 0.03 * (1 + len(t.split())), (t, got[k], want)


def test_packing():
    for x in (np.zeros(0, np.uint32), np.arange(7, dtype=np.int64) - 3, np.array([1.5, -2]), np.array([True, False])):
        assert (pitman_yor.unpack(pitman_yor.pack(x)) == x).all() and pitman_yor.unpack(pitman_yor.pack(x)).dtype == x.dtype


# ---- near duplicates ----------------------------------------------------------------------------


def brute_classes(ids, texts):
    h, off = near_dup.shingle_sets(pa.array(texts, pa.string()))
    sets = [set(h[a:b].tolist()) for a, b in zip(off[:-1], off[1:])]
    n, par = [0] * len(sets), list(range(len(sets)))

    def find(x):
        while par[x] != x:
            x = par[x]
        return x

    for i in range(len(sets)):
        for j in range(i):
            c = len(sets[i] & sets[j])
            if c and 5 * c >= 4 * (len(sets[i]) + len(sets[j]) - c):
                n[i] += 1
                n[j] += 1
                par[max(find(i), find(j))] = min(find(i), find(j))
    least = {}
    for k in range(len(sets)):
        r = find(k)
        own = [x for x in (least.get(r), ids[k]) if x is not None]
        least[r] = min(own) if own else None
    return [(ids[k], least[find(k)], n[k]) for k in range(len(sets))]


def test_band_choice():
    bands, rows = near_dup.choose_bands()
    assert 1 - (1 - 0.8**rows) ** bands >= 0.9995 and bands * rows <= near_dup.MAX_HASHES


def test_classes_against_brute_force(spark, monkeypatch):
    base = [f"w{k}" for k in range(120)]
    texts = [None, "", "...", "one", "one", "one two", "a b c d e", "A b, c d e!"] + [" ".join(base)] * 3
    rng = np.random.default_rng(3)
    for _ in range(60):
        w = list(base)
        for p in rng.integers(0, 120, rng.integers(1, 4)):
            w[p] = f"z{rng.integers(1000)}"
        texts.append(" ".join(w))
    ids = [*range(100, 100 + len(texts) - 1), None]
    docs = spark.createDataFrame(list(zip(ids, texts)), "doc_id long, text string")
    for tile, large in ((768, 3_000), (16, 3_000), (16, 10)):  # small tiles: a group's pairs are dealt to several tasks; small groups are banded again
        monkeypatch.setattr("stratastore.llm.components.TILE", tile)
        monkeypatch.setattr(near_dup, "LARGE", large)
        got = [(r.doc_id, r.class_id, r.n_links) for r in near_dup.similarity_classes(docs).collect()]
        assert sorted(got, key=repr) == sorted(brute_classes(ids, texts), key=repr)
    kept = near_dup.keep_one(docs).count()
    assert kept < 25
    assert near_dup.similarity_classes(docs.limit(0)).isEmpty()


@pytest.mark.parametrize("links", [[(k, k + 1) for k in range(120)], [(120 - k, 119 - k) for k in range(120)], [(0, k) for k in range(60)], [(7, 7)], []])
def test_components(spark, links):
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    want = {x for a, b in links if a != b for x in (a, b)}
    assert got == {x: min(want) for x in want}


def brute_vectors(rows, threshold=0.98):
    ok = {}
    for k, (i, v, lab) in enumerate(rows):
        a = np.array([np.nan if x is None else x for x in v], float) if v is not None else None
        if lab is not None and a is not None and len(a) and np.isfinite(a).all() and a.any():
            ok[k] = (lab, a.astype(np.float32).astype(float))
    n, par = Counter(), {k: k for k in range(len(rows))}

    def find(x):
        while par[x] != x:
            x = par[x]
        return x

    for i in ok:
        for j in ok:
            if i < j and ok[i][0] == ok[j][0] and len(ok[i][1]) == len(ok[j][1]):
                a, b = ok[i][1], ok[j][1]
                if a @ b / np.sqrt((a @ a) * (b @ b)) >= threshold:
                    n[i] += 1
                    n[j] += 1
                    par[max(find(i), find(j))] = min(find(i), find(j))
    least = {}
    for k in range(len(rows)):
        least[find(k)] = min(least.get(find(k), rows[k][0]), rows[k][0])
    return sorted((rows[k][0], n[k], least[find(k)], rows[k][0] == least[find(k)]) for k in range(len(rows)))


def test_vectors_against_brute_force(spark, monkeypatch):
    monkeypatch.setattr("stratastore.llm.components.TILE", 20)
    rng = np.random.default_rng(5)
    rows = []
    for c in range(4):
        centre = rng.standard_normal(16)
        rows += [(len(rows) + k, (centre + rng.standard_normal(16) * 0.05).tolist(), c % 2) for k in range(30)]
    same = rng.standard_normal(16).tolist()
    rows += [(200 + k, same, 1) for k in range(5)] + [(210, [2 * x for x in same], 1), (211, same, None), (212, same, 0)]
    rows += [(220, None, 1), (221, [0.0] * 16, 1), (222, [float("nan")] * 16, 1), (223, [None, *same[1:]], 1), (224, [], 1), (225, same[:8], 1), (226, [float("inf")] * 16, 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    found = embed_dup.near_duplicates(df)
    assert sorted(map(tuple, found.collect())) == brute_vectors(rows)
    assert embed_dup.near_duplicates(df.limit(0)).isEmpty()


def test_audit(spark, monkeypatch):
    rng = np.random.default_rng(11)
    centres = rng.standard_normal((12, 16))
    rows = [(k, (centres[k % 12] + rng.standard_normal(16) * 0.06).tolist(), k % 2) for k in range(240)] + [(500, None, 1)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>, label int")
    found = embed_dup.near_duplicates(df)
    for block in (4_096, 7):
        monkeypatch.setattr(embed_dup, "BLOCK", block)
        r = embed_dup.audit_recall(df, found, every=3).first()
        want = sum(n for i, n, *_ in brute_vectors(rows) if i is not None and i % 3 == 0)
        assert (r.links, r.links_found, r.recall) == (want, want, 1.0) and want > 50
    half = found.withColumn("n_links", F.floor(F.col("n_links") / 2))
    assert embed_dup.audit_recall(df, half, every=3).first().recall < 0.6
    assert embed_dup.audit_recall(df.limit(0), found, every=3).first().links == 0


def test_a_short_search_is_noticed_and_goes_on(spark, monkeypatch):
    """A graph that starts from one table and gets no rounds misses links; the query's own audit sees it and searches on."""
    rng = np.random.default_rng(12)
    base = rng.standard_normal((150, 32))
    x = np.concatenate((base, base + 0.1 * rng.standard_normal(base.shape)))
    rows = [(k, v.tolist(), 1) for k, v in enumerate(x)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")
    asked, plain = [], embed_dup.neighbour_graph
    monkeypatch.setattr(embed_dup, "CELL", 1)
    monkeypatch.setattr(embed_dup, "tables_for", lambda used, threshold, least: least)

    def poor(*a, **k):
        asked.append(k["tables"])
        return plain(*a, **k | ({"tables": 1, "rounds": 0} if len(asked) == 1 else {}))

    monkeypatch.setattr(embed_dup, "neighbour_graph", poor)
    got = sum(r.n_links for r in embed_dup.near_duplicates(df).collect())
    want = sum(r[1] for r in brute_vectors(rows))
    assert len(asked) > 1 and want >= 250 and 0.99 * want <= got <= want


# ---- pipeline -----------------------------------------------------------------------------------


def test_pipeline(spark, tables):
    docs, labels = tables
    names = [n for n, _ in corpus_pipeline.STAGES]
    assert len(names) == 5 and corpus_pipeline.ORACLE_SQL is None
    out = corpus_pipeline.run(spark, SMALL)
    rows = {r.doc_id: r for r in out.collect()}
    assert out.columns == ["doc_id", "lang", "source", "ids"] and 0 < len(rows) < docs.count()
    good = labels.where("quality = 1 AND toxic = 0").select("doc_id")
    bad = {r.doc_id for r in labels.where("toxic = 1").collect()}
    assert len(bad & set(rows)) <= 8 and len({r.doc_id for r in good.collect()} & set(rows)) > 0.8 * good.count()
    text = {r.doc_id: r.text for r in docs.collect()}
    kept = [text[k] for k in rows]
    assert len(set(kept)) == len(kept)
