"""The quality model uses the longer context, and its cuts come from all trusted rows."""

from __future__ import annotations

import time

import numpy as np

from stratastore.llm import quality, shared


def test_order_of_known_pairs_counts(spark):
    docs = spark.createDataFrame([(k, "a x b" if k % 2 else "c x d", "en") for k in range(400)], "doc_id long, text string, lang string")
    labels = spark.createDataFrame([(k, 1) for k in range(400)], "doc_id long, quality int")
    model = quality.fit_quality(docs, labels)
    texts = spark.createDataFrame([(1, "a x b", "en"), (2, "a x d", "en")], "doc_id long, text string, lang string")
    own, spliced = (r.perplexity for r in quality.score(texts, model.model).orderBy("doc_id").collect())
    assert spliced > 1.5 * own  # every pair of words is as common in either


def test_cuts_come_from_all_rows_outside_the_sample(spark):
    rng = np.random.default_rng(3)
    docs = spark.createDataFrame([(k, " ".join(f"w{x}" for x in rng.integers(0, 40, 12)), "de" if k < 2 else "en") for k in range(900)], "doc_id long, text string, lang string")
    labels = docs.selectExpr("doc_id", "1 AS quality")
    model = quality.fit_quality(docs, labels, max_train=20, min_held_out=200)
    rows = quality.score(docs, model.model).collect()
    ids = set(quality.training_ids(docs, labels, quality.F.col("quality") == 1, 20, 10**9))
    assert len(ids) == 20
    held = [r for r in rows if r.doc_id not in ids]
    assert set(model.thresholds) == {"en"}  # two rows of a language are no quantile
    assert np.isclose(model.overall, np.quantile([r.perplexity for r in held], quality.QUANTILE))
    assert np.isclose(model.thresholds["en"], np.quantile([r.perplexity for r in held if r.lang == "en"], quality.QUANTILE))


def test_a_long_text_does_not_end_the_sample(spark):
    docs = spark.createDataFrame([(k, "x" * (5_000 if k % 7 == 0 else 10)) for k in range(200)], "doc_id long, text string")
    ids = quality.training_ids(docs, docs.selectExpr("doc_id", "1 AS quality"), quality.F.col("quality") == 1, 100, 900)
    assert len(ids) > 60 and all(k % 7 for k in ids)


def test_one_value_many_times(spark):
    rows = spark.createDataFrame([("a", 1.0)] * 500 + [("b", float(k)) for k in range(1, 4)], "g string, x double")
    assert quality.upper_quantiles(rows, "g", "x", 0.5) == {"a": (500, 1.0), "b": (3, 2.0)}
    for n in (250, 20_001):
        got = quality.upper_quantiles(spark.range(n).selectExpr("0 AS g", "double(id) AS x"), "g", "x", 0.995)
        assert np.isclose(got[0][1], np.quantile(np.arange(n), 0.995))


def test_sharded_scores_equal_the_table_in_one_place(spark, monkeypatch):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text", "lang")
    odd = spark.createDataFrame([(-1, None, None), (-2, "", "en"), (None, "The word", "xx"), (-3, "w " * 50_000, "de")], "doc_id long, text string, lang string")
    docs = docs.unionByName(odd)
    counts = quality.fit_counts(docs.where("doc_id % 3 = 0").select("text"), 3)
    model = counts.in_memory()
    rows = docs.collect()
    n, logs = model.log10(quality.pa.array([r.text for r in rows], quality.pa.string()))
    want = sorted((str(r.doc_id), int(k), float(x)) for r, k, x in zip(rows, n, logs, strict=True))
    monkeypatch.setattr(quality, "CHUNK_BYTES", 40_000)
    for tokens, group in ((2_000_000, 64), (5_000, 3)):  # one chunk, and many that meet copies of the shards
        monkeypatch.setattr(quality, "CHUNK_TOKENS", tokens)
        monkeypatch.setattr(quality, "CHUNK_GROUP", group)
        got = sorted((str(r.doc_id), r.n_tokens, r.log10_prob) for r in quality.score(docs, counts).collect())
        assert [x[:2] for x in got] == [x[:2] for x in want] and np.allclose([x[2] for x in got], [x[2] for x in want], rtol=1e-6)


def test_a_filter_that_lets_all_pass_changes_nothing(spark):
    docs = spark.createDataFrame([(k, f"a b{k % 7} c{k % 5} d") for k in range(60)], "doc_id long, text string")
    counts = quality.fit_counts(docs.select("text"), 3)
    some = {r.doc_id: r.log10_prob for r in quality.score(docs, counts).collect()}
    counts.bits = ~np.zeros_like(counts.bits)
    assert some == {r.doc_id: r.log10_prob for r in quality.score(docs, counts).collect()}


def test_rejected_texts_go_by_text_and_language(spark):
    docs = spark.createDataFrame([(k, f"a b c d{k % 3}", "en", "s") for k in range(600)] + [(700, "x y z q r s t u v", "en", "s"), (701, "x y z q r s t u v", "en", None), (None, None, None, None)], "doc_id long, text string, lang string, source string")
    labels = spark.createDataFrame([(k, 1) for k in range(600)], "doc_id long, quality int")
    judged = {(r.doc_id, r.keep) for r in quality.judge(docs, labels).collect()}
    kept = quality.keep_good(docs, labels)
    assert kept.columns == docs.columns and (700, False) in judged
    assert sorted(str(r.doc_id) for r in kept.collect()) == sorted(str(i) for i, k in judged if k)


def test_every_trusted_row_is_counted_or_held_out(spark):
    docs = spark.createDataFrame([(k, f"only{k}", "en") for k in range(7_000)], "doc_id long, text string, lang string")
    labels = docs.selectExpr("doc_id", "int(doc_id % 10 > 0) AS quality")
    counts, trained = quality._fit(docs, labels, quality.F.col("quality") == 1, 1, None, None)
    ids = {r.doc_id for r in trained.collect()}
    assert ids == {k for k in range(7_000) if k % 10 and quality.zlib.crc32(str(k).encode()) % 7 != 2} and 5_300 < len(ids) < 5_500
    # each row has one word of its own, and all have the end
    assert len(counts.in_memory().levels[0].gram_keys) == len(ids) + 1


def test_shards_grow_with_the_trusted_text(spark, monkeypatch):
    docs = spark.createDataFrame([(k, f"a b{k % 7} c{k % 5} d") for k in range(600)], "doc_id long, text string")
    few = quality.fit_counts(docs.select("text"), 3)
    monkeypatch.setattr(quality, "SHARD_BYTES", 100)
    many = quality.fit_counts(docs.select("text"), 3)
    assert (few.shards, many.shards) == (32, 64)
    assert sorted(map(str, quality.score(docs, few).collect())) == sorted(map(str, quality.score(docs, many).collect()))


def test_chunks_do_not_depend_on_batches(spark, monkeypatch):
    docs = spark.createDataFrame([(k, "a b c d " * (k % 9), "en") for k in range(300)], "doc_id long, text string, lang string").repartition(3, "doc_id")
    model = quality.fit_counts(docs.where("doc_id % 2 = 0").select("text"), 3)
    want = sorted(map(str, quality.score(docs, model).collect()))
    monkeypatch.setattr(quality, "CHUNK_TOKENS", 100)
    key = "spark.sql.execution.arrow.maxRecordsPerBatch"
    before = spark.conf.get(key)
    rows = quality.score(docs, model)
    spark.conf.set(key, "7")
    try:
        assert sorted(map(str, rows.collect())) == want
    finally:
        spark.conf.set(key, before)


def test_documents_many_for_the_shards_meet_copies(spark, monkeypatch):
    docs = spark.createDataFrame([(k, f"a b{k % 7} c{k % 5} d{k % 3} only{k}") for k in range(900)], "doc_id long, text string")
    model = quality.fit_counts(docs.where("doc_id % 3 = 0").select("text"), 3)
    want = sorted(map(str, quality.score(docs, model).collect()))
    for name, value in (("CHUNK_TOKENS", 40), ("CHUNK_BYTES", 40), ("CHUNK_GROUP", 3)):
        monkeypatch.setattr(quality, name, value)
    assert sorted(map(str, quality.score(docs, model).collect())) == want


def test_words_that_are_not_frequent_are_asked_for(spark, monkeypatch):
    docs = spark.createDataFrame([(k, f"a b{k % 7} only{k} x{k % 50}") for k in range(500)], "doc_id long, text string")
    monkeypatch.setattr(quality, "FREQUENT", 1)
    model = quality.fit_counts(docs.where("doc_id % 2 = 0").select("text"), 3)
    assert len(model.frequent.keys) <= model.shards < 250
    rows = docs.collect()
    _, logs = model.in_memory().log10(quality.pa.array([r.text for r in rows]))
    got = {r.doc_id: r.log10_prob for r in quality.score(docs, model).collect()}
    assert np.allclose([got[r.doc_id] for r in rows], logs, rtol=1e-8)


def test_exchanges_leave_no_files(spark):
    blocks = lambda: spark._jvm.org.apache.spark.SparkEnv.get().blockManager().diskBlockManager().getAllBlocks().toString().count("shuffle_")
    before = blocks()
    rows = shared.released(spark.range(1_000).repartition(5, "id"), "rows")
    until = time.time() + 20
    while blocks() > before and time.time() < until:
        time.sleep(0.2)
    assert blocks() <= before and rows.count() == 1_000


def test_the_model_keeps_words_not_tuples(spark):
    rng = np.random.default_rng(5)
    docs = spark.createDataFrame([(" ".join(f"w{x}" for x in rng.integers(0, 3_000, 400)),) for k in range(1_000)], "text string")
    model = quality.fit_counts(docs, 3)
    assert sum(len(r.keys or b"") + len(r.value or b"") for r in model.words.collect()) < 1_000_000  # 400,000 tuples of three words are counted


def test_places_and_orders_of_hashes():
    rng, u64 = np.random.default_rng(8), np.uint64
    for keys in (rng.integers(0, 1 << 64, 500, dtype=u64)[rng.integers(0, 500, 900)], rng.integers(0, 9, 900, dtype=u64), rng.integers(0, 9, 900, dtype=u64) << u64(60), np.zeros(0, u64), np.array([0, 2**64 - 1, 0], u64)):
        want, first, inverse, n = np.unique(keys, return_index=True, return_inverse=True, return_counts=True)
        assert all(np.array_equal(*x) for x in zip(quality._distinct(keys), (want, first, n), strict=True))
        assert all(np.array_equal(*x) for x in zip(quality._inverse(keys), (want, inverse), strict=True))
        asked = np.concatenate([keys, keys + u64(1), keys - u64(1), rng.integers(0, 1 << 64, 50, dtype=u64)])
        assert np.array_equal(quality.Places(want).find(asked), [dict(zip(want.tolist(), range(900))).get(x, -1) for x in asked.tolist()])
    run = np.append(np.arange(5_000, dtype=u64), u64(2**64 - 1))  # all but one alike in their leading bits
    assert np.array_equal(quality.Places(run).find(np.append(run, u64(6_000))), [*range(5_001), -1])


def test_grams_are_found_in_less_time_than_by_halving():
    rng = np.random.default_rng(9)
    keys = np.unique(rng.integers(0, 1 << 64, 1_000_000, dtype=np.uint64))
    asked = np.concatenate([rng.choice(keys, 1_000_000), rng.integers(0, 1 << 64, 1_000_000, dtype=np.uint64)])

    def least(find) -> float:
        took = []
        for _ in range(3):
            began = time.process_time()
            find()
            took.append(time.process_time() - began)
        return min(took)

    assert least(lambda: quality.Places(keys).find(asked)) < 0.6 * least(lambda: np.searchsorted(keys, asked))
