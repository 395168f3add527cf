"""Nulls in every column, empty and very long texts, repeated rows, empty tables, and columns whose names clash."""

from __future__ import annotations

import public_tokenizers as tokenizers_at
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from stratastore.llm import decontaminate, embed_dup, html, near_dup, pieces, pitman_yor, quality, sharding, token_files, toxicity

SMALL = "/root/testdata/sf0.001"
CLASHES = ("keep", "is_toxic", "contaminated", "ids", "n_words", "shard", "slot", "spans", "items", "perplexity", "threshold", "n_tokens", "node", "grp", "class_id", "decoded", "id", "n", "fold")


@pytest.fixture(scope="module")
def odd(spark):
    rows = [
        (1, "a common text of a few words", "en", "s", 28), (1, "a common text of a few words", "en", "s", 28), (2, None, None, None, None), (None, "no id here", "en", "s", 10), (3, "", "xx", "s", 0),
        (4, "w" * 300_000, "en", "s", 300_000), (5, "word " * 60_000, "de", "s", 300_000), (6, "\n\t ▁  ", "fr", "s", 6), (None, None, None, None, None),
    ]
    out = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long")
    return out.withColumns({c: F.lit(c) for c in CLASHES})


def both(odd, f):
    """The operator over the odd rows and over none."""
    out = f(odd)
    assert f(odd.limit(0)).isEmpty()
    return out.collect()


def test_each_operator_keeps_its_rows(spark, odd):
    labels = spark.read.parquet(f"{SMALL}/labels.parquet")
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    piece, word = tokenizers_at.path("piece_bpe_32k.model"), tokenizers_at.path("word_bpe_49k.json")
    chain = toxicity.fit_chain(docs, labels, ["toxic"])
    model = quality.fit_quality(docs, labels)
    bench = spark.read.parquet(f"{SMALL}/benchmark.parquet")
    operators = {
        "pieces": lambda d: pieces.encode(d, piece), "round trip": lambda d: pieces.round_trip(d, piece), "shards": sharding.shuffle_into_shards, "toxicity": lambda d: toxicity.score_chain(d, chain),
        "files": lambda d: token_files.read(spark, token_files.write(d, token_files.place(spark), word)), "language model": pitman_yor.score_corpus, "quality": lambda d: quality.classify(d, model),
        "contamination": lambda d: decontaminate.find_contamination(d, bench), "classes": near_dup.similarity_classes,
    }
    for name, f in operators.items():
        assert len(both(odd, f)) == 9, name


def test_fits_without_rows(spark, odd):
    none = spark.read.parquet(f"{SMALL}/labels.parquet").limit(0)
    assert toxicity.score_chain(odd, toxicity.fit_chain(odd, none, ["toxic"])).count() == 9
    assert quality.classify(odd, quality.fit_quality(odd, none)).where("_keep").count() == 9
    assert decontaminate.find_contamination(odd, spark.createDataFrame([], "item_id long, text string")).where("_contaminated").isEmpty()


@pytest.mark.parametrize(("name", "stage"), corpus_pipeline.STAGES)
def test_stages(spark, odd, name, stage):
    out = stage(spark, odd, SMALL)
    if stage is not corpus_pipeline.STAGES[-1][1]:
        assert out.columns == odd.columns
    assert out.count() <= 9
    assert stage(spark, odd.limit(0), SMALL).isEmpty()


def test_pages_and_vectors(spark):
    pages = spark.createDataFrame([(1, None, None, "t"), (None, "x", "<p>a", "t"), (2, "http://h/", "<article>" + "<p>y" * 20_000, "t"), (2, "http://h/", "<article>" + "<p>y" * 20_000, "t")], "page_id long, url string, html string, text string")
    assert [len(r._text) for r in sorted(both(pages, html.extract), key=lambda r: len(r._text))] == [0, 1, 39_999, 39_999]
    v = spark.createDataFrame([(1, [1.0, 0.0], 1, 9), (1, [1.0, 0.0], 1, 9), (None, [1.0, 0.0], 1, 9), (2, None, None, 9)], "vec_id long, embedding array<float>, label int, node int")
    got = {(r.vec_id, r.n_links) for r in both(v, embed_dup.near_duplicates)}
    assert got == {(1, 2), (None, 2), (2, 0)}
