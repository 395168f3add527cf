"""A training corpus from raw documents: quality, toxicity, near duplicates, contamination, tokens.

Each stage takes (spark, docs, sf_dir), works on all rows of docs, and returns a DataFrame; all but the
last return the columns of documents. Between stages the rows are written and read again.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stratastore.llm import decontaminate, near_dup, pieces, quality, toxicity
from stratastore.llm.queries import CATEGORIES, category_labels, tokenizer_path
from stratastore.llm.shared import table, written

#: No stage but decontamination can be said in SQL as a whole.
ORACLE_SQL = None


def _where_last(judged: DataFrame, wanted: bool, docs: DataFrame) -> DataFrame:
    """The documents whose last column, the verdict, is as wanted; its name avoids those that documents have."""
    verdict = F.col(judged.columns[-1])
    return judged.where(verdict if wanted else ~verdict).select(*docs.columns)


def keep_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose perplexity under the model of trusted text is within their language's quantile."""
    return quality.keep_good(docs, table(spark, sf_dir, "labels")).select(*docs.columns)


def drop_toxic(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier chain does not call toxic."""
    chain = toxicity.fit_chain(docs, category_labels(table(spark, sf_dir, "labels")), CATEGORIES)
    return _where_last(toxicity.score_chain(docs, chain), False, docs)


def drop_near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near duplicates: that of the least id."""
    return near_dup.keep_one(docs).select(*docs.columns)


def drop_contaminated(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that hold no benchmark passage of weight."""
    found = decontaminate.find_contamination(docs, table(spark, sf_dir, "benchmark"))
    return decontaminate.remove_documents(found, found.columns[-1]).select(*docs.columns)


def to_pieces(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """(doc_id, lang, source, ids) of each document."""
    encoded = pieces.encode(docs, tokenizer_path("piece_bpe_32k.model"))
    return encoded.select("doc_id", "lang", "source", F.col(encoded.columns[-1]).alias("ids"))


STAGES = [
    ("quality classifier", keep_quality),
    ("toxicity", drop_toxic),
    ("n-gram Jaccard join", drop_near_duplicates),
    ("benchmark decontamination", drop_contaminated),
    ("SentencePiece encoding and decoding", to_pieces),
]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for name, stage in STAGES[:-1]:
        docs = written(stage(spark, docs, sf_dir), name.replace(" ", "-").lower())
    return STAGES[-1][1](spark, docs, sf_dir)
