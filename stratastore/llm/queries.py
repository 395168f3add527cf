"""Queries of the ten operators with production parameters, over whole tables, and their SQL where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from . import decontaminate, embed_dup, html, near_dup, pieces, pitman_yor, quality, sharding, token_files, toxicity
from .shared import crc32_text, table

#: Categories of the chain, in order, as columns made from the labels: abuse in prose, abuse in junk, and either.
CATEGORIES = ["toxic_prose", "toxic_junk", "toxic"]


def tokenizer_path(name: str) -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def category_labels(labels: DataFrame) -> DataFrame:
    """One 0/1 column for each category of toxicity."""
    toxic, good = F.col("toxic") == 1, F.col("quality") == 1
    return labels.select("doc_id", (toxic & good).cast("int").alias("toxic_prose"), (toxic & ~good).cast("int").alias("toxic_junk"), F.col("toxic").cast("int").alias("toxic"))


def op1_sentencepiece(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return pieces.round_trip(docs, tokenizer_path("piece_bpe_32k.model")).select("doc_id", "n_tokens", "ids_crc32", "same")


def op2_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = sharding.shuffle_into_shards(table(spark, sf_dir, "documents"), sharding.N_SHARDS)
    size = F.octet_length(F.coalesce("text", F.lit(""))).cast("long") + 1
    return out.select("doc_id", size.alias("size"), crc32_text(F.col("text")).alias("text_crc32"), F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op3_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    chain = toxicity.fit_chain(docs, category_labels(table(spark, sf_dir, "labels")), CATEGORIES)
    out = toxicity.score_chain(docs, chain)
    return out.select("doc_id", "p_toxic_prose", "p_toxic_junk", "p_toxic", F.col("is_toxic").alias("toxic"), (~F.col("is_toxic")).alias("kept"))


def op4_token_files(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = token_files.write(table(spark, sf_dir, "documents"), token_files.place(spark), tokenizer_path("word_bpe_49k.json"))
    return token_files.crc_of_ids(token_files.read(spark, out)).select("doc_id", "start", "n_tokens", "ids_crc32")


def op5_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pitman_yor.score_corpus(table(spark, sf_dir, "documents").select("doc_id", "text"))


def op6_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text", "lang")
    return quality.judge(docs, table(spark, sf_dir, "labels")).select("doc_id", "lang", "n_tokens", "log10_prob", "perplexity", "threshold", F.col("keep").alias("kept"))


def op7_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    found = decontaminate.find_contamination(docs, table(spark, sf_dir, "benchmark"))
    return found.select("doc_id", "n_words", "n_hit", F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), "contaminated")


def op8_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").select("doc_id", "text")
    return near_dup.similarity_classes(docs).select("doc_id", "class_id", "n_links", F.col("doc_id").eqNullSafe(F.col("class_id")).alias("kept"))


def op9_embedding_near_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return embed_dup.near_duplicates(table(spark, sf_dir, "embeddings")).select("vec_id", "n_links", "component_id", "kept")


def op10_html(spark: SparkSession, sf_dir: str) -> DataFrame:
    return html.extract(table(spark, sf_dir, "pages")).select("page_id", "url", "text", F.char_length("text").cast("long").alias("n_chars"))


#: Windows of 13 words (fewer for short items) as joined words; hit words by position.
OP7_SQL = """
WITH w AS (
  SELECT doc_id, row_number() OVER () AS rid, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS words
  FROM documents),
b AS (
  SELECT item_id, row_number() OVER () AS iid, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS words
  FROM benchmark),
bw AS (
  SELECT DISTINCT item_id, iid, least(len(words), 13) AS width, array_to_string(words[i:i + least(len(words), 13) - 1], ' ') AS win
  FROM b, unnest(range(1, greatest(len(words) - 13, 0) + 2)) AS u(i) WHERE len(words) > 0),
widths AS (SELECT DISTINCT width FROM bw),
dw AS (
  SELECT rid, i AS pos, width, array_to_string(words[i:i + width - 1], ' ') AS win
  FROM w, widths, unnest(range(1, len(words) - width + 2)) AS u(i) WHERE len(words) >= width),
hits AS (SELECT rid, pos, width, item_id FROM dw JOIN bw USING (width, win)),
pos AS (SELECT rid, count(DISTINCT p) AS n_hit FROM hits, unnest(range(pos, pos + width)) AS v(p) GROUP BY rid),
items AS (SELECT rid, count(*) AS n_items, string_agg(item, ',' ORDER BY item) AS names FROM (SELECT DISTINCT rid, CAST(item_id AS VARCHAR) AS item FROM hits WHERE item_id IS NOT NULL) GROUP BY rid)
SELECT w.doc_id, CAST(len(w.words) AS BIGINT) AS n_words, CAST(coalesce(n_hit, 0) AS BIGINT) AS n_hit, CAST(coalesce(n_items, 0) AS BIGINT) AS n_items,
  sha256(coalesce(names, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AND 20 * coalesce(n_hit, 0) >= len(w.words) AS contaminated
FROM w LEFT JOIN pos USING (rid) LEFT JOIN items USING (rid)
"""


#: All pairs of equal label by brute force, and components by reach.
OP9_SQL = """
WITH RECURSIVE v AS (
  SELECT vec_id, label, CAST(embedding AS DOUBLE[]) AS e FROM embeddings),
ok AS (
  SELECT vec_id, label, e, sqrt(list_sum(list_transform(e, lambda x: x * x))) AS n FROM v
  WHERE label IS NOT NULL AND e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND list_sum(list_transform(e, lambda x: x * x)) > 0),
links AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM ok a JOIN ok b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
  WHERE list_inner_product(a.e, b.e) / (a.n * b.n) >= 0.98),
reach AS (
  SELECT vec_id AS a, vec_id AS b FROM v
  UNION
  SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
comp AS (SELECT a AS vec_id, min(b) AS component_id FROM reach GROUP BY a),
deg AS (SELECT a AS vec_id, count(*) AS n FROM links GROUP BY a)
SELECT v.vec_id, CAST(coalesce(deg.n, 0) AS BIGINT) AS n_links, comp.component_id, v.vec_id = comp.component_id AS kept
FROM v JOIN comp USING (vec_id) LEFT JOIN deg USING (vec_id)
"""

#: Shingle sets, all pairs that share a shingle, and classes by reach.
OP8_SQL = """
WITH RECURSIVE w AS (
  SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+') AS words FROM documents),
s AS (
  SELECT DISTINCT doc_id, array_to_string(words[i:i + 4], ' ') AS sh FROM w, unnest(range(1, greatest(len(words) - 4, 1) + 1)) AS u(i) WHERE len(words) > 0),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
common AS (SELECT x.doc_id AS a, y.doc_id AS b, count(*) AS c FROM s x JOIN s y ON x.sh = y.sh AND x.doc_id <> y.doc_id GROUP BY 1, 2),
links AS (SELECT a, b FROM common JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 10 * c >= 8 * (na.n + nb.n - c)),
reach AS (
  SELECT doc_id AS a, doc_id AS b FROM documents
  UNION
  SELECT r.a, l.b FROM reach r JOIN links l ON r.b = l.a),
class AS (SELECT a AS doc_id, min(b) AS class_id FROM reach GROUP BY a),
deg AS (SELECT a AS doc_id, count(*) AS n_links FROM links GROUP BY a)
SELECT doc_id, class_id, CAST(coalesce(n_links, 0) AS BIGINT) AS n_links, doc_id = class_id AS kept
FROM documents JOIN class USING (doc_id) LEFT JOIN deg USING (doc_id)
"""


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = [op1_sentencepiece, op2_sharding, op3_toxicity, op4_token_files, op5_lm_scoring, op6_quality, op7_decontamination, op8_jaccard_join, op9_embedding_near_dedup, op10_html]
    return {f.__name__: f for f in own}


def oracle_sql() -> dict[str, str]:
    return {"op7_decontamination": OP7_SQL, "op8_jaccard_join": OP8_SQL, "op9_embedding_near_dedup": OP9_SQL}
