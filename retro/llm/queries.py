"""The queries of this subpackage: one for each operator, over its whole table, and the pipeline."""

from __future__ import annotations

from collections.abc import Callable

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from retro.llm import pipeline_stages, quotation
from retro.llm.embedding_dedup import EmbeddingDedup
from retro.llm.jaccard_join import JaccardJoin
from retro.llm.language_id import LanguageId
from retro.llm.packing import VectorBestFit
from retro.llm.quality import Quality
from retro.llm.runtime import fold, table
from retro.llm.token_codec import round_trip_digest
from retro.llm.token_files import TokenFiles
from retro.llm.toxicity import Toxicity
from retro.llm.vector_search import PrefixForest

WORDS, BYTES = "word_bpe_49k.json", "byte_bpe_50k.json"


def op1_quotation_linking(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quotation.reply_ordered(table(spark, sf_dir, "conversations"))


def op2_prefix_forest(spark: SparkSession, sf_dir: str) -> DataFrame:
    return PrefixForest().search(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0, 20)


def op3_speculative_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return round_trip_digest(table(spark, sf_dir, "documents"), public_tokenizers.path(WORDS))


def op4_quadratic_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    labels = table(spark, sf_dir, "labels").select("doc_id", F.col("quality").alias("label"))
    _, scores = Quality().fit_predict(table(spark, sf_dir, "documents"), labels, fold("doc_id", 4) != 2)
    return scores.select("doc_id", (fold("doc_id", 4) == 2).alias("held_out"), "score", "predicted")


def op5_vector_best_fit(spark: SparkSession, sf_dir: str) -> DataFrame:
    return VectorBestFit(capacity=1024).pack(table(spark, sf_dir, "documents"), public_tokenizers.path(BYTES), 2)


def op6_hyperplane_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return EmbeddingDedup(threshold=0.98).dedup(table(spark, sf_dir, "embeddings"))


def op7_ftrl_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs, labels = table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels").select("doc_id", F.col("toxic").alias("label"))
    scores = Toxicity().fit(docs, labels, fold("doc_id", 3) != 1).predict(docs)
    return scores.select("doc_id", (fold("doc_id", 3) == 1).alias("held_out"), "score", "predicted")


def op8_bit_packed_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    return TokenFiles(public_tokenizers.path(WORDS), end_id=1).digest(table(spark, sf_dir, "documents"))


def op9_metric_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return JaccardJoin(width=5, similar=80, whole=100).join(table(spark, sf_dir, "documents"))


def op10_nearest_centroid_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    found = LanguageId().fit(docs, fold("doc_id", 3) != 1).predict(docs)
    return found.select("doc_id", (fold("doc_id", 3) == 1).alias("held_out"), "lang_pred", "score", "rejected")


def pipeline(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pipeline_stages.run(spark, sf_dir)


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    own = (op1_quotation_linking, op2_prefix_forest, op3_speculative_bpe, op4_quadratic_quality, op5_vector_best_fit, op6_hyperplane_dedup, op7_ftrl_toxicity, op8_bit_packed_tokens, op9_metric_jaccard_join, op10_nearest_centroid_language, pipeline)
    return {f.__name__: f for f in own}


def oracle_sql() -> dict[str, str]:
    return {"op6_hyperplane_dedup": OP6, "op9_metric_jaccard_join": OP9}


#: All pairs of one label by cosine in double precision, and the least vec_id reachable.
OP6 = """
WITH RECURSIVE v AS (
  SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings
  WHERE embedding IS NOT NULL AND label IS NOT NULL AND list_count(embedding) = len(embedding)
    AND len(list_filter(embedding, lambda x: NOT isfinite(x))) = 0 AND list_sum(list_transform(embedding::DOUBLE[], lambda x: x * x)) > 0),
pairs AS (
  SELECT a.vec_id AS a, b.vec_id AS b FROM v a JOIN v b ON a.label = b.label AND a.vec_id <> b.vec_id AND len(a.e) = len(b.e)
  WHERE list_cosine_similarity(a.e, b.e) >= 0.98),
reach(node, r) AS (SELECT a, least(a, b) FROM pairs UNION SELECT p.b, x.r FROM reach x JOIN pairs p ON p.a = x.node WHERE x.r < p.b),
comp AS (SELECT node, min(r) AS c FROM reach GROUP BY node),
links AS (SELECT a, count(*) AS n FROM pairs GROUP BY a)
SELECT e.vec_id, coalesce(n, 0)::BIGINT AS n_links, coalesce(least(c, e.vec_id), e.vec_id) AS component_id, coalesce(least(c, e.vec_id), e.vec_id) = e.vec_id AS kept
FROM embeddings e LEFT JOIN comp ON comp.node = e.vec_id LEFT JOIN links ON links.a = e.vec_id
"""

#: Shingle sets as SQL lists, pairs that share a shingle, exact ratio, least doc_id reachable.
OP9 = r"""
WITH RECURSIVE w AS (
  SELECT doc_id, list_filter(regexp_split_to_array(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS ws FROM documents),
s AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(ws) = 0 THEN [] WHEN len(ws) < 5 THEN [array_to_string(ws, ' ')]
    ELSE list_transform(range(1, len(ws) - 3), lambda i: array_to_string(ws[i:i+4], ' ')) END) AS g FROM w),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
i AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM i JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * k >= 80 * (x.n + y.n - k)),
both_ways AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
reach(node, r) AS (SELECT b, a FROM l UNION SELECT p.b, x.r FROM reach x JOIN both_ways p ON p.a = x.node WHERE x.r < p.b),
comp AS (SELECT node, min(r) AS c FROM reach GROUP BY node)
SELECT d.doc_id, coalesce(n.n, 0)::BIGINT AS n_shingles, coalesce(least(c, d.doc_id), d.doc_id) AS component_id
FROM documents d LEFT JOIN n ON n.doc_id = d.doc_id LEFT JOIN comp ON comp.node = d.doc_id
"""
