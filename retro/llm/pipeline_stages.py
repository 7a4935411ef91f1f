"""The four stages of the corpus pipeline: language, toxicity, near duplicates, packing.

Each takes (spark, docs, sf_dir) and returns what it keeps, with the columns of docs (packing: the pieces). Defined results for all: rows
without a doc_id are no documents and go; columns beyond doc_id and text pass through as they are; an empty table stays empty.
"""

from __future__ import annotations

import uuid

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from retro.llm.jaccard_join import JaccardJoin
from retro.llm.language_id import LanguageId
from retro.llm.packing import VectorBestFit
from retro.llm.runtime import checkpointed, fold, shared_dir, table
from retro.llm.toxicity import Toxicity


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that language ID rejects: no letter (null and empty texts among them), or too far from every language's centroids. Repeated rows
    are judged each; with nothing to learn from, all go."""
    return LanguageId().fit(docs, fold("doc_id", 3) != 1).accepted(docs)


def toxicity(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops the documents that are predicted to be toxic. Null and empty texts have the intercept's score; repeated rows are judged each; with labels of one
    class only, all documents get that class."""
    labels = table(spark, sf_dir, "labels").select("doc_id", F.col("toxic").alias("label"))
    return Toxicity().fit(docs, labels, fold("doc_id", 3) != 1).accepted(docs)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the least id of each group of near duplicates. Texts without words link with nothing and stay; of rows that repeat a
    doc_id, which are one document, one stays."""
    kept = JaccardJoin().join(docs).where("doc_id = component_id").groupBy("doc_id").agg((F.count("*") > 1).alias("again"))
    kept = checkpointed(kept)
    once = docs.join(kept.where("not again").select("doc_id"), "doc_id", "left_semi")
    again = kept.where("again").select("doc_id")
    return once if again.isEmpty() else once.unionByName(docs.join(again, "doc_id", "left_semi").dropDuplicates(["doc_id"]))


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Packs what is left into sequences of at most 1024 tokens. Null and empty texts are a piece with the end id alone; repeated rows are packed each."""
    return VectorBestFit(capacity=1024).pack(docs, public_tokenizers.path("byte_bpe_50k.json"), 2)


STAGES = [("language", language), ("toxicity", toxicity), ("near_duplicates", near_duplicates), ("packing", packing)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over `documents`; each result is written as Parquet in the shared folder and read again as the next stage's docs."""
    docs = table(spark, sf_dir, "documents")
    folder = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
    for name, stage in STAGES:
        stage(spark, docs, sf_dir).write.parquet(f"{folder}/{name}")
        docs = spark.read.parquet(f"{folder}/{name}")
    return docs
