"""A training corpus from documents: stages (name, function), each on all that the one before kept.

A function takes (spark, docs, sf_dir) and returns a DataFrame, which is written as Parquet and read again as the docs of the next.
All but the last return the columns of documents.
"""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ivsearch.llm import line_dedup, mixing, ngram_join, packing, quality_classifier
from ivsearch.llm.common import held, shared_dir, table


def good_quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Learns from labels outside the held-out fifth; documents scored under 0.3 go."""
    fold = held("doc_id", 5) != 0
    model = quality_classifier.train(docs.select("doc_id", "text").where(fold), table(spark, sf_dir, "labels").where(fold))
    return quality_classifier.classify(docs, model).where("predicted = 1").select(*docs.columns)


def fresh_lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeated lines go; a document of which nothing but blanks is left goes with them, n_chars follows the text."""
    out = line_dedup.dedup_lines(docs).where("n_copies + n_near = 0 or trim(translate(text, '\t\n\r', '   ')) <> ''")
    return out.withColumn("n_chars", F.when((F.col("n_copies") + F.col("n_near")) > 0, F.length("text").cast("long")).otherwise(F.col("n_chars"))).select(*docs.columns)


def one_of_each_group(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Five words, similarity of 0.8 or more: of each group the smallest id stays."""
    return ngram_join.drop_near_copies(docs)


def mixed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return mixing.mix(docs).withColumn("n_chars", F.length("text").cast("long"))


def packed(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs.select("doc_id", "text"))


STAGES = [
    ("quality classifier", good_quality),
    ("line dedup", fresh_lines),
    ("n-gram jaccard join", one_of_each_group),
    ("mixing", mixed),
    ("packing", packed),
]
#: SQL can express neither the classifier nor the packing; tests compare with brute force.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    for _, stage in STAGES:
        out = f"{shared_dir(spark)}/pipeline-{uuid.uuid4().hex}"
        stage(spark, docs, sf_dir).write.parquet(out)
        docs = spark.read.parquet(out)
    return docs
