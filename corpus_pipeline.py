"""A training-data pipeline over documents: language, exact copies, near copies, mixture, packing.

Every stage takes (spark, docs, sf_dir) and works on all rows that the one before it kept; all but the last return the
columns of documents. ``run`` writes each stage's rows and reads them again, so a lost executor costs one stage at most.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from stepgraph.llm import exact_dedup, langid, mixing, ngram_join, packing
from stepgraph.llm.common import Scratch
from stepgraph.llm.queries import CAPACITY, EPOCHS, SEED, WEIGHTS, tokenizer_files


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the language models know; what they reject goes."""
    model = langid.train(docs.where(~langid.held_out(F.col("doc_id"))))
    return langid.identify(docs, model).where("not rejected").select(*docs.columns)


def exact_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of equal texts the row with the largest id."""
    return exact_dedup.drop_duplicates(docs, keep="max")


def near_copies(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Of each group of linked texts the row with the smallest id."""
    return ngram_join.keep_one(docs)


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Rows as often as their source's target asks for."""
    return mixing.mixed_rows(docs, "doc_id", "text", "source", WEIGHTS, EPOCHS, SEED)


def sequences(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the documents' tokens and their places in training sequences."""
    return packing.pack(docs, "doc_id", "text", tokenizer_files(), end_id=1, capacity=CAPACITY)


STAGES = [("language", language), ("exact_copies", exact_copies), ("near_copies", near_copies), ("mixture", mixture), ("sequences", sequences)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch, docs = Scratch(spark), spark.read.parquet(f"{sf_dir}/documents.parquet")
    for _, stage in STAGES:
        new = scratch.keep(stage(spark, docs, sf_dir))
        scratch.drop(docs)
        docs = new
    return docs
