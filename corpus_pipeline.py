"""Corpus pipeline: documents to packed training sequences in five stages, each written as Parquet and read by the next."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from detspark.llm import lines, mixture, packing, quality, simhash
from detspark.plans.scratch import staged


#: runs with known token ids in a packing worker: fewer than by default, as workers outlive the stage and other stages need the memory
REMEMBERED = 100_000


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the quality classifier accepts; it learns from the rows of ``labels`` in its training folds.

    A null or empty text is scored by the bias alone.
    """
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality")
    cfg = quality.QualityConfig()
    fold = ~quality.held_out()
    return quality.accept(docs, quality.train(docs.where(fold), labels.where(fold), cfg), cfg)


def line_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """All documents, without lines that an earlier line matches; a text may become empty."""
    return lines.dedup(docs)


def simhash_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each near-duplicate group; texts without words are one group."""
    return simhash.keep_one(docs)


def mixture_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as the mix takes them: a text has the words of its taken blocks, repeats included; untaken ones go."""
    return mixture.mix_documents(docs)


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of documents with their token ids (``ids``) and their places in sequences; a null or empty text is the end id alone."""
    return packing.pack(packing.pieces(docs, packing.word_tokenizer(), with_ids=True, young=REMEMBERED))


STAGES = [
    ("quality", quality_stage),
    ("line_dedup", line_stage),
    ("simhash", simhash_stage),
    ("mixture", mixture_stage),
    ("packing", packing_stage),
]

#: training, hashing and packing by least squares are not SQL; tests hold the stages against brute-force versions
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = staged(stage(spark, docs, sf_dir), f"pipeline-{name}")
    return docs
