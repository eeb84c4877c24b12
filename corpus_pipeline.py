"""Corpus pipeline: language, repeated lines, near copies, source mix, packing.

Each stage takes all rows that the one before it kept; all but the last return the columns of ``documents``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from worldfold.llm import langid, linededup, mixing, packing, simhash
from worldfold.llm.common import cut, small


def language_id(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents whose language is identified; the others (a few) go."""
    h = F.xxhash64("text")
    judged = langid.posteriors(docs.withColumn("__row", F.struct(F.col("doc_id").alias("k"), h.alias("h"))), key="__row")
    go = cut(judged.where(~F.col("kept")).select("__row.k", F.col("__row.h").alias("__h")).distinct())
    same = F.col("doc_id").eqNullSafe(F.col("k")) & (F.col("__hash") == F.col("__h"))
    return docs.withColumn("__hash", h).join(small(go), same, "left_anti").select(*docs.columns)


def line_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Boilerplate lines of each source are taken out; n_chars follows the text."""
    out = linededup.dedup(docs).withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType))
    return out.select(*docs.columns)


def near_dedup(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group of exact and near copies stays."""
    return simhash.keep_one(docs)


def mix_sources(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents as often as the mix takes them."""
    return mixing.mixed_documents(docs)


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of the mixed documents in sequences of 2048 tokens."""
    return packing.pack(docs)


STAGES = [("language_id", language_id), ("line_dedup", line_dedup), ("near_dedup", near_dedup), ("mix_sources", mix_sources), ("pack", pack)]

#: Tokenizing and near copies are not SQL; tests hold the stages against brute-force versions.
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = stage(spark, docs, sf_dir)
        if name != STAGES[-1][0]:
            docs = cut(docs)
    return docs
