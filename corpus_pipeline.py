"""A corpus pipeline of five stages over documents: rules, language, near-duplicates, mixing, packing."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from seqnorm.llm import best_fit, dart_minhash, language_crf, quality_cascade, temperature_mix
from seqnorm.llm.common import scratch

COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")

#: A language that is this sure overrules the label, and the document goes as mislabelled; below the other, no language holds the text.
SURE, LEAST = 0.97, 0.4

#: The mixture's part of the tokens that come to it.
MIXED = 0.95


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that no rule of the cascade rejects."""
    return quality_cascade.keep_good(docs.select(*COLUMNS))


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents without text of a language, of no clear language, or surely of another than their label's go."""
    return language_crf.keep_clear(docs.select(*COLUMNS), language_crf.learn(docs), LEAST, SURE)


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each class of near-duplicates."""
    return dart_minhash.keep_one(docs).select(*COLUMNS)


def mixing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sources in tempered weights and without repeats, over MIXED of all tokens: the smallest exponent that asks no
    source for more than it holds, so that it is the largest sources that give documents up."""
    target = temperature_mix.Target(entropy=None, exponent=0.0, max_repeats=1.0, part=MIXED)
    return temperature_mix.mixed(docs, target).select(*COLUMNS)


def packing(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Sequences of 2048 tokens."""
    return best_fit.pack_documents(docs)


STAGES = [
    ("quality rules", quality),
    ("language ID", language),
    ("MinHash near-dedup", near_duplicates),
    ("mixing sources to target weights", mixing),
    ("best-fit packing", packing),
]

ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages; each result is written to the shared folder and read again as the next one's documents."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for k, (_, stage) in enumerate(STAGES):
        out = stage(spark, docs, sf_dir)
        if k == len(STAGES) - 1:
            return out
        path = scratch(spark, f"stage-{k}")
        out.write.parquet(path)
        docs = spark.read.parquet(path)
    return docs
