"""A corpus pipeline over the training-data operators.

quality classifier, line dedup, SimHash near-dedup, mixing to target weights,
packing.  Each stage works on all that its predecessor kept.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowsketch.llm import line_dedup, mixing, packing, quality_classifier, simhash
from rowsketch.llm.common import named
from rowsketch.llm.queries import tokenizer_path
from rowsketch.shared import materialise

#: No stage but the mixing can be said in SQL; the tests hold the others against brute force.
ORACLE_SQL = None


def quality(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Documents that the classifier rejects go; the others stay as they are."""
    return quality_classifier.keep_good(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))


def lines(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Later repeats of runs of lines leave the texts; n_chars follows."""
    kept = line_dedup.dedup_lines(docs)
    return kept.select(*[F.length("text").cast("long").alias(c) if c == "n_chars" else named(c) for c in kept.columns])


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """One document of each group stays; five-word similarity of 0.8 or more makes a group."""
    return simhash.keep_similar(docs)


def mix(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """A row for each copy that the mix takes."""
    return mixing.mix(docs, weight=mixing.length_odds())


def pack(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pieces of packed sequences, with their token ids."""
    return packing.pack_documents(docs, tokenizer_path(), with_ids=True)


STAGES = [("quality_classifier", quality), ("line_dedup", lines), ("simhash_near_dedup", near_duplicates), ("mixing", mix), ("packing", pack)]


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written to the shared folder and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES:
        docs = materialise(stage(spark, docs, sf_dir), name)
    return docs
