"""Stored sketches: packed rows in Parquet by view and period, answered by merging."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowsketch.kernel import packed
from rowsketch.operators.dist import FAN_IN, merge_tree
from rowsketch.shared import materialise


def write(sketches: DataFrame, path: str, view: str, period: str | None = None) -> None:
    """Adds packed sketches; ``period`` names the column of their periods (absent: one period, 'all')."""
    rows = sketches.select(F.lit(view).alias("view"), (F.col(period).cast("string") if period else F.lit("all")).alias("period"), *packed.NAMES)
    rows.write.mode("append").partitionBy("view", "period").parquet(path)


def read(spark: SparkSession, path: str, view: str, periods: list[str] | None = None) -> DataFrame:
    """Packed sketches; view and periods prune directories."""
    df = spark.read.parquet(path).where(F.col("view") == view)
    return df.where(F.col("period").cast("string").isin(periods)) if periods else df


def answer(spark: SparkSession, path: str, view: str, periods: list[str] | None = None, keys: list[str] | None = None, fan_in: int = FAN_IN) -> DataFrame:
    """The sketch of the union of stored parts, without reading the data they were made from."""
    parts = read(spark, path, view, periods)
    return merge_tree(spread(parts, n := max(1, parts.count())), keys=keys, fan_in=fan_in, tasks=n)


def spread(parts: DataFrame, n: int) -> DataFrame:
    """Packed sketches with places 0 .. n - 1, so that ``n`` of them merge about a fan-in at a time."""
    return parts.withColumn("pid", F.pmod(F.xxhash64("body"), F.lit(n)).cast("int"))


def cube(cells: DataFrame, keys: list[str], fan_in: int = FAN_IN) -> DataFrame:
    """Every grouping of ``keys`` from the finest cells by merging; a key that is grouped over is null.

    A cell is repeated 2^keys times, as in Spark's own cube, but cells are
    already one sketch a group.  ``grouping`` tells groups over a key from
    groups of a null.
    """
    cells = materialise(cells, "cells")
    n = max(1, cells.count())
    sets = []
    for bits in range(1 << len(keys)):
        kept = [F.when(F.lit(bool(bits >> i & 1)), F.lit(None)).otherwise(F.col(k)).alias(k) for i, k in enumerate(keys)]
        sets.append(F.struct(*kept, F.lit(bits).alias("grouping")))
    wide = cells.select(F.explode(F.array(*sets)).alias("c"), *packed.NAMES).select("c.*", *packed.NAMES)
    return merge_tree(spread(wide, n), keys=[*keys, "grouping"], fan_in=fan_in, tasks=n)
