"""Approximate item counts: local counter summaries, their merge tree, and checks by a second pass."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rowsketch.kernel.counters import CounterState
from rowsketch.operators.dist import FAN_IN, partitions_of, rounds_for
from rowsketch.operators.sketch import Sketch, ell_for_heavy

SCHEMA = "pid int, ell int, n long, shed long, items array<string>, counts array<long>"


def _batch(pid: int, s: CounterState) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays(
        [pa.array([pid], pa.int32()), pa.array([s.ell], pa.int32()), pa.array([s.n], pa.int64()), pa.array([s.shed], pa.int64()), pa.array([list(s.counts)], pa.list_(pa.string())), pa.array([list(s.counts.values())], pa.list_(pa.int64()))],
        ["pid", "ell", "n", "shed", "items", "counts"],
    )


def summarise(df: DataFrame, item: str, ell: int, *, precount: bool = True, fan_in: int = FAN_IN) -> DataFrame:
    """One packed counter summary of a column.

    ``precount`` counts each Arrow batch first and adds the counts at once
    (same bounds, fewer steps); without it items go in one after the other.
    Null items are left out.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        s = CounterState(ell)
        for rb in batches:
            if precount:
                for at in range(0, rb.num_rows, 100_000):
                    pairs = rb.column(0).slice(at, 100_000).value_counts()
                    s.add_counts(dict(zip(pairs.field(0).to_pylist(), pairs.field(1).to_pylist())))
            else:
                s.extend(rb.column(0).to_pylist())
        if s.n:
            yield _batch(TaskContext.get().partitionId(), s)

    column = df.select(F.col(item).cast("string").alias("item")).where("item is not null")
    return merge_tree(column.mapInArrow(run, SCHEMA), tasks=partitions_of(column), fan_in=fan_in)


def merge_tree(summaries: DataFrame, *, tasks: int, fan_in: int = FAN_IN) -> DataFrame:
    def merge(table: pa.Table) -> pa.Table:
        rows = sorted(table.to_pylist(), key=lambda r: r["pid"])
        s = CounterState(min(r["ell"] for r in rows))
        for r in rows:
            s.add_counts(dict(zip(r["items"], r["counts"])), r["n"], r["shed"])
        return pa.Table.from_batches([_batch(rows[0]["pid"] // fan_in, s)])

    rounds = rounds_for(tasks, fan_in)
    for r in range(rounds):
        group = F.lit(0) if r == rounds - 1 else F.floor(F.col("pid") / fan_in)
        summaries = summaries.groupBy(group.alias("g")).applyInArrow(merge, SCHEMA)
    return summaries


def in_order(df: DataFrame, item: str, order: list[str], ell: int) -> DataFrame:
    """The row-by-row summary in a given order; for short streams, as one task reads it all."""

    def run(batches):
        s = CounterState(ell)
        for rb in batches:
            s.extend(rb.column(rb.num_columns - 1).to_pylist())
        if s.n:
            yield _batch(0, s)

    return df.orderBy(*order).select(F.col(item).cast("string").alias("item")).coalesce(1).mapInArrow(run, SCHEMA)


def estimates(summary: DataFrame) -> DataFrame:
    """(item, low, high, n, shed)."""
    return summary.select("n", "shed", F.explode(F.arrays_zip("items", "counts")).alias("x")).select(F.col("x.items").alias("item"), F.col("x.counts").alias("low"), (F.col("x.counts") + F.col("shed")).alias("high"), "n", "shed")


def exact_counts(df: DataFrame, item: str) -> DataFrame:
    return df.select(F.col(item).cast("string").alias("item")).where("item is not null").groupBy("item").agg(F.count("*").alias("cnt"))


def exact_topk(df: DataFrame, item: str, k: int) -> DataFrame:
    return exact_counts(df, item).orderBy(F.desc("cnt"), "item").limit(k)


def tails(counts: DataFrame, most: int) -> DataFrame:
    """(k, tail): what the items beyond the k most frequent add up to, for k up to ``most``."""
    total = counts.agg(F.sum("cnt").alias("n"))
    top = counts.orderBy(F.desc("cnt"), "item").limit(most)
    ranked = top.select("cnt", F.row_number().over(Window.partitionBy(F.lit(0)).orderBy(F.desc("cnt"), "item")).alias("k"))
    running = ranked.select("k", F.sum("cnt").over(Window.partitionBy(F.lit(0)).orderBy("k")).alias("head"))
    return running.crossJoin(F.broadcast(total)).select("k", (F.col("n") - F.col("head")).alias("tail"))


def counter_bound(ell: int, k: int, tail: float) -> float:
    """Most an estimate can be too low, from the mass beyond the k most frequent items."""
    return tail / (ell - k)


def counter_error(df: DataFrame, item: str, summary: DataFrame) -> DataFrame:
    """One row: n, shed, least and greatest f - estimate, over all items."""
    exact = exact_counts(df, item)
    est = estimates(summary).select("item", "low")
    joined = exact.join(est, "item", "full_outer").select((F.coalesce("cnt", F.lit(0)) - F.coalesce("low", F.lit(0))).alias("gap"))
    gaps = joined.agg(F.min("gap").alias("least_gap"), F.max("gap").alias("greatest_gap"), F.avg("gap").alias("mean_gap"))
    return gaps.crossJoin(F.broadcast(summary.select("n", "shed", "ell")))


def topk_residual(df: DataFrame, item: str, summary: DataFrame, k: int) -> DataFrame:
    """n less the estimates of the k truly most frequent items, with the exact tail beyond them."""
    top = exact_topk(df, item, k)
    est = estimates(summary).select("item", "low")
    one = top.join(est, "item", "left").agg(F.sum("cnt").alias("head"), F.sum(F.coalesce("low", F.lit(0))).alias("kept"))
    return one.crossJoin(F.broadcast(summary.select("n", "ell"))).select((F.col("n") - F.col("kept")).alias("residual"), (F.col("n") - F.col("head")).alias("tail"), "ell")


def frequent_items(df: DataFrame, item: str, eps: float, verify: bool = True) -> DataFrame:
    """Items above eps * n.  Without ``verify`` candidates with bounds; with it, exact counts by a second pass.

    There are fewer than 1 / eps + 1 candidates, which bounds the broadcast.
    """
    summary = summarise(df, item, ell_for_heavy(eps))
    est = estimates(summary).where(F.col("high") > F.lit(eps) * F.col("n"))
    if not verify:
        return est
    found = df.select(F.col(item).cast("string").alias("item")).join(F.broadcast(est.select("item", "n")), "item")
    return found.groupBy("item", "n").agg(F.count("*").alias("cnt")).where(F.col("cnt") > F.lit(eps) * F.col("n")).select("item", "cnt", "n")


def to_sketch(summary: DataFrame, places: dict[str, int]) -> Sketch:
    """Counters as a row sketch: item j becomes sqrt(count) e_j."""
    r = summary.first()
    pairs = [(places[i], c) for i, c in zip(r["items"], r["counts"]) if i in places]
    rows = np.zeros((len(pairs), len(places)))
    for at, (j, c) in enumerate(sorted(pairs, key=lambda p: -p[1])):
        rows[at, j] = math.sqrt(c)
    return Sketch(rows, r["ell"], len(places), r["n"], float(r["n"]), float(r["shed"]))
