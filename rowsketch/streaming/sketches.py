"""Sketches of streams: one for all rows, for windows and sessions, and for each key.

Most go through a store: each micro-batch writes packed sketches under its
batch id, so a batch that is replayed overwrites its own rows, and what is
stored is merged when it is read, a batch's place in the merge tree being its
id.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from rowsketch.kernel import packed
from rowsketch.kernel.paced import PacedState
from rowsketch.kernel.shrink import ShrinkState
from rowsketch.operators import dist, items
from rowsketch.operators.dist import merge_tree
from rowsketch.shared import materialise


def timed(stream: DataFrame, ts: str, watermark: str) -> DataFrame:
    """The stream with its watermark; a time without a zone counts in the session's."""
    return stream.withColumn(ts, F.col(ts).cast("timestamp")).withWatermark(ts, watermark)


def run_available(df: DataFrame, checkpoint: str, each, mode: str = "append") -> None:
    """Feeds all data there is to ``each(batch, id)`` and stops; a second call goes on from the checkpoint."""
    q = df.writeStream.outputMode(mode).option("checkpointLocation", checkpoint).foreachBatch(each).trigger(availableNow=True).start()
    q.awaitTermination()


def _write(df: DataFrame, path: str, batch_id: int) -> None:
    df.write.mode("overwrite").parquet(f"{path}/batch={batch_id:010d}")


def _stored(spark: SparkSession, path: str, fields: list[T.StructField]) -> tuple[DataFrame, int]:
    """What the batches wrote, with ``pid`` the batch id, and how many batches there may be."""
    df = spark.read.schema(T.StructType([*fields, T.StructField("batch", T.LongType())])).option("basePath", path).parquet(f"{path}/batch=*")
    last = df.agg(F.max("batch")).first()[0]
    return df.withColumn("pid", F.col("batch").cast("int")).drop("batch"), int(last or 0) + 1


def global_sketch(stream: DataFrame, ell: int, d: int, path: str, checkpoint: str, **options) -> None:
    """Sketches each micro-batch, and writes one packed row for it under its batch id.

    A batch that is replayed overwrites its own row, so the store holds each
    row of the stream once.
    """
    run_available(stream, checkpoint, lambda batch, i: _write(dist.sketch(batch, ell, d=d, **options), path, i))


def read_global(spark: SparkSession, path: str, fan_in: int = dist.FAN_IN) -> DataFrame:
    """The sketch of all batches so far."""
    parts, n = _stored(spark, path, packed.FIELDS)
    return merge_tree(parts, fan_in=fan_in, tasks=n)


def compact(spark: SparkSession, path: str, to: str) -> None:
    """One row in place of all batches."""
    read_global(spark, path).write.mode("overwrite").parquet(to)


def panes(df: DataFrame, ts: str, length: str) -> DataFrame:
    """Adds ``pane``, the start of the tumbling window that a row falls in."""
    return df.withColumn("pane", F.window(ts, length)["start"])


def window_sketches(stream: DataFrame, ell: int, d: int, ts: str, pane: str, path: str, checkpoint: str, watermark: str | None = None, **options) -> None:
    """A packed row for each (pane, micro-batch).

    ``stream`` has the columns ts, row_id and vec.  With a ``watermark`` rows
    that are older, by more than it, than the latest time of the batches before
    theirs are dropped, and counted (:func:`late_rows`).
    """

    def each(batch: DataFrame, batch_id: int) -> None:
        batch = batch.withColumn(ts, F.col(ts).cast("timestamp"))
        if watermark:
            batch = _on_time(batch, batch_id, ts, watermark, path)
        keyed = panes(batch, ts, pane).select("pane", "row_id", "vec")
        _write(dist.sketch(keyed, ell, d=d, keys=["pane"], **options), path, batch_id)

    run_available(stream, checkpoint, each)


MARKS = "latest timestamp, n_late long, f2_late double"


def _on_time(batch: DataFrame, batch_id: int, ts: str, watermark: str, path: str) -> DataFrame:
    """The rows within the watermark; what is late, and the latest time so far, go to the marks of the store.

    A replayed batch reads the marks of the batches before it only.
    """
    spark = batch.sparkSession
    latest = None
    if batch_id:
        marks = spark.read.schema(MARKS + ", batch long").option("basePath", f"{path}/marks").parquet(f"{path}/marks/batch=*")
        latest = marks.where(F.col("batch") < batch_id).agg(F.max("latest").alias("latest")).first()["latest"]
    limit = (F.lit(latest) - F.expr(f"INTERVAL {watermark}")) if latest is not None else None
    late = F.coalesce(F.col(ts) < limit, F.lit(False)) if limit is not None else F.lit(False)
    energy = F.aggregate("vec", F.lit(0.0), lambda s, x: s + x * x)
    mark = batch.agg(F.greatest(F.max(ts), F.lit(latest).cast("timestamp")).alias("latest"), F.count(F.when(late, 1)).alias("n_late"), F.coalesce(F.sum(F.when(late, energy)), F.lit(0.0)).alias("f2_late"))
    _write(mark, f"{path}/marks", batch_id)
    return batch.where(~late)


def late_rows(spark: SparkSession, path: str) -> DataFrame:
    """(n_rows, f2) of what the watermark dropped."""
    return spark.read.schema(MARKS).parquet(f"{path}/marks/batch=*").agg(F.sum("n_late").alias("n_rows"), F.sum("f2_late").alias("f2"))


def tumbling(spark: SparkSession, path: str, fan_in: int = dist.FAN_IN) -> DataFrame:
    """One sketch for each pane."""
    parts, n = _stored(spark, path, [T.StructField("pane", T.TimestampType()), *packed.FIELDS])
    return merge_tree(parts, keys=["pane"], fan_in=fan_in, tasks=n)


def sliding(pane_sketches: DataFrame, length: int, pane_seconds: int, fan_in: int = dist.FAN_IN) -> DataFrame:
    """Windows of ``length`` panes, one starting at each pane: sketches cannot be subtracted, so panes are merged."""
    starts = F.expr(f"transform(sequence(0, {length - 1}), k -> pane - make_interval(0, 0, 0, 0, 0, 0, k * {pane_seconds}))")
    names = [c for c in packed.NAMES if c != "pid"]
    wide = pane_sketches.select(F.posexplode(starts).alias("pid", "window_start"), *names).select("window_start", *packed.NAMES)
    return merge_tree(wide, keys=["window_start"], fan_in=fan_in, tasks=length)


# sessions


def session_sketches(stream: DataFrame, ts: str, key: str, ell: int, d: int, gap_seconds: int, path: str, checkpoint: str) -> None:
    """Sketches by key and stretch of ``gap_seconds``, with each stretch's first and last time.

    Rows of one stretch are less than the gap apart, so they are of one
    session, and a key has a row for each stretch of time and not for each of
    its events.  ``stream`` has the columns ts, key, row_id and vec.
    """

    def each(batch: DataFrame, batch_id: int) -> None:
        rows = batch.withColumn(ts, F.col(ts).cast("timestamp"))
        keyed = rows.select(F.col(key).cast("string").alias("key"), F.floor(F.unix_seconds(ts) / gap_seconds).cast("long").alias("stretch"), ts, "row_id", "vec")
        _write(keyed.groupBy("key", "stretch").agg(F.min(ts).alias("first"), F.max(ts).alias("last")), f"{path}/times", batch_id)
        _write(dist.local_runs(keyed.drop(ts), ell, d=d, keys=["key", "stretch"]), path, batch_id)  # merged when they are read

    run_available(stream, checkpoint, each)


def sessions(spark: SparkSession, path: str, gap_seconds: int, fan_in: int = dist.FAN_IN) -> DataFrame:
    """(key, session_start, session_end, sketch columns): a session ends where nothing follows within the gap."""
    keys = [T.StructField("key", T.StringType()), T.StructField("stretch", T.LongType())]
    times = spark.read.schema("key string, stretch long, first timestamp, last timestamp").parquet(f"{path}/times/batch=*")
    times = times.groupBy("key", "stretch").agg(F.min("first").alias("first"), F.max("last").alias("last"))
    order = Window.partitionBy("key").orderBy("stretch")
    opens = times.select("*", F.coalesce(F.unix_micros("first") - F.unix_micros(F.lag("last").over(order)) > gap_seconds * 1_000_000, F.lit(True)).alias("opens"))
    numbered = opens.select("*", F.sum(F.col("opens").cast("int")).over(order).alias("nth"))
    whole = Window.partitionBy("key", "nth")
    dated = numbered.select("key", "stretch", F.min("first").over(whole).alias("session_start"), F.max("last").over(whole).alias("session_end"))
    parts, _ = _stored(spark, path, [*keys, *packed.FIELDS])
    ends = ["key", "session_start", "session_end"]
    place = F.row_number().over(Window.partitionBy(*ends).orderBy("stretch", "pid")) - 1
    joined = materialise(parts.join(dated, ["key", "stretch"]).withColumn("pid", place.cast("int")).drop("stretch"), "sessions")
    most = joined.agg(F.max("pid")).first()[0]
    return dist.merge_runs(joined, keys=ends, fan_in=fan_in, tasks=int(most or 0) + 1)


# by key, in the engine's own state

STATE = "ell int, d int, n_rows long, f2 double, shed double, shrinks long, live int, body binary, live2 int, body2 binary"


def keyed_sketches(stream: DataFrame, key: str, ell: int, d: int, variant: str = "buffered") -> DataFrame:
    """A stream of (key, n_rows, f2, shed, live, body, most_flops): each key's sketch after each micro-batch that touched it.

    A key's state is its live rows only.  With ``variant='paced'`` the work at
    every single row is bounded; ``most_flops`` is the most that one row of the
    batch took, and what a decomposition under way still lacks is done when
    the batch ends, so that the state between batches is rows and no more.
    """
    out = f"{key} string, n_rows long, f2 double, shed double, live int, body binary, most_flops long"

    def update(k, frames: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        paced = variant == "paced"
        s = PacedState(ell, d, trace=True) if paced else ShrinkState(ell, d, variant)
        if state.exists:
            _, _, n, f2, shed, shrinks, live, body, live2, body2 = state.get
            own = packed.body_rows(bytes(body), live, d)
            if paced:
                s.active[:live], s.live, s.other = own, live, packed.body_rows(bytes(body2), live2, d)
                s.n_rows, s.f2, s.shed, s.shrinks = n, f2, shed, shrinks
            else:
                s.merge(own, n, f2, shed, shrinks)
        for f in frames:
            if len(f):
                s.extend(np.stack(f["vec"].to_numpy()))
        if paced:
            s.settle()
        rows = (s.active if paced else s.rows)[: s.live]
        other = s.other if paced else np.zeros((0, d))
        pack = lambda x: np.ascontiguousarray(x, "<f8").tobytes()
        state.update((ell, d, s.n_rows, s.f2, s.shed, s.shrinks, len(rows), pack(rows), len(other), pack(other)))
        flops = max(s.flops, default=0) if paced else 0
        yield pd.DataFrame({key: [str(k[0])], "n_rows": [s.n_rows], "f2": [s.f2], "shed": [s.shed], "live": [len(rows) + len(other)], "body": [pack(other) + pack(rows)], "most_flops": [flops]})

    return stream.select(F.col(key).cast("string").alias(key), "vec").groupBy(key).applyInPandasWithState(update, out, STATE, "update", "NoTimeout")


def stream_counters(stream: DataFrame, item: str, ell: int, path: str, checkpoint: str) -> None:
    """A counter summary for each micro-batch under its batch id."""
    run_available(stream, checkpoint, lambda batch, i: _write(items.summarise(batch, item, ell), path, i))


def read_counters(spark: SparkSession, path: str) -> DataFrame:
    parts, n = _stored(spark, path, list(T._parse_datatype_string(items.SCHEMA)))
    return items.merge_tree(parts, tasks=n)


# built-in aggregates beside them


def window_energy(stream: DataFrame, ts: str, length: str, slide: str | None = None, watermark: str = "1 day") -> DataFrame:
    """Built-in aggregates by window: (window_start, n_rows, f2)."""
    w = F.window(ts, length, slide) if slide else F.window(ts, length)
    return timed(stream, ts, watermark).groupBy(w.alias("w")).agg(F.count("*").alias("n_rows"), F.sum(F.col("value") * F.col("value")).alias("f2")).select(F.col("w.start").alias("window_start"), "n_rows", "f2")


def session_energy(stream: DataFrame, ts: str, user: str, gap: str = "30 minutes", watermark: str = "1 day") -> DataFrame:
    w = F.session_window(ts, gap)
    return timed(stream, ts, watermark).groupBy(user, w.alias("w")).agg(F.count("*").alias("n_rows"), F.sum(F.col("value") * F.col("value")).alias("f2")).select(user, F.col("w.start").alias("session_start"), "n_rows", "f2")


def dedup_events(stream: DataFrame, ts: str, key: str, within: str = "1 hour") -> DataFrame:
    return timed(stream, ts, within).dropDuplicatesWithinWatermark([key])


def with_table(stream: DataFrame, table: DataFrame, on: str, key: str, how: str = "left") -> DataFrame:
    """A stream joined with a table that stands still: micro-batch by micro-batch, no state."""
    return stream.join(table, stream[on] == table[key], how).drop(table[key])
