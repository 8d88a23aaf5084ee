"""Sketching a matrix view with Spark: one pass of local kernels, then a merge tree.

A view has ``row_id long, vec array<double>`` (and optional key columns).
Filters and projections belong before :func:`sketch`: they then sit below the
Python node and reach the scan.  Each task turns its Arrow batches into one
packed row; merge rounds group ``fan_in`` packed rows at a time, so no task
reads more than that many sketches.  Nothing runs before the caller's action.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T
from pyspark.sql.pandas.types import to_arrow_type

from rowsketch.kernel import packed
from rowsketch.kernel.paced import PacedState
from rowsketch.kernel.shrink import ShrinkState

FAN_IN = 32
#: Taken for the number of tasks where the plan does not tell it.
MANY_TASKS = 1 << 20
#: Rows of sketches that a task holds for its keys before it hands them on.
STATE_BYTES = 256 << 20
#: Rows of sketches in one Arrow batch, in bytes.
BATCH_BYTES = 32 << 20


def vectors(column: pa.Array, d: int | None, on_bad_row: str = "error") -> np.ndarray:
    """A list column as an n x d block; rows that are null, of another length or not finite follow ``on_bad_row``."""
    n = len(column)
    if not n:
        return np.zeros((0, d or 0))
    if column.null_count == 0:
        lengths = column.value_lengths().to_numpy()
        width = d or int(lengths[0])
        flat = column.flatten()
        if (lengths == width).all() and flat.null_count == 0:
            block = flat.to_numpy(zero_copy_only=False).astype(np.float64, copy=False).reshape(n, width)
            good = np.isfinite(block).all(axis=1)
            if good.all():
                return block
            if on_bad_row == "error":
                raise ValueError("a vector holds a value that is not finite")
            return block[good] if on_bad_row == "skip" else np.where(np.isfinite(block), block, 0.0)
    if on_bad_row == "error":
        raise ValueError("a vector is null, holds a null, or has another length")
    rows = column.to_pylist()
    width = d or next((len(r) for r in rows if r), 0)
    out = []
    for r in rows:
        if on_bad_row == "skip":
            if r is not None and len(r) == width and all(x is not None and math.isfinite(x) for x in r):
                out.append(r)
        else:
            r = [x if x is not None and math.isfinite(x) else 0.0 for x in (r or [])]
            out.append((r + [0.0] * width)[:width])
    return np.array(out, np.float64).reshape(len(out), width)


def make_state(ell: int, d: int, variant: str, svd: str, buffer_factor: float):
    return PacedState(ell, d) if variant == "paced" else ShrinkState(ell, d, variant, svd, buffer_factor)


def partitions_of(df: DataFrame) -> int:
    """Most tasks that ``df`` can run with; no job runs.

    Below a shuffle the count is that of the topmost exchange, which run time
    may only lower.  A plan of files is asked for its splits.  Where neither
    tells, as for a union over shuffles, the answer is generous: a merge round
    too many moves one sketch, a round too few would move all to one task.
    """
    plan = df._jdf.queryExecution()
    text = plan.executedPlan().toString()
    if "Exchange" not in text:
        return max(1, int(plan.toRdd().getNumPartitions()))
    dealt = re.search(r"RoundRobinPartitioning\((\d+)\)|partitioning\([^\n]*?, (\d+)\)", text)
    if not dealt or "Union" in text:
        return MANY_TASKS
    return int(dealt.group(1) or dealt.group(2))


def layout(df: DataFrame, order: str, partitions: int | None = None) -> DataFrame:
    """'as_is' takes the scan's splits; 'stable' deals rows by id and orders them, so results repeat bit for bit."""
    if order == "as_is":
        return df
    if order != "stable":
        raise ValueError(f"unknown order {order!r}")
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return df.repartition(n, "row_id").sortWithinPartitions("row_id", "vec")


def sketch(
    df: DataFrame,
    ell: int,
    *,
    d: int | None = None,
    variant: str = "buffered",
    keys: list[str] | None = None,
    fan_in: int = FAN_IN,
    order: str = "as_is",
    partitions: int | None = None,
    buffer_factor: float = 2.0,
    svd: str = "auto",
    transport: str = "float64",
    on_bad_row: str = "error",
) -> DataFrame:
    """The packed shrink sketch of a view, one row for each combination of ``keys`` (one in all without)."""
    partial = local_sketches(layout(df, order, partitions), ell, d=d, variant=variant, keys=keys, buffer_factor=buffer_factor, svd=svd, transport=transport, on_bad_row=on_bad_row)
    tasks = partitions if order == "stable" and partitions else partitions_of(df)
    return merge_tree(partial, keys=keys, fan_in=fan_in, tasks=tasks, transport=transport, svd=svd)


def grouped(columns: list[pa.Array], n: int) -> Iterator[tuple[tuple, np.ndarray | None]]:
    """The distinct keys of a batch and the rows of each; columns are compared by code, only distinct keys become Python values."""
    if not columns:
        yield (), None
        return
    codes = np.zeros(n, np.int64)
    for c in columns:
        own = c.dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False).astype(np.int64)
        codes = np.unique(codes * (int(own.max()) + 1) + own, return_inverse=True)[1]
    order = np.argsort(codes, kind="stable")
    for at in np.split(order, np.flatnonzero(np.diff(codes[order])) + 1):
        yield tuple(c[int(at[0])].as_py() for c in columns), at


def local_sketches(df: DataFrame, ell: int, *, d: int | None = None, variant: str = "buffered", keys: list[str] | None = None, buffer_factor: float = 2.0, svd: str = "auto", transport: str = "float64", on_bad_row: str = "error") -> DataFrame:
    """A packed row for each task (and key) that saw rows; with very many keys a task hands on a key's sketch more than once."""
    keys = list(keys or [])
    schema = T.StructType([df.schema[k] for k in keys] + packed.FIELDS)
    kinds = [to_arrow_type(df.schema[k].dataType) for k in keys]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states: dict[tuple, object] = {}
        pid = TaskContext.get().partitionId()

        def hand_on() -> Iterator[pa.RecordBatch]:
            names, rows, size = [], [], 0
            for key, s in states.items():
                names.append(key)
                rows.append(packed.row(pid, s, s.finish(), transport))
                size += len(rows[-1][-1])
                if size >= BATCH_BYTES:
                    yield packed.batch(rows, names, keys, kinds)
                    names, rows, size = [], [], 0
            if rows:
                yield packed.batch(rows, names, keys, kinds)
            states.clear()

        for rb in batches:
            if not rb.num_rows:
                continue
            column = rb.column(rb.num_columns - 1)
            for key, at in grouped(rb.columns[: len(keys)], rb.num_rows):
                state = states.get(key)
                block = vectors(column if at is None else column.take(pa.array(at)), state.d if state else d, on_bad_row)
                if not len(block):
                    continue
                if state is None:
                    state = states[key] = make_state(ell, block.shape[1], variant, svd, buffer_factor)
                state.extend(block)
            if keys and sum(s.held_bytes for s in states.values()) > STATE_BYTES:
                yield from hand_on()
        yield from hand_on()

    return df.select(*keys, "vec").mapInArrow(run, schema)


def merge_packed(rows: list[dict], svd: str = "auto") -> tuple[ShrinkState, np.ndarray]:
    """Packed rows (as dicts) of disjoint data, in the order of their pid, as one sketch.

    Sketches of different ell merge at the least of them; different widths are
    an error.
    """
    rows = sorted(rows, key=lambda r: r["pid"])
    if len({r["d"] for r in rows}) != 1:
        raise ValueError("sketches of different width cannot be merged")
    state = ShrinkState(min(r["ell"] for r in rows), rows[0]["d"], svd=svd)
    for r in rows:
        state.merge(packed.body_rows(r["body"], r["live"], r["d"]), r["n_rows"], r["f2"], r["shed"], r["shrinks"])
    return state, state.finish()


def rounds_for(tasks: int, fan_in: int) -> int:
    """Rounds until ``tasks`` results are one, ``fan_in`` at a time."""
    rounds, left = 1, -(-tasks // fan_in)
    while left > 1:
        rounds, left = rounds + 1, -(-left // fan_in)
    return rounds


def merge_tree(sketches: DataFrame, *, keys: list[str] | None = None, fan_in: int = FAN_IN, tasks: int | None = None, transport: str = "float64", svd: str = "auto") -> DataFrame:
    """Packed sketches to one for each key, ``fan_in`` at a time.

    ``tasks`` is how many there may be to a key; it sets the number of rounds.
    """
    keys = list(keys or [])
    rounds = rounds_for(tasks or partitions_of(sketches), fan_in)
    schema = T.StructType([sketches.schema[k] for k in keys] + packed.FIELDS)
    kinds = [to_arrow_type(sketches.schema[k].dataType) for k in keys]
    for r in range(rounds):
        last = r == rounds - 1
        group = F.lit(0) if last else F.floor(F.col("pid") / F.lit(fan_in)).cast("int")

        def merge(table: pa.Table) -> pa.Table:
            rows = table.select(packed.NAMES).to_pylist()
            state, body = merge_packed(rows, svd)
            key = [tuple(table.column(k)[0].as_py() for k in keys)]
            return pa.Table.from_batches([packed.batch([packed.row(table.column("_group")[0].as_py(), state, body, transport)], key, keys, kinds)])

        sketches = sketches.withColumn("_group", group).groupBy(*keys, "_group").applyInArrow(merge, schema)
    return sketches


def _runs(columns: list[pa.Array], n: int) -> np.ndarray:
    """Where runs of equal keys begin, and ``n``; columns are compared by code."""
    differ = np.zeros(n, bool)
    differ[0] = True
    for c in columns:
        own = c.dictionary_encode(null_encoding="encode").indices.to_numpy(zero_copy_only=False)
        differ[1:] |= own[1:] != own[:-1]
    return np.append(np.flatnonzero(differ), n)


def local_runs(df: DataFrame, ell: int, *, d: int, keys: list[str], svd: str = "auto", on_bad_row: str = "error") -> DataFrame:
    """As :func:`local_sketches`, for keys that may be as many as the rows.

    A task sorts its rows by key, so it holds one state at a time; the sketches
    of keys with one row in the task are packed a batch at a time.
    """
    schema = T.StructType([df.schema[k] for k in keys] + packed.FIELDS)
    kinds = [to_arrow_type(df.schema[k].dataType) for k in keys]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pid = TaskContext.get().partitionId()
        name, state = None, None  # the run that the last batch broke off in

        for rb in batches:
            if not rb.num_rows:
                continue
            own, column = rb.columns[:-1], rb.column(rb.num_columns - 1)
            edges = _runs(own, rb.num_rows)
            whole = vectors(column, d, on_bad_row)
            kept = len(whole) == rb.num_rows  # with rows left out, each run is looked at by itself
            single = np.flatnonzero((np.diff(edges) == 1)[:-1]) if kept and ell > 1 else np.zeros(0, np.int64)
            if len(single) and single[0] == 0 and name is not None:
                single = single[1:]  # may go on with the last batch's run
            alone = np.zeros(len(edges) - 1, bool)
            alone[single] = True
            done = []
            for k in np.flatnonzero(~alone):
                at, to = int(edges[k]), int(edges[k + 1])
                key = tuple(c[at].as_py() for c in own)
                if key != name:
                    if state is not None:
                        done.append((name, packed.row(pid, state, state.finish())))
                    name, state = key, None
                block = whole[at:to] if kept else vectors(column.slice(at, to - at), d, on_bad_row)
                if len(block):
                    state = state or ShrinkState(ell, d, svd=svd)
                    state.extend(block)
            if done:
                yield packed.batch([row for _, row in done], [key for key, _ in done], keys, kinds)
            if len(single):
                at = edges[single]
                yield packed.ones(pid, ell, whole[at], [c.take(pa.array(at)) for c in own], keys)
        if state is not None:
            yield packed.batch([packed.row(pid, state, state.finish())], [name], keys, kinds)

    return df.select(*keys, "vec").sortWithinPartitions(*keys).mapInArrow(run, schema)


def merge_runs(sketches: DataFrame, *, keys: list[str], fan_in: int = FAN_IN, tasks: int | None = None, svd: str = "auto") -> DataFrame:
    """As :func:`merge_tree`, for very many keys: groups are runs of sorted rows, and a group of one row passes as it is."""
    rounds = rounds_for(tasks or partitions_of(sketches), fan_in)
    schema = T.StructType([sketches.schema[k] for k in keys] + packed.FIELDS)
    kinds = [to_arrow_type(sketches.schema[k].dataType) for k in keys]
    width = len(keys)

    def merged(pieces: list[pa.RecordBatch]) -> tuple[tuple, tuple]:
        rows = [r for p in pieces for r in p.select(packed.NAMES).to_pylist()]
        state, body = merge_packed(rows, svd)
        return tuple(pieces[0].column(k)[0].as_py() for k in range(width)), packed.row(pieces[0].column("_group")[0].as_py(), state, body)

    def passed(rb: pa.RecordBatch) -> pa.RecordBatch:
        return pa.RecordBatch.from_arrays([rb.column("_group") if n == "pid" else rb.column(n) for n in [*keys, *packed.NAMES]], [*keys, *packed.NAMES])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[pa.RecordBatch] = []  # slices of the run that the last batch broke off in
        own = lambda rb: tuple(rb.column(k)[0].as_py() for k in range(width + 1))

        def closed(pieces: list[pa.RecordBatch]) -> pa.RecordBatch:
            if sum(p.num_rows for p in pieces) == 1:
                return passed(pieces[0])
            key, row = merged(pieces)
            return packed.batch([row], [key], keys, kinds)

        for rb in batches:
            if not rb.num_rows:
                continue
            edges = _runs(rb.columns[: width + 1], rb.num_rows)
            first, last = rb.slice(0, int(edges[1])), rb.slice(int(edges[-2]))
            if held and own(held[0]) == own(first):
                held.append(first)
                edges = edges[1:]
            if len(edges) == 1:
                continue
            if held:
                yield closed(held)
            held = [last]
            sizes = np.diff(edges)[:-1]
            one = edges[:-2][sizes == 1]
            if len(one):
                yield passed(rb.take(pa.array(one)))
            many = [merged([rb.slice(at, n)]) for at, n in zip(edges[:-2][sizes > 1].tolist(), sizes[sizes > 1].tolist())]
            if many:
                yield packed.batch([row for _, row in many], [key for key, _ in many], keys, kinds)
        if held:
            yield closed(held)

    for r in range(rounds):
        group = F.lit(0) if r == rounds - 1 else F.floor(F.col("pid") / F.lit(fan_in)).cast("int")
        dealt = sketches.select(*keys, group.alias("_group"), *packed.NAMES).repartition(*keys, "_group")
        sketches = dealt.sortWithinPartitions(*keys, "_group", "pid").mapInArrow(run, schema)
    return sketches


def sketch_rows(sketches: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """Packed sketches as rows (keys, row_no, sigma, vec)."""
    keys = list(keys or [])
    schema = T.StructType([sketches.schema[k] for k in keys] + [T.StructField("row_no", T.IntegerType()), T.StructField("sigma", T.DoubleType()), T.StructField("vec", T.ArrayType(T.DoubleType()))])
    kinds = [to_arrow_type(sketches.schema[k].dataType) for k in keys]

    def run(batches):
        for rb in batches:
            out = []
            for r in rb.to_pylist():
                rows = packed.body_rows(r["body"], r["live"], r["d"])
                out += [(*[r[k] for k in keys], i, float(np.sqrt(v @ v)), v.tolist()) for i, v in enumerate(rows)]
            types = [*kinds, pa.int32(), pa.float64(), pa.list_(pa.float64())]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out) if out else [[]] * len(types), types)], [*keys, "row_no", "sigma", "vec"])

    return sketches.select(*keys, *packed.NAMES).mapInArrow(run, schema)


def sketch_gram(sketches: DataFrame, keys: list[str] | None = None) -> DataFrame:
    """(keys, i, j, g, n_rows): the Gram matrix of each sketch, i <= j."""
    keys = list(keys or [])
    schema = T.StructType([sketches.schema[k] for k in keys] + [T.StructField("i", T.IntegerType()), T.StructField("j", T.IntegerType()), T.StructField("g", T.DoubleType()), T.StructField("n_rows", T.LongType())])
    kinds = [to_arrow_type(sketches.schema[k].dataType) for k in keys]

    def run(batches):
        for rb in batches:
            for r in rb.to_pylist():
                rows = packed.body_rows(r["body"], r["live"], r["d"])
                i, j = np.triu_indices(r["d"])
                g = (rows.T @ rows)[i, j]
                cols = [pa.array([r[k]] * len(g), t) for k, t in zip(keys, kinds)]
                yield pa.RecordBatch.from_arrays([*cols, pa.array(i.astype(np.int32)), pa.array(j.astype(np.int32)), pa.array(g), pa.array([r["n_rows"]] * len(g), pa.int64())], [*keys, "i", "j", "g", "n_rows"])

    return sketches.select(*keys, *packed.NAMES).mapInArrow(run, schema)
