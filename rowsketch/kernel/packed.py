"""Sketches as rows: the packed schema and its conversion to kernel states."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import types as T

FIELDS = [
    T.StructField("pid", T.IntegerType()),
    T.StructField("ell", T.IntegerType()),
    T.StructField("d", T.IntegerType()),
    T.StructField("n_rows", T.LongType()),
    T.StructField("f2", T.DoubleType()),
    T.StructField("shed", T.DoubleType()),
    T.StructField("shrinks", T.LongType()),
    T.StructField("live", T.IntegerType()),
    T.StructField("body", T.BinaryType()),
]
SCHEMA = T.StructType(FIELDS)
NAMES = [f.name for f in FIELDS]
_KINDS = [pa.int32(), pa.int32(), pa.int32(), pa.int64(), pa.float64(), pa.float64(), pa.int64(), pa.int32(), pa.binary()]


def row(pid: int, state, rows: np.ndarray, transport: str = "float64") -> tuple:
    body = np.ascontiguousarray(rows, "<f4" if transport == "float32" else "<f8").tobytes()
    return (pid, state.ell, state.d, state.n_rows, state.f2, state.shed, state.shrinks, len(rows), body)


def batch(rows: list[tuple], keys: list[tuple] | None = None, key_names: list[str] = (), key_types: list = ()) -> pa.RecordBatch:
    columns, names = [], []
    for k, name in enumerate(key_names):
        columns.append(pa.array([x[k] for x in keys or []], key_types[k]))
        names.append(name)
    columns += [pa.array(c, t) for c, t in zip(zip(*rows) if rows else [[]] * len(_KINDS), _KINDS)]
    return pa.RecordBatch.from_arrays(columns, names + NAMES)


def ones(pid: int, ell: int, rows: np.ndarray, keys: list[pa.Array], key_names: list[str]) -> pa.RecordBatch:
    """Sketches (of ell above 1) of one row each, as :func:`batch` of their finished states has them."""
    n, d = rows.shape
    lead = rows[np.arange(n), np.abs(rows).argmax(axis=1)]
    live = (lead != 0).astype(np.int32)
    body = np.ascontiguousarray((rows * np.where(lead < 0, -1.0, 1.0)[:, None])[live > 0], "<f8")
    offsets = np.concatenate([[0], np.cumsum(live, dtype=np.int64)]) * (8 * d)
    bodies = pa.Array.from_buffers(pa.binary(), n, [None, pa.py_buffer(offsets.astype(np.int32)), pa.py_buffer(body)])
    same = lambda x, kind: pa.array(np.full(n, x), kind)
    columns = [same(pid, pa.int32()), same(ell, pa.int32()), same(d, pa.int32()), same(1, pa.int64()), pa.array(np.einsum("ij,ij->i", rows, rows)), same(0.0, pa.float64()), same(0, pa.int64()), pa.array(live), bodies]
    return pa.RecordBatch.from_arrays([*keys, *columns], [*key_names, *NAMES])


def body_rows(body: bytes, live: int, d: int) -> np.ndarray:
    """The rows of a body; four or eight bytes a value, told by its length."""
    kind = "<f4" if live and len(body) == 4 * live * d else "<f8"
    return np.frombuffer(body, kind).reshape(live, d).astype(np.float64)
