"""Synthetic matrices: signal plus noise, and the adversarial instances of the lower bounds.

Gaussians come from a counter-based generator on (seed, row, column), so the
data do not depend on how rows are dealt to tasks.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowsketch.operators.baselines import uniforms

#: Greatest value of 2x sqrt(1 - x^2) - x^2 on [0, 1].
ZETA = 2 / math.sqrt(5) + math.sqrt(5) / 10 - 0.5
ZETA_AT = math.sqrt(0.5 - math.sqrt(5) / 10)


def gaussians(rows: np.ndarray, first: int, count: int, seed: int) -> np.ndarray:
    """Standard normal numbers for columns first .. first + count - 1 of the given rows (Box-Muller, both halves used)."""
    pairs = -(-count // 2)
    slots = (np.uint64(2 * first) + 2 * np.arange(pairs, dtype=np.uint64))[None, :]
    u = uniforms(rows[:, None], slots, seed)
    w = uniforms(rows[:, None], slots + np.uint64(1), seed)
    r = np.sqrt(-2 * np.log(u))
    return np.stack([r * np.cos(2 * np.pi * w), r * np.sin(2 * np.pi * w)], axis=2).reshape(len(rows), 2 * pairs)[:, :count]


def signal_space(m: int, d: int, seed: int) -> np.ndarray:
    """m orthonormal rows in d dimensions."""
    rng = np.random.default_rng(seed)
    return np.linalg.qr(rng.standard_normal((d, m)))[0].T


def signal_block(rows: np.ndarray, d: int, m: int, noise_div: float, seed: int, space: np.ndarray | None = None) -> np.ndarray:
    """Rows of S D U + N / noise_div with D falling from 1 in steps of 1 / m."""
    space = signal_space(m, d, seed) if space is None else space
    weights = 1.0 - np.arange(m) / m
    return (gaussians(rows, 0, m, seed) * weights) @ space + gaussians(rows, 1_000_000, d, seed) / noise_div


def signal_noise(spark: SparkSession, n: int = 10_000, d: int = 1000, m: int = 10, noise_div: float = 10.0, seed: int = 1, partitions: int | None = None, carrier: DataFrame | None = None) -> DataFrame:
    """The view (row_id, vec); ``carrier`` with a ``row_id`` column gives the rows instead of 0 .. n - 1."""
    rows = carrier.select("row_id") if carrier is not None else spark.range(0, n, 1, partitions or max(1, min(200, n // 2000))).select(F.col("id").alias("row_id"))
    space = signal_space(m, d, seed)

    step = max(1, min(1024, 4_000_000 // d))  # rows made at once

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rb in batches:
            for at in range(0, rb.num_rows, step):
                part = rb.slice(at, step)
                x = signal_block(part.column(0).to_numpy(), d, m, noise_div, seed, space)
                offsets = pa.array(np.arange(0, (len(x) + 1) * d, d, dtype=np.int32))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(offsets, pa.array(x.ravel()))], ["row_id", "vec"])

    return rows.mapInArrow(run, "row_id long, vec array<double>")


def block_instance(k: int, r: int, d: int, seed: int = 1) -> np.ndarray:
    """r rows [I, R], R of signs over sqrt(d - r), above k of those coordinates' unit rows; F2 = 2r + k."""
    rng = np.random.default_rng(seed)
    signs = rng.choice([-1.0, 1.0], (r, d - r)) / math.sqrt(d - r)
    top = np.concatenate([np.eye(r), signs], axis=1)
    chosen = rng.choice(r, k, replace=False)
    bottom = np.zeros((k, d))
    bottom[np.arange(k), chosen] = 1.0
    return np.concatenate([top, bottom])


def decode_signs(rows: np.ndarray, k: int, r: int, chosen: int) -> np.ndarray:
    """Signs of the R part of row ``chosen``, read off the projection on the leading k directions."""
    v = np.linalg.svd(rows, full_matrices=False)[2][:k].T
    e = np.zeros(rows.shape[1])
    e[chosen] = 1.0
    return np.sign(v @ (v.T @ e))[r:]


def projection_instance(ell: int, d: int, seed: int = 1) -> np.ndarray:
    """ell / 4 orthonormal rows."""
    return signal_space(max(1, ell // 4), d, seed)


def binary_instance(k: int, d: int, seed: int = 1) -> np.ndarray:
    """k rows of zeros and ones."""
    return np.random.default_rng(seed).integers(0, 2, (k, d)).astype(float)


def pair_instance(v: np.ndarray) -> np.ndarray:
    """[e + v; e] for a unit v orthogonal to the unit e."""
    e = np.zeros(len(v) + 1)
    e[0] = 1.0
    w = np.concatenate([[0.0], v])
    return np.stack([e + w, e])


def primitive(x: float) -> np.ndarray:
    """The 2 x 2 matrix [1, x; 1, 0]."""
    return np.array([[1.0, x], [1.0, 0.0]])


def register_source(spark: SparkSession) -> None:
    """spark.read.format('signal_noise').option('n', ...): the same rows through the data source interface."""
    from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

    class Span(InputPartition):
        def __init__(self, lo: int, hi: int):
            self.lo, self.hi = lo, hi

    class Reader(DataSourceReader):
        def __init__(self, options):
            get = lambda k, default: type(default)(options.get(k, default))
            self.n, self.d, self.m = get("n", 10_000), get("d", 1000), get("m", 10)
            self.noise, self.seed, self.parts = get("noise_div", 10.0), get("seed", 1), get("partitions", 8)

        def partitions(self):
            edges = [self.n * i // self.parts for i in range(self.parts + 1)]
            return [Span(a, b) for a, b in zip(edges, edges[1:]) if b > a]

        def read(self, span):
            from rowsketch.sources.datagen import signal_block, signal_space

            space = signal_space(self.m, self.d, self.seed)
            for at in range(span.lo, span.hi, 1024):
                ids = np.arange(at, min(at + 1024, span.hi))
                x = signal_block(ids, self.d, self.m, self.noise, self.seed, space)
                yield pa.RecordBatch.from_arrays([pa.array(ids), pa.array(list(x), pa.list_(pa.float64()))], ["row_id", "vec"])

    class SignalNoise(DataSource):
        @classmethod
        def name(cls):
            return "signal_noise"

        def schema(self):
            return "row_id long, vec array<double>"

        def reader(self, schema):
            return Reader(self.options)

    spark.dataSource.register(SignalNoise)
