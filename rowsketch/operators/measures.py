"""Accuracy and cost measures, and the certificate of a sketch."""

from __future__ import annotations

import statistics
import time
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from rowsketch.functions.vectors import vec_norm2
from rowsketch.operators import baselines
from rowsketch.operators.dist import vectors
from rowsketch.operators.sketch import Sketch, guarantee

#: Widest matrix whose covariance error is computed from the whole Gram.
EXACT_LIMIT = 4096


def cov_error_of(gram: np.ndarray, rows: np.ndarray) -> float:
    """||G(A) - G(B)||_2 / F2; the difference may have either sign."""
    f2 = float(np.trace(gram))
    return float(np.abs(np.linalg.eigvalsh(gram - rows.T @ rows)).max() / f2) if f2 else 0.0


def proj_error_of(gram: np.ndarray, rows: np.ndarray, k: int) -> tuple[float | None, float]:
    """||A - A V_k V_k^T||_F^2 over the best possible (None where that is nothing), and the numerator."""
    v = np.linalg.svd(rows, full_matrices=False)[2][:k].T if len(rows) else np.zeros((len(gram), 0))
    if len(rows):
        s = np.linalg.svd(rows, compute_uv=False)[:k]
        v = v[:, s > s[0] * 1e-12] if len(s) and s[0] > 0 else v[:, :0]
    f2 = float(np.trace(gram))
    top = f2 - float(np.einsum("ij,ij->", v, gram @ v))
    tail = float(np.sort(np.linalg.eigvalsh(gram))[::-1][k:].sum())
    return (top / tail if tail > 1e-9 * f2 else None), top


def cov_error(df: DataFrame, sk: Sketch, mode: str = "exact", rounds: int = 30, tol: float = 1e-4) -> float:
    if mode == "exact" and sk.d <= EXACT_LIMIT:
        return cov_error_of(baselines.gram_block(df, sk.d), sk.rows)
    return power_cov_error(df, sk, rounds, tol)


def power_cov_error(df: DataFrame, sk: Sketch, rounds: int = 30, tol: float = 1e-4, seed: int = 1) -> float:
    """Power iteration on G(A) - G(B): each round is one scan with a broadcast vector of d numbers."""
    rng = np.random.default_rng(seed)
    v = rng.standard_normal(sk.d)
    v /= np.linalg.norm(v)
    f2, found = 0.0, 0.0
    for _ in range(rounds):
        w, f2 = _gram_times(df, v)
        w -= sk.rows.T @ (sk.rows @ v)
        size = float(np.linalg.norm(w))
        if size == 0.0:
            return 0.0
        done = abs(size - found) <= tol * size
        v, found = w / size, size
        if done:
            break
    return found / f2 if f2 else 0.0


def _gram_times(df: DataFrame, v: np.ndarray) -> tuple[np.ndarray, float]:
    d = len(v)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        w, f2 = np.zeros(d), 0.0
        for rb in batches:
            x = vectors(rb.column(0), d)
            w += x.T @ (x @ v)
            f2 += float(np.einsum("ij,ij->", x, x))
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(d + 1), pa.int32()), pa.array(np.append(w, f2))], ["i", "w"])

    got = df.select("vec").mapInArrow(run, "i int, w double").groupBy("i").agg(F.sum("w").alias("w")).collect()
    out = np.zeros(d + 1)
    for r in got:
        out[r["i"]] = r["w"]
    return out[:d], float(out[d])


def projected_energy(df: DataFrame, bases: dict[str, np.ndarray], d: int) -> dict[str, float]:
    """||A V||_F^2 for several V (d x k) in one pass, and F2 under the key ''."""
    names = list(bases)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(len(names) + 1)
        for rb in batches:
            x = vectors(rb.column(0), d)
            total[-1] += float(np.einsum("ij,ij->", x, x))
            for i, n in enumerate(names):
                y = x @ bases[n]
                total[i] += float(np.einsum("ij,ij->", y, y))
        yield pa.RecordBatch.from_arrays([pa.array([*names, ""]), pa.array(total)], ["tag", "e"])

    got = df.select("vec").mapInArrow(run, "tag string, e double").groupBy("tag").agg(F.sum("e").alias("e")).collect()
    return {n: 0.0 for n in [*names, ""]} | {r["tag"]: r["e"] for r in got}


def proj_error(df: DataFrame, sk: Sketch, k: int, tail: float | None = None) -> tuple[float | None, float]:
    """As :func:`proj_error_of`, by Pythagoras in one pass; ``tail`` saves the exact Gram."""
    if tail is None:
        values = np.sort(np.linalg.eigvalsh(baselines.gram_block(df, sk.d)))[::-1]
        tail = float(np.maximum(values[k:], 0).sum())
    e = projected_energy(df, {"v": sk.directions(k)}, sk.d)
    top = e[""] - e["v"]
    return (top / tail if tail > 1e-9 * e[""] else None), top


def matrix_stats(df: DataFrame) -> DataFrame:
    """(n_rows, f2, max_norm2): one JVM aggregate."""
    w = vec_norm2("vec")
    return df.agg(F.count("*").alias("n_rows"), F.sum(w).alias("f2"), F.max(w).alias("max_norm2"))


def stable_rank(gram: np.ndarray) -> float:
    top = float(np.linalg.eigvalsh(gram)[-1])
    return float(np.trace(gram)) / top if top > 0 else 0.0


def certificate_rows(gram: np.ndarray, sk: Sketch, ks: list[int] | None = None, tol: float = 1e-9) -> list[tuple[str, int, float, float, bool]]:
    """(check, k, lhs, rhs, ok) of every property the method guarantees, from the exact Gram of the data."""
    f2 = float(np.trace(gram))
    slack = tol * max(f2, 1e-300)
    gap = np.linalg.eigvalsh(gram - sk.gram())
    values = np.maximum(np.sort(np.linalg.eigvalsh(gram))[::-1], 0)
    b2 = float(np.einsum("ij,ij->", sk.rows, sk.rows))
    out = [
        ("never_more", 0, float(gap[0]), 0.0, bool(gap[0] >= -slack)),
        ("never_less_than_shed", 0, float(gap[-1]), sk.shed, bool(gap[-1] <= sk.shed + slack)),
        ("shed_is_paid_for", 0, sk.ell * sk.shed, f2 - b2, bool(sk.ell * sk.shed <= f2 - b2 + slack)),
        ("totals_carried", 0, sk.f2, f2, bool(abs(sk.f2 - f2) <= 1e-6 * max(f2, 1e-300))),
        ("fewer_rows_than_ell", 0, float(len(sk.rows)), float(sk.ell), len(sk.rows) <= max(sk.ell - 1, 0) or len(sk.rows) <= sk.ell),
    ]
    for k in ks if ks is not None else range(0, min(sk.ell, len(values))):
        if k >= sk.ell:
            continue
        tail = float(values[k:].sum())
        out.append(("shed_within_tail", k, sk.shed, tail / (sk.ell - k), bool(sk.shed <= tail / (sk.ell - k) + slack)))
        error, top = proj_error_of(gram, sk.rows, k)
        bound = sk.ell / (sk.ell - k)
        out.append(("projection_within_bound", k, top, bound * tail, bool(top <= bound * tail + slack)))
    return out


def certificate(df: DataFrame, sk: Sketch, ks: list[int] | None = None) -> DataFrame:
    """The certificate as a DataFrame (check, k, lhs, rhs, ok)."""
    rows = certificate_rows(baselines.gram_block(df, sk.d), sk, ks)
    return df.sparkSession.createDataFrame(rows, "check string, k int, lhs double, rhs double, ok boolean")


def timed(fn: Callable[[], object], runs: int = 5) -> float:
    """Median wall seconds."""
    out = []
    for _ in range(runs):
        t = time.perf_counter()
        fn()
        out.append(time.perf_counter() - t)
    return statistics.median(out)


def update_seconds(state, rows: np.ndarray) -> np.ndarray:
    """Seconds of a kernel's update at each row."""
    each = np.empty(len(rows))
    for i in range(len(rows)):
        t = time.perf_counter()
        state.extend(rows[i : i + 1])
        each[i] = time.perf_counter() - t
    return each


def update_latency(make: Callable[[], object], rows: np.ndarray) -> dict[str, float]:
    """Seconds of a kernel's updates, row by row: amortised, median, 99th percentile and worst."""
    each = update_seconds(make(), rows)
    return {"mean": float(each.mean()), "p50": float(np.percentile(each, 50)), "p99": float(np.percentile(each, 99)), "max": float(each.max())}


def space_words(method: str, ell: int, d: int) -> int:
    return {"gram": d * d, "zero": 0, "paced": 4 * ell * d, "buffered": 2 * ell * d}.get(method, ell * d)


__all__ = ["certificate", "certificate_rows", "cov_error", "cov_error_of", "guarantee", "matrix_stats", "power_cov_error", "proj_error", "proj_error_of", "projected_energy", "space_words", "stable_rank", "timed", "update_latency"]
