"""A finished sketch on the driver (ell x d numbers) and what it answers without another pass."""

from __future__ import annotations

import math
from dataclasses import dataclass, replace
from fractions import Fraction

import numpy as np
from pyspark.sql import DataFrame

from rowsketch.kernel import packed
from rowsketch.kernel.shrink import ShrinkState
from rowsketch.operators.dist import merge_packed


@dataclass
class Sketch:
    rows: np.ndarray
    ell: int
    d: int
    n_rows: int
    f2: float
    shed: float
    shrinks: int = 0

    @classmethod
    def from_row(cls, r) -> Sketch:
        r = r.asDict() if hasattr(r, "asDict") else r
        return cls(packed.body_rows(bytes(r["body"]), r["live"], r["d"]), r["ell"], r["d"], r["n_rows"], r["f2"], r["shed"], r["shrinks"])

    @classmethod
    def from_df(cls, df: DataFrame) -> Sketch:
        """Of the one packed row of an ungrouped sketch; an empty view gives an empty sketch."""
        found = df.select(*packed.NAMES).take(2)
        if len(found) > 1:
            raise ValueError("more than one sketch; filter to one key first")
        return cls.from_row(found[0]) if found else cls(np.zeros((0, 1)), 1, 1, 0, 0.0, 0.0)

    @classmethod
    def of(cls, block: np.ndarray, ell: int, **options) -> Sketch:
        state = ShrinkState(ell, block.shape[1], **options)
        state.extend(block)
        rows = state.finish().copy()
        return cls(rows, ell, state.d, state.n_rows, state.f2, state.shed, state.shrinks)

    def as_row(self, pid: int = 0) -> dict:
        return dict(zip(packed.NAMES, packed.row(pid, self, self.rows)))

    def merge(self, other: Sketch) -> Sketch:
        state, rows = merge_packed([self.as_row(0), other.as_row(1)])
        return Sketch(rows.copy(), state.ell, state.d, state.n_rows, state.f2, state.shed, state.shrinks)

    # what the rows say

    def gram(self) -> np.ndarray:
        return self.rows.T @ self.rows

    @property
    def spectrum(self) -> np.ndarray:
        """Squared singular values, descending."""
        if not len(self.rows):
            return np.zeros(0)
        return np.maximum(np.linalg.svd(self.rows, compute_uv=False), 0) ** 2

    def directions(self, k: int) -> np.ndarray:
        """The leading k right singular directions as columns (d x k)."""
        if not len(self.rows):
            return np.zeros((self.d, 0))
        return np.linalg.svd(self.rows, full_matrices=False)[2][:k].T

    def quad_interval(self, x: np.ndarray) -> tuple[float, float]:
        """Bounds of ||Ax||^2 for a unit direction."""
        low = float(np.sum((self.rows @ x) ** 2))
        return low, low + self.shed

    def heavy_directions(self, eps: float | None = None, t: float | None = None) -> list[dict]:
        """Directions that may carry ``eps`` of F2 (or length ``t``), with which of them certainly do.

        No direction so heavy is orthogonal to the span of the candidates.
        """
        goal = eps * self.f2 if t is None else t * t
        if not len(self.rows):
            return []
        _, s, vt = np.linalg.svd(self.rows, full_matrices=False)
        return [{"sigma2": float(x * x), "certain": bool(x * x >= goal), "vec": v} for x, v in zip(s, vt) if x * x >= goal - self.shed]

    def choose_rank(self, t: float) -> tuple[int, list[tuple[float, float]]]:
        """The least k whose remaining singular values lie under ``t``, and each square's interval."""
        s = self.spectrum
        return int((s >= t * t).sum()), [(float(x), float(x + self.shed)) for x in s]

    # algebra

    def columns(self, idx: list[int]) -> Sketch:
        """The sketch of some columns; what was shed bounds them too. F2 of the columns is not known and stays an upper bound."""
        return replace(self, rows=self.rows[:, idx], d=len(idx))

    def right_multiply(self, w: np.ndarray) -> Sketch:
        """The sketch of A W; shed grows by the squared norm of W."""
        norm = float(np.linalg.norm(w, 2)) ** 2
        return replace(self, rows=self.rows @ w, d=w.shape[1], shed=self.shed * norm, f2=self.f2 * norm)

    def reduce(self, ell: int) -> Sketch:
        """A shorter sketch of the same rows."""
        state = ShrinkState(min(ell, self.ell), self.d)
        state.merge(self.rows, self.n_rows, self.f2, self.shed, self.shrinks)
        rows = state.finish().copy()
        return Sketch(rows, state.ell, state.d, state.n_rows, state.f2, state.shed, state.shrinks)

    def words(self) -> int:
        return self.ell * self.d


def _exact(eps) -> Fraction:
    return eps if isinstance(eps, Fraction) else Fraction(str(eps))


def ell_for_cov(k: int, eps) -> int:
    """Rows that keep the covariance error within eps times the tail beyond rank k."""
    return math.ceil(k + 1 / _exact(eps))


def ell_for_proj(k: int, eps) -> int:
    """Rows that keep the rank-k projection within 1 + eps of the best."""
    return math.ceil(k + k / _exact(eps))


def ell_for_heavy(eps) -> int:
    """Least number of rows above 1 / eps."""
    return math.floor(1 / _exact(eps)) + 1


def guarantee(ell: int, k: int) -> tuple[float, float | None]:
    """Relative covariance and projection guarantees."""
    return 1.0 / ell, ell / (ell - k) if k < ell else None


def space_floor(d: int, k: int, eps) -> float:
    """Order of the words any method needs for the covariance guarantee (constant left out)."""
    return d * (k + float(1 / _exact(eps)))


def space_floor_proj(d: int, k: int, eps) -> float:
    """Order of the bits any randomised streaming method needs for the projection guarantee."""
    return float(k * d / _exact(eps))


def counter_floor_bits(k: int, eps) -> float:
    """Order of the bits any approximate counter summary needs."""
    return float(k / _exact(eps))
