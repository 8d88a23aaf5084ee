"""The shrink step and the states that feed it, on NumPy blocks.

A state sees each row once and keeps at most ``capacity`` rows.  When they are
all in use it rotates them by their singular value decomposition and takes the
``ell``-th squared singular value off every squared singular value; fewer than
``ell`` rows survive.  The sum of what was taken off (``shed``) bounds what any
direction has lost.
"""

from __future__ import annotations

import numpy as np

#: Blocks whose largest entry lies outside are scaled before they are squared.
SAFE = (1e-100, 1e100)


def _spectrum(block: np.ndarray, svd: str, orthogonal: int = 0) -> tuple[np.ndarray, np.ndarray, str]:
    """Squared singular values, descending, with what turns the block into rotated rows.

    Returns (squares, basis, side): side 'left' has columns of U (r x m),
    'right' has rows of V^T (m x d).
    """
    r, d = block.shape
    if svd == "auto":
        svd = "gram"
    if svd == "lapack":
        _, s, vt = np.linalg.svd(block, full_matrices=False)
        return s * s, vt, "right"
    if svd == "arrowhead" and r <= d and 0 < orthogonal == r - 1:
        # orthogonal rows and one more: products with the last row are all that is unknown
        g = np.diag(np.einsum("ij,ij->i", block, block))
        g[-1, :] = g[:, -1] = block @ block[-1]
        values, u = np.linalg.eigh(g)
        return np.maximum(values[::-1], 0.0), u[:, ::-1], "left"
    if r <= d:
        values, u = np.linalg.eigh(block @ block.T)
        return np.maximum(values[::-1], 0.0), u[:, ::-1], "left"
    values, v = np.linalg.eigh(block.T @ block)
    return np.maximum(values[::-1], 0.0), v[:, ::-1].T, "right"


def shrink(block: np.ndarray, ell: int, svd: str = "auto", take: bool = True, orthogonal: int = 0) -> tuple[np.ndarray, float]:
    """Rotated rows of ``block``, descending, each shortened by the ell-th square; and that square.

    ``take=False`` only rotates.  With fewer than ``ell`` singular values
    nothing is taken.
    """
    if not len(block):
        return block, 0.0
    top = float(np.abs(block).max())
    if top == 0.0:
        return block[:0], 0.0
    scale = top if not SAFE[0] < top < SAFE[1] else 1.0
    block = block / scale if scale != 1.0 else block
    squares, basis, side = _spectrum(block, svd, orthogonal)
    delta = float(squares[ell - 1]) if take and len(squares) >= ell else 0.0
    floor = squares[0] * 1e-15 * max(block.shape)
    live = squares > max(delta, floor)
    if take:
        live[ell - 1 :] = False
    if side == "left":
        rows = basis[:, live].T @ block
        if delta:
            rows *= np.sqrt(1.0 - delta / squares[live])[:, None]
    else:
        rows = np.sqrt(squares[live] - delta)[:, None] * basis[live]
    return (rows * scale if scale != 1.0 else rows), delta * scale * scale


class ShrinkState:
    """The sketch of the rows seen so far.

    variant: 'per_row' keeps ell rows and shrinks at each row once they are
    full; 'buffered' keeps ``buffer_factor`` times ell.
    """

    def __init__(self, ell: int, d: int, variant: str = "buffered", svd: str = "auto", buffer_factor: float = 2.0, trace: bool = False):
        if ell < 1 or d < 1:
            raise ValueError("ell and d must be positive")
        if variant not in ("per_row", "buffered"):
            raise ValueError(f"unknown variant {variant!r}")
        self.ell, self.d, self.svd, self.variant = ell, d, svd, variant
        self.capacity = ell if variant == "per_row" else max(ell + 1, int(np.ceil(buffer_factor * ell)))
        self.rows = np.zeros((0, d))  # grows to the capacity only as rows arrive
        self.live = 0
        self.n_rows = 0
        self.f2 = 0.0
        self.shed = 0.0
        self.shrinks = 0
        self.orthogonal = 0
        self.trace: list[tuple[float, float, float]] | None = [] if trace else None

    def _room(self, wanted: int) -> None:
        if self.live + wanted > len(self.rows):
            grown = np.zeros((min(self.capacity, max(2 * len(self.rows), self.live + wanted, 8)), self.d))
            grown[: self.live] = self.rows[: self.live]
            self.rows = grown

    def extend(self, block: np.ndarray, count: bool = True) -> None:
        """Takes rows in; ``count=False`` for rows of another sketch, whose totals are added apart."""
        block = np.asarray(block, np.float64)
        if count:
            self.n_rows += len(block)
            self.f2 += float(np.einsum("ij,ij->", block, block))
        at = 0
        while at < len(block):
            take = min(self.capacity - self.live, len(block) - at)
            self._room(take)
            self.rows[self.live : self.live + take] = block[at : at + take]
            self.live += take
            at += take
            if self.live == self.capacity:
                self._shrink()

    def _shrink(self, take: bool = True) -> None:
        block = self.rows[: self.live]
        before = float(np.einsum("ij,ij->", block, block)) if self.trace is not None else 0.0
        rows, delta = shrink(block, self.ell, self.svd, take, self.orthogonal)
        if self.trace is not None:
            self.trace.append((delta, before, float(np.einsum("ij,ij->", rows, rows))))
        self.rows[: len(rows)] = rows
        self.rows[len(rows) :] = 0.0
        self.live = self.orthogonal = len(rows)
        self.shed += delta
        self.shrinks += int(take)

    def merge(self, rows: np.ndarray, n_rows: int, f2: float, shed: float, shrinks: int) -> None:
        """Stacks another sketch; what both have shed adds up."""
        self.extend(rows, count=False)
        self.n_rows += n_rows
        self.f2 += f2
        self.shed += shed
        self.shrinks += shrinks

    def finish(self) -> np.ndarray:
        """At most ell - 1 rows (all of them below ell live rows), longest first, signs fixed."""
        self._shrink(take=self.live >= self.ell)
        rows = self.rows[: self.live]
        if len(rows):
            lead = rows[np.arange(len(rows)), np.abs(rows).argmax(axis=1)]
            rows *= np.where(lead < 0, -1.0, 1.0)[:, None]
        return rows

    @property
    def held_bytes(self) -> int:
        return self.rows.nbytes

    @property
    def words(self) -> int:
        return self.capacity * self.d


def expected_shrinks(n: int, ell: int) -> int:
    """Shrinks of the buffered state over n rows in general position, before it is finished."""
    return 0 if n < 2 * ell else (n - 2 * ell) // (ell + 1) + 1
