"""The shrink sketch with bounded work at every row.

Two buffers of 2 ell rows take turns.  While one takes rows in, the other's
decomposition advances by a slice at each arriving row: inner products first,
then rounds of Jacobi rotations on the small Gram matrix (a round turns
disjoint pairs of rows at once, and costs O(ell^2)), then the shortened rows
are written.  A buffer has at least ell + 1 free rows after its shrink, so the
work is cut into about ell slices.  Work still undone when the buffers must
swap is finished there and counted in ``overruns``.
"""

from __future__ import annotations

import numpy as np

from rowsketch.kernel.shrink import ShrinkState


def _pairings(r: int) -> list[tuple[np.ndarray, np.ndarray]]:
    """Round-robin rounds: every pair of 0 .. r-1 once, the pairs of a round disjoint."""
    n = r + r % 2
    ring = list(range(n))
    rounds = []
    for _ in range(n - 1):
        pairs = [(ring[i], ring[n - 1 - i]) for i in range(n // 2) if max(ring[i], ring[n - 1 - i]) < r]
        rounds.append((np.array([min(p) for p in pairs]), np.array([max(p) for p in pairs])))
        ring = [ring[0], ring[-1], *ring[1:-1]]
    return rounds


class _Upkeep:
    """The decomposition of one full buffer, as a generator of slices that yield their flops."""

    SWEEPS = 12

    def __init__(self, block: np.ndarray, ell: int, slices: int):
        self.block, self.ell = block, ell
        self.rows = np.zeros((0, block.shape[1]))
        self.delta = 0.0
        self.done = False
        self._steps = self._work(max(1, slices // 3))

    def step(self) -> int:
        try:
            return next(self._steps)
        except StopIteration:
            self.done = True
            return 0

    def _work(self, share: int):
        block = self.block
        r, d = block.shape
        gram = np.zeros((r, r))
        each = -(-r // share)
        for at in range(0, r, each):  # a few rows of inner products at a time
            gram[at : at + each] = block[at : at + each] @ block.T
            yield 2 * each * r * d
        turn = np.eye(r)
        if d >= self.ell**2:  # one solve of the small matrix is within a row's budget
            values, turn = np.linalg.eigh(gram)
            gram = np.diag(values)
            yield 9 * r**3
        else:
            rounds = _pairings(r)
            each = -(-self.SWEEPS * len(rounds) // share)
            done = flops = 0
            for _ in range(self.SWEEPS):
                for i, j in rounds:
                    self._rotate(gram, turn, i, j)
                    done, flops = done + 1, flops + 12 * r * r
                    if done == each:
                        yield flops
                        done = flops = 0
                off = np.abs(gram - np.diag(np.diag(gram))).max()
                if off <= 1e-14 * max(np.abs(np.diag(gram)).max(), 1e-300):
                    break
            yield flops
        squares = np.maximum(np.diag(gram), 0.0)
        order = np.argsort(-squares, kind="stable")
        squares, turn = squares[order], turn[:, order]
        m = min(r, d)
        self.delta = float(squares[self.ell - 1]) if m >= self.ell else 0.0
        live = np.flatnonzero(squares[: self.ell - 1] > max(self.delta, squares[0] * 1e-15 * max(r, d)))
        out = np.zeros((len(live), d))
        each = max(1, -(-len(live) // share))
        for at in range(0, len(live), each):
            own = live[at : at + each]
            out[at : at + each] = np.sqrt(1.0 - self.delta / squares[own])[:, None] * (turn[:, own].T @ block)
            yield 2 * each * r * d
        self.rows = out

    @staticmethod
    def _rotate(g: np.ndarray, turn: np.ndarray, i: np.ndarray, j: np.ndarray) -> None:
        a, b, c = g[i, i], g[j, j], g[i, j]
        with np.errstate(divide="ignore", invalid="ignore", over="ignore"):
            tau = (b - a) / (2 * c)
            t = np.where(c == 0, 0.0, np.where(tau >= 0, 1.0, -1.0) / (np.abs(tau) + np.sqrt(1 + tau * tau)))
        t = np.nan_to_num(t)
        cos = 1 / np.sqrt(1 + t * t)
        sin = t * cos
        for m in (g, turn):
            x, y = m[:, i].copy(), m[:, j].copy()
            m[:, i], m[:, j] = cos * x - sin * y, sin * x + cos * y
        x, y = g[i].copy(), g[j].copy()
        g[i], g[j] = cos[:, None] * x - sin[:, None] * y, sin[:, None] * x + cos[:, None] * y


class PacedState:
    """Same interface as :class:`ShrinkState`; ``flops`` holds the upkeep spent at each row."""

    def __init__(self, ell: int, d: int, budget: int | None = None, trace: bool = False):
        self.ell, self.d = ell, d
        self.capacity = max(ell + 1, 2 * ell)
        self.slices = budget or max(1, self.capacity - ell)
        self.active = np.zeros((self.capacity, d))
        self.live = 0
        self.other = np.zeros((0, d))
        self.upkeep: _Upkeep | None = None
        self.n_rows = self.shrinks = self.overruns = 0
        self.f2 = self.shed = 0.0
        self.flops: list[int] | None = [] if trace else None

    def extend(self, block: np.ndarray, count: bool = True) -> None:
        block = np.asarray(block, np.float64)
        if count:
            self.n_rows += len(block)
            self.f2 += float(np.einsum("ij,ij->", block, block))
        for row in block:
            self.active[self.live] = row
            self.live += 1
            spent = self.upkeep.step() if self.upkeep else 0
            self._collect()
            if self.live == self.capacity:
                self._swap()
            if self.flops is not None:
                self.flops.append(spent)

    def _collect(self) -> None:
        if self.upkeep and self.upkeep.done:
            self.other = self.upkeep.rows
            self.shed += self.upkeep.delta
            self.shrinks += 1
            self.upkeep = None

    def settle(self) -> None:
        """Ends the decomposition under way."""
        while self.upkeep:
            self.upkeep.step()
            self._collect()

    def _swap(self) -> None:
        if self.upkeep:
            self.overruns += 1
            self.settle()
        full, self.active = self.active, np.zeros((self.capacity, self.d))
        self.live = len(self.other)
        self.active[: self.live] = self.other
        self.other = np.zeros((0, self.d))
        self.upkeep = _Upkeep(full, self.ell, self.slices)

    def merge(self, rows: np.ndarray, n_rows: int, f2: float, shed: float, shrinks: int) -> None:
        self.extend(rows, count=False)
        self.n_rows, self.f2, self.shed, self.shrinks = self.n_rows + n_rows, self.f2 + f2, self.shed + shed, self.shrinks + shrinks

    def finish(self) -> np.ndarray:
        """Both buffers merged into one sketch."""
        self.settle()
        last = ShrinkState(self.ell, self.d)
        last.extend(self.other, count=False)
        last.extend(self.active[: self.live], count=False)
        rows = last.finish()
        self.shed += last.shed
        self.shrinks += last.shrinks
        return rows

    @property
    def held_bytes(self) -> int:
        return 8 * self.words

    @property
    def words(self) -> int:
        return 2 * self.capacity * self.d
