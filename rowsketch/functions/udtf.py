"""Table functions for SQL: rows of a packed sketch, and a sketch for each partition of a table argument."""

from __future__ import annotations

import numpy as np


class SketchRows:
    """sketch_rows(body, live, d): the rows of a packed sketch."""

    def eval(self, body: bytes, live: int, d: int):
        from rowsketch.kernel.packed import body_rows

        for i, v in enumerate(body_rows(bytes(body), live, d)):
            yield i, float(np.sqrt(v @ v)), v.tolist()


class ShrinkSketchTable:
    """shrink_sketch(row => TABLE(t) PARTITION BY key, ell => n) for groups of moderate size; t has (key, vec).

    A table function has no partial step; large data go through ``sketch``.
    """

    BLOCK = 512

    def __init__(self):
        self.state = None
        self.held: list = []
        self.key = None

    def eval(self, row, ell: int):
        self.key = str(row["key"])
        if self.state is None:
            from rowsketch.kernel.shrink import ShrinkState

            self.state = ShrinkState(ell, len(row["vec"]))
        self.held.append(row["vec"])
        if len(self.held) >= self.BLOCK:
            self.state.extend(np.array(self.held, np.float64))
            self.held = []
        return
        yield

    def terminate(self):
        if self.state is None:
            return
        if self.held:
            self.state.extend(np.array(self.held, np.float64))
        for i, v in enumerate(self.state.finish()):
            yield self.key, i, float(np.sqrt(v @ v)), float(self.state.shed), int(self.state.n_rows), v.tolist()
