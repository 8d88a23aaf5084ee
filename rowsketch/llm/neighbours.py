"""Approximate nearest neighbours by shifted space-filling curves.

Each of several curves projects the vectors on a few random directions, shifts
them, and orders the cells of a grid along a Hilbert curve.  Spark deals a
curve's order out in ranges of equal share, the boundaries read off a bounded
sample; a query goes to its own range, and to the one beside it when its window
reaches over the border.  What travels with a curve is a byte a component, not
the vector.  In a range, a query meets a window of places around its own key;
rows whose product with it may still be among its best, by a bound on the
rounding of the bytes, are its candidates.  The candidates of all curves are
merged, pruned by the same bound, and reranked with the vectors themselves.

Equal vectors are one point: the least ids that a result can need stand for
them, found in salted steps, so a vector that a third of all rows share is one
row of the search, and its ties come out whole.  Ties between different vectors
go to the smaller id: no candidate that may tie is pruned, and each pair's
product is added up once, in one order.

A row takes no part if its vector is null, of another length than most, zero,
or holds a null or a value that is not finite, or if its id is null.  A query
gets all candidates if there are fewer than ``k``; rows that repeat an id with
one vector are one candidate; an empty table gives an empty result; other
columns are not read.

Cost: a window has ``WINDOW_SCALE * n ** WINDOW_POWER`` places of n points, so a
query meets about ``CURVES`` windows, a share of all rows that falls as tables
grow.  On vectors without low-dimensional structure no ordering finds nine
tenths of the true neighbours with much less (figures in the README).
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from rowsketch.shared import materialise

K = 20
EVERY = 20
CURVES = 64
#: Places of a query's window on a curve over n points: WINDOW_SCALE * n ** WINDOW_POWER, WINDOW_LEAST at least.
WINDOW_SCALE = 0.18
WINDOW_POWER = 0.7
WINDOW_LEAST = 64
#: Up to this many points are one window in any case.
ONE_WINDOW = 512
#: Ranges of a curve, at most; past them a range is met in several blocks.
RANGES = 1024
#: Parts of a range, by which it is told whether a window reaches over its border.
PARTS = 8
#: Projected dimensions and bits of each, of a curve's grid.
DIMS = 10
GRID_BITS = 4
#: Vectors read to place grids and range boundaries.
SAMPLE = 20_000
#: Candidates of a block.
BLOCK = 8_192
#: Queries beside each other on a curve that meet the rows of their windows together.
TOGETHER = 2
SALTS = 64


def hilbert(cells: np.ndarray, bits: int) -> np.ndarray:
    """Place along the Hilbert curve of grid points (n, d), d * bits at most 63.

    Skilling's transform: undo the excess work of each bit level, then Gray
    decode, then interleave.
    """
    x = cells.T.astype(np.int64).copy()
    d = len(x)
    q = 1 << (bits - 1)
    while q > 1:
        p = q - 1
        for i in range(d):
            set_ = (x[i] & q) != 0
            swap = np.where(set_, 0, (x[0] ^ x[i]) & p)
            x[0] ^= np.where(set_, p, swap)
            x[i] ^= swap
        q >>= 1
    for i in range(1, d):
        x[i] ^= x[i - 1]
    t = np.zeros_like(x[0])
    q = 1 << (bits - 1)
    while q > 1:
        t ^= np.where((x[d - 1] & q) != 0, q - 1, 0)
        q >>= 1
    x ^= t
    key = np.zeros(x.shape[1], np.int64)
    for b in range(bits - 1, -1, -1):
        for i in range(d):
            key = (key << 1) | ((x[i] >> b) & 1)
    return key


class Curves:
    """Projections, shifts and range boundaries of all curves, made from a sample of vectors."""

    def __init__(self, sample: np.ndarray, curves: int = CURVES, ranges: int = 1, dims: int = DIMS, bits: int = GRID_BITS, seed: int = 11):
        rng = np.random.default_rng(seed)
        d = sample.shape[1]
        dims = min(dims, d, 63 // bits)
        self.bits, self.ranges = bits, ranges
        #: Low bits of a key that its place in a block does without.
        self.cut = max(0, dims * bits - 32)
        self.turn = np.stack([np.linalg.qr(rng.standard_normal((d, d)))[0][:, :dims] for _ in range(curves)])
        self.shift = rng.random((curves, dims)) * 0.5
        self.low = np.empty((curves, dims))
        self.span = np.empty((curves, dims))
        parts = ranges * PARTS
        self.edges = np.empty((curves, parts - 1), np.int64)
        for c in range(curves):
            y = sample @ self.turn[c]
            self.low[c] = np.percentile(y, 0.5, axis=0)
            self.span[c] = np.maximum(np.percentile(y, 99.5, axis=0) - self.low[c], 1e-12)
            keys = np.sort(self.keys(sample, c))
            self.edges[c] = keys[(np.arange(1, parts) * len(keys)) // parts]

    def keys(self, x: np.ndarray, c: int) -> np.ndarray:
        y = (x @ self.turn[c] - self.low[c]) / self.span[c] * 0.5 + self.shift[c]
        top = 1 << self.bits
        return hilbert(np.clip((y * top).astype(np.int64), 0, top - 1), self.bits)

    def parts_of(self, keys: np.ndarray, c: int) -> np.ndarray:
        """The part that a key falls in; PARTS of them are a range."""
        return np.searchsorted(self.edges[c], keys, "right")


def window_of(n: int) -> int:
    """Places of a query's window over n points."""
    return max(WINDOW_LEAST, int(np.ceil(WINDOW_SCALE * n**WINDOW_POWER)))


def codes(x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A byte a component and the step that a byte stands for, row by row."""
    step = (np.abs(x).max(axis=1) / 127).astype(np.float32)
    step = np.where(step > 0, step, np.finfo(np.float32).tiny)
    return np.clip(np.rint(x / step[:, None].astype(np.float64)), -127, 127).astype(np.int8), step


def slack_of(step: np.ndarray, length: np.ndarray | float, d: int) -> np.ndarray:
    """What a product with a coded row may be off by, at most; ``length``: of the other vector."""
    return (0.5 + 1e-4) * np.sqrt(d) * step * length + 1e-5 * length * step * 127 * np.sqrt(d)


def _usable(df: DataFrame, vec_id: str, vector: str) -> DataFrame:
    rows = df.select(F.col(vec_id).cast("long").alias("id"), F.col(vector).cast("array<double>").alias("v"))
    rows = rows.where("id is not null and v is not null and size(v) > 0 and forall(v, x -> x is not null and not isnan(x) and abs(x) < double('infinity')) and exists(v, x -> x <> 0)")
    usual = rows.groupBy(F.size("v").alias("n")).count().orderBy(F.desc("count"), "n").limit(1).collect()
    return rows.where(F.size("v") == (usual[0]["n"] if usual else 0))


def _points(rows: DataFrame, keep: int) -> DataFrame:
    """(rep, ids, v): distinct vectors with their ``keep`` least ids; ``rep`` is the least."""
    first = Window.partitionBy("v", "salt").orderBy("id")
    salted = rows.select("*", F.pmod(F.xxhash64("id"), F.lit(SALTS)).alias("salt")).dropDuplicates(["v", "salt", "id"])
    few = salted.select("*", F.row_number().over(first).alias("r")).where(F.col("r") <= keep)
    ids = few.groupBy("v").agg(F.slice(F.sort_array(F.collect_list("id")), 1, keep).alias("ids"))
    return ids.select(F.col("ids")[0].alias("rep"), "ids", "v")


def search(df: DataFrame, *, k: int = K, every: int = EVERY, curves: int = CURVES, window: int | None = None, block: int = BLOCK, sample: int = SAMPLE, seed: int = 11, vec_id: str = "vec_id", vector: str = "embedding") -> DataFrame:
    """(query_id, rank, vec_id, score): the ``k`` nearest found of each row whose id is divisible by ``every``."""
    rows = materialise(_usable(df, vec_id, vector), "vectors")
    points = materialise(_points(rows, k + 1), "points")
    asking = rows.where(F.col("id") % every == 0).select("id", "v").join(points.select("rep", "v"), "v").select("rep", F.col("id").alias("query_id")).distinct()
    asking = materialise(asking, "queries")
    met = candidates(points, asking, k=k, curves=curves, window=window, block=block, sample=sample, seed=seed)
    if met is None:
        return df.sparkSession.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    return _answers(materialise(_reranked(materialise(met, "candidates"), points, k), "merged"), asking, k)


def candidates(points: DataFrame, asking: DataFrame, *, k: int = K, curves: int = CURVES, window: int | None = None, block: int = BLOCK, sample: int = SAMPLE, seed: int = 11) -> DataFrame | None:
    """(rep, near, met): each asking point, the points that may be among its ``k + 1`` best, and how many products it took; None without points."""
    n = points.count()
    drawn = points.select("v").orderBy(F.xxhash64("rep"), "rep").limit(sample).toPandas()["v"]
    if not n:
        return None
    window = window or window_of(n)
    if n <= max(ONE_WINDOW, curves * window):  # windows that would cover all points are one window on one curve
        window, curves = 2 * n, 1
    ranges = max(1, min(RANGES, n // max(block, 4 * window)))
    make = Curves(np.array(drawn.tolist()), curves, ranges, seed=seed)
    reach = -(-window * ranges * PARTS // (2 * n))  # parts that half a window may cover
    marked = points.join(asking.select("rep").distinct().withColumn("asks", F.lit(True)), "rep", "left").select("rep", "v", F.coalesce("asks", F.lit(False)).alias("asks"))
    marked = materialise(marked, "marked")

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        n = np.zeros((curves, ranges), np.int64)
        for rb in batches:
            if rb.num_rows:
                x = rb.column(0).flatten().to_numpy().reshape(rb.num_rows, -1)
                for c in range(curves):
                    n[c] += np.bincount(make.parts_of(make.keys(x, c), c) // PARTS, minlength=ranges)
        yield pa.RecordBatch.from_arrays([pa.array(np.repeat(np.arange(curves), ranges), pa.int32()), pa.array(np.tile(np.arange(ranges), curves), pa.int32()), pa.array(n.ravel())], ["curve", "range", "n"])

    # one number for each range and curve, RANGES * curves at most: how many blocks its rows fill
    blocks = np.ones((curves, ranges), np.int64)
    if n > block:
        for r in marked.select("v").mapInArrow(count, "curve int, range int, n long").groupBy("curve", "range").agg(F.sum("n").alias("n")).collect():
            blocks[r["curve"], r["range"]] = max(1, -(-r["n"] // (2 * block)))

    def deal(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for rb in batches:
            if not rb.num_rows:
                continue
            x = rb.column(1).flatten().to_numpy().reshape(rb.num_rows, -1)
            reps = rb.column(0).to_numpy()
            asks = np.flatnonzero(np.array(rb.column(2)))
            code, step = codes(x)
            whole = x.astype(np.float32)
            out: list[tuple] = []

            def put(c: int, r: int, b: int, kind: int, at: np.ndarray) -> None:
                body = whole[at].tobytes() if kind else code[at].tobytes()
                out.append((c, r, b, kind, short[at].tobytes(), reps[at].tobytes(), step[at].tobytes(), body))

            spread = (reps.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)) >> np.uint64(32)
            for c in range(curves):
                keys = make.keys(x, c)
                part = make.parts_of(keys, c)
                short = (keys >> make.cut).astype(np.uint32)
                where = part // PARTS
                sub = (spread % blocks[c, where].astype(np.uint64)).astype(np.int64)
                order = np.lexsort((sub, where))
                cut = np.flatnonzero(np.diff(where[order]) | np.diff(sub[order])) + 1
                for own in np.split(order, cut):
                    put(c, int(where[own[0]]), int(sub[own[0]]), 0, own)
                for r in range(ranges):
                    own = asks[(part[asks] + reach >= r * PARTS) & (part[asks] - reach < (r + 1) * PARTS)]
                    if len(own):
                        for b in range(blocks[c, r]):
                            put(c, r, b, 1, own)
            kinds = (pa.int32(), pa.int32(), pa.int32(), pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(col, t) for col, t in zip(zip(*out), kinds)], ["curve", "range", "block", "kind", "keys", "reps", "step", "body"])

    names = ["rep", "near", "score", "slack", "met"]
    types = [pa.int64(), pa.binary(), pa.binary(), pa.binary(), pa.int64()]

    def meet(table: pa.Table) -> pa.Table:
        kind = np.array(table.column("kind"))
        join = lambda name, t, which: np.concatenate([np.frombuffer(table.column(name)[int(i)].as_py(), t) for i in np.flatnonzero(kind == which)] or [np.empty(0, t)])
        reps, who = join("reps", np.int64, 0), join("reps", np.int64, 1)
        if not len(who) or not len(reps):
            return pa.Table.from_arrays([pa.array([], t) for t in types], names=names)
        half = -(-window // (2 * int(blocks[table.column("curve")[0].as_py(), table.column("range")[0].as_py()])))
        keys, asked = join("keys", np.uint32, 0), join("keys", np.uint32, 1)
        order, line = np.lexsort((reps, keys)), np.lexsort((who, asked))
        reps, who = reps[order], who[line]
        step = join("step", np.float32, 0)[order].astype(np.float64)
        x = join("body", np.int8, 0).reshape(len(reps), -1)[order].astype(np.float32)
        y = join("body", np.float32, 1).reshape(len(who), -1)[line]
        length = np.sqrt((y.astype(np.float64) ** 2).sum(axis=1))
        place = np.searchsorted(keys[order], asked[line])
        found: list[tuple] = []
        for at in range(0, len(who), TOGETHER):
            lo, hi = max(0, place[at] - half), min(len(reps), place[min(at + TOGETHER, len(who)) - 1] + half)
            if lo >= hi:
                lo, hi = (lo - 1, lo) if lo else (0, 1)
            s = (y[at : at + TOGETHER] @ x[lo:hi].T).astype(np.float64) * step[lo:hi]
            off = slack_of(step[lo:hi][None, :], length[at : at + TOGETHER, None], x.shape[1])
            top = min(k + 1, hi - lo)
            sure = np.partition(s - off, hi - lo - top, axis=1)[:, hi - lo - top]
            for i in range(len(s)):
                near = np.flatnonzero(s[i] + off[i] >= sure[i])
                found.append((int(who[at + i]), reps[lo + near].tobytes(), s[i, near].astype(np.float32).tobytes(), off[i, near].astype(np.float32).tobytes(), hi - lo))
        return pa.Table.from_arrays([pa.array(col, t) for col, t in zip(zip(*found), types)], names=names)

    def merge(table: pa.Table) -> pa.Table:
        join = lambda name, t: np.concatenate([np.frombuffer(b, t) for b in table.column(name).to_pylist()])
        near, score, off = join("near", np.int64), join("score", np.float32).astype(np.float64), join("slack", np.float32).astype(np.float64)
        near, once = np.unique(near, return_index=True)
        score, off = score[once], off[once]
        top = min(k + 1, len(near))
        near = near[score + off >= np.partition(score - off, len(near) - top)[len(near) - top]]
        met = sum(table.column("met").to_pylist())
        return pa.Table.from_arrays([pa.array([table.column("rep")[0].as_py()], pa.int64()), pa.array([near], pa.list_(pa.int64())), pa.array([met], pa.int64())], names=["rep", "near", "met"])

    dealt = marked.mapInArrow(deal, "curve int, range int, block int, kind int, keys binary, reps binary, step binary, body binary")
    met = dealt.groupBy("curve", "range", "block").applyInArrow(meet, "rep long, near binary, score binary, slack binary, met long")
    return met.groupBy("rep").applyInArrow(merge, "rep long, near array<long>, met long")


def _reranked(met: DataFrame, points: DataFrame, k: int) -> DataFrame:
    """(rep, ids, scores): the ``k + 1`` best ids of each asking point by the product of the vectors, each added up in one order.

    A point that very many queries are near to is dealt out with its queries by salt.
    """
    salt = F.pmod(F.xxhash64("rep"), F.lit(SALTS)).alias("salt")
    pairs = met.select("rep", F.explode("near").alias("other"), salt).join(points.select("rep", F.col("v").alias("q")), "rep")
    wanted = pairs.select("other", "salt").distinct()
    others = points.select(F.col("rep").alias("other"), "ids", "v").join(wanted, "other")
    product = F.aggregate(F.zip_with("q", "v", lambda a, b: a * b), F.lit(0.0), lambda s, x: s + x)
    scored = pairs.join(others, ["other", "salt"]).select("rep", product.alias("score"), F.explode("ids").alias("id"))
    best = F.slice(F.sort_array(F.collect_list(F.struct((-F.col("score")).alias("less"), F.col("id")))), 1, k + 1)
    return scored.groupBy("rep").agg(best.alias("b")).select("rep", F.col("b.id").alias("ids"), F.transform("b.less", lambda x: -x).alias("scores"))


def _answers(merged: DataFrame, asking: DataFrame, k: int) -> DataFrame:
    """Each query's own list: its point's, without itself, at most ``k`` long."""
    own = asking.join(merged, "rep").select("query_id", F.expr("filter(arrays_zip(ids, scores), x -> x.ids <> query_id)").alias("near"))
    listed = own.select("query_id", F.posexplode(F.slice("near", 1, k)).alias("pos", "x"))
    return listed.select("query_id", (F.col("pos") + 1).cast("int").alias("rank"), F.col("x.ids").alias("vec_id"), F.col("x.scores").alias("score"))


def brute_force(ids: np.ndarray, vectors: np.ndarray, k: int = K, every: int = EVERY) -> dict[int, list[tuple[int, float]]]:
    """The exact answer, for tests and recall."""
    out = {}
    for i in np.flatnonzero(ids % every == 0):
        s = vectors @ vectors[i]
        order = [j for j in np.lexsort((ids, -s)) if j != i][:k]
        out[int(ids[i])] = [(int(ids[j]), float(s[j])) for j in order]
    return out
