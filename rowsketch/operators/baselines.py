"""The methods the shrink sketch is compared with.

Linear ones (Gram, bucket signs, dense signs) combine by sums, sampling by
minima; all go through local partial results and a keyed combine.  Each random
method has a block path, with a counter-based generator, and an SQL path whose
random numbers are md5 digests, the same in any engine.  The two paths draw
different numbers.
"""

from __future__ import annotations

import time
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from rowsketch.functions.vectors import vec_norm2
from rowsketch.kernel.shrink import ShrinkState
from rowsketch.operators.dist import FAN_IN, partitions_of, rounds_for, vectors
from rowsketch.operators.sketch import Sketch

#: Widest matrix whose Gram is made whole.
GRAM_LIMIT = 20_000
TILE_ROWS = 256


# numbers from (row, slot, seed)


def mixed(row: np.ndarray, slot: np.ndarray | int, seed: int) -> np.ndarray:
    """64 random bits for each (row, slot), splitmix fashion."""
    with np.errstate(over="ignore"):
        x = row.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15) + np.asarray(slot, np.uint64) * np.uint64(0xD1B54A32D192ED03) + np.uint64(seed * 2 + 1) * np.uint64(0x8CB92BA72F3D8DD7)
        for shift, mul in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
            x = (x ^ (x >> np.uint64(shift))) * np.uint64(mul)
        return x ^ (x >> np.uint64(31))


def uniforms(row: np.ndarray, slot, seed: int) -> np.ndarray:
    return ((mixed(row, slot, seed) >> np.uint64(12)).astype(np.float64) + 0.5) / 2.0**52


def digest(*parts: Column | str) -> Column:
    """32 bits of md5 over the parts joined by ':'."""
    text = F.concat_ws(":", *[p.cast("string") if isinstance(p, Column) else F.lit(p) for p in parts])
    return F.conv(F.substring(F.md5(text.cast("binary")), 1, 8), 16, 10).cast("long")


def digest_uniform(*parts) -> Column:
    return (digest(*parts).cast("double") + 0.5) / 4294967296.0


# accumulators of the block paths


class Zero:
    """Reads every row and keeps nothing of it."""

    def __init__(self, ell: int, d: int, seed: int = 0):
        self.rows = 0

    def extend(self, block: np.ndarray, ids: np.ndarray) -> None:
        self.rows += len(block)

    def partial(self) -> list[tuple[int, bytes]]:
        return [(0, np.zeros(0).tobytes())]


class GramTiles:
    def __init__(self, ell: int, d: int, seed: int = 0):
        self.g = np.zeros((d, d))

    def extend(self, block: np.ndarray, ids: np.ndarray) -> None:
        self.g += block.T @ block

    def partial(self) -> list[tuple[int, bytes]]:
        return [(t, self.g[at : at + TILE_ROWS].tobytes()) for t, at in enumerate(range(0, len(self.g), TILE_ROWS))]


class BucketSigns:
    """Each row, with a random sign, is added to one of ell rows."""

    def __init__(self, ell: int, d: int, seed: int):
        self.b, self.seed = np.zeros((ell, d)), seed

    def extend(self, block: np.ndarray, ids: np.ndarray) -> None:
        x = mixed(ids, 0, self.seed)
        bucket = (x >> np.uint64(8)) % np.uint64(len(self.b))
        order = np.argsort(bucket, kind="stable")
        first = np.flatnonzero(np.diff(bucket[order], prepend=np.uint64(len(self.b))))
        if len(first):
            signed = np.where(x[order] & np.uint64(1), 1.0, -1.0)[:, None] * block[order]
            self.b[bucket[order[first]].astype(np.int64)] += np.add.reduceat(signed, first, axis=0)

    def partial(self) -> list[tuple[int, bytes]]:
        return [(0, self.b.tobytes())]


class DenseSigns:
    """Each row is added to all ell rows, with random signs or Gaussians over sqrt(ell)."""

    def __init__(self, ell: int, d: int, seed: int, dist: str = "sign"):
        self.b, self.seed, self.dist = np.zeros((ell, d)), seed, dist

    def extend(self, block: np.ndarray, ids: np.ndarray) -> None:
        ell = len(self.b)
        slots = np.arange(ell, dtype=np.uint64)[:, None]
        if self.dist == "sign":
            s = np.where(mixed(ids[None, :], slots, self.seed) & np.uint64(1), 1.0, -1.0)
        else:
            s = np.sqrt(-2 * np.log(uniforms(ids[None, :], slots, self.seed))) * np.cos(2 * np.pi * uniforms(ids[None, :], slots + np.uint64(ell), self.seed))
        self.b += (s / np.sqrt(ell)) @ block

    def partial(self) -> list[tuple[int, bytes]]:
        return [(0, self.b.tobytes())]


class NormRaces:
    """Slot s keeps the row with the least -ln(u) / ||a||^2: a row wins with its share of F2."""

    def __init__(self, ell: int, d: int, seed: int):
        self.key = np.full(ell, np.inf)
        self.rows = np.zeros((ell, d))
        self.seed, self.f2 = seed, 0.0

    def extend(self, block: np.ndarray, ids: np.ndarray) -> None:
        w = np.einsum("ij,ij->i", block, block)
        self.f2 += float(w.sum())
        live = w > 0
        if not live.any():
            return
        block, ids, w = block[live], ids[live], w[live]
        races = -np.log(uniforms(ids[None, :], np.arange(len(self.key), dtype=np.uint64)[:, None], self.seed)) / w[None, :]
        best = races.argmin(axis=1)
        least = races[np.arange(len(best)), best]
        won = least < self.key
        self.key[won] = least[won]
        self.rows[won] = block[best[won]]

    def partial(self) -> list[tuple[int, bytes]]:
        return [(0, np.concatenate([[self.f2], self.key, self.rows.ravel()]).tobytes())]


class ShrinkRows:
    """The buffered shrink sketch, beside other methods in one scan."""

    HEAD = 5

    def __init__(self, ell: int, d: int, seed: int = 0):
        self.state = ShrinkState(ell, d)

    def extend(self, block: np.ndarray, ids: np.ndarray) -> None:
        self.state.extend(block)

    def partial(self) -> list[tuple[int, bytes]]:
        return [(0, self.packed().tobytes())]

    def packed(self) -> np.ndarray:
        rows = self.state.finish()
        return np.concatenate([[self.state.n_rows, self.state.f2, self.state.shed, self.state.shrinks, len(rows)], rows.ravel()])

    def take(self, body: np.ndarray) -> None:
        n, f2, shed, shrinks, live = body[: self.HEAD]
        self.state.merge(body[self.HEAD :].reshape(int(live), -1) if live else np.zeros((0, self.state.d)), int(n), f2, shed, int(shrinks))


ACCUMULATORS = {"shrink": ShrinkRows, "zero": Zero, "gram": GramTiles, "bucket": BucketSigns, "dense": DenseSigns, "norm": NormRaces}


def combine(kind: str, a: np.ndarray, b: np.ndarray, ell: int) -> np.ndarray:
    """Two partial results of one (tag, part)."""
    if kind != "norm":
        return a + b
    d = (len(a) - 1) // ell - 1
    out = a.copy()
    out[0] = a[0] + b[0]
    won = b[1 : 1 + ell] < a[1 : 1 + ell]
    out[1 : 1 + ell][won] = b[1 : 1 + ell][won]
    out[1 + ell :].reshape(ell, d)[won] = b[1 + ell :].reshape(ell, d)[won]
    return out


def finish(kind: str, body: np.ndarray, ell: int, d: int):
    """Rows of a method's sketch from its combined partial result; a :class:`Sketch` of the shrink method."""
    if kind == "shrink":
        n, f2, shed, shrinks, live = body[: ShrinkRows.HEAD]
        return Sketch(body[ShrinkRows.HEAD :].reshape(int(live), d), ell, d, int(n), float(f2), float(shed), int(shrinks))
    if kind == "zero":
        return np.zeros((ell, d))
    if kind == "norm":
        f2, key, rows = body[0], body[1 : 1 + ell], body[1 + ell :].reshape(ell, d)
        w = np.einsum("ij,ij->i", rows, rows)
        ok = np.isfinite(key) & (w > 0)
        return np.where(ok[:, None], rows * np.sqrt(f2 / (ell * np.where(ok, w, 1.0)))[:, None], 0.0)
    return body.reshape(ell, d)


def accumulate(df: DataFrame, jobs: dict[str, tuple[str, int, int]], d: int, fan_in: int = FAN_IN, dist: str = "sign", seconds: dict[str, float] | None = None) -> dict:
    """One scan for many jobs: tag -> (kind, ell, seed).  Returns each tag's rows (a Gram: d x d; a shrink sketch: a Sketch).

    ``dist``: "sign" or "gaussian", what the dense method draws.  ``seconds``
    is filled with each tag's own processor time, summed over the tasks, and that
    of reading under ''.

    Partial results of equal (tag, part) are combined ``fan_in`` tasks at a
    time until one is left; what reaches the driver is one result a tag.
    """
    kinds = {t: (k, ell) for t, (k, ell, _) in jobs.items()}
    schema = "tag string, part int, pid int, body binary, seconds double"
    names = ["tag", "part", "pid", "body", "seconds"]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        states = {t: ACCUMULATORS[k](ell, d, seed, **({"dist": dist} if k == "dense" else {})) for t, (k, ell, seed) in jobs.items()}
        spent = dict.fromkeys(["", *states], 0.0)
        seen = False
        clock = time.process_time()
        for rb in batches:
            if rb.num_rows:
                seen = True
                ids = rb.column(0).to_numpy()
                block = vectors(rb.column(1), d)
                spent[""] += time.process_time() - clock
                for t, s in states.items():
                    clock = time.process_time()
                    s.extend(block, ids)
                    spent[t] += time.process_time() - clock
                clock = time.process_time()
        if seen:
            pid = TaskContext.get().partitionId()
            for t, s in states.items():
                clock = time.process_time()
                parts = s.partial()
                spent[t] += time.process_time() - clock
                for part, body in parts:
                    yield pa.RecordBatch.from_arrays([pa.array([t]), pa.array([part], pa.int32()), pa.array([pid], pa.int32()), pa.array([body], pa.binary()), pa.array([spent[t] if part == 0 else 0.0])], names)
            yield pa.RecordBatch.from_arrays([pa.array([""]), pa.array([0], pa.int32()), pa.array([pid], pa.int32()), pa.array([b""], pa.binary()), pa.array([spent[""]])], names)

    def add(table: pa.Table) -> pa.Table:
        tag = table.column("tag")[0].as_py()
        kind, ell = kinds.get(tag, ("zero", 0))
        column = table.column("body")
        order = np.argsort(table.column("pid").to_numpy(), kind="stable")
        clock = time.process_time()
        if kind == "shrink":
            whole = ShrinkRows(ell, d)
            for i in order:
                whole.take(np.frombuffer(column[int(i)].as_py()))
            total = whole.packed()
        else:
            total = np.frombuffer(column[int(order[0])].as_py()).copy()
            for i in order[1:]:
                total = combine(kind, total, np.frombuffer(column[int(i)].as_py()), ell)
        spent = sum(table.column("seconds").to_pylist()) + (time.process_time() - clock if tag else 0.0)
        return pa.Table.from_arrays([pa.array([tag]), table.column("part").slice(0, 1).combine_chunks(), pa.array([int(table.column("pid")[0].as_py()) // fan_in], pa.int32()), pa.array([total.tobytes()], pa.binary()), pa.array([spent])], names=names)

    rows = df.select("row_id", "vec")
    found = rows.mapInArrow(run, schema)
    rounds = rounds_for(partitions_of(rows), fan_in)
    for r in range(rounds):
        group = F.lit(0) if r == rounds - 1 else F.floor(F.col("pid") / fan_in)
        found = found.groupBy("tag", "part", group.alias("g")).applyInArrow(add, schema)
    whole = found.collect()
    if seconds is not None:
        for t in ["", *jobs]:
            seconds[t] = sum(r["seconds"] for r in whole if r["tag"] == t)
    out = {}
    for t, (kind, ell, _) in jobs.items():
        parts = sorted((r["part"], bytes(r["body"])) for r in whole if r["tag"] == t)
        if not parts:
            out[t] = np.zeros((d, d)) if kind == "gram" else Sketch(np.zeros((0, d)), ell, d, 0, 0.0, 0.0) if kind == "shrink" else np.zeros((ell, d))
        elif kind == "gram":
            out[t] = np.frombuffer(b"".join(b for _, b in parts)).reshape(d, d)
        else:
            out[t] = finish(kind, np.frombuffer(parts[0][1]), ell, d)
    return out


# exact Gram, in three ways


def gram_block(df: DataFrame, d: int) -> np.ndarray:
    """The d x d Gram matrix on the driver, refused where it would not fit."""
    if d > GRAM_LIMIT:
        raise ValueError(f"the Gram matrix of {d} columns is too large; use the sketch or power iteration")
    return accumulate(df, {"g": ("gram", 1, 0)}, d)["g"]


def gram_sql(df: DataFrame, row: str = "row_id") -> DataFrame:
    """(i, j, g), i <= j, of a view with unique row ids: products of a row's entries, summed."""
    cells = df.select(row, F.posexplode("vec").alias("i", "x")).where("x <> 0")
    other = cells.select(row, F.col("i").alias("j"), F.col("x").alias("y"))
    return cells.join(other, row).where("i <= j").groupBy("i", "j").agg(F.sum(F.col("x") * F.col("y")).alias("g"))


def gram_mllib(df: DataFrame) -> np.ndarray:
    """Spark's own distributed Gram, as a cross-check."""
    from pyspark.mllib.linalg.distributed import RowMatrix

    m = RowMatrix(df.select("vec").rdd.map(lambda r: r["vec"]))
    return m.computeGramianMatrix().toArray()


def top_of_gram(g: np.ndarray, ell: int) -> np.ndarray:
    """Rows sqrt(lambda) v of the ell largest eigenvalues."""
    values, v = np.linalg.eigh(g)
    order = np.argsort(-values)[:ell]
    return np.sqrt(np.maximum(values[order], 0))[:, None] * v[:, order].T


def gram_top(df: DataFrame, ell: int, d: int, path: str = "block") -> Sketch:
    """Brute force: the best rank-ell sketch."""
    if path == "sql":
        g = np.zeros((d, d))
        for r in gram_sql(df).collect():  # d^2 / 2 numbers at most
            g[r["i"], r["j"]] = g[r["j"], r["i"]] = r["g"]
    else:
        g = gram_mllib(df) if path == "mllib" else gram_block(df, d)
    return Sketch(top_of_gram(g, ell), ell, d, 0, float(np.trace(g)), 0.0)


def best_rank_k(df: DataFrame, k: int, d: int) -> Sketch:
    return gram_top(df, k, d)


def zero_sketch(df: DataFrame, ell: int) -> DataFrame:
    """Reads every row, returns zero rows: (row_no, vec, n_rows, f2)."""
    one = df.agg(F.count("*").alias("n_rows"), F.sum(vec_norm2("vec")).alias("f2"), F.max(F.size("vec")).alias("d"))
    return one.select(F.explode(F.sequence(F.lit(0), F.lit(ell - 1))).alias("row_no"), F.array_repeat(F.lit(0.0), F.col("d")).alias("vec"), "n_rows", "f2")


# SQL paths, for oracles and small views


def norm_sample_sql(df: DataFrame, ell: int, seed: int) -> DataFrame:
    """(slot, row_id, p, vec): the winner of each slot's race, scaled by 1 / sqrt(ell p).

    Races are run over (row_id, weight); only the winners, ``ell`` rows at
    most, are joined back to their vectors.
    """
    weighted = df.select("row_id", vec_norm2("vec").alias("w")).where("w > 0")
    total = weighted.agg(F.sum("w").alias("f2"))
    slots = F.explode(F.sequence(F.lit(0), F.lit(ell - 1))).alias("slot")
    races = weighted.select("row_id", "w", slots).select("slot", "row_id", "w", (-F.log(digest_uniform(F.col("row_id"), F.col("slot"), str(seed))) / F.col("w")).alias("race"))
    won = races.groupBy("slot").agg(F.min_by(F.struct("row_id", "w"), F.struct("race", "row_id")).alias("a")).select("slot", "a.row_id", "a.w")
    scaled = won.crossJoin(F.broadcast(total)).select("slot", "row_id", (F.col("w") / F.col("f2")).alias("p"))
    found = df.select("row_id", "vec").join(F.broadcast(scaled), "row_id")
    return found.select("slot", "row_id", "p", F.transform("vec", lambda x: x / F.sqrt(ell * F.col("p"))).alias("vec"))


def norm_sample_without_replacement(df: DataFrame, ell: int, seed: int) -> DataFrame:
    """The ell best of a single race: (row_id, race, vec)."""
    race = -F.log(digest_uniform(F.col("row_id"), "0", str(seed))) / vec_norm2("vec")
    return df.where(vec_norm2("vec") > 0).select("row_id", race.alias("race"), "vec").orderBy("race", "row_id").limit(ell)


def bucket_sign_sql(df: DataFrame, ell: int, seed: int) -> DataFrame:
    """(bucket, pos, val)."""
    sign = F.when(F.pmod(digest(F.col("row_id"), "s", str(seed)), F.lit(2)) == 0, 1.0).otherwise(-1.0)
    signed = df.select(F.pmod(digest(F.col("row_id"), "b", str(seed)), F.lit(ell)).cast("int").alias("bucket"), sign.alias("sign"), F.posexplode("vec").alias("pos", "x"))
    return signed.groupBy("bucket", "pos").agg(F.sum(F.col("sign") * F.col("x")).alias("val"))


def dense_sign_sql(df: DataFrame, ell: int, seed: int) -> DataFrame:
    """(slot, pos, val): a row's signs are drawn once, and each entry is added to all slots at once."""
    signs = F.array(*[F.when(F.pmod(digest(F.col("row_id"), F.lit(s), str(seed)), F.lit(2)) == 0, 1.0).otherwise(-1.0) for s in range(ell)])
    signed = df.select(signs.alias("signs"), F.posexplode("vec").alias("pos", "x"))
    sums = signed.groupBy("pos").agg(*[F.sum(F.col("signs")[s] * F.col("x")).alias(f"s{s}") for s in range(ell)])
    slots = F.posexplode(F.array(*[f"s{s}" for s in range(ell)])).alias("slot", "val")
    return sums.select("pos", slots).select("slot", "pos", (F.col("val") / F.sqrt(F.lit(float(ell)))).alias("val"))


def sparsify(df: DataFrame, keep: float, seed: int) -> DataFrame:
    """Entries kept with probability min(1, keep * x^2 / mean square) and rescaled: (row_id, pos, val)."""
    cells = df.select("row_id", F.posexplode("vec").alias("pos", "x")).where("x <> 0")
    mean = cells.agg(F.avg(F.col("x") * F.col("x")).alias("mean"))
    p = F.least(F.lit(1.0), keep * F.col("x") * F.col("x") / F.col("mean"))
    drawn = cells.crossJoin(F.broadcast(mean)).select("row_id", "pos", "x", p.alias("p"), digest_uniform(F.col("row_id"), F.col("pos"), str(seed)).alias("u"))
    return drawn.where("u < p").select("row_id", "pos", (F.col("x") / F.col("p")).alias("val"))


def leverage_sample(df: DataFrame, ell: int, k: int, d: int, seed: int) -> DataFrame:
    """Rows drawn by the squared length of their projection on the best rank-k space: (row_id, leverage, race)."""
    v = best_rank_k(df, k, d).directions(k)
    vk = F.array(*[F.array(*[F.lit(float(x)) for x in v[:, c]]) for c in range(v.shape[1])])
    weight = F.aggregate(F.transform(vk, lambda b: F.pow(F.aggregate(F.zip_with("vec", b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x), F.lit(2))), F.lit(0.0), lambda s, x: s + x)
    rows = df.select("row_id", weight.alias("leverage")).where("leverage > 0")
    return rows.select("row_id", "leverage", (-F.log(digest_uniform(F.col("row_id"), "0", str(seed))) / F.col("leverage")).alias("race")).orderBy("race", "row_id").limit(ell)
