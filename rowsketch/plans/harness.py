"""The experiments: errors and times of every method over sketch lengths, data sets and seeds."""

from __future__ import annotations

import time

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowsketch.kernel.paced import PacedState
from rowsketch.kernel.shrink import ShrinkState
from rowsketch.operators import baselines, measures
from rowsketch.operators.dist import local_sketches, merge_tree, rounds_for, sketch, vectors
from rowsketch.operators.sketch import Sketch, guarantee
from rowsketch.shared import materialise
from rowsketch.sources import datagen

REPORT = "dataset string, method string, ell int, k int, seed int, cov_error double, proj_error double, guarantee_cov double, guarantee_proj double, seconds double, words long"
RANDOM = {"norm-sampling": "norm", "bucket-sign": "bucket", "dense-sign": "dense"}
ELLS = (12, 20, 40, 60, 80, 100)


def error_report(df: DataFrame, name: str, d: int, k: int, ells=ELLS, seeds=(1, 2, 3, 4, 5), timing: bool = False) -> DataFrame:
    """Errors of all methods, and with ``timing`` the processor seconds of each, from one scan.

    The seconds of a method are those of reading the rows and its own, added
    up over all tasks; a method without chance is run once a seed for them.
    """
    jobs: dict[str, tuple[str, int, int]] = {"gram": ("gram", 1, 0)}
    runs = seeds if timing else seeds[:1]
    for s in runs:
        if timing:
            jobs[f"gram-top|0|{s}"] = ("gram", 1, 0)
        for ell in ells:
            jobs[f"shrink|{ell}|{s}"] = ("shrink", ell, 0)
            jobs[f"zero|{ell}|{s}"] = ("zero", ell, 0)
    for method, kind in RANDOM.items():
        for ell in ells:
            for s in seeds:
                jobs[f"{method}|{ell}|{s}"] = (kind, ell, s)
    spent: dict[str, float] = {}
    found = baselines.accumulate(df, jobs, d, seconds=spent)
    gram = found["gram"]
    rows = []

    def add(method: str, ell: int, seed: int, b: np.ndarray, own: float) -> None:
        g = guarantee(ell, k)
        rows.append((name, method, ell, k, seed, measures.cov_error_of(gram, b), measures.proj_error_of(gram, b, k)[0], g[0], g[1], spent[""] + own if timing else None, measures.space_words("buffered" if method == "shrink" else method, ell, d)))

    for tag, b in found.items():
        if tag != "gram" and not tag.startswith("gram-top"):
            method, ell, s = tag.split("|")
            add(method, int(ell), int(s), b.rows if method == "shrink" else b, spent[tag])
    for ell in ells:
        for s in runs:
            clock = time.process_time()
            top = baselines.top_of_gram(gram, ell)
            add("gram-top", ell, int(s), top, spent.get(f"gram-top|0|{s}", 0.0) + time.process_time() - clock)
    return df.sparkSession.createDataFrame(rows, REPORT)


#: What holds for each method at every length, whatever the data.
CHECKS = {"shrink": ("within_guarantee", "not_below_gram_top"), "gram-top": ("least_error", "within_guarantee"), "zero": ("same_at_every_length",), "norm-sampling": ("not_below_gram_top",), "bucket-sign": ("not_below_gram_top",), "dense-sign": ("not_below_gram_top",)}


def report_checks(report: DataFrame) -> list[tuple[str, str, int, str, bool]]:
    """(dataset, method, ell, check, ok) of the medians of a report."""
    rows = report.collect()
    at = {(r["dataset"], r["method"], r["ell"]): r for r in rows}
    out = []
    for r in rows:
        top = at[r["dataset"], "gram-top", r["ell"]]
        others = [x for x in rows if x["dataset"] == r["dataset"] and x["method"] == r["method"]]
        own = {
            "within_guarantee": bool(r["within"]),
            "not_below_gram_top": r["cov_error"] >= top["cov_error"] - 1e-9,
            "least_error": all(x["cov_error"] >= r["cov_error"] - 1e-9 for x in rows if (x["dataset"], x["ell"]) == (r["dataset"], r["ell"])),
            "same_at_every_length": len({round(x["cov_error"], 12) for x in others}) == 1,
        }
        out += [(r["dataset"], r["method"], r["ell"], c, bool(own[c])) for c in CHECKS[r["method"]]]
        if r["seconds"] is not None:
            out.append((r["dataset"], r["method"], r["ell"], "timed", r["seconds"] > 0))
    return out


def medians(report: DataFrame) -> DataFrame:
    """The middle of the seeds' runs, with whether the guarantee holds there."""
    m = lambda c: F.expr(f"percentile({c}, 0.5)")
    out = report.groupBy("dataset", "method", "ell", "k").agg(m("cov_error").alias("cov_error"), m("proj_error").alias("proj_error"), F.first("guarantee_cov").alias("guarantee_cov"), F.first("guarantee_proj").alias("guarantee_proj"), m("seconds").alias("seconds"), F.first("words").alias("words"))
    return out.withColumn("within", (F.col("cov_error") <= F.col("guarantee_cov") + 1e-9) & F.coalesce(F.col("proj_error") <= F.col("guarantee_proj") + 1e-9, F.lit(True)))


def method_seconds(df: DataFrame, method: str, ell: int, d: int, runs: int = 1) -> float:
    """Median wall seconds of one method alone."""

    def run() -> None:
        if method == "shrink":
            sketch(df, ell, d=d).collect()
        elif method == "gram-top":
            baselines.gram_top(df, ell, d)
        else:
            baselines.accumulate(df, {"m": (RANDOM.get(method, "zero"), ell, 1)}, d)

    return measures.timed(run, runs)


def synthetic(spark: SparkSession, n: int = 10_000, d: int = 1000, m: int = 10, noise_div: float = 10.0, seed: int = 1) -> DataFrame:
    """The synthetic view, written once and reread by every method."""
    return materialise(datagen.signal_noise(spark, n, d, m, noise_div, seed), "synthetic")


def signal_sweep(spark: SparkSession, ms=(10, 20, 50), ells=ELLS, n: int = 10_000, d: int = 1000, timing: bool = False) -> DataFrame:
    """Errors (and times) against length, by signal dimension; k is the signal dimension."""
    out = None
    for m in ms:
        own = [e for e in ells if e > m]
        r = error_report(synthetic(spark, n, d, m), f"signal {m}", d, m, own, timing=timing)
        out = r if out is None else out.unionByName(r)
    return out


def noise_sweep(spark: SparkSession, noises=(5, 10, 15, 20), ells=ELLS, n: int = 10_000, d: int = 1000, m: int = 10, timing: bool = False) -> DataFrame:
    out = None
    for z in noises:
        r = error_report(synthetic(spark, n, d, m, float(z)), f"noise {z}", d, m, [e for e in ells if e > m], timing=timing)
        out = r if out is None else out.unionByName(r)
    return out


def scaling(df: DataFrame, times=(1, 2, 5, 10), ds=(512, 1024, 2048), ell: int = 40, runs: int = 3) -> DataFrame:
    """Processor seconds of the buffered sketch's kernel against rows and columns, with the exponents of both: (n, d, ell, seconds, mb_per_s, slope_n, slope_d).

    Rows are those of the view of 64 columns, whole and several times over, as products of all their entries with the first d / 64; seconds are the median of the runs.
    """
    spark, count, at = df.sparkSession, df.count(), {}
    ns = [count * t for t in times]
    for d in ds:
        wide = F.flatten(F.transform(F.slice("vec", 1, d // 64), lambda y: F.transform("vec", lambda x: x * y)))
        own = df.select("row_id", wide.alias("vec"))
        for t in times:
            spent: dict[str, float] = {}
            many = own.select("row_id", "vec", F.explode(F.sequence(F.lit(1), F.lit(t)))).select("row_id", "vec")
            baselines.accumulate(many, {f"s|{r}": ("shrink", ell, 0) for r in range(runs)}, d, seconds=spent)
            at[count * t, d] = float(np.median([spent[f"s|{r}"] for r in range(runs)]))
    slopes = {d: slope(np.array(ns), np.array([at[n, d] for n in ns])) for d in ds}
    across = {n: slope(np.array(ds), np.array([at[n, d] for d in ds])) for n in ns}
    rows = [(n, d, ell, s, n * d * 4 / 1e6 / s, slopes[d], across[n]) for (n, d), s in at.items()]
    return spark.createDataFrame(rows, "n long, d int, ell int, seconds double, mb_per_s double, slope_n double, slope_d double")


def slope(x: np.ndarray, y: np.ndarray) -> float:
    """Exponent of a power law through the points."""
    return float(np.polyfit(np.log(x), np.log(y), 1)[0])


def merging(df: DataFrame, d: int, ell: int, parts=(1, 4, 16, 64), fan_ins=(4, 32)) -> DataFrame:
    """Error and time against the number of parts and the fan-in: (parts, fan_in, rounds, cov_error, shed_share, seconds, moved_bytes).

    ``moved_bytes`` are the bodies of the packed rows that the merge tree reads.
    """
    spark = df.sparkSession
    gram = baselines.gram_block(df, d)
    f2 = float(np.trace(gram))
    rows = []
    for p in parts:
        local = materialise(local_sketches(df.repartition(p, "row_id"), ell, d=d), "local")
        moved = local.agg(F.sum(F.octet_length("body"))).first()[0]
        for f in fan_ins:
            clock = time.perf_counter()
            sk = Sketch.from_df(merge_tree(local, fan_in=f, tasks=p))
            rows.append((p, f, rounds_for(p, f), measures.cov_error_of(gram, sk.rows), sk.shed / f2, time.perf_counter() - clock, int(moved)))
    return spark.createDataFrame(rows, "parts int, fan_in int, rounds int, cov_error double, shed_share double, seconds double, moved_bytes long")


def paced_work(df: DataFrame, d: int, ell: int = 20, early: int = 200) -> DataFrame:
    """(most, early, overruns) of each task: the most work at one row of all, and of its first ``early``."""

    def run(batches):
        s, seen, most, first = PacedState(ell, d, trace=True), 0, 0, 0
        for rb in batches:
            x = vectors(rb.column(0), d)
            for at in range(0, len(x), early):
                s.extend(x[at : at + early])
                first = max([first, *s.flops[: max(0, early - seen)]])
                most, seen = max([most, *s.flops]), seen + len(s.flops)
                s.flops.clear()
        if seen:
            yield pa.RecordBatch.from_arrays([pa.array([most]), pa.array([first]), pa.array([s.overruns])], ["most", "early", "overruns"])

    return df.select("vec").mapInArrow(run, "most long, early long, overruns long")


def latencies(df: DataFrame, d: int, ell: int = 20, runs: int = 5) -> DataFrame:
    """(variant, mean, p50, p99, worst): seconds of single updates over all rows of a view, each the median of the runs."""

    def run(batches):
        makes = {"per_row": lambda: ShrinkState(ell, d, "per_row"), "buffered": lambda: ShrinkState(ell, d), "paced": lambda: PacedState(ell, d)}
        states = {(v, r): make() for v, make in makes.items() for r in range(runs)}
        for rb in batches:
            x = vectors(rb.column(0), d)
            for (v, r), state in states.items():
                each = measures.update_seconds(state, x)
                yield pa.RecordBatch.from_arrays([pa.array([v] * len(x)), pa.array(np.full(len(x), r, np.int32)), pa.array(each)], ["variant", "run", "seconds"])

    each = materialise(df.select("vec").mapInArrow(run, "variant string, run int, seconds double"), "latencies")
    by_run = each.groupBy("variant", "run").agg(F.avg("seconds").alias("mean"), F.percentile("seconds", F.lit(0.5)).alias("p50"), F.percentile("seconds", F.lit(0.99)).alias("p99"), F.max("seconds").alias("worst"))
    return by_run.groupBy("variant").agg(*[F.percentile(c, F.lit(0.5)).alias(c) for c in ("mean", "p50", "p99", "worst")])
