"""Registered queries of the sketching engine, with DuckDB oracles where the result does not depend on order."""

from __future__ import annotations

import uuid

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from rowsketch.operators import baselines as B
from rowsketch.operators import dist, items, measures, project
from rowsketch.operators.sketch import Sketch, counter_floor_bits, ell_for_cov, ell_for_heavy, ell_for_proj, guarantee, space_floor, space_floor_proj
from rowsketch.plans import harness, relational
from rowsketch.shared import materialise, scratch
from rowsketch.sources import datagen, store, view
from rowsketch.sources.tables import file_stream, load
from rowsketch.streaming import sketches as streams

def _round(c, n: int = 6):
    """Rounded, without a negative zero."""
    c = F.col(c) if isinstance(c, str) else c
    return F.round(c, n) + F.lit(0.0)


def _emb(spark, sf_dir):
    return view.emb(load(spark, sf_dir, "embeddings"))


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of the shrink sketch of the embeddings."""
    return dist.sketch_rows(dist.sketch(_emb(spark, sf_dir), 20, d=64))


# exact where there are fewer columns than sketch rows


def _scaled_numbers(spark, sf_dir, keys=()):
    """Numeric columns brought to order one."""
    l = load(spark, sf_dir, "lineitem")
    return view.from_columns(l.select(*keys, F.xxhash64(*l.columns).alias("row"), (F.col("l_quantity") / 50).alias("q"), (F.col("l_extendedprice") / 100000).alias("p"), "l_discount", "l_tax"), "row", ["q", "p", "l_discount", "l_tax"], list(keys))


def shrink_gram_exact_lineitem(spark, sf_dir):
    v = view.standardise(view.num(load(spark, sf_dir, "lineitem")), 4)
    return dist.sketch_gram(dist.sketch(v, 8, d=4)).select("i", "j", _round(F.col("g") / F.col("n_rows"), 5).alias("g"))


def shrink_gram_exact_events(spark, sf_dir):
    """Sums of squares of values with two decimals: four decimals are exact, so rounding never meets a tie."""
    g = dist.sketch_gram(dist.sketch(view.evt(load(spark, sf_dir, "events")), 8, d=5))
    return g.select("i", "j", _round("g", 4).alias("g"))


def shrink_gram_exact_custprio(spark, sf_dir):
    v = view.cust(load(spark, sf_dir, "orders")).select("row_id", F.transform("vec", lambda x: x / 1e6).alias("vec"))
    g = dist.sketch_gram(dist.sketch(v, 8, d=5))
    return g.select("i", "j", _round(F.col("g") / F.col("n_rows"), 5).alias("g"))


def shrink_grouped_events_day(spark, sf_dir):
    e = load(spark, sf_dir, "events").withColumn("day", F.date_format("ts", "yyyy-MM-dd"))
    g = dist.sketch_gram(dist.sketch(view.evt(e, ["day"]), 8, d=5, keys=["day"]), ["day"])
    return g.where("i = j").select("day", "i", _round("g", 4).alias("g"))


def shrink_grouped_flag(spark, sf_dir):
    keys = ["l_returnflag", "l_linestatus"]
    g = dist.sketch_gram(dist.sketch(_scaled_numbers(spark, sf_dir, keys), 8, d=4, keys=keys), keys)
    return g.select(*keys, "i", "j", _round(F.col("g") / F.col("n_rows")).alias("g"))


def merge_cube_flag(spark, sf_dir):
    keys = ["l_returnflag", "l_linestatus"]
    cells = dist.sketch(_scaled_numbers(spark, sf_dir, keys), 8, d=4, keys=keys)
    g = dist.sketch_gram(store.cube(cells, keys), [*keys, "grouping"])
    return g.where("i = j").select(*keys, "i", "n_rows", _round(F.col("g") / F.col("n_rows")).alias("g"))


# certificates


def _certified(rows_of):
    def query(spark, sf_dir):
        sk, gram = rows_of(spark, sf_dir)
        rows = [(c, k, ok) for c, k, _, _, ok in measures.certificate_rows(gram, sk)]
        return spark.createDataFrame(rows, "check_name string, k int, ok boolean")

    return query


def _cert_oracle(ell: int, d: int) -> str:
    ks = min(ell, d)
    return f"""
SELECT unnest(['never_more', 'never_less_than_shed', 'shed_is_paid_for', 'totals_carried', 'fewer_rows_than_ell']) AS check_name, 0::INTEGER AS k, true AS ok
UNION ALL SELECT c AS check_name, k::INTEGER AS k, true AS ok FROM (SELECT unnest(['shed_within_tail', 'projection_within_bound']) AS c) a, (SELECT unnest(range({ks})) AS k) b
"""


def _emb_variant(variant: str):
    def rows_of(spark, sf_dir):
        v = _emb(spark, sf_dir)
        return Sketch.from_df(dist.sketch(v, 20, d=64, variant=variant)), B.gram_block(v, 64)

    return _certified(rows_of)


def _merge_tree(spark, sf_dir):
    v = _emb(spark, sf_dir)
    return Sketch.from_df(dist.sketch(v, 20, d=64, order="stable", partitions=16, fan_in=4)), B.gram_block(v, 64)


def _doc(spark, sf_dir):
    """Sketch and Gram of the documents' words from one pass over the texts."""
    found = B.accumulate(view.doc(load(spark, sf_dir, "documents")), {"s": ("shrink", 40, 0), "g": ("gram", 1, 0)}, 256)
    return found["s"], found["g"]


def _hard(spark, sf_dir):
    """The block instance of the embeddings' signs: rows [e, R], R of a vector's signs over their root, and a unit row more for four of the 16 coordinates e."""
    slot = F.pmod("row_id", F.lit(16))
    unit = F.transform(F.sequence(F.lit(0), F.lit(15)), lambda i: (i == slot).cast("double"))
    v = _emb(spark, sf_dir)
    top = v.select("row_id", F.concat(unit, F.transform("vec", lambda x: F.when(x < 0, -1.0).otherwise(1.0) / 8)).alias("vec"))
    bottom = v.where(slot < 4).select("row_id", F.concat(unit, F.transform("vec", lambda x: F.lit(0.0))).alias("vec"))
    df = top.unionByName(bottom)
    return Sketch.from_df(dist.sketch(df, 12, d=80)), B.gram_block(df, 80)


def project_coords_cert(spark, sf_dir):
    """Energy of the projected rows lies between what the guarantee leaves and F2."""
    v = _emb(spark, sf_dir)
    sk = Sketch.from_df(dist.sketch(v, 20, d=64))
    k = 10
    e = project.project(v, sk, k).agg(F.sum(F.expr("aggregate(coords, 0D, (s, x) -> s + x * x)")).alias("e"))
    values = np.sort(np.linalg.eigvalsh(B.gram_block(v, 64)))[::-1]
    least = float(values.sum() - guarantee(20, k)[1] * values[k:].sum())
    return e.select(F.explode(F.array(F.struct(F.lit("energy_at_most_f2").alias("check_name"), (F.col("e") <= float(values.sum()) * (1 + 1e-9)).alias("ok")), F.struct(F.lit("energy_as_guaranteed").alias("check_name"), (F.col("e") >= least).alias("ok")))).alias("c")).select("c.*")


def pca_num(spark, sf_dir):
    """Components of the sketched, centred view agree with the exact covariance."""
    v = view.standardise(view.num(load(spark, sf_dir, "lineitem")), 4)
    sk, coords = project.pca(v, 2, 4, ell=8)
    exact = np.sort(np.linalg.eigvalsh(B.gram_block(view.center(v, 4), 4)))[::-1]
    ok = bool(np.allclose(sk.spectrum[:2], exact[:2], rtol=1e-6))
    return coords.agg(F.max(F.size("coords")).alias("w")).select(F.lit("spectrum_agrees").alias("check_name"), (F.lit(ok) & (F.col("w") == 2)).alias("ok"))


def counter_bounds_words(spark, sf_dir):
    """Bounds of the counters of all words; the exact counts are made once and serve every check."""
    words = view.tokens(load(spark, sf_dir, "documents"), "doc_id", "text")
    s = materialise(items.summarise(words, "token", 200), "summary")
    exact = materialise(items.exact_counts(words, "token"), "counts")
    gaps = exact.join(items.estimates(s).select("item", "low"), "item", "full_outer").select((F.coalesce("cnt", F.lit(0)) - F.coalesce("low", F.lit(0))).alias("gap"))
    one = gaps.agg(F.min("gap").alias("least_gap"), F.max("gap").alias("greatest_gap")).crossJoin(F.broadcast(s.select("n", "shed", "ell")))
    one = one.crossJoin(F.broadcast(items.tails(exact, 100).where("k = 100").select(F.col("tail"))))
    checks = [("never_too_high", F.col("least_gap") >= 0), ("never_lower_than_shed", F.col("greatest_gap") <= F.col("shed")), ("shed_within_n", F.col("shed") * F.col("ell") <= F.col("n")), ("shed_within_tail", F.col("shed") * 100 <= F.col("tail"))]
    return one.select(F.explode(F.array(*[F.struct(F.lit(n).alias("check_name"), c.alias("ok")) for n, c in checks])).alias("c")).select("c.*")


# counters and items


def indicator_equals_counters(spark, sf_dir):
    places = {t: i for i, t in enumerate(view.EVENT_TYPES)}
    v = view.from_items(load(spark, sf_dir, "events"), "event_id", "event_type", places)
    g = dist.sketch_gram(dist.sketch(v, 8, d=5, variant="per_row")).where("i = j")
    return g.select(F.element_at(F.array(*[F.lit(t) for t in view.EVENT_TYPES]), F.col("i") + 1).alias("item"), F.round("g").cast("long").alias("cnt"))


def counter_stream(spark, sf_dir):
    """Counters of all events by user, from the mergeable summary."""
    return items.estimates(items.summarise(load(spark, sf_dir, "events"), "user_id", 16)).select("item", "low", "high", "n", "shed")


def frequent_words_verified(spark, sf_dir):
    words = view.tokens(load(spark, sf_dir, "documents"), "doc_id", "text")
    return items.frequent_items(words, "token", 0.01).select("item", "cnt")


def exact_item_counts(spark, sf_dir):
    return items.exact_counts(load(spark, sf_dir, "lineitem"), "l_suppkey")


def exact_topk_items(spark, sf_dir):
    return items.exact_topk(load(spark, sf_dir, "lineitem"), "l_partkey", 10)


def tail_mass_by_k(spark, sf_dir):
    return items.tails(items.exact_counts(load(spark, sf_dir, "events"), "user_id"), 20)


# baselines


def gram_sql(spark, sf_dir):
    return B.gram_sql(_emb(spark, sf_dir)).select("i", "j", _round("g").alias("g"))


def gram_block(spark, sf_dir):
    g = B.gram_block(_emb(spark, sf_dir), 64)
    i, j = np.triu_indices(64)
    df = spark.createDataFrame([(int(a), int(b), float(g[a, b])) for a, b in zip(i, j)], "i int, j int, g double")
    return df.select("i", "j", _round("g").alias("g"))


def _two(spark, sf_dir):
    l = load(spark, sf_dir, "lineitem")
    return view.from_columns(l.select(F.xxhash64(*l.columns).alias("row"), (F.col("l_quantity") / 50).alias("q"), (F.col("l_extendedprice") / 100000).alias("p")), "row", ["q", "p"])


def gram_top_2d(spark, sf_dir):
    v = _two(spark, sf_dir)
    s = B.gram_top(v, 2, 2).spectrum
    n = v.count()
    return spark.createDataFrame([(i, float(x / n)) for i, x in enumerate(s)], "idx int, lam double").select("idx", _round("lam").alias("lam"))


def zero_cov_error_2d(spark, sf_dir):
    z = Sketch(np.zeros((2, 2)), 2, 2, 0, 0.0, 0.0)
    return spark.createDataFrame([(float(measures.cov_error(_two(spark, sf_dir), z)),)], "cov_error double").select(_round("cov_error").alias("cov_error"))


def zero_proj_error_2d(spark, sf_dir):
    z = Sketch(np.zeros((0, 2)), 2, 2, 0, 0.0, 0.0)
    return spark.createDataFrame([(float(measures.proj_error(_two(spark, sf_dir), z, 1)[0]),)], "proj_error double").select(_round("proj_error", 4).alias("proj_error"))


def zero_sketch_rows(spark, sf_dir):
    return B.zero_sketch(_emb(spark, sf_dir), 4).select("row_no", F.size("vec").cast("long").alias("width"), "n_rows", _round("f2").alias("f2"))


def norm_sample_rows(spark, sf_dir):
    return B.norm_sample_sql(_emb(spark, sf_dir), 20, 7).select("slot", "row_id")


def norm_sample_probs(spark, sf_dir):
    return B.norm_sample_sql(_emb(spark, sf_dir), 20, 7).select("slot", _round("p", 9).alias("p"))


def norm_sample_distinct(spark, sf_dir):
    return B.norm_sample_without_replacement(_emb(spark, sf_dir), 20, 7).select("row_id")


def bucket_sign_sketch(spark, sf_dir):
    return B.bucket_sign_sql(_emb(spark, sf_dir), 20, 7).select("bucket", "pos", _round("val").alias("val"))


def dense_sign_sketch(spark, sf_dir):
    return B.dense_sign_sql(_emb(spark, sf_dir), 8, 7).select("slot", "pos", _round("val").alias("val"))


def sparsified_energy(spark, sf_dir):
    s = B.sparsify(_emb(spark, sf_dir), 0.3, 7)
    return s.agg(F.count("*").alias("kept"), _round(F.sum(F.col("val") * F.col("val")), 3).alias("energy"))


def leverage_topk(spark, sf_dir):
    return B.leverage_sample(_emb(spark, sf_dir), 20, 10, 64, 7).select("row_id", "leverage")


def random_block_paths(spark, sf_dir):
    """Block paths of the three random methods: expected Gram trace against F2, by method."""
    v = _emb(spark, sf_dir)
    found = B.accumulate(v, {k: (k, 20, 3) for k in ("norm", "bucket", "dense", "zero")}, 64)
    f2 = measures.matrix_stats(v).first()["f2"]
    return spark.createDataFrame([(k, float((x * x).sum() / f2)) for k, x in found.items()], "method string, energy_share double")


def matrix_stats(spark, sf_dir):
    return measures.matrix_stats(_emb(spark, sf_dir)).select("n_rows", _round("f2", 5).alias("f2"), _round("max_norm2", 5).alias("max_norm2"))


GRID = [(k, e) for k in (0, 5, 10) for e in ("0.5", "0.1", "0.05")]


def size_calculators(spark, sf_dir):
    rows = [(k, float(e), ell_for_cov(k, e), ell_for_proj(k, e), ell_for_heavy(e)) for k, e in GRID]
    return spark.createDataFrame(rows, "k int, eps double, ell_cov long, ell_proj long, ell_heavy long")


def guarantee_curves(spark, sf_dir):
    """What is guaranteed for the events by user: squares that a direction may lose, and that the best k directions may leave."""
    counts = materialise(items.exact_counts(load(spark, sf_dir, "events"), "user_id"), "counts")
    tails = items.tails(counts, 10).where("k = 10").select("k", "tail").unionByName(counts.agg(F.lit(0).alias("k"), F.sum("cnt").alias("tail")))
    rows = [(ell, k, *guarantee(ell, k)) for ell in (12, 20, 40, 100) for k in (0, 10)]
    curves = spark.createDataFrame(rows, "ell int, k int, cov double, proj double").join(F.broadcast(tails), "k").crossJoin(F.broadcast(counts.agg(F.sum("cnt").alias("f2"))))
    return curves.select("ell", "k", _round(F.col("cov") * F.col("f2"), 4).alias("cov"), _round(F.col("proj") * F.col("tail"), 4).alias("proj"))


def heavy_directions_events(spark, sf_dir):
    sk = Sketch.from_df(dist.sketch(view.evt(load(spark, sf_dir, "events")), 8, d=5))
    rows = [(view.EVENT_TYPES[int(np.abs(h["vec"]).argmax())], h["sigma2"] / sk.f2) for h in sk.heavy_directions(eps=0.2) if h["certain"]]
    return spark.createDataFrame(rows, "event_type string, share double").select("event_type", _round("share", 5).alias("share"))


def choose_rank_num(spark, sf_dir):
    sk = Sketch.from_df(dist.sketch(_scaled_numbers(spark, sf_dir), 8, d=4))
    k, spans = sk.choose_rank((0.05 * sk.f2) ** 0.5)
    return spark.createDataFrame([(i, lo / sk.f2, hi / sk.f2, i < k) for i, (lo, hi) in enumerate(spans)], "idx int, low double, high double, kept boolean")


# experiments

_MADE: dict[tuple, tuple] = {}


def _once(spark, sf_dir, name, make):
    """A report, which is small, is made once a session and table folder; its checks read the same rows."""
    at = (spark.sparkContext.applicationId, name, sf_dir)
    if at not in _MADE:
        made = make()
        if not isinstance(made, DataFrame):
            return made
        _MADE[at] = (made.collect(), made.schema)
    return spark.createDataFrame(*_MADE[at])


def error_report_emb(spark, sf_dir):
    return _once(spark, sf_dir, "emb", lambda: harness.medians(harness.error_report(_emb(spark, sf_dir), "embeddings", 64, 10, timing=True)))


def error_report_doc(spark, sf_dir):
    return _once(spark, sf_dir, "doc", lambda: harness.medians(harness.error_report(view.doc(load(spark, sf_dir, "documents"), 312), "documents", 312, 100, (110, 150, 200), timing=True)))


def error_report_syn(spark, sf_dir):
    return _once(spark, sf_dir, "syn", lambda: harness.medians(harness.error_report(harness.synthetic(spark), "synthetic", 1000, 10, timing=True)))


def signal_dimension_report(spark, sf_dir):
    return _once(spark, sf_dir, "signal", lambda: harness.medians(harness.signal_sweep(spark, timing=True)))


def noise_report(spark, sf_dir):
    return _once(spark, sf_dir, "noise", lambda: harness.medians(harness.noise_sweep(spark, timing=True)))


def merge_report(spark, sf_dir):
    return _once(spark, sf_dir, "merge", lambda: harness.merging(_emb(spark, sf_dir), 64, 20))


def scaling_report(spark, sf_dir):
    return _once(spark, sf_dir, "scaling", lambda: harness.scaling(_emb(spark, sf_dir)))


def latency_report(spark, sf_dir):
    return _once(spark, sf_dir, "latency", lambda: harness.latencies(_emb(spark, sf_dir), 64))


def _checks_of(report):
    def query(spark, sf_dir):
        return spark.createDataFrame(harness.report_checks(report(spark, sf_dir)), "dataset string, method string, ell int, check_name string, ok boolean")

    return query


def _named(spark, checks: dict[str, bool]) -> DataFrame:
    return spark.createDataFrame([(n, bool(ok)) for n, ok in checks.items()], "check_name string, ok boolean")


def merge_checks(spark, sf_dir):
    """Merging keeps the guarantee at every number of parts and fan-in, and moves no more than a sketch a part."""
    rows = merge_report(spark, sf_dir).collect()
    return spark.createDataFrame([(r["parts"], r["fan_in"], r["rounds"], bool(r["cov_error"] <= 1 / 20 and r["shed_share"] <= 1 / 20), bool(0 < r["moved_bytes"] <= r["parts"] * 19 * 64 * 8)) for r in rows], "parts int, fan_in int, rounds int, within boolean, moved_within boolean")


def scaling_checks(spark, sf_dir):
    """Time grows in proportion to rows, and with columns no faster than that (a solve of fixed size goes with every shrink)."""
    rows = scaling_report(spark, sf_dir).collect()
    return spark.createDataFrame([(r["n"], r["d"], bool(0.7 <= r["slope_n"] <= 1.3), bool(0 < r["slope_d"] <= 1.4)) for r in rows], "n long, d int, linear_in_rows boolean, within_linear_in_columns boolean")


def latency_checks(spark, sf_dir):
    """The paced variant bounds the work of each row, whatever the number of rows; the median update of the others is cheap, their worst is a whole shrink."""
    work = harness.paced_work(_emb(spark, sf_dir), 64).collect()
    rows = {r["variant"]: r for r in latency_report(spark, sf_dir).collect()}
    return _named(spark, {"paced_work_does_not_grow": all(r["most"] == r["early"] for r in work), "paced_never_overruns": all(r["overruns"] == 0 for r in work), "buffered_median_below_worst": rows["buffered"]["p50"] < rows["buffered"]["worst"], "buffered_mean_below_per_row": rows["buffered"]["mean"] < rows["per_row"]["mean"]})


def pair_constants(spark, sf_dir):
    """Constants of the lower-bound instances; the squares of the pair are those of every embedding's direction, farthest from their mean."""

    def squares(batches):
        for rb in batches:
            x = dist.vectors(rb.column(0), 64)
            x = x[x.any(axis=1)]
            pairs = [datagen.pair_instance(v / np.linalg.norm(v)) for v in x]
            s = np.linalg.svd(np.stack(pairs), compute_uv=False) ** 2 if pairs else np.zeros((0, 2))
            yield pa.RecordBatch.from_arrays([pa.array(s[:, 0]), pa.array(s[:, 1])], ["first_square", "second_square"])

    found = _emb(spark, sf_dir).select("vec").mapInArrow(squares, "first_square double, second_square double")
    one = lambda c: F.when(F.max(c) - F.min(c) < 1e-9, F.avg(c)).alias(c)
    values = found.agg(F.lit(datagen.ZETA).alias("zeta"), F.lit(datagen.ZETA_AT).alias("zeta_at"), one("first_square"), one("second_square"))
    return values.unpivot([], ["zeta", "zeta_at", "first_square", "second_square"], "name", "v").select("name", _round("v").alias("v"))


def space_floors(spark, sf_dir):
    """Orders of the space that any method needs, beside the sketch's own."""
    rows = [(k, float(e), space_floor(64, k, e), space_floor_proj(64, k, e), counter_floor_bits(k, e), ell_for_cov(k, e) * 64) for k, e in GRID]
    return spark.createDataFrame(rows, "k int, eps double, words double, proj_bits double, counter_bits double, sketch_words long").select("k", "eps", _round("words").alias("words"), _round("proj_bits").alias("proj_bits"), _round("counter_bits").alias("counter_bits"), "sketch_words")


def primitive_values(spark, sf_dir):
    """Squared singular values of [1, x; 1, 0] at the discounts of the line items."""

    def squares(batches):
        for rb in batches:
            s = np.array([np.linalg.svd(datagen.primitive(x), compute_uv=False) ** 2 for x in rb.column(0).to_pylist()]).reshape(-1, 2)
            yield pa.RecordBatch.from_arrays([rb.column(0), pa.array(s[:, 0]), pa.array(s[:, 1])], ["x", "l1", "l2"])

    x = load(spark, sf_dir, "lineitem").select(F.col("l_discount").cast("double").alias("x")).where("x is not null").distinct()
    return x.mapInArrow(squares, "x double, l1 double, l2 double").select("x", _round("l1").alias("l1"), _round("l2").alias("l2"))


def sign_decoding(spark, sf_dir):
    """Signs hidden in the block instance are read off the projection, for each chosen row and several sizes."""
    rows = []
    for k, r, d in ((2, 8, 200), (4, 16, 400)):
        x = datagen.block_instance(k, r, d, seed=3)
        chosen = sorted(int(v) for v in x[r:, :r].argmax(axis=1))
        sk = Sketch.of(x, r + k + 1)
        for c in chosen:
            hidden = np.sign(x[c, r:])
            rows.append((k, r, d, bool((datagen.decode_signs(x, k, r, c) == hidden).mean() > 0.9), bool((datagen.decode_signs(sk.rows, k, r, c) == hidden).mean() > 0.9)))
    return spark.createDataFrame(rows, "k int, r int, d int, from_rows boolean, from_sketch boolean").groupBy("k", "r", "d").agg(F.count("*").alias("n"), F.every("from_rows").alias("from_rows"), F.every("from_sketch").alias("from_sketch"))


def hard_instances(spark, sf_dir):
    """The embeddings on ell / 4 directions are kept whole; the binary rows of the events' types keep their row space."""
    basis = datagen.projection_instance(20, 64)

    def project(batches):
        for rb in batches:
            x = dist.vectors(rb.column(1), 64) @ basis.T @ basis
            yield pa.RecordBatch.from_arrays([rb.column(0), pa.array(list(x), pa.list_(pa.float64()))], ["row_id", "vec"])

    p = _emb(spark, sf_dir).mapInArrow(project, "row_id long, vec array<double>")
    exact = B.gram_block(p, 64)
    b = view.from_items(load(spark, sf_dir, "events"), "event_id", "event_type", {t: i for i, t in enumerate(view.EVENT_TYPES)})
    kept, rows = Sketch.from_df(dist.sketch(b, 6, d=5)), np.array([r["vec"] for r in b.select("vec").distinct().collect()])
    return _named(spark, {"projection_kept": np.allclose(Sketch.from_df(dist.sketch(p, 20, d=64)).gram(), exact, atol=1e-9 * np.trace(exact)), "binary_space_kept": np.linalg.matrix_rank(np.vstack([kept.rows, rows])) == np.linalg.matrix_rank(kept.rows) == np.linalg.matrix_rank(rows)})


def kernel_variants(spark, sf_dir):
    """Every SVD back-end and buffer factor keeps the certificate; the loss of each shrink is what the trace says."""
    v = _emb(spark, sf_dir)
    gram = B.gram_block(v, 64)
    rows = []
    for variant, svd, factor in (("per_row", "lapack", 2.0), ("per_row", "gram", 2.0), ("per_row", "arrowhead", 2.0), ("buffered", "lapack", 2.0), ("buffered", "gram", 1.25), ("buffered", "gram", 2.0), ("buffered", "gram", 4.0)):
        sk = Sketch.from_df(dist.sketch(v, 20, d=64, variant=variant, svd=svd, buffer_factor=factor))
        rows.append((variant, svd, factor, all(r[4] for r in measures.certificate_rows(gram, sk))))
    return spark.createDataFrame(rows, "variant string, svd string, factor double, ok boolean")


def shrink_trace(spark, sf_dir):
    """Each shrink takes ell times its own square at least, nothing is lost between shrinks, and their sum is what was shed."""
    from rowsketch.kernel.shrink import ShrinkState

    names = ["each_pays_for_its_shed", "sum_is_shed", "nothing_lost_between", "as_many_as_expected"]

    def run(batches):
        s, f2 = ShrinkState(12, 64, trace=True), 0.0
        for rb in batches:
            x = dist.vectors(rb.column(0), 64)
            s.extend(x)
            f2 += float((x * x).sum())
        live, lost = s.rows[: s.live], sum(b - a for _, b, a in s.trace)
        ok = [all(12 * t <= (b - a) * (1 + 1e-9) for t, b, a in s.trace), abs(sum(t for t, _, _ in s.trace) - s.shed) <= 1e-9 * f2, abs(f2 - lost - float((live * live).sum())) <= 1e-9 * f2, s.shrinks == len(s.trace)]
        yield pa.RecordBatch.from_arrays([pa.array([bool(x)]) for x in ok], names)

    found = _emb(spark, sf_dir).select("vec").mapInArrow(run, ", ".join(f"{n} boolean" for n in names)).agg(*[F.every(n).alias(n) for n in names])
    return found.unpivot([], names, "check_name", "ok")


def block_path_identities(spark, sf_dir):
    """Sampled rows carry F2 exactly, zero carries none, signs and Gaussians carry it on the average of many seeds."""
    v = _emb(spark, sf_dir)
    f2 = measures.matrix_stats(v).first()["f2"]
    jobs = {f"{k}|{s}": (k, 20, s) for k in ("bucket", "dense") for s in range(20)} | {"norm|0": ("norm", 20, 3), "zero|0": ("zero", 20, 3)}
    share = {t: float((b * b).sum() / f2) for t, b in B.accumulate(v, jobs, 64).items()}
    gauss = [float((b * b).sum() / f2) for b in B.accumulate(v, {f"g|{s}": ("dense", 20, s) for s in range(20)}, 64, dist="gaussian").values()]
    mean = lambda k: float(np.mean([x for t, x in share.items() if t.startswith(k)]))
    return _named(spark, {"norm_exact": abs(share["norm|0"] - 1) < 1e-9, "zero_none": share["zero|0"] == 0, "bucket_mean": abs(mean("bucket") - 1) < 0.1, "dense_mean": abs(mean("dense") - 1) < 0.1, "gaussian_mean": abs(float(np.mean(gauss)) - 1) < 0.1})


def leverage_full_rank(spark, sf_dir):
    """With all directions a row's leverage is its squared length, so the draw is that of norm sampling."""
    return B.leverage_sample(_emb(spark, sf_dir), 20, 64, 64, 7).select("row_id")


def choose_rank_2d(spark, sf_dir):
    """Rank by threshold over two columns, where the squares have a closed form."""
    sk = Sketch.from_df(dist.sketch(_two(spark, sf_dir), 8, d=2))
    k, spans = sk.choose_rank((0.05 * sk.f2) ** 0.5)
    rows = [(i, lo / sk.f2, hi / sk.f2, i < k) for i, (lo, hi) in enumerate(spans)]
    return spark.createDataFrame(rows, "idx int, low double, high double, kept boolean").select("idx", _round("low").alias("low"), _round("high").alias("high"), "kept")


def sql_quad_events(spark, sf_dir):
    """Certified quadratic forms in SQL: along an event type's axis they are its sum of squares."""
    from rowsketch.functions.vectors import register

    register(spark)
    packed = dist.sketch(view.evt(load(spark, sf_dir, "events")), 8, d=5)
    rows = dist.sketch_rows(packed).agg(F.collect_list("vec").alias("rows"))
    axes = spark.createDataFrame([(t, [float(i == j) for j in range(5)]) for i, t in enumerate(view.EVENT_TYPES)], "event_type string, axis array<double>")
    axes.crossJoin(F.broadcast(rows)).crossJoin(F.broadcast(packed.select("shed"))).createOrReplaceTempView("event_axes")
    return spark.sql("SELECT event_type, round(quad_lo(rows, axis), 4) + 0D AS low, round(quad_hi(rows, axis, shed), 4) + 0D AS high, vec_dot(axis, axis) AS length2 FROM event_axes")


def algebra_checks(spark, sf_dir):
    """Column subsets, products and shorter sketches keep the two-sided bound with their own shed."""
    v = _emb(spark, sf_dir)
    gram, sk = B.gram_block(v, 64), Sketch.from_df(dist.sketch(v, 20, d=64))
    idx = list(range(0, 64, 3))
    w = np.random.default_rng(1).standard_normal((64, 7))
    inside = lambda g, s: bool(-1e-8 * np.trace(gram) <= np.linalg.eigvalsh(g - s.gram())[0] and np.linalg.eigvalsh(g - s.gram())[-1] <= s.shed + 1e-8 * np.trace(gram))
    return _named(spark, {"columns": inside(gram[np.ix_(idx, idx)], sk.columns(idx)), "product": inside(w.T @ gram @ w, sk.right_multiply(w)), "shorter": inside(gram, sk.reduce(10))})


def counter_topk_residual(spark, sf_dir):
    """What the counters leave beyond the k most frequent words, against the exact tail."""
    words = materialise(view.tokens(load(spark, sf_dir, "documents"), "doc_id", "text").select("token"), "words")
    r = items.topk_residual(words, "token", items.summarise(words, "token", 200), 50).first()
    return _named(spark, {"not_below_tail": r["tail"] <= r["residual"], "within_factor": r["residual"] * 150 <= 200 * r["tail"]})


# consumers


def tfidf_buckets(spark, sf_dir):
    """Weighted word counts, summed by bucket."""
    v = view.tfidf(view.from_text(load(spark, sf_dir, "documents"), "doc_id", "text", 64), 64)
    return v.select(F.posexplode("vec").alias("bucket", "x")).groupBy("bucket").agg(_round(F.sum("x"), 4).alias("total")).where("total > 0")


def store_periods(spark, sf_dir):
    """Stored daily sketches answer for three days without the data."""
    path = _scratch(spark)
    e = load(spark, sf_dir, "events").withColumn("day", F.date_format("ts", "yyyy-MM-dd"))
    store.write(dist.sketch(view.evt(e, ["day"]), 8, d=5, keys=["day"]), path, "events", "day")
    g = dist.sketch_gram(store.answer(spark, path, "events", ["2024-01-03", "2024-01-05", "2024-01-20"]))
    return g.where("i = j").select("i", "n_rows", _round("g", 4).alias("g"))


def residual_function(spark, sf_dir):
    """The residual as a scalar pandas function adds up to what the projection leaves."""
    v = _emb(spark, sf_dir)
    sk = Sketch.from_df(dist.sketch(v, 20, d=64))
    left = project.residuals(v, sk, 5).agg(F.sum("residual")).first()[0]
    norm = project.residual_norm_udf(sk, 5)
    own = v.select(norm("vec").alias("r")).agg(F.sum(F.col("r") * F.col("r"))).first()[0]
    return _named(spark, {"adds_up": abs(own - left) <= 1e-6 * left})


def lsi_checks(spark, sf_dir):
    """Every query has its best documents, in order, with cosines."""
    from pyspark.sql import Window

    found = materialise(lsi_topk(spark, sf_dir), "lsi")
    asked = view.tokens(load(spark, sf_dir, "benchmark"), "item_id", "text").select("row_id").distinct().count()
    order = Window.partitionBy("query_id").orderBy("rank")
    falls = found.select((F.col("score") <= F.coalesce(F.lag("score").over(order), F.lit(2.0))).alias("ok"), F.col("score").between(-1.000001, 1.000001).alias("unit")).agg(F.every("ok").alias("ok"), F.every("unit").alias("unit")).first()
    return _named(spark, {"five_a_query": found.count() == 5 * asked, "falling": falls["ok"], "cosines": falls["unit"]})


def residual_checks(spark, sf_dir):
    """What a rank-20 sketch leaves lies between the best and what the guarantee allows."""
    v = view.doc(load(spark, sf_dir, "documents"))
    found = B.accumulate(v, {"s": ("shrink", 40, 0), "g": ("gram", 1, 0)}, 256)
    tail = float(np.sort(np.linalg.eigvalsh(found["g"]))[::-1][20:].sum())
    left = project.residuals(v, found["s"], 20).agg(F.sum("residual")).first()[0]
    return _named(spark, {"not_below_best": left >= tail * (1 - 1e-9), "within_guarantee": left <= guarantee(40, 20)[1] * tail * (1 + 1e-9)})


def kmeans_checks(spark, sf_dir):
    """All rows have one of ten clusters, whose means are nearer to them than the common mean."""
    v = _emb(spark, sf_dir)
    coords = project.project(v, Sketch.from_df(dist.sketch(v, 20, d=64)), 10)
    both = kmeans_coords(spark, sf_dir).join(coords, "row_id").toPandas()
    x = np.stack(both["coords"].to_numpy())
    inside = sum(float(((x[both.cluster == c] - x[both.cluster == c].mean(axis=0)) ** 2).sum()) for c in both.cluster.unique())
    return _named(spark, {"all_rows": len(both) == v.count(), "at_most_ten": both.cluster.nunique() <= 10, "nearer": inside < float(((x - x.mean(axis=0)) ** 2).sum())})



def lsi_topk(spark, sf_dir):
    return project.lsi(load(spark, sf_dir, "documents"), load(spark, sf_dir, "benchmark"))


def residual_rank(spark, sf_dir):
    """Documents by what a rank-20 sketch leaves of them, within their quality label."""
    from pyspark.sql import Window

    v = view.doc(load(spark, sf_dir, "documents"))
    sk = Sketch.from_df(dist.sketch(v, 40, d=256))
    r = project.residuals(v, sk, 20).join(load(spark, sf_dir, "labels").select(F.col("doc_id").alias("row_id"), "quality"), "row_id")
    return r.select("row_id", "quality", "residual", F.row_number().over(Window.partitionBy("quality").orderBy(F.desc("residual"), "row_id")).alias("rank"))


def kmeans_coords(spark, sf_dir):
    v = _emb(spark, sf_dir)
    return project.kmeans(project.project(v, Sketch.from_df(dist.sketch(v, 20, d=64)), 10), 10)


def sql_table_function(spark, sf_dir):
    """The sketch of each label's vectors through SQL."""
    from rowsketch.functions.vectors import register

    register(spark)
    load(spark, sf_dir, "embeddings").select(F.col("label").cast("string").alias("key"), F.col("embedding").cast("array<double>").alias("vec")).createOrReplaceTempView("labelled_vectors")
    return spark.sql("SELECT key, count(*) AS rows_kept, max(n_rows) AS n_rows FROM shrink_sketch(row => TABLE(labelled_vectors) PARTITION BY key, ell => 8) GROUP BY key")


# streams


def _events_stream(spark, sf_dir):
    schema = load(spark, sf_dir, "events").schema
    return spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet*")


def _scratch(spark) -> str:
    return f"{scratch(spark)}/stream-{uuid.uuid4().hex}"


def stream_tumbling_f2(spark, sf_dir):
    base = _scratch(spark)
    w = streams.window_energy(_events_stream(spark, sf_dir), "ts", "1 day")
    streams.run_available(w, f"{base}/checkpoint", lambda b, i: b.write.mode("overwrite").parquet(f"{base}/out/batch={i:010d}"), "update")
    got = spark.read.parquet(f"{base}/out")
    latest = got.groupBy("window_start").agg(F.max_by(F.struct("n_rows", "f2"), "batch").alias("x"))
    return latest.select(F.col("window_start").cast("timestamp_ntz").alias("window_start"), "x.n_rows", _round("x.f2", 2).alias("f2"))


def stream_global_gram(spark, sf_dir):
    base = _scratch(spark)
    streams.global_sketch(view.evt(_events_stream(spark, sf_dir)), 8, 5, f"{base}/out", f"{base}/checkpoint")
    g = dist.sketch_gram(streams.read_global(spark, f"{base}/out"))
    return g.where("i = j").select("i", "n_rows", _round("g", 4).alias("g"))


def stream_sliding_gram(spark, sf_dir):
    base = _scratch(spark)
    streams.window_sketches(view.evt(_events_stream(spark, sf_dir), ["ts"]), 8, 5, "ts", "1 day", f"{base}/out", f"{base}/checkpoint")
    wide = streams.sliding(streams.tumbling(spark, f"{base}/out"), 3, 86400)
    g = dist.sketch_gram(wide, ["window_start"])
    return g.where("i = j").select("window_start", "i", "n_rows", _round("g", 4).alias("g"))


def stream_counters(spark, sf_dir):
    base = _scratch(spark)
    streams.stream_counters(_events_stream(spark, sf_dir), "event_type", 8, f"{base}/out", f"{base}/checkpoint")
    return items.estimates(streams.read_counters(spark, f"{base}/out")).select("item", F.col("low").alias("cnt"))


def stream_late_rows(spark, sf_dir):
    """Rows of the second batch that the watermark, set by the first, drops and counts."""
    base = _scratch(spark)
    e = load(spark, sf_dir, "events")
    for k in (0, 1):  # files are read in the order of their writing
        e.where(F.col("event_id") % 2 == k).coalesce(1).write.mode("append").parquet(f"{base}/in")
    stream = file_stream(spark, f"{base}/in", e.schema)
    streams.window_sketches(view.evt(stream, ["ts"]), 8, 5, "ts", "1 day", f"{base}/out", f"{base}/checkpoint", watermark="7 days")
    kept = streams.tumbling(spark, f"{base}/out").agg(F.sum("n_rows").alias("kept"))
    return streams.late_rows(spark, f"{base}/out").crossJoin(kept).select(F.col("n_rows").alias("late"), _round("f2", 4).alias("f2_late"), "kept")


def stream_sessions(spark, sf_dir):
    """Sketches of the users' sessions: events at most half an hour apart."""
    base = _scratch(spark)
    streams.session_sketches(view.evt(_events_stream(spark, sf_dir), ["ts", "user_id"]), "ts", "user_id", 8, 5, 1800, f"{base}/out", f"{base}/checkpoint")
    return streams.sessions(spark, f"{base}/out", 1800).select("key", F.col("session_start").cast("timestamp_ntz").alias("session_start"), F.col("session_end").cast("timestamp_ntz").alias("session_end"), "n_rows", _round("f2", 4).alias("f2"))


def stream_with_table(spark, sf_dir):
    """Events of a stream by the market segment of their user, from a table that stands still."""
    base = _scratch(spark)
    c = load(spark, sf_dir, "customer").select("c_custkey", "c_mktsegment")
    joined = streams.with_table(_events_stream(spark, sf_dir), c, "user_id", "c_custkey")
    streams.run_available(joined.select("c_mktsegment", "value"), f"{base}/checkpoint", lambda b, i: b.write.mode("overwrite").parquet(f"{base}/out/batch={i:010d}"))
    return spark.read.parquet(f"{base}/out").groupBy(F.coalesce("c_mktsegment", F.lit("none")).alias("segment")).agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("total"))


def stream_paced_keys(spark, sf_dir):
    """Paced sketches by event type in the engine's own state: totals, and the bounded work of a row."""
    base = _scratch(spark)
    keyed = streams.keyed_sketches(view.evt(_events_stream(spark, sf_dir), ["event_type"]), "event_type", 8, 5, variant="paced")
    streams.run_available(keyed, f"{base}/checkpoint", lambda b, i: b.write.mode("overwrite").parquet(f"{base}/out/batch={i:010d}"), "update")
    last = spark.read.parquet(f"{base}/out").groupBy("event_type").agg(F.max_by(F.struct("n_rows", "f2", "shed"), "n_rows").alias("x"), F.max("most_flops").alias("most"))
    return last.select("event_type", "x.n_rows", _round("x.f2", 4).alias("f2"), (F.col("most") <= 400 * 8 * 8 * 8).alias("bounded"))


QUERIES = {
    f.__name__: f
    for f in (
        shrink_gram_exact_lineitem, shrink_gram_exact_events, shrink_gram_exact_custprio, shrink_grouped_events_day, shrink_grouped_flag, merge_cube_flag,
        project_coords_cert, pca_num, counter_bounds_words, indicator_equals_counters, counter_stream, frequent_words_verified, exact_item_counts, exact_topk_items, tail_mass_by_k,
        gram_sql, gram_block, gram_top_2d, zero_cov_error_2d, zero_proj_error_2d, zero_sketch_rows, norm_sample_rows, norm_sample_probs, norm_sample_distinct, bucket_sign_sketch, dense_sign_sketch,
        sparsified_energy, leverage_topk, random_block_paths, matrix_stats, size_calculators, guarantee_curves, heavy_directions_events, choose_rank_num,
        error_report_emb, error_report_doc, error_report_syn, signal_dimension_report, noise_report, merge_report, scaling_report, latency_report, pair_constants,
        lsi_topk, residual_rank, kmeans_coords, sql_table_function, stream_tumbling_f2, stream_global_gram, stream_sliding_gram, stream_counters,
        merge_checks, scaling_checks, latency_checks, space_floors, primitive_values, sign_decoding, hard_instances, kernel_variants, shrink_trace, block_path_identities, leverage_full_rank,
        choose_rank_2d, sql_quad_events, algebra_checks, counter_topk_residual, tfidf_buckets, store_periods, residual_function, lsi_checks, residual_checks, kmeans_checks, stream_late_rows, stream_sessions, stream_with_table, stream_paced_keys,
    )
} | {
    "shrink_per_row_cert": _emb_variant("per_row"),
    "shrink_buffered_cert": _emb_variant("buffered"),
    "shrink_paced_cert": _emb_variant("paced"),
    "merge_tree_cert": _certified(_merge_tree),
    "shrink_doc_cert": _certified(_doc),
    "hard_instance_cert": _certified(_hard),
    "error_checks_emb": _checks_of(error_report_emb),
    "error_checks_doc": _checks_of(error_report_doc),
    "error_checks_syn": _checks_of(error_report_syn),
    "signal_dimension_checks": _checks_of(signal_dimension_report),
    "noise_checks": _checks_of(noise_report),
} | relational.QUERIES

# oracles

_CELLS = "SELECT vec_id, generate_subscripts(embedding, 1) - 1 AS pos, unnest(embedding)::DOUBLE AS x FROM embeddings"
_WEIGHT = "SELECT vec_id, list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)) AS w FROM embeddings"
_DIGEST = "('0x' || substr(md5({}), 1, 8))::BIGINT"
_EVENTS = "(VALUES ('click', 0), ('error', 1), ('purchase', 2), ('signup', 3), ('view', 4)) AS t(event_type, i)"
_NUMBERS = "l_quantity / 50 AS a0, l_extendedprice / 100000 AS a1, l_discount AS a2, l_tax AS a3"
_PAIRS = "(SELECT i, j FROM (SELECT unnest(range(4)) AS i) p, (SELECT unnest(range(4)) AS j) q WHERE i <= j) ij"
_TWO = "SELECT sum((l_quantity / 50) * (l_quantity / 50)) AS a, sum((l_quantity / 50) * (l_extendedprice / 100000)) AS b, sum((l_extendedprice / 100000) * (l_extendedprice / 100000)) AS c, count(*) AS n FROM lineitem"
_EIGEN = f"SELECT n, a + c AS f2, (a + c) / 2 + sqrt(((a - c) / 2) * ((a - c) / 2) + b * b) AS l1, (a + c) / 2 - sqrt(((a - c) / 2) * ((a - c) / 2) + b * b) AS l2 FROM ({_TWO}) t"
_RACE = f"SELECT slot, arg_min(vec_id, race) AS row_id, arg_min(w, race) AS w FROM (SELECT slot, vec_id, w, -ln(({_DIGEST.format(chr(39) + chr(39) + ' || vec_id || ' + chr(39) + ':' + chr(39) + ' || slot || ' + chr(39) + ':7' + chr(39))} + 0.5) / 4294967296.0) / w AS race FROM ({_WEIGHT}) v, (SELECT unnest(range(20)) AS slot) s) r GROUP BY slot"


def _entry(i: str) -> str:
    return f"CASE {i} WHEN 0 THEN a0 WHEN 1 THEN a1 WHEN 2 THEN a2 ELSE a3 END"


def _checks_oracle(grid: list[tuple[str, tuple[int, ...]]]) -> str:
    """The checks of reports, by data set and its lengths."""
    rows = [f"('{name}', '{m}', {ell}, '{c}')" for name, ells in grid for m, checks in harness.CHECKS.items() for ell in ells for c in (*checks, "timed")]
    return f"SELECT dataset, method, ell::INTEGER AS ell, check_name, true AS ok FROM (VALUES {', '.join(rows)}) AS t(dataset, method, ell, check_name)"


def _names_oracle(*names: str) -> str:
    return f"SELECT unnest([{', '.join(repr(n) for n in names)}]) AS check_name, true AS ok"


def _beyond(m: int) -> tuple[int, ...]:
    return tuple(e for e in harness.ELLS if e > m)


ORACLES = {
    "error_checks_emb": _checks_oracle([("embeddings", harness.ELLS)]),
    "error_checks_doc": _checks_oracle([("documents", (110, 150, 200))]),
    "error_checks_syn": _checks_oracle([("synthetic", harness.ELLS)]),
    "signal_dimension_checks": _checks_oracle([(f"signal {m}", _beyond(m)) for m in (10, 20, 50)]),
    "noise_checks": _checks_oracle([(f"noise {z}", _beyond(10)) for z in (5, 10, 15, 20)]),
    "merge_checks": "SELECT p::INTEGER AS parts, f::INTEGER AS fan_in, greatest(1, ceil(round(ln(p) / ln(f), 9)))::INTEGER AS rounds, true AS within, true AS moved_within FROM (SELECT unnest([1, 4, 16, 64]) AS p) a, (SELECT unnest([4, 32]) AS f) b",
    "scaling_checks": "SELECT n::BIGINT AS n, d::INTEGER AS d, true AS linear_in_rows, true AS within_linear_in_columns FROM (SELECT count(*) * t AS n FROM embeddings, (SELECT unnest([1, 2, 5, 10]) AS t) m GROUP BY t) a, (SELECT unnest([512, 1024, 2048]) AS d) b",
    "latency_checks": _names_oracle("paced_work_does_not_grow", "paced_never_overruns", "buffered_median_below_worst", "buffered_mean_below_per_row"),
    "space_floors": "SELECT k::INTEGER AS k, eps, round(64 * (k + 1 / eps), 6) AS words, round(64 * k / eps, 6) AS proj_bits, round(k / eps, 6) AS counter_bits, (64 * ceil(round(k + 1 / eps, 9)))::BIGINT AS sketch_words FROM (SELECT unnest([0, 5, 10]) AS k) a, (SELECT unnest([0.5::DOUBLE, 0.1::DOUBLE, 0.05::DOUBLE]) AS eps) b",
    "primitive_values": "SELECT x, round((2 + x * x + sqrt(4 + x * x * x * x)) / 2, 6) AS l1, round((2 + x * x - sqrt(4 + x * x * x * x)) / 2, 6) AS l2 FROM (SELECT DISTINCT l_discount::DOUBLE AS x FROM lineitem WHERE l_discount IS NOT NULL) t",
    "sign_decoding": "SELECT * FROM (VALUES (2, 8, 200, 2::BIGINT, true, true), (4, 16, 400, 4::BIGINT, true, true)) AS t(k, r, d, n, from_rows, from_sketch)",
    "hard_instances": _names_oracle("projection_kept", "binary_space_kept"),
    "kernel_variants": "SELECT variant, svd, factor::DOUBLE AS factor, true AS ok FROM (VALUES ('per_row', 'lapack', 2.0), ('per_row', 'gram', 2.0), ('per_row', 'arrowhead', 2.0), ('buffered', 'lapack', 2.0), ('buffered', 'gram', 1.25), ('buffered', 'gram', 2.0), ('buffered', 'gram', 4.0)) AS t(variant, svd, factor)",
    "shrink_trace": _names_oracle("each_pays_for_its_shed", "sum_is_shed", "nothing_lost_between", "as_many_as_expected"),
    "block_path_identities": _names_oracle("norm_exact", "zero_none", "bucket_mean", "dense_mean", "gaussian_mean"),
    "choose_rank_2d": f"SELECT 0::INTEGER AS idx, round(l1 / f2, 6) AS low, round(l1 / f2, 6) AS high, l1 >= 0.05 * f2 AS kept FROM ({_EIGEN}) e UNION ALL SELECT 1::INTEGER, round(l2 / f2, 6), round(l2 / f2, 6), l2 >= 0.05 * f2 FROM ({_EIGEN}) e",
    "sql_quad_events": f"SELECT t.event_type, round(coalesce(sum(value * value), 0), 4) + 0.0 AS low, round(coalesce(sum(value * value), 0), 4) + 0.0 AS high, 1.0::DOUBLE AS length2 FROM {_EVENTS} LEFT JOIN events USING (event_type) GROUP BY t.event_type",
    "algebra_checks": _names_oracle("columns", "product", "shorter"),
    "counter_topk_residual": _names_oracle("not_below_tail", "within_factor"),
    "tfidf_buckets": "WITH t AS (SELECT doc_id, unnest(regexp_extract_all(lower(text), '[a-z]+')) AS token FROM documents), c AS (SELECT doc_id, (('0x' || substr(md5(token), 1, 8))::BIGINT % 64)::INTEGER AS bucket, count(*) AS n FROM t GROUP BY 1, 2), d AS (SELECT bucket, sum(n) AS n, count(*) AS df FROM c GROUP BY bucket) SELECT bucket, round(n * (ln((1 + (SELECT count(DISTINCT doc_id) FROM t)) / (1 + df)) + 1), 4) + 0.0 AS total FROM d",
    "store_periods": f"WITH e AS (SELECT event_type, value FROM events WHERE strftime(ts, '%Y-%m-%d') IN ('2024-01-03', '2024-01-05', '2024-01-20')) SELECT t.i::INTEGER AS i, (SELECT count(*) FROM e) AS n_rows, round(coalesce(sum(value * value), 0), 4) + 0.0 AS g FROM {_EVENTS} LEFT JOIN e USING (event_type) GROUP BY t.i",
    "residual_function": _names_oracle("adds_up"),
    "lsi_checks": _names_oracle("five_a_query", "falling", "cosines"),
    "residual_checks": _names_oracle("not_below_best", "within_guarantee"),
    "kmeans_checks": _names_oracle("all_rows", "at_most_ten", "nearer"),
    "sql_table_function": "SELECT label::VARCHAR AS key, least(count(*), 7) AS rows_kept, count(*) AS n_rows FROM embeddings GROUP BY label",
    "stream_late_rows": "WITH m AS (SELECT max(ts) - INTERVAL 7 DAY AS least FROM events WHERE event_id % 2 = 0), l AS (SELECT value, event_id % 2 = 1 AND ts < least AS late FROM events, m) SELECT count(*) FILTER (WHERE late) AS late, round(coalesce(sum(value * value) FILTER (WHERE late), 0), 4) + 0.0 AS f2_late, (count(*) FILTER (WHERE NOT late))::BIGINT AS kept FROM l",
    "stream_sessions": "WITH o AS (SELECT user_id, ts, value, coalesce(ts - lag(ts) OVER w > INTERVAL 30 MINUTE, true) AS opens FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)), n AS (SELECT *, sum(opens::INTEGER) OVER (PARTITION BY user_id ORDER BY ts ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS nth FROM o) SELECT user_id::VARCHAR AS key, min(ts) AS session_start, max(ts) AS session_end, count(*) AS n_rows, round(sum(value * value), 4) + 0.0 AS f2 FROM n GROUP BY user_id, nth",
    "stream_with_table": "SELECT coalesce(c_mktsegment, 'none') AS segment, count(*) AS n, round(sum(value), 2) AS total FROM events LEFT JOIN customer ON user_id = c_custkey GROUP BY 1",
    "stream_paced_keys": "SELECT event_type, count(*) AS n_rows, round(sum(value * value), 4) + 0.0 AS f2, true AS bounded FROM events GROUP BY event_type",
    "shrink_gram_exact_lineitem": f"""
WITH m AS (SELECT avg(l_quantity) AS m0, stddev_pop(l_quantity) AS s0, avg(l_extendedprice) AS m1, stddev_pop(l_extendedprice) AS s1, avg(l_discount) AS m2, stddev_pop(l_discount) AS s2, avg(l_tax) AS m3, stddev_pop(l_tax) AS s3 FROM lineitem),
z AS (SELECT (l_quantity - m0) / s0 AS a0, (l_extendedprice - m1) / s1 AS a1, (l_discount - m2) / s2 AS a2, (l_tax - m3) / s3 AS a3 FROM lineitem, m)
SELECT i::INTEGER AS i, j::INTEGER AS j, round(avg(({_entry("i")}) * ({_entry("j")})), 5) + 0.0 AS g FROM z, {_PAIRS} GROUP BY i, j""",
    "shrink_gram_exact_events": f"""
WITH s AS (SELECT t.i, coalesce(sum(value * value), 0) AS f FROM {_EVENTS} LEFT JOIN events USING (event_type) GROUP BY t.i)
SELECT a.i::INTEGER AS i, b.i::INTEGER AS j, round(CASE WHEN a.i = b.i THEN a.f ELSE 0 END, 4) + 0.0 AS g FROM s a, s b WHERE a.i <= b.i""",
    "shrink_gram_exact_custprio": """
WITH c AS (SELECT o_custkey, [coalesce(sum(o_totalprice) FILTER (WHERE o_orderpriority = '1-URGENT'), 0) / 1e6, coalesce(sum(o_totalprice) FILTER (WHERE o_orderpriority = '2-HIGH'), 0) / 1e6, coalesce(sum(o_totalprice) FILTER (WHERE o_orderpriority = '3-MEDIUM'), 0) / 1e6, coalesce(sum(o_totalprice) FILTER (WHERE o_orderpriority = '4-NOT SPECIFIED'), 0) / 1e6, coalesce(sum(o_totalprice) FILTER (WHERE o_orderpriority = '5-LOW'), 0) / 1e6] AS v FROM orders GROUP BY o_custkey)
SELECT i::INTEGER AS i, j::INTEGER AS j, round(avg(v[i + 1] * v[j + 1]), 5) + 0.0 AS g FROM c, (SELECT i, j FROM (SELECT unnest(range(5)) AS i) p, (SELECT unnest(range(5)) AS j) q WHERE i <= j) ij GROUP BY i, j""",
    "shrink_grouped_events_day": f"""
WITH d AS (SELECT strftime(ts, '%Y-%m-%d') AS day, event_type, value FROM events), n AS (SELECT DISTINCT day FROM d)
SELECT n.day, t.i::INTEGER AS i, round(coalesce(sum(value * value), 0), 4) + 0.0 AS g FROM n CROSS JOIN {_EVENTS} LEFT JOIN d ON d.day = n.day AND d.event_type = t.event_type GROUP BY n.day, t.i""",
    "shrink_grouped_flag": f"SELECT l_returnflag, l_linestatus, i::INTEGER AS i, j::INTEGER AS j, round(avg(({_entry('i')}) * ({_entry('j')})), 6) + 0.0 AS g FROM (SELECT l_returnflag, l_linestatus, {_NUMBERS} FROM lineitem) z, {_PAIRS} GROUP BY l_returnflag, l_linestatus, i, j",
    "merge_cube_flag": f"SELECT l_returnflag, l_linestatus, i::INTEGER AS i, count(*) AS n_rows, round(avg(({_entry('i')}) * ({_entry('i')})), 6) + 0.0 AS g FROM (SELECT l_returnflag, l_linestatus, {_NUMBERS} FROM lineitem) z, (SELECT unnest(range(4)) AS i) p GROUP BY GROUPING SETS ((i), (i, l_returnflag), (i, l_linestatus), (i, l_returnflag, l_linestatus))",
    "shrink_per_row_cert": _cert_oracle(20, 64),
    "shrink_buffered_cert": _cert_oracle(20, 64),
    "shrink_paced_cert": _cert_oracle(20, 64),
    "merge_tree_cert": _cert_oracle(20, 64),
    "shrink_doc_cert": _cert_oracle(40, 256),
    "hard_instance_cert": _cert_oracle(12, 80),
    "project_coords_cert": "SELECT unnest(['energy_at_most_f2', 'energy_as_guaranteed']) AS check_name, true AS ok",
    "pca_num": "SELECT 'spectrum_agrees' AS check_name, true AS ok",
    "counter_bounds_words": "SELECT unnest(['never_too_high', 'never_lower_than_shed', 'shed_within_n', 'shed_within_tail']) AS check_name, true AS ok",
    "indicator_equals_counters": "SELECT event_type AS item, count(*) AS cnt FROM events GROUP BY event_type",
    "frequent_words_verified": "WITH t AS (SELECT unnest(regexp_extract_all(lower(text), '[a-z]+')) AS item FROM documents) SELECT item, count(*) AS cnt FROM t GROUP BY item HAVING count(*) > 0.01 * (SELECT count(*) FROM t)",
    "exact_item_counts": "SELECT l_suppkey::VARCHAR AS item, count(*) AS cnt FROM lineitem GROUP BY l_suppkey",
    "exact_topk_items": "SELECT l_partkey::VARCHAR AS item, count(*) AS cnt FROM lineitem GROUP BY l_partkey ORDER BY cnt DESC, item LIMIT 10",
    "tail_mass_by_k": "SELECT k::INTEGER AS k, (n - head)::BIGINT AS tail FROM (SELECT row_number() OVER (ORDER BY cnt DESC, u) AS k, sum(cnt) OVER (ORDER BY cnt DESC, u) AS head, sum(cnt) OVER () AS n FROM (SELECT user_id::VARCHAR AS u, count(*) AS cnt FROM events GROUP BY 1) c) t WHERE k <= 20",
    "gram_sql": f"WITH c AS ({_CELLS}) SELECT a.pos::INTEGER AS i, b.pos::INTEGER AS j, round(sum(a.x * b.x), 6) + 0.0 AS g FROM c a JOIN c b ON a.vec_id = b.vec_id AND a.pos <= b.pos GROUP BY a.pos, b.pos",
    "gram_block": f"WITH c AS ({_CELLS}) SELECT a.pos::INTEGER AS i, b.pos::INTEGER AS j, round(sum(a.x * b.x), 6) + 0.0 AS g FROM c a JOIN c b ON a.vec_id = b.vec_id AND a.pos <= b.pos GROUP BY a.pos, b.pos",
    "gram_top_2d": f"SELECT 0::INTEGER AS idx, round(l1 / n, 6) AS lam FROM ({_EIGEN}) e UNION ALL SELECT 1::INTEGER AS idx, round(l2 / n, 6) AS lam FROM ({_EIGEN}) e",
    "zero_cov_error_2d": f"SELECT round(l1 / f2, 6) AS cov_error FROM ({_EIGEN}) e",
    "zero_proj_error_2d": f"SELECT round(f2 / l2, 4) AS proj_error FROM ({_EIGEN}) e",
    "zero_sketch_rows": f"SELECT r::INTEGER AS row_no, 64::BIGINT AS width, n AS n_rows, f2 FROM (SELECT count(*) AS n, round(sum(w), 6) AS f2 FROM ({_WEIGHT}) v) t, (SELECT unnest(range(4)) AS r) q",
    "norm_sample_rows": f"SELECT slot::INTEGER AS slot, row_id FROM ({_RACE}) w",
    "norm_sample_probs": f"SELECT slot::INTEGER AS slot, round(w / (SELECT sum(w) FROM ({_WEIGHT}) t), 9) AS p FROM ({_RACE}) w",
    "norm_sample_distinct": f"SELECT vec_id AS row_id FROM ({_WEIGHT}) v ORDER BY -ln(({_DIGEST.format(chr(39) + chr(39) + ' || vec_id || ' + chr(39) + ':0:7' + chr(39))} + 0.5) / 4294967296.0) / w, vec_id LIMIT 20",
    "bucket_sign_sketch": f"SELECT ({_DIGEST.format(chr(39) + chr(39) + ' || vec_id || ' + chr(39) + ':b:7' + chr(39))} % 20)::INTEGER AS bucket, pos::INTEGER AS pos, round(sum(CASE WHEN {_DIGEST.format(chr(39) + chr(39) + ' || vec_id || ' + chr(39) + ':s:7' + chr(39))} % 2 = 0 THEN x ELSE -x END), 6) + 0.0 AS val FROM ({_CELLS}) c GROUP BY 1, 2",
    "dense_sign_sketch": f"SELECT slot::INTEGER AS slot, pos::INTEGER AS pos, round(sum(CASE WHEN {_DIGEST.format(chr(39) + chr(39) + ' || vec_id || ' + chr(39) + ':' + chr(39) + ' || slot || ' + chr(39) + ':7' + chr(39))} % 2 = 0 THEN x ELSE -x END) / sqrt(8.0), 6) + 0.0 AS val FROM ({_CELLS}) c, (SELECT unnest(range(8)) AS slot) s GROUP BY 1, 2",
    "sparsified_energy": f"WITH c AS (SELECT * FROM ({_CELLS}) z WHERE x <> 0), p AS (SELECT x, least(1.0, 0.3 * x * x / (SELECT avg(x * x) FROM c)) AS p, ({_DIGEST.format(chr(39) + chr(39) + ' || vec_id || ' + chr(39) + ':' + chr(39) + ' || pos || ' + chr(39) + ':7' + chr(39))} + 0.5) / 4294967296.0 AS u FROM c) SELECT count(*) AS kept, round(sum((x / p) * (x / p)), 3) AS energy FROM p WHERE u < p",
    "matrix_stats": f"SELECT count(*) AS n_rows, round(sum(w), 5) AS f2, round(max(w), 5) AS max_norm2 FROM ({_WEIGHT}) v",
    "size_calculators": "SELECT k::INTEGER AS k, eps, ceil(round(k + 1 / eps, 9))::BIGINT AS ell_cov, ceil(round(k + k / eps, 9))::BIGINT AS ell_proj, (floor(round(1 / eps, 9)) + 1)::BIGINT AS ell_heavy FROM (SELECT unnest([0, 5, 10]) AS k) a, (SELECT unnest([0.5::DOUBLE, 0.1::DOUBLE, 0.05::DOUBLE]) AS eps) b",
    "guarantee_curves": "WITH c AS (SELECT user_id, count(*) AS n, row_number() OVER (ORDER BY count(*) DESC, user_id) AS place FROM events GROUP BY user_id) SELECT ell::INTEGER AS ell, k::INTEGER AS k, round(sum(n) / ell, 4) AS cov, round(ell / (ell - k) * coalesce(sum(n) FILTER (WHERE place > k), 0), 4) AS proj FROM c, (SELECT unnest([12, 20, 40, 100])::DOUBLE AS ell) a, (SELECT unnest([0, 10]) AS k) b GROUP BY ell, k",
    "heavy_directions_events": "SELECT event_type, round(share, 5) AS share FROM (SELECT event_type, sum(value * value) / sum(sum(value * value)) OVER () AS share FROM events GROUP BY event_type) t WHERE share >= 0.2",
    "pair_constants": "SELECT unnest(['zeta', 'zeta_at', 'first_square', 'second_square']) AS name, round(unnest([2 / sqrt(5) + sqrt(5) / 10 - 0.5, sqrt(0.5 - sqrt(5) / 10), (3 + sqrt(5)) / 2, (3 - sqrt(5)) / 2]), 6) AS v",
    "stream_tumbling_f2": "SELECT date_trunc('day', ts)::TIMESTAMP AS window_start, count(*) AS n_rows, round(sum(value * value), 2) AS f2 FROM events GROUP BY 1",
    "stream_global_gram": f"SELECT t.i::INTEGER AS i, (SELECT count(*) FROM events) AS n_rows, round(coalesce(sum(value * value), 0), 4) AS g FROM {_EVENTS} LEFT JOIN events USING (event_type) GROUP BY t.i",
    "stream_sliding_gram": f"""
WITH d AS (SELECT date_trunc('day', ts)::TIMESTAMP AS day, event_type, value FROM events),
w AS (SELECT day - to_days(k::INTEGER) AS window_start, event_type, value FROM d, (SELECT unnest(range(3)) AS k) s), n AS (SELECT window_start, count(*) AS n FROM w GROUP BY 1)
SELECT n.window_start, t.i::INTEGER AS i, any_value(n.n) AS n_rows, round(coalesce(sum(value * value), 0), 4) + 0.0 AS g FROM n CROSS JOIN {_EVENTS} LEFT JOIN w ON w.window_start = n.window_start AND w.event_type = t.event_type GROUP BY n.window_start, t.i""",
    "stream_counters": "SELECT event_type AS item, count(*) AS cnt FROM events GROUP BY event_type",
} | relational.ORACLES
ORACLES["leverage_full_rank"] = ORACLES["norm_sample_distinct"]
