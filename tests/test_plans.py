"""Plans: what is not shuffled, how many rounds there are, and what a task holds."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from rowsketch.operators import baselines as B
from rowsketch.operators import dist, measures, project
from rowsketch.operators.sketch import Sketch
from rowsketch.plans import harness
from rowsketch.sources import datagen, tables, view


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


def test_texts_are_counted_without_a_shuffle(spark, sf):
    docs = tables.load(spark, sf, "documents")
    v = view.from_text(docs, "doc_id", "text", 64)
    assert "Exchange" not in plan(v)
    got = {r["row_id"]: r["vec"] for r in v.collect()}
    t = view.tokens(docs, "doc_id", "text").groupBy("row_id", view.token_bucket(F.col("token"), 64).alias("i")).count().collect()
    want = {}
    for r in t:
        want.setdefault(r["row_id"], [0.0] * 64)[r["i"]] = float(r["count"])
    assert got == want
    odd = spark.createDataFrame([(1, None), (2, ""), (3, "123 !"), (4, "A a K İx"), (4, "again")], "doc_id long, text string")
    assert sorted((r["row_id"], sum(r["vec"])) for r in view.from_text(odd, "doc_id", "text", 8).collect()) == [(4, 1.0), (4, 5.0)]


def test_sketch_and_gram_from_one_scan(spark, sf):
    v = view.emb(tables.load(spark, sf, "embeddings"))
    spent = {}
    found = B.accumulate(v.repartition(9), {"s": ("shrink", 12, 0), "g": ("gram", 1, 0)}, 64, fan_in=2, seconds=spent)
    assert all(r[4] for r in measures.certificate_rows(found["g"], found["s"])) and found["s"].n_rows == 500
    assert set(spent) == {"", "s", "g"} and all(x > 0 for x in spent.values())
    assert B.accumulate(v.where("false"), {"s": ("shrink", 4, 0)}, 64)["s"].n_rows == 0


def test_numbers_of_tasks(spark, sf, tmp_path):
    spark.range(100).repartition(37).write.parquet(str(tmp_path / "many"))
    files = spark.read.parquet(str(tmp_path / "many"))
    assert dist.partitions_of(files) == files.rdd.getNumPartitions()
    assert dist.partitions_of(files.repartition(11)) == 11
    assert dist.partitions_of(files.repartition(11).union(files)) == dist.MANY_TASKS
    assert dist.partitions_of(files.union(files)) == 2 * files.rdd.getNumPartitions()


@pytest.mark.parametrize("limit", [1 << 28, 2000])
def test_grouped_by_codes(spark, monkeypatch, limit):
    """Keys of several types, nulls among them; with little room a key is handed on more than once."""
    rng = np.random.default_rng(1)
    x = rng.standard_normal((400, 4))
    keys = [(None if k % 7 == 0 else f"k{k % 5}", None if k % 11 == 0 else k % 3) for k in range(400)]
    df = spark.createDataFrame([(*keys[k], k, x[k].tolist()) for k in range(400)], "a string, b int, row_id long, vec array<double>").coalesce(2)
    monkeypatch.setattr(dist, "STATE_BYTES", limit)
    monkeypatch.setattr(dist, "BATCH_BYTES", 200)
    got = dist.sketch(df, 6, d=4, keys=["a", "b"]).collect()
    assert len(got) == len(set(keys))
    for r in got:
        own = x[[k for k in range(400) if keys[k] == (r["a"], r["b"])]]
        rows = Sketch.from_row(r).rows
        assert r["n_rows"] == len(own) and np.allclose(rows.T @ rows, own.T @ own)


def test_many_keys(spark):
    df = spark.range(20_000).select((F.col("id") % 4000).alias("user"), F.col("id").alias("row_id"), F.array(F.lit(1.0), F.col("id").cast("double")).alias("vec"))
    got = dist.sketch(df, 4, d=2, keys=["user"])
    assert got.agg(F.count("*"), F.sum("n_rows")).first()[:] == (4000, 20_000)


@pytest.mark.parametrize("size", ["3", "64", "10000"])
def test_runs_of_keys(spark, size):
    """Sorted runs give the sketches of the tree, wherever Arrow batches end, with no group of its own for a key."""
    rng = np.random.default_rng(2)
    x, who = rng.standard_normal((600, 3)), np.concatenate([np.arange(200), rng.integers(0, 40, 360), np.full(40, 7)])
    x[5] = 0.0
    keys = [(None if k % 13 == 0 else f"u{k}", int(k % 3)) for k in who.tolist()]
    df = spark.createDataFrame([(*keys[k], k, x[k].tolist()) for k in range(600)], "a string, b long, row_id long, vec array<double>").repartition(5, "row_id")
    before = spark.conf.get("spark.sql.execution.arrow.maxRecordsPerBatch")
    spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", size)
    try:
        found = dist.merge_runs(dist.local_runs(df, 4, d=3, keys=["a", "b"]), keys=["a", "b"], fan_in=2, tasks=5)
        assert "FlatMapGroups" not in plan(found)
        got = found.collect()
    finally:
        spark.conf.set("spark.sql.execution.arrow.maxRecordsPerBatch", before)
    assert len(got) == len(set(keys))
    for r in got:
        own = x[[k for k in range(600) if keys[k] == (r["a"], r["b"])]]
        sk = Sketch.from_row(r)
        gap = np.linalg.eigvalsh(own.T @ own - sk.rows.T @ sk.rows)
        assert r["n_rows"] == len(own) and np.isclose(r["f2"], (own * own).sum()) and len(sk.rows) < 4
        assert gap[0] >= -1e-8 and gap[-1] <= sk.shed + 1e-8 and 4 * sk.shed <= r["f2"] + 1e-8


def test_nearest_by_blocks_of_queries(spark, sf):
    docs, asked = tables.load(spark, sf, "documents"), tables.load(spark, sf, "benchmark")
    one = {(r["query_id"], r["rank"]): (r["row_id"], round(r["score"], 9)) for r in project.lsi(docs, asked).collect()}
    some = {(r["query_id"], r["rank"]): (r["row_id"], round(r["score"], 9)) for r in project.lsi(docs, asked, block=3).collect()}
    assert one == some and len(one) == 5 * len({q for q, _ in one})
    text = plan(project.lsi(docs, asked))  # the only cross join is with the one row of word weights
    assert "Cartesian" not in text and text.count("BroadcastNestedLoopJoin BuildRight, Cross") <= 2
    assert project.lsi(docs, asked.where("false")).count() == 0


def test_races_carry_no_vectors(spark, sf):
    v = view.emb(tables.load(spark, sf, "embeddings"))
    text = B.norm_sample_sql(v, 20, 7)._jdf.queryExecution().optimizedPlan().toString()
    assert "min_by(struct(row_id" in text and "vec" not in text.split("min_by", 1)[1].split("\n", 1)[0]
    signs = plan(B.dense_sign_sql(v, 8, 7))
    assert "BroadcastNestedLoopJoin" not in signs and "Cartesian" not in signs


def test_report_has_times_and_checks(spark):
    a = datagen.signal_noise(spark, 400, 30, 3, 10.0, 1)
    full = harness.error_report(a, "x", 30, 3, (6, 12), (1, 2, 3), timing=True)
    assert full.where("seconds is null").count() == 0 and full.where("method = 'shrink' and ell = 6").count() == 3
    checks = harness.report_checks(harness.medians(full))
    assert checks and all(ok for *_, ok in checks), [c for c in checks if not c[-1]]
    assert {c[3] for c in checks} == {"within_guarantee", "not_below_gram_top", "least_error", "same_at_every_length", "timed"}


def test_method_seconds_is_a_median(spark, sf):
    v = view.emb(tables.load(spark, sf, "embeddings"))
    assert all(harness.method_seconds(v, m, 12, 64, runs=3) > 0 for m in ("shrink", "gram-top", "zero", "bucket-sign"))


def test_sparse_rows(spark):
    df = spark.createDataFrame([(1, [0, 3], [1.0, 2.0]), (2, [], []), (3, [9, 1], [5.0, 4.0])], "id long, i array<int>, x array<double>")
    got = {r["row_id"]: r["vec"] for r in view.from_sparse(df, "id", "i", "x", 4).collect()}
    assert got == {1: [1.0, 0.0, 0.0, 2.0], 2: [0.0] * 4, 3: [0.0, 4.0, 0.0, 0.0]}
