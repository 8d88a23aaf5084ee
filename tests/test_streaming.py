"""Late rows, sessions, bounded work by key, and tables beside a stream, against plain counts."""

import math
from datetime import datetime, timedelta

import numpy as np
import pytest
from pyspark.sql import functions as F

from rowsketch.operators import baselines
from rowsketch.sources import tables, view
from rowsketch.streaming import sketches as streams

START = datetime(2024, 1, 1)


def at(minutes):
    return START + timedelta(minutes=minutes)


def feed(spark, path, batches):
    """One file a batch, read in this order."""
    schema = "row_id long, ts timestamp, user string, vec array<double>"
    for rows in batches:
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(path)
    return tables.file_stream(spark, path, spark.createDataFrame([], schema).schema)


def test_late_rows_are_dropped_and_counted(spark, tmp_path):
    base = str(tmp_path)
    batches = [[(1, at(0), "a", [1.0, 0.0]), (2, at(600), "a", [2.0, 0.0])], [(3, at(545), "a", [0.0, 3.0]), (4, at(530), "a", [0.0, 5.0])], [(5, at(5), "a", [7.0, 0.0]), (6, at(541), "a", [1.0, 1.0])]]
    stream = feed(spark, f"{base}/in", batches)
    streams.window_sketches(stream, 3, 2, "ts", "1 hour", f"{base}/out", f"{base}/c", watermark="1 hour")
    late = streams.late_rows(spark, f"{base}/out").first()
    assert (late["n_rows"], late["f2"]) == (2, 25.0 + 49.0)
    got = {r["pane"]: (r["n_rows"], r["f2"]) for r in streams.tumbling(spark, f"{base}/out").collect()}
    assert sum(n for n, _ in got.values()) == 4 and math.isclose(sum(f for _, f in got.values()), 1 + 4 + 9 + 2)


def test_without_a_watermark_nothing_is_late(spark, tmp_path):
    base = str(tmp_path)
    stream = feed(spark, f"{base}/in", [[(1, at(6000), "a", [1.0, 0.0])], [(2, at(0), "a", [2.0, 0.0])]])
    streams.window_sketches(stream, 3, 2, "ts", "1 hour", f"{base}/out", f"{base}/c")
    assert streams.tumbling(spark, f"{base}/out").count() == 2


def test_sessions_over_batches(spark, tmp_path):
    """Sessions of a user are found whichever batch their events come in."""
    base, rng = str(tmp_path), np.random.default_rng(1)
    rows = [(k, at(float(rng.integers(0, 3000))), "abc"[int(rng.integers(0, 3))], rng.standard_normal(3).tolist()) for k in range(200)]
    stream = feed(spark, f"{base}/in", [rows[k::3] for k in range(3)])
    streams.session_sketches(stream, "ts", "user", 4, 3, 1200, f"{base}/out", f"{base}/c")
    want = {}
    for user in "abc":
        now = None
        for _, t, _, v in sorted((r for r in rows if r[2] == user), key=lambda r: r[1]):
            if now is None or t - now[1] > timedelta(seconds=1200):
                now = want[user, t] = [t, t, 0, 0.0]
            now[1], now[2], now[3] = t, now[2] + 1, now[3] + float(np.dot(v, v))
    got = {(r["key"], r["session_start"]): (r["session_end"], r["n_rows"], r["f2"]) for r in streams.sessions(spark, f"{base}/out", 1200).collect()}
    assert got.keys() == want.keys() and len(got) > 10
    for k, (_, end, n, f2) in want.items():
        assert got[k][:2] == (end, n) and math.isclose(got[k][2], f2)


def test_session_totals(spark, sf, tmp_path):
    """The built-in session windows hold every event, and agree with the sketched sessions."""
    base = str(tmp_path)
    e = tables.load(spark, sf, "events").select("event_id", "ts", F.col("user_id").cast("string").alias("user"), "event_type", "value")
    e.coalesce(1).write.parquet(f"{base}/in")
    stream = lambda: tables.file_stream(spark, f"{base}/in", e.schema)
    streams.session_sketches(view.evt(stream(), ["ts", "user"]), "ts", "user", 8, 5, 1800, f"{base}/out", f"{base}/c")
    mine = {(r["key"], r["session_start"]): (r["n_rows"], round(r["f2"], 4)) for r in streams.sessions(spark, f"{base}/out", 1800).collect()}
    streams.run_available(streams.session_energy(stream(), "ts", "user", watermark="60 days"), f"{base}/cs", lambda b, i: b.write.mode("append").parquet(f"{base}/s"), "complete")
    theirs = {}
    for r in spark.read.parquet(f"{base}/s").collect():
        theirs[r["user"], r["session_start"]] = (r["n_rows"], round(r["f2"], 4))
    assert mine == theirs and sum(n for n, _ in mine.values()) == e.count()


def test_many_sessions_have_no_group_of_their_own(spark, tmp_path):
    """A session costs a row of a sorted batch, not a call of Python."""
    base = str(tmp_path)
    stream = feed(spark, f"{base}/in", [[(1, at(0), "a", [1.0, 0.0]), (2, at(31), "a", [2.0, 0.0])], [(3, at(5), "b", [0.0, 3.0])]])
    streams.session_sketches(stream, "ts", "user", 3, 2, 1800, f"{base}/out", f"{base}/c")
    found = streams.sessions(spark, f"{base}/out", 1800)
    assert found.count() == 3 and "FlatMapGroups" not in found._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("variant", ["per_row", "buffered", "paced"])
def test_keyed_variants(spark, tmp_path, variant):
    base, rng = str(tmp_path), np.random.default_rng(2)
    x = rng.standard_normal((900, 12))
    batches = [[(k, at(k), "ab"[k % 2], x[k].tolist()) for k in range(b * 300, (b + 1) * 300)] for b in range(3)]
    keyed = streams.keyed_sketches(feed(spark, f"{base}/in", batches), "user", 5, 12, variant=variant)
    streams.run_available(keyed, f"{base}/c", lambda b, i: b.write.parquet(f"{base}/out/batch={i}"), "update")
    for k, user in enumerate("ab"):
        last = spark.read.parquet(f"{base}/out").where(F.col("user") == user).orderBy(F.desc("n_rows")).first()
        own = x[k::2]
        rows = np.frombuffer(bytes(last["body"])).reshape(last["live"], 12)
        gap = np.linalg.eigvalsh(own.T @ own - rows.T @ rows)
        assert last["n_rows"] == 450 and math.isclose(last["f2"], float((own * own).sum()))
        assert gap[0] >= -1e-8 and gap[-1] <= last["shed"] + 1e-8 and 5 * last["shed"] <= last["f2"]
        assert variant != "paced" or 0 < last["most_flops"] <= 400 * 12 * 5 * 5


def test_paced_work_does_not_grow_with_the_stream(spark, tmp_path):
    rng, most = np.random.default_rng(3), []
    for n in (200, 1600):
        base = str(tmp_path / str(n))
        rows = [(k, at(k), "a", rng.standard_normal(20).tolist()) for k in range(n)]
        keyed = streams.keyed_sketches(feed(spark, f"{base}/in", [rows]), "user", 6, 20, variant="paced")
        streams.run_available(keyed, f"{base}/c", lambda b, i, base=base: b.write.parquet(f"{base}/out/batch={i}"), "update")
        most.append(spark.read.parquet(f"{base}/out").agg(F.max("most_flops")).first()[0])
    assert most[0] == most[1]


def test_rate_and_memory(spark):
    q = tables.memory_sink(tables.rate_stream(spark, 50).select("value"), "numbers")
    try:
        for _ in range(60):
            q.processAllAvailable()
            if spark.table("numbers").count() >= 20:
                break
        found = [r["value"] for r in spark.table("numbers").collect()]
    finally:
        q.stop()
    assert len(found) >= 20 and sorted(found) == list(range(len(found)))


def test_stream_beside_a_table(spark, tmp_path):
    base = str(tmp_path)
    stream = feed(spark, f"{base}/in", [[(1, at(0), "a", [1.0])], [(2, at(1), "b", [2.0]), (3, at(2), "z", [3.0])]])
    names = spark.createDataFrame([("a", "first"), ("b", "second")], "u string, name string")
    streams.run_available(streams.with_table(stream, names, "user", "u"), f"{base}/c", lambda b, i: b.write.parquet(f"{base}/out/batch={i}"))
    assert {(r["row_id"], r["name"]) for r in spark.read.parquet(f"{base}/out").collect()} == {(1, "first"), (2, "second"), (3, None)}


def test_many_batches_merge_a_fan_in_at_a_time(spark, tmp_path):
    base = str(tmp_path)
    rng = np.random.default_rng(4)
    x = rng.standard_normal((40, 3))
    stream = feed(spark, f"{base}/in", [[(k, at(k), "a", x[k].tolist())] for k in range(40)])
    streams.global_sketch(stream, 5, 3, f"{base}/out", f"{base}/c")
    merged = streams.read_global(spark, f"{base}/out", fan_in=4)
    assert merged._jdf.queryExecution().optimizedPlan().toString().count("FlatMapGroupsInArrow") == 3
    rows = merged.collect()
    assert len(rows) == 1 and rows[0]["n_rows"] == 40
    body = np.frombuffer(bytes(rows[0]["body"])).reshape(rows[0]["live"], 3)
    assert np.allclose(body.T @ body, x.T @ x)
    assert np.allclose(baselines.gram_block(spark.createDataFrame([(k, v.tolist()) for k, v in enumerate(x)], "row_id long, vec array<double>"), 3), x.T @ x)
