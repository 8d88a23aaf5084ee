"""The counters of all events, and row-by-row counters against brute force."""

from collections import Counter

import pytest

import __spark_entry__ as entry
from rowsketch.operators import items
from rowsketch.sources import tables


def test_every_event_is_read(spark):
    sf = "/root/testdata/sf0.01"
    exact = Counter(str(r["user_id"]) for r in tables.load(spark, sf, "events").select("user_id").collect() if r["user_id"] is not None)
    got = entry.queries()["counter_stream"](spark, sf).collect()
    assert {r["n"] for r in got} == {sum(exact.values())} and sum(exact.values()) > 1000
    shed = got[0]["shed"]
    assert shed * 16 <= sum(exact.values()) and len(got) < 16
    low = {r["item"]: r["low"] for r in got}
    assert all(low.get(u, 0) <= c <= low.get(u, 0) + shed for u, c in exact.items())


@pytest.mark.parametrize("ell", [3, 5])
def test_row_by_row_against_brute_force(spark, ell):
    stream = [(k, "abcdefg"[k * k % 7 % (1 + k % 5)]) for k in range(60)]
    counts, shed = {}, 0
    for _, x in stream:
        counts[x] = counts.get(x, 0) + 1
        if len(counts) == ell:
            least = min(counts.values())
            shed += least
            counts = {k: c - least for k, c in counts.items() if c > least}
    got = items.estimates(items.in_order(spark.createDataFrame(stream, "k long, x string").repartition(3), "x", ["k"], ell)).collect()
    assert {r["item"]: r["low"] for r in got} == counts and {r["shed"] for r in got} <= {shed}
