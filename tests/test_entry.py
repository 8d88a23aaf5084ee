"""The entry module: names agree, and a handful of queries match DuckDB at the smallest scale."""

import math

import pytest

import __spark_entry__ as entry

NAMES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


@pytest.fixture(scope="module")
def duck(sf):
    import duckdb

    c = duckdb.connect()
    for t in NAMES:
        c.execute(f"CREATE VIEW {t} AS SELECT * FROM '{sf}/{t}.parquet'")
    return c


def rows(found):
    out = []
    for r in found:
        out.append(tuple(repr(round(v, 8) + 0.0) if isinstance(v, float) and not math.isnan(v) else str(v) for v in r))
    return sorted(out)


def test_entry_has_rows(spark):
    df = entry.entry(spark)
    assert df.columns == ["row_no", "sigma", "vec"] and df.count() > 0


def test_oracles_have_queries():
    assert set(entry.oracle_sql()) <= set(entry.queries())


CHECKED = ["shrink_gram_exact_lineitem", "shrink_gram_exact_events", "shrink_grouped_flag", "merge_cube_flag", "shrink_buffered_cert", "shrink_paced_cert", "indicator_equals_counters", "norm_sample_rows", "bucket_sign_sketch", "gram_sql", "stream_global_gram", "stream_sliding_gram", "window_ranks", "join_range", "bag_of_words"]


@pytest.mark.parametrize("name", CHECKED)
def test_matches_duckdb(spark, sf, duck, name):
    df = entry.queries()[name](spark, sf)
    columns = sorted(df.columns)
    r = duck.execute(entry.oracle_sql()[name])
    at = [d[0] for d in r.description]
    want = [tuple(x[at.index(c)] for c in columns) for x in r.fetchall()]
    assert rows([tuple(x) for x in df.select(*columns).collect()]) == rows(want)
